import pytest
from conftest import same_rows

from pacedfl.llm import common, url_filter as u
from pacedfl.llm.queries import ORACLE, op5_urls

URLS = [
    ("http://example.com/en/x?y", "example.com", "/en/x", "example.com/en/", "block"),
    ("http://WWW.Example.com/en/x#y", "www.example.com", "/en/x", "www.example.com/en/", "allow"),
    ("http://a.www.example.com/en/", "a.www.example.com", "/en/", "www.example.com/en/", "allow"),
    ("https://b.example.com/en", "b.example.com", "/en", "com/", "allow"),
    ("https://notexample.com/en/", "notexample.com", "/en/", "com/", "allow"),
    ("https://x.net/fr/1", "x.net", "/fr/1", "net/fr/", "block"),
    ("https://x.net/de/1", "x.net", "/de/1", None, None),
    ("https://x.com?a=/b", "x.com", "", None, None),
    ("ftp://y.org/a://b/c", "y.org", "/a://b/c", None, None),
    ("x.com/en/", "", "", None, "allow"),
    ("", "", "", None, "allow"),
    (None, "", "", None, "allow"),
    ("://", "", "", None, "allow"),
    ("http://ÀB.com/É", "Àb.com", "/É", "com/", "allow"),
]


def test_rules(spark):
    pages = spark.createDataFrame([(i, x[0], None, "z") for i, x in enumerate(URLS)], "page_id long, url string, html string, verdict string")
    rows = {r.page_id: r for r in u.judge_urls(pages).collect()}
    for i, (_, host, path, rule, verdict) in enumerate(URLS):
        assert (rows[i].host, rows[i].path, rows[i].rule) == (host, path, rule)
        assert verdict is None or rows[i].verdict == verdict


def linked(spark):
    link = lambda *hosts: "".join(f"<p><a class=x href='http://{h}/'>l</a>" for h in hosts)
    rows = [(1, "http://spam.net/fr/", None), (2, "http://spam.net/fr/2", ""), (3, "http://farm.org/", link("spam.net", "spam.net")), (4, "http://farm.org/2", link("//spam.net".replace("//", ""))),
            (5, "http://good.com/", link("friend.org")), (6, "http://friend.org/", link("good.com")), (7, "http://far.org/", link("farm.org")), (8, "http://calm.org/", '<a href="/local">x</a>'), (9, None, link("spam.net")), (None, "http://farm.org/3", None)]
    return spark.createDataFrame(rows, "page_id long, url string, html string")


def test_links_spread_distrust(spark):
    pages = linked(spark)
    edges = {(r.source, r.target): r.n for r in u.host_edges(pages).collect()}
    assert edges == {("farm.org", "spam.net"): 3, ("good.com", "friend.org"): 1, ("friend.org", "good.com"): 1, ("far.org", "farm.org"): 1}
    rows = {r.page_id: r for r in u.judge_urls(pages, threshold=0.1, settled=0.01).collect()}
    assert rows[3].verdict == rows[4].verdict == "block"  # it links to a blocked host
    assert rows[6].verdict == rows[8].verdict == rows[9].verdict == "allow"
    assert rows[3].host_score > 0.1 and rows[6].host_score < 0 and rows[8].host_score == 0


def brute_ranks(seed, edges, rounds=400):
    rank = dict(seed)
    for _ in range(rounds):
        ended = sum(rank[h] for h in rank if all(s != h for s, _, _ in edges))
        new = {h: 0.15 * seed[h] + 0.85 * ended * seed[h] for h in rank}
        for s, t, w in edges:
            new[t] += 0.85 * rank[s] * w / sum(x for a, _, x in edges if a == s)
        rank = new
    return rank


@pytest.mark.parametrize("share", [1000, 3])
def test_pagerank_settles_at_brute_force(spark, monkeypatch, share):
    """Also with hosts dealt over several tasks."""
    monkeypatch.setattr(common, "HOT_SHARE", share)
    seeds = spark.createDataFrame([("trust", "a", 0.25), ("trust", "b", 0.75)], "kind string, host string, seed double")
    links = [("a", "b", 1), ("a", "c", 3), ("b", "c", 1), ("c", "d", 1), ("c", "a", 2)]
    edges = spark.createDataFrame([("trust", *x) for x in links], "kind string, source string, target string, n long")
    got = {r.host: r["rank"] for r in u.propagate(seeds, edges, 1e-3).collect()}
    assert got == pytest.approx(brute_ranks({"a": 0.25, "b": 0.75, "c": 0, "d": 0}, links), abs=1e-2) and sum(got.values()) == pytest.approx(1)
    rough = {r.host: r["rank"] for r in u.propagate(seeds, edges, settled=0.5).collect()}
    assert rough != pytest.approx(got, abs=1e-3)


def test_hot_hosts_and_repeated_rows(spark, monkeypatch):
    """One host holds most pages, some rows occur twice, one page is very long: same verdicts as without dealing."""
    rows = [(i % 40, f"http://{'big.org' if i % 4 else f'h{i % 7}.net'}/{'fr' if i % 4 == 0 else 'x'}/{i}", "<a href='http://h0.net/'>x</a>" * (50_000 if i == 3 else 1)) for i in range(80)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    want = sorted(u.judge_urls(pages, settled=0.1).collect())
    monkeypatch.setattr(common, "HOT_SHARE", 5)
    assert sorted(u.judge_urls(pages, settled=0.1).collect()) == want and len(want) == 80


def test_query_equals_sql(spark, duck, small):
    assert same_rows(op5_urls(spark, small).toPandas(), duck.sql(ORACLE["op5_urls"]).df())


def test_sql_on_linked_pages(spark):
    import duckdb

    pages = linked(spark)
    c = duckdb.connect()
    c.register("pages", pages.toPandas())
    got = u.judge_urls(pages).select("page_id", "host", "path", "rule", "verdict")
    assert same_rows(got.toPandas(), c.sql(ORACLE["op5_urls"]).df())


def test_empty(spark, small):
    assert u.judge_urls(spark.read.parquet(f"{small}/pages.parquet").limit(0)).count() == 0
