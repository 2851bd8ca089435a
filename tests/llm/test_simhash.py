import numpy as np
import pytest
import xxhash

from pacedfl.llm import common, similar_dedup as wide, simhash_dedup as s
from pacedfl.llm.common import WordHash
from pacedfl.llm.queries import op4_simhash


def by_the_book(text):
    words = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    import re

    words = re.findall(r"[^\x20\x09-\x0D]+", words)
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [" ".join(words)]
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def closed(links, ids):
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in links:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


@pytest.mark.parametrize("text", ["", " \t\n", "one", "One TWO", "a b c", "É É é\x85x y\x1cz w", "a b c " * 30])
def test_fingerprint(text):
    assert s.fingerprint(text.encode()) == by_the_book(text)


def test_query_equals_brute_force(spark, small):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    fp = {i: by_the_book(t) for i, t in docs.items()}
    want = closed([(a, b) for a in fp for b in fp if a < b and (fp[a] ^ fp[b]).bit_count() <= 3], fp)
    rows = op4_simhash(spark, small).collect()
    assert {r.doc_id: int(r.fingerprint, 16) for r in rows} == fp and {r.doc_id: r.component_id for r in rows} == want


@pytest.mark.parametrize("hot", [s.HOT, 4])
def test_chains_and_hot_keys(spark, hot):
    """A ball of close fingerprints, a chain of steps of three bits, and strangers; keys split where crowded."""
    rng = np.random.default_rng(3)
    base = int(rng.integers(0, 2**62))
    fps = {base ^ sum(1 << int(b) for b in rng.choice(64, rng.integers(0, 6), replace=False)) for _ in range(120)}
    x = int(rng.integers(0, 2**62))
    for k in range(12):
        fps.add(x)
        x ^= 0b111 << (5 * k)
    fps |= {int(v) for v in rng.integers(0, 2**63, 60)}
    fps = sorted(f & (2**64 - 1) for f in fps)
    signed = [f - 2**64 if f >> 63 else f for f in fps]
    links = s.near_links(spark.createDataFrame([(f,) for f in signed], "fp long"), hot)
    got = {r.node: r.root for r in s.components(links).collect()}
    want = closed([(a, b) for i, a in enumerate(signed) for b in signed[i + 1 :] if ((a ^ b) & s.ALL).bit_count() <= 3], signed)
    assert {i: got.get(i, i) for i in signed} == want


def test_edge_rows(spark):
    docs = spark.createDataFrame([(5, None, "c"), (3, "", "c"), (9, "same words here now", "c"), (9, "same words here now", "c"), (None, "same words here now", "c"), (7, "Same  WORDS here now", "c"), (None, "alone at last", "c")], "doc_id long, text string, component_id string")
    rows = s.near_duplicate_components(docs).collect()
    assert sorted(((r.doc_id, r.component_id) for r in rows), key=repr) == sorted([(5, 3), (3, 3), (9, 7), (9, 7), (None, 7), (7, 7), (None, None)], key=repr)
    assert s.near_duplicate_components(docs.limit(0)).count() == 0
    only = docs.where("doc_id = 9")
    assert wide.one_of_each_group(only).count() == 1


def exact_components(docs):
    cache = WordHash()
    sets = {i: set(wide.shingle_hashes((t or "").encode(), cache).tolist()) for i, t in docs.items()}
    ids = sorted(sets)
    return closed([(a, b) for k, a in enumerate(ids) for b in ids[k + 1 :] if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])], ids)


@pytest.mark.parametrize("hot", [wide.HOT, 3])
def test_similar_components_equal_exact_similarity(spark, hot):
    rng = np.random.default_rng(4)
    word = lambda: f"w{rng.integers(2000)}"
    docs, n = {}, 0
    for _ in range(25):
        text = [word() for _ in range(rng.integers(30, 200))]
        for c in range(rng.integers(1, 9)):
            copy = list(text)
            for _ in range(c):
                copy[rng.integers(len(copy))] = word()
            docs[n] = " ".join(copy)
            n += 1
    docs |= {n: None, n + 1: "", n + 2: "two words", n + 3: "Two words"}
    want = exact_components(docs)
    rows = wide.similar_components(spark.createDataFrame(list(docs.items()), "doc_id long, text string"), hot=hot).collect()
    got = {r.doc_id: r.component_id for r in rows}
    wrong = [i for i in docs if got[i] != want[i]]
    assert len(wrong) <= 0.02 * len(docs)
    merged = {i for i in docs if got[i] < want[i]}
    assert not merged  # nothing below the similarity is ever joined


def test_one_of_each_group(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    want = exact_components({r.doc_id: r.text for r in docs.collect()})
    kept = wide.one_of_each_group(docs)
    assert kept.columns == docs.columns
    got = {r.doc_id for r in kept.collect()}
    assert got >= set(want.values()) and len(got) <= len(set(want.values())) + 1
    assert wide.one_of_each_group(docs.limit(0)).count() == 0


def similar(spark, docs, **more):
    return {r.doc_id: r.component_id for r in wide.similar_components(spark.createDataFrame(list(docs.items()), "doc_id long, text string"), **more).collect()}


@pytest.mark.parametrize("short, long, shared", [(8, 9, 8), (12, 15, 12), (13, 14, 12), (16, 19, 16), (5, 5, 5)])
def test_short_texts_at_the_threshold(spark, short, long, shared):
    """Pairs of a few words that are just similar enough: no fingerprint may drop them."""
    docs = {}
    for k in range(200):
        head = [f"{k}w{i}" for i in range(shared)]
        docs[2 * k] = " ".join(head + [f"{k}x{i}" for i in range(short - shared)])
        docs[2 * k + 1] = " ".join(head + [f"{k}y{i}" for i in range(long - shared)])
    assert similar(spark, docs) == exact_components(docs)


def graded_copies():
    """A text under more and more edits: many copies are near the threshold to many others."""
    rng = np.random.default_rng(6)
    base, docs = [f"b{i}" for i in range(120)], {}
    for n in range(600):
        copy = list(base)
        for _ in range(rng.integers(0, 12)):
            copy[rng.integers(len(copy))] = f"e{rng.integers(10**6)}"
        docs[n] = " ".join(copy)
    return docs


def test_graded_copies(spark):
    """A copy whose nearest neighbour by fingerprint is not similar enough is linked by another one."""
    docs = graded_copies()
    assert similar(spark, docs) == exact_components(docs)


def test_crowded_bands_lose_no_pair(spark):
    """A crowded band is dealt in blocks that all meet: the result is that of whole bands."""
    docs = dict(list(graded_copies().items())[:200])
    assert similar(spark, docs, hot=20) == similar(spark, docs) == exact_components(docs)


def test_hot_nodes_and_copies(spark, monkeypatch):
    """A star, a chain and copies that hold most rows, dealt over several tasks; and a very long text."""
    monkeypatch.setattr(common, "HOT_SHARE", 3)
    star = [(5, i) for i in range(100, 160)] + [(i, i + 1) for i in range(200, 290)]
    got = {r.node: r.root for r in s.components(spark.createDataFrame(star, "a long, b long")).collect()}
    assert got == {**{i: 5 for i in [5, *range(100, 160)]}, **{i: 200 for i in range(200, 291)}}
    docs = [(i, "the same words in every row" if i % 3 else f"{i} own words {i * i} and more {i * 7}") for i in range(90)] + [(90, "long text " * 200_000), (91, "long text " * 200_000)]
    got = {r.doc_id: r.component_id for r in s.near_duplicate_components(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert all(got[i] == 1 for i in range(90) if i % 3) and got[91] == 90 and len(got) == 92


def test_pivots_discard_pairs():
    rng = np.random.default_rng(3)
    fps = np.unique(rng.integers(0, 2**63, 300, dtype=np.uint64))
    fps = np.unique(np.concatenate([fps, fps[:40] ^ np.uint64(1 << 7), fps[:10] ^ np.uint64(0b10101)]))
    counts = s.pivot_counts(fps)
    assert counts[0] == len(fps) * (len(fps) - 1) // 2 and all(a >= b for a, b in zip(counts, counts[1:]))
    exact = sum(int(a ^ b).bit_count() <= 3 for i, a in enumerate(fps.tolist()) for b in fps.tolist()[i + 1 :])
    assert counts[-1] == exact and counts[-2] < 0.02 * counts[0]


def test_similar_documents_with_odd_rows(spark):
    """Null identifiers stay, rows that repeat an identifier leave one, other columns may have any name."""
    text = " ".join(f"w{i}" for i in range(40))
    rows = [(1, text, "a", 1), (2, text + " end", "b", 2), (2, text + " end", "b", 3), (None, text, "c", 4), (None, text, "c", 5), (7, None, "d", 6), (8, "", None, 7), (9, "alone here", "e", 8), (9, "alone here", "e", 9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, __loser string, node int")
    kept = wide.one_of_each_group(docs)
    assert kept.columns == docs.columns
    assert sorted((r.doc_id for r in kept.collect()), key=repr) == sorted([1, None, None, 7, 9], key=repr)


def test_near_components_hold_links_of_both_kinds(spark):
    """Groups of the pipeline's stage are those of all pairs by fingerprint or by similarity, links of either kind in a chain."""
    docs = dict(list(graded_copies().items())[:60])
    common = "spam " * 300
    docs |= {100: common + "alpha beta gamma delta epsilon zeta", 101: common + "one two three four five six", 102: None, 103: " "}
    docs |= {104: docs[101] + " seven", 105: "own words of this text alone"}
    bits = {i: s.fingerprint((t or "").encode()) for i, t in docs.items()}
    similar_to = exact_components(docs)
    root = dict(similar_to)
    for i in docs:
        for j in docs:
            if (bits[i] ^ bits[j]).bit_count() <= 3 and root[i] != root[j]:
                low, high = sorted((root[i], root[j]))
                root = {k: low if r == high else r for k, r in root.items()}
    assert similar_to[100] != similar_to[101] and root[101] == root[100] == 100
    rows = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    assert {r.doc_id: r.component_id for r in wide.near_components(rows).collect()} == root


def test_signatures_and_bits_take_one_python_operator(spark, monkeypatch):
    """Texts go through Python once: chained operators hold a worker each, for every task, at the same time."""
    plans = {}
    monkeypatch.setattr(wide, "written", lambda df, tag: plans.update({tag: df._jdf.queryExecution().executedPlan().toString()}) or common.written(df, tag))
    texts = ["", None, "Two words", "a text of more than five words", "spam " * 300]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert wide.near_components(rows).count() == len(texts)
    assert plans["signatures"].count("MapInArrow") == 1
    got = wide.signatures(rows, with_bits=True).collect()
    assert {r.doc_id: r.bits % 2**64 for r in got} == {i: s.fingerprint((t or "").encode()) for i, t in enumerate(texts)}
