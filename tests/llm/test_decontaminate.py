import numpy as np
import pytest

from pacedfl.llm import decontaminate as d
from pacedfl.llm.common import WordHash, popcount
from pacedfl.llm.queries import op3_decontaminate

CACHE = WordHash()


def hashed(text):
    return CACHE.of(d.words_of(text))


def brute(docs, items):
    """Best similarity of every pair over all item-sized windows."""
    out = {}
    for doc, text in docs:
        h = hashed(text or "")
        for item, t in items:
            want = hashed(t or "")
            if not len(h) or not len(want):
                continue
            a = d.shingles_of(want)
            n = min(len(h), len(want))
            if len(want) < d.SHINGLE and len(h) < len(want):
                continue
            best = max(d.similarity(d.shingles_of(h[i : i + n]), a) for i in range(len(h) - n + 1))
            if best >= d.SIMILARITY:
                out[doc, item] = best
    return out


def test_multi_index_finds_all_within_radius():
    rng = np.random.default_rng(1)
    prints = rng.integers(0, 2**64, 40, dtype=np.uint64)
    windows = prints[rng.integers(0, 40, 500)].copy()
    for i in range(500):
        for b in rng.choice(64, i % 30, replace=False):
            windows[i] ^= np.uint64(1 << int(b))
    w, i, dist = d.MultiIndex(prints).within(windows)
    got = set(zip(w.tolist(), i.tolist(), strict=True))
    all_ = popcount(windows[:, None] ^ prints[None])
    assert got == set(zip(*map(np.ndarray.tolist, np.nonzero(all_ <= d.RADIUS)), strict=True)) and (dist <= d.RADIUS).all()


def test_index_and_radius_separate():
    """Unrelated fingerprints: a seventh share a block, hardly any is within the radius. Texts just at the similarity
    are within it."""
    rng = np.random.default_rng(5)
    prints, windows = rng.integers(0, 2**64, 300, dtype=np.uint64), rng.integers(0, 2**64, 400, dtype=np.uint64)
    index = d.MultiIndex(prints)
    assert len(index.candidates(windows)[0]) < 0.17 * 300 * 400 and len(index.within(windows)[0]) < 0.003 * 300 * 400
    far = 0
    for _ in range(2000):
        n = 9 * int(rng.integers(1, 12))
        a = rng.integers(0, 2**64, n, dtype=np.uint64)
        b = np.concatenate([a[n // 9 :], rng.integers(0, 2**64, n // 9, dtype=np.uint64)])
        assert d.similarity(a, b) == pytest.approx(0.8)
        far += int(popcount(d.simhash_windows(a, np.array([0]), n) ^ d.simhash_windows(b, np.array([0]), n))[0]) > d.RADIUS
    assert far <= 20


def test_equals_brute_force(spark):
    rng = np.random.default_rng(2)
    word = lambda: f"w{rng.integers(300)}"
    items = [(i, " ".join(word() for _ in range(rng.integers(14, 60)))) for i in range(12)]
    docs = []
    for k in range(60):
        text = [word() for _ in range(rng.integers(0, 80))]
        if k % 2:
            copy = items[k % 12][1].split()
            for _ in range(k % 5):
                copy[rng.integers(len(copy))] = "changed"
            at = rng.integers(len(text) + 1)
            text[at:at] = copy[: len(copy) - k % 3]
        docs.append((k, " ".join(text).title()))
    want = brute(docs, items)
    got = d.find_leaks(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()
    assert {(r.doc_id, r.item_id): r.similarity for r in got} == pytest.approx(want) and len(want) > 5


def test_edge_rows(spark):
    docs = spark.createDataFrame([(1, None, 0.5), (2, "", 0.5), (3, "tiny item here", 0.5), (None, "tiny item here", 0.5), (3, "tiny item here", 0.5), (4, "a b c d e f g", 0.5)], "doc_id long, text string, similarity double")
    items = spark.createDataFrame([(1, None), (2, ""), (3, "Tiny item"), (4, "tiny ITEM"), (5, "a b c d e f g"), (None, "x")], "item_id long, text string")
    got = sorted(((r.doc_id or 0, r.item_id) for r in d.find_leaks(docs, items).collect()))
    assert got == [(0, 3), (0, 4), (3, 3), (3, 3), (3, 4), (3, 4), (4, 5)]
    left = d.without_leaks(docs, items)
    assert left.columns == docs.columns and sorted(r.doc_id for r in left.collect()) == [1, 2]
    assert d.find_leaks(docs.limit(0), items).count() == 0 and d.find_leaks(docs, items.limit(0)).count() == 0


def test_slices_of_a_large_benchmark(spark):
    items = spark.createDataFrame([(i, f"one{i} two three{i} four five{i} six seven") for i in range(50)], "item_id long, text string")
    parts = list(d.benchmark_slices(items, max_items=10))
    assert len(parts) > 1 and sorted(x for p in parts for x in p.ids.tolist()) == list(range(50)) and max(len(p.ids) for p in parts) <= 20


def test_whole_items_are_found_in_the_given_table(spark, small):
    got = {(r.doc_id, r.item_id) for r in op3_decontaminate(spark, small).collect()}
    docs, items = (spark.read.parquet(f"{small}/{t}.parquet").collect() for t in ("documents", "benchmark"))
    want = {(x.doc_id, i.item_id) for x in docs for i in items if i.text in x.text}
    assert want and want <= got


def test_items_without_identifier_are_looked_for(spark):
    docs = spark.createDataFrame([(1, "some words and then a passage of the benchmark that leaks here"), (2, "nothing of that kind")], "doc_id long, text string")
    items = spark.createDataFrame([(None, "a passage of the benchmark that leaks"), (None, "nothing of"), (None, None), (7, "not in any text")], "item_id long, text string")
    assert sorted((r.doc_id, r.item_id) for r in d.find_leaks(docs, items).collect()) == [(1, None), (2, None)]
    assert d.without_leaks(docs, items).count() == 0
    assert sum(len(p.ids) for p in d.benchmark_slices(items, max_items=1)) == 3
