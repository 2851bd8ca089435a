import hashlib
import re

import numpy as np
import pytest
from conftest import same_rows
from pyspark.sql import functions as F

from pacedfl.llm import substring_dedup as s
from pacedfl.llm.queries import ORACLE, op9_substring


def brute(docs):
    words = {i: re.findall(r"[^\x20\x09-\x0D]+", t or "") for i, t in docs.items()}
    first = {}
    for i in sorted(words):
        for k in range(len(words[i]) - 12):
            first.setdefault(tuple(words[i][k : k + 13]), i)
    out = {}
    for i, w in words.items():
        gone = {k + j for k in range(len(w) - 12) if first[tuple(w[k : k + 13])] < i for j in range(13)}
        kept = [x for k, x in enumerate(w) if k not in gone]
        out[i] = (len(w), len(gone), hashlib.sha256(" ".join(kept).encode()).hexdigest())
    return out


def as_dict(df):
    return {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in df.collect()}


def shared(seed, n=60):
    rng = np.random.default_rng(seed)
    word = lambda: f"w{rng.integers(5000)}"
    passages = [[word() for _ in range(rng.integers(10, 90))] for _ in range(6)]
    docs = {}
    for i in rng.permutation(n).tolist():
        text = [word() for _ in range(rng.integers(0, 60))]
        for _ in range(rng.integers(0, 4)):
            p = passages[rng.integers(6)]
            a = rng.integers(0, max(1, len(p) - 13))
            text += p[a : a + rng.integers(5, 80)] + [word()]
        docs[i] = " \n".join(text)
    return docs


@pytest.mark.parametrize("seed", range(3))
def test_equals_brute_force(spark, seed):
    docs = shared(seed)
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string").repartition(5)
    assert as_dict(s.remove_repeats(df)) == brute(docs)


def test_edge_rows(spark):
    long = " ".join(f"t{i}" for i in range(40))
    rows = [(1, long, 1), (2, long, 1), (3, None, 1), (4, "", 1), (5, " ".join(long.split()[:12]), 1), (6, " ".join(long.split()[:13]), 1), (None, long, 1), (2, long, 1), (7, ("a " * 20000) + long, 1)]
    got = s.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string, n_words int")).collect()
    removed = sorted(((r.doc_id, r.n_words, r.n_removed) for r in got), key=repr)
    assert removed == sorted([(1, 40, 0), (2, 40, 40), (2, 40, 40), (3, 0, 0), (4, 0, 0), (5, 12, 0), (6, 13, 13), (None, 40, 0), (7, 20040, 40)], key=repr)
    assert s.remove_repeats(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def brute_paths(docs):
    """Nonbranching paths of repeated windows, each as the set of its edges; edges are tuples of 13 words."""
    holders = {}
    for i, t in docs.items():
        w = t.split()
        for k in range(len(w) - 12):
            holders.setdefault(tuple(w[k : k + 13]), set()).add(i)
    edges = [e for e, who in holders.items() if len(who) > 1]
    out, into = {}, {}
    for e in edges:
        out.setdefault(e[:-1], []).append(e)
        into.setdefault(e[1:], []).append(e)
    through = {n for n in out if len(out[n]) == 1 and len(into.get(n, ())) == 1}
    root = {e: e for e in edges}

    def find(e):
        while root[e] != e:
            e = root[e]
        return e

    for n in through:
        root[find(out[n][0])] = find(into[n][0])
    groups = {}
    for e in edges:
        groups.setdefault(find(e), set()).add(e)
    return {frozenset(g) for g in groups.values()}


def branching(seed):
    """Documents over passages that fork, join, run across documents and come round again."""
    rng = np.random.default_rng(seed)
    word = lambda n: [f"x{rng.integers(100_000)}" for _ in range(n)]
    a, b, c, d, ring = word(30), word(40), word(25), word(50), word(20)
    parts = [a + b, a + c, b + c, a + b + d, ring * 3, ring[7:] + ring * 2, d[:30], d[20:], b[5:] + d + a, word(60), word(9)]
    docs = [word(rng.integers(0, 5)) + parts[k] + word(rng.integers(0, 5)) for k in range(len(parts))] + [word(3) + d[10:45] + a[3:] for _ in range(2)]
    return {int(i): " ".join(t) for i, t in zip(rng.permutation(100)[: len(docs)], docs, strict=True)}


@pytest.mark.parametrize("slice_text", [1, 4 << 20])
@pytest.mark.parametrize("seed", range(3))
def test_paths_equal_brute_force(spark, monkeypatch, seed, slice_text):
    """Branching, paths across documents and closed paths; one document a slice, and all in one."""
    monkeypatch.setattr(s, "SLICE_TEXT", slice_text)
    docs = branching(seed)
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string").coalesce(1)
    got, before = {}, {}
    for r in s.repeated_paths(df).collect():
        w = docs[r.doc_id].split()
        got.setdefault(r.path, set()).update(tuple(w[k : k + 13]) for k in range(r.start_word, r.start_word + r.words - 12))
        before.setdefault(r.path, []).append((r.before, r.words - 12))
    assert {frozenset(x) for x in got.values()} == brute_paths(docs)
    for x in before.values():  # segments of a path follow each other without a gap
        x.sort()
        assert [b for b, _ in x] == [sum(n for _, n in x[:k]) for k in range(len(x))]
    assert as_dict(s.remove_repeats(df)) == brute(docs)


def test_compaction_doubles_and_breaks_rings(spark):
    """A chain of 40 segments has one head; a ring begins at its smallest coordinate."""
    chain = [(1, 100 * k, 5, 1 if k < 39 else None, 100 * (k + 1) if k < 39 else None) for k in range(40)]
    ring = [(2, 100 * k, 3, 2, 100 * ((k + 2) % 3)) for k in range(3)] + [(3, 0, 4, 3, 0)]
    segments = spark.createDataFrame(chain + ring, "slice long, at int, size int, from_slice long, from_at int")
    got = {(r.slice, r.at): (tuple(r.head), r.before) for r in s.paths(segments).collect()}
    assert all(got[1, 100 * k] == ((1, 0), 5 * k) for k in range(40))
    assert got[3, 0] == ((3, 0), 0) and got[2, 0] == ((2, 0), 0)
    assert got[2, 200] == ((2, 0), 3) and got[2, 100] == ((2, 0), 6)


def test_one_span_for_a_path(spark):
    docs = spark.createDataFrame([(1, " ".join(f"t{i}" for i in range(60))), (2, " ".join(f"t{i}" for i in range(10, 50)))], "doc_id long, text string").coalesce(1)
    spans, segments = s.repeated_spans(s.blocks(docs, "doc_id", "text"))
    assert [(r.at, r.size, r.from_at) for r in spans.collect()] == [(60, 28, 10)]
    assert [(r.at, r.size, r.before) for r in segments.collect()] == [(10, 28, 0)]


def test_unverified_spans_keep_their_words(spark, monkeypatch):
    """Only spans whose words are equal at both ends are removed, within a slice and across slices."""
    monkeypatch.setattr(s, "SLICE_TEXT", 1)
    a, b = " ".join(f"a{i}" for i in range(14)), " ".join(f"b{i}" for i in range(14))
    df = spark.createDataFrame([(1, a), (2, b), (3, a)], "doc_id long, text string").coalesce(1)
    of = {}

    def find(packed):
        of.update({r.ids[0]: r.slice for r in packed.collect()})
        spans = [(of[2], 0, 2, of[1], 0), (of[3], 0, 2, of[1], 0)]
        segments = [(of[1], 0, 2)]
        return spark.createDataFrame(spans, "slice long, at int, size int, from_slice long, from_at int"), spark.createDataFrame(segments, "slice long, at int, size int")

    assert {k: v[1] for k, v in as_dict(s.remove_repeats(df, find=find)).items()} == {1: 0, 2: 0, 3: 14}
    assert len(set(of.values())) == 3


def test_packing():
    node = np.arange(5, dtype=np.uint64) + np.uint64(7 << 50)
    after, before, flags = np.arange(5, dtype=np.uint64) + np.uint64(2**48 - 9), np.arange(5, dtype=np.uint64) + np.uint64(70_000), np.arange(5, dtype=np.uint8)
    at = np.array([0, 1, 5, 70000, 70001])
    for doc in (np.array([-3, 3, 9, 9, 9]), np.array([-(1 << 62), 3, 9, 9, 1 << 61])):
        for want, got in zip((node, after, before, flags, at, doc), s._unpack(s._pack(node, after, before, flags, at, doc)), strict=True):
            assert (want == got).all()


def test_many_continuations_of_one_passage(spark, monkeypatch):
    """Every document goes on differently after a common passage; nothing is left unverified."""
    passage = " ".join(f"p{i}" for i in range(20))
    docs = {i: f"a{i} {passage} b{i} " + " ".join(f"c{i}x{k}" for k in range(12)) for i in range(6000)}
    monkeypatch.setattr(s, "SLICE_TEXT", 3000)
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string").coalesce(4)
    spans, segments = s.repeated_spans(s.blocks(df, "doc_id", "text"))
    assert segments.count() == 1 and spans.count() == 5999 and {r.size for r in spans.collect()} == {8}
    assert {r.n_removed for r in s.remove_repeats(df).where("doc_id > 0").collect()} == {20}


def test_slice_bounds_do_not_matter(spark, monkeypatch):
    docs = shared(5, 80)
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string").repartition(3)
    for size in (1, 500, 5000):
        monkeypatch.setattr(s, "SLICE_TEXT", size)
        assert as_dict(s.remove_repeats(df)) == brute(docs)


def test_query_equals_sql(spark, duck, small):
    assert same_rows(op9_substring(spark, small).toPandas(), duck.sql(ORACLE["op9_substring"]).df())
    assert op9_substring(spark, small).agg(F.sum("n_removed")).first()[0] > 0
