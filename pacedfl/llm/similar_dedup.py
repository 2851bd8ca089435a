"""Near-duplicates at a shingle similarity: min-hash bands, wide SimHash for order, exact comparison.

Documents are grouped by bands of min-hashes of their five-word shingles (a pair at a Jaccard similarity of
THRESHOLD shares a band with probability 0.999). The shingle sets themselves go to each group of two or more, and
within a group only the exact similarity decides: pairs are found by the rarest shingles of each set, as many as
a pair at the threshold cannot all differ in, and compared unless they are connected already. Fingerprints of
BITS bits only say which pairs are compared first; no pair is dropped by them.

near_components first links documents by the operator of op4 (64-bit fingerprints, keys of equal blocks, pivot tables of
distances that discard pairs, exact count of bits) and joins its groups with those at the similarity, which 64 bits are
too coarse to find; a link of either kind counts.

Copies with the same words are folded first. A group of more than HOT distinct documents, or of more than
HOT_SHINGLES shingles, is dealt in blocks and every two blocks meet in a task, so that no pair of it is lost.
Edge cases: texts with fewer words than a shingle have their whole word sequence as one shingle; texts without
words are alike; null identifiers are left alone; repeated rows count as copies.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from pacedfl.llm.common import WordHash, checkpointed, dealt, mix, multipliers, popcount, raw, repeated, salted, slices, window_hashes, written
from pacedfl.llm.simhash_dedup import components, fingerprint, near_links

SIZE = 5
THRESHOLD = 0.8
WORDS64 = 8
BITS = 64 * WORDS64
BANDS, ROWS = 10, 3
HOT = 4_000
HOT_SHINGLES = 2_000_000
_SHINGLE = multipliers(SIZE, 21)
_WHOLE = multipliers(SIZE, 22)
_MIN = multipliers(BANDS * ROWS, 23)
_SEEDS = multipliers(WORDS64, 24)


def shingle_hashes(text: bytes, cache: WordHash) -> np.ndarray:
    """Distinct hashes of the text's word shingles, sorted; A-Z count as lower case."""
    h = cache.of(text.lower().split())
    if len(h) < SIZE:
        return window_hashes(h, _WHOLE[: len(h)]) if len(h) else np.zeros(1, np.uint64)
    return np.unique(window_hashes(h, _SHINGLE))


def signature(s: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(wide fingerprint as unsigned words, min-hashes) of a set of shingles."""
    wide = np.empty(WORDS64, np.uint64)
    for j, seed in enumerate(_SEEDS):
        on = np.zeros(64, np.int64)
        for a in range(0, len(s), 1 << 16):
            h = mix(s[a : a + (1 << 16)] * seed)
            on += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
        wide[j] = np.packbits(2 * on > len(s)).view(np.uint64)[0]
    return wide, np.array([mix(s * m).min() for m in _MIN], dtype=np.uint64)


def signatures(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", with_bits: bool = False) -> DataFrame:
    """(id, same, size, fp, mins): a hash of the shingle set, its size, the wide fingerprint and the min-hashes; with_bits
    adds the 64-bit fingerprint of op4 as bits, in the same pass: a second Python operator would take workers and copies
    of the texts of its own. No shuffle."""
    more = ["bits"] if with_bits else []

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = WordHash()
        for batch in batches:
            for part in slices(batch, text_col):
                same, sizes, fps, mins = [], [], [], []
                read = raw(part, text_col)
                for t in read:
                    s = shingle_hashes(t, cache)
                    wide, low = signature(s)
                    same.append(int(mix(np.array([np.bitwise_xor.reduce(mix(s)) + np.uint64(len(s))], np.uint64)).view(np.int64)[0]))
                    sizes.append(len(s))
                    fps.append(wide.tobytes())
                    mins.append(low.tobytes())
                bits = [pa.array(np.fromiter(map(fingerprint, read), np.uint64, len(read)).view(np.int64)) for _ in more]
                yield pa.RecordBatch.from_arrays([part.column(id_col).cast(pa.int64()), pa.array(same, pa.int64()), pa.array(sizes, pa.int64()), pa.array(fps, pa.binary()), pa.array(mins, pa.binary()), *bits], names=[id_col, "same", "size", "fp", "mins", *more])

    return docs.select(id_col, text_col).mapInArrow(run, ", ".join([f"{id_col} bigint, same bigint, size bigint, fp binary, mins binary", *(f"{c} bigint" for c in more)]))


def _banded(nodes: DataFrame) -> DataFrame:
    """(band, node, size) rows: BANDS a node."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            m = np.frombuffer(b"".join(batch.column("mins").to_pylist()), np.uint64).reshape(n, BANDS * ROWS)
            for k in range(BANDS):
                key = np.zeros(n, np.uint64)
                for r in range(ROWS):
                    key = mix(key * np.uint64(0x9E3779B97F4A7C15) + m[:, k * ROWS + r])
                yield pa.RecordBatch.from_arrays([pa.array(mix(key + np.uint64(k)).view(np.int64)), batch.column("node"), batch.column("size")], names=["band", "node", "size"])

    return nodes.select("node", "size", "mins").mapInArrow(run, "band bigint, node bigint, size bigint")


def forest(sets: list[np.ndarray], fps: np.ndarray, threshold: float = THRESHOLD) -> tuple[np.ndarray, np.ndarray]:
    """Positions (a, b) of edges at the threshold that connect all pairs of sets at the threshold."""
    n = len(sets)
    size = np.array([len(s) for s in sets])
    if n == 2:
        both = len(np.intersect1d(sets[0], sets[1], assume_unique=True))
        near = int(both >= threshold * (size.sum() - both))
        return np.zeros(near, np.int64), np.ones(near, np.int64)
    order = np.argsort(size, kind="stable")
    size, fps = size[order], fps[order]
    shingle, count = np.unique(np.concatenate(sets), return_counts=True)
    rarity = np.empty(len(count), np.int32)
    rarity[np.argsort(count, kind="stable")] = np.arange(len(count))
    count = np.sort(count)
    codes = [np.sort(rarity[np.searchsorted(shingle, sets[i])]) for i in order]  # set by set: an inverse of all takes several copies
    least = np.ceil(threshold * size - 1e-9).astype(np.int64)  # common shingles that a set needs with any other
    rare = [c[: k + 1][count[c[: k + 1]] > 1] for c, k in zip(codes, size - least, strict=True)]
    member = np.repeat(np.arange(n), [len(c) for c in rare])
    token = np.concatenate(rare)
    by = np.argsort(token, kind="stable")
    member, token = member[by], token[by]
    smallest = np.searchsorted(size, least)
    root, mark = np.arange(n), np.zeros(len(count), np.uint8)
    a, b = [], []
    for i in range(n):
        meets = np.zeros(n, bool)
        for lo, hi in zip(np.searchsorted(token, rare[i]), np.searchsorted(token, rare[i], side="right"), strict=True):
            meets[member[lo:hi]] = True
        near = np.flatnonzero(meets[smallest[i] : i]) + smallest[i]
        near = near[np.argsort(popcount(fps[near] ^ fps[i]).sum(axis=1, dtype=np.int64), kind="stable")]
        mark[codes[i]] = 1
        step = 4
        while len(near):
            some, near = near[:step], near[step:]
            both = np.add.reduceat(mark[np.concatenate([codes[j] for j in some])], np.cumsum(size[some]) - size[some], dtype=np.int64)
            for j in some[both >= threshold * (size[some] + size[i] - both)]:
                if root[j] != root[i]:
                    root[root == root[j]] = root[i]
                    a.append(i)
                    b.append(j)
            near = near[root[near] != root[i]]
            step = min(4 * step, 256)
        mark[codes[i]] = 0
    return order[np.array(a, np.int64)], order[np.array(b, np.int64)]


def _members(nodes: DataFrame, docs: DataFrame, id_col: str, text_col: str, hot: int) -> DataFrame:
    """(band, part, node, fp, s): the shingle set of each node in each band that it shares, and in each part of a
    crowded one. A text is read once for all of them."""
    banded = _banded(nodes)
    blocks = F.greatest(F.ceil(F.count("*") / hot), F.ceil(F.sum("size") / HOT_SHINGLES)).cast("int")
    shared = banded.groupBy("band").agg(F.count("*").alias("n"), blocks.alias("blocks")).where("n > 1").select("band", "blocks")
    mine, other, k = F.col("mine"), F.col("other"), F.col("blocks")
    places = banded.join(shared, "band").withColumn("mine", F.pmod(F.xxhash64("node"), k).cast("int"))
    places = places.withColumn("other", F.explode(F.sequence(F.lit(0), k - 1))).where((k == 1) | (mine != other))
    places = places.select("node", F.struct("band", (F.least(mine, other).cast("long") * k + F.greatest(mine, other)).alias("part")).alias("at"))
    places = places.groupBy("node").agg(F.collect_set("at").alias("at"))
    texts = docs.select(F.col(id_col).cast("bigint").alias("node"), F.col(text_col).alias("__text")).where("node is not null")
    rows = places.join(nodes.groupBy("node").agg(F.min("fp").alias("fp")), "node").join(texts, "node")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = WordHash()
        for batch in batches:
            for part in slices(batch, "__text", 1 << 20):
                at = part.column("at")
                row = np.repeat(np.arange(part.num_rows), np.diff(at.offsets.to_numpy()))
                sets = pa.array([shingle_hashes(t, cache).tobytes() for t in raw(part, "__text")], pa.binary())
                places = at.flatten()
                for a in range(0, len(row), 1000):
                    i = pa.array(row[a : a + 1000])
                    yield pa.RecordBatch.from_arrays([*(places.field(c)[a : a + 1000] for c in ("band", "part")), part.column("node").take(i), part.column("fp").take(i), sets.take(i)], names=["band", "part", "node", "fp", "s"])

    return rows.select("node", "fp", "at", "__text").mapInArrow(run, "band bigint, part bigint, node bigint, fp binary, s binary")


def similar_edges(nodes: DataFrame, docs: DataFrame, id_col: str, text_col: str, threshold: float = THRESHOLD, hot: int = HOT) -> DataFrame:
    """Edges (a, b) between nodes (node, size, fp, mins), all at the threshold exactly, that connect all pairs at
    the threshold that share a band."""
    dealt = _members(nodes, docs, id_col, text_col, hot).repartition("band", "part").sortWithinPartitions("band", "part")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        key = None

        def links() -> Iterator[pa.RecordBatch]:
            node = np.concatenate([x.column("node").to_numpy() for x in held])
            if len(node) < 2:
                return
            fps = np.frombuffer(b"".join(f for x in held for f in x.column("fp").to_pylist()), np.uint64).reshape(len(node), WORDS64)
            a, b = forest([np.frombuffer(s.as_buffer(), np.uint64) for x in held for s in x.column("s")], fps, threshold)
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(node[a]), pa.array(node[b])], names=["a", "b"])

        for batch in batches:
            if not batch.num_rows:
                continue
            keys = np.stack([batch.column(c).to_numpy() for c in ("band", "part")])
            cuts = np.flatnonzero((keys[:, 1:] != keys[:, :-1]).any(axis=0)) + 1
            for lo, hi in zip([0, *cuts], [*cuts, batch.num_rows], strict=True):
                if (at := tuple(keys[:, lo])) != key and held:
                    yield from links()
                    held.clear()
                key = at
                held.append(batch.slice(lo, hi - lo))
        if held:
            yield from links()

    found = dealt.mapInArrow(run, "a bigint, b bigint")
    return found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a <> b").distinct()


def _named(marked: DataFrame, docs: DataFrame, id_col: str, text_col: str, threshold: float, hot: int) -> DataFrame:
    """(same, fp, component_id) of the signatures: groups at the similarity."""
    nodes = written(marked.groupBy("same", "size", "fp", "mins").agg(F.min(id_col).alias("node")), "nodes")
    links = checkpointed(similar_edges(nodes, docs, id_col, text_col, threshold, hot))
    return nodes.join(components(links), "node", "left").select("same", "fp", F.coalesce("root", "node").alias("component_id"))


def _with_id(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("bigint").alias(id_col), F.col(text_col).alias(text_col)).where(F.col(id_col).isNotNull())


def similar_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD, hot: int = HOT) -> DataFrame:
    """(id, component_id) of every row with an id: the smallest id reachable over links at the threshold."""
    marked = written(signatures(_with_id(docs, id_col, text_col), id_col, text_col), "signatures")
    names = _named(marked, docs, id_col, text_col, threshold, hot)
    return marked.select(id_col, "same", "fp").join(names, ["same", "fp"]).select(id_col, "component_id")


def near_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD, hot: int = HOT) -> DataFrame:
    """(id, component_id) of every row with an id: the smallest id reachable over links of 64-bit fingerprints, found by
    pivot tables, and links at the threshold."""
    marked = written(signatures(_with_id(docs, id_col, text_col), id_col, text_col, with_bits=True), "signatures")
    close = components(near_links(checkpointed(marked.select(F.col("bits").alias("fp")).distinct())))  # (node, root) of fingerprints
    names = written(_named(marked, docs, id_col, text_col, threshold, hot), "names")
    both = marked.select("same", "fp", "bits").distinct().join(names, ["same", "fp"]).select("bits", "component_id").distinct()
    both = both.join(close.withColumnRenamed("node", "bits"), "bits", "left").select(F.coalesce("root", "bits").alias("close"), "component_id")
    both = checkpointed(both.distinct())
    heads = checkpointed(both.groupBy("close").agg(F.min("component_id").alias("head"), F.count("*").alias("n")).where("n > 1"))
    many = checkpointed(dealt(heads, "close", both.count()))
    met = salted(both, many, "close", F.col("component_id")).join(repeated(heads.select("close", "head"), many, "close"), ["close", "__salt"])
    joined = components(met.where("component_id <> head").select(F.col("component_id").alias("a"), F.col("head").alias("b")))
    names = names.join(joined.withColumnRenamed("node", "component_id"), "component_id", "left").select("same", "fp", F.coalesce("root", "component_id").alias("component_id"))
    return marked.select(id_col, "same", "fp").join(names, ["same", "fp"]).select(id_col, "component_id")


def one_of_each_group(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD, groups_of: Callable[..., DataFrame] = similar_components) -> DataFrame:
    """docs without all but one document of each group (the smallest id stays), all columns kept.

    Of rows that repeat an id that stays, one stays; rows without id stay.
    """
    groups = checkpointed(groups_of(docs, id_col, text_col, threshold))
    losers = groups.where(f"{id_col} <> component_id").select(F.col(id_col).alias("__loser")).distinct()
    again = checkpointed(groups.groupBy(id_col).count().where(F.col("count") > 1).select(F.col(id_col).alias("__again")))
    stay = docs.join(losers, docs[id_col] == losers["__loser"], "left_anti")
    if again.isEmpty():
        return stay
    once = stay.join(again, stay[id_col] == again["__again"], "left_semi").dropDuplicates([id_col])
    return stay.join(again, stay[id_col] == again["__again"], "left_anti").unionByName(once)
