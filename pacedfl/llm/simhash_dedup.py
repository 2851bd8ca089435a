"""SimHash near-duplicates by pivot distance tables.

Every distinct fingerprint gets a table row of Hamming distances to PIVOTS reference fingerprints. By the
triangle inequality a pair within RADIUS differs by at most RADIUS in every coordinate; pairs that differ
more in any coordinate are discarded, and the survivors are verified on the fingerprints themselves.
Pairs are only looked at within blocks of equal bits: of BLOCKS blocks of a fingerprint, two fingerprints
within RADIUS agree on at least BLOCKS - RADIUS, so one of the keys made of that many blocks is equal.

A key shared by more than HOT distinct fingerprints is split again by the bits that it leaves free; after
that a group can hold at most 2^18 distinct fingerprints, whatever the size of the input. A group sends out
a spanning forest of its links, never all its pairs. Exact copies share one fingerprint and are folded
before anything else. Connected components are found by min-label propagation with pointer jumping.

Edge cases: null or empty text has fingerprint 0 and links like any other; null identifiers get a
component only through rows that have one, else null; repeated rows give repeated results.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, functions as F

from pacedfl.llm.common import checkpointed, dealt, mix, popcount, raw, repeated, salted, slices

RADIUS = 3
PIVOTS = 12
BLOCKS = 5
SPLIT_BLOCKS = 7
HOT = 30_000
ALL = (1 << 64) - 1
_PIVOTS = mix(np.arange(1, PIVOTS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def fingerprint(text: bytes, size: int = 3) -> int:
    """Bit i is set if it is set in over half of the hashes of the text's word shingles, repeats included."""
    words = text.lower().split()
    if not words:
        return 0
    if len(words) < size:
        shingles = [b" ".join(words)]
    else:
        shingles = list(map(b" ".join, zip(*(words[i:] for i in range(size)))))  # noqa: B905
    digest = xxhash.xxh64_digest
    packed = b"".join([digest(s, 42) for s in shingles])
    bits = np.zeros(64, np.int64)
    for a in range(0, len(packed), 8 << 16):
        part = np.frombuffer(packed[a : a + (8 << 16)], np.uint8).reshape(-1, 8)
        bits += np.unpackbits(part, axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * bits > len(shingles)).tobytes(), "big")


def fingerprints(docs: DataFrame, keep: list[str] | None = None, id_col: str = "doc_id", text_col: str = "text", size: int = 3) -> DataFrame:
    """(id, fp bigint) for every row, or the columns keep and fp; no shuffle."""
    keep = keep or [id_col]
    schema = docs.select(*keep).schema.add("fp", "long")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, text_col):
                fps = np.fromiter((fingerprint(t, size) for t in raw(part, text_col)), np.uint64, part.num_rows).view(np.int64)
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), pa.array(fps)], names=[*keep, "fp"])

    return docs.select(*dict.fromkeys([*keep, text_col])).mapInArrow(run, schema)


def _blocks(free: int, count: int) -> list[int]:
    """The set bits of free as count masks of nearly equal size."""
    bits = [i for i in range(64) if free >> i & 1]
    return [sum(1 << i for i in part.tolist()) for part in np.array_split(np.array(bits, dtype=object), count)]


def _masks(free: int, count: int) -> list[int]:
    """Masks that keep all bits outside free and all but RADIUS blocks of it."""
    return [ALL & ~sum(left) for left in combinations(_blocks(free, count), RADIUS)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _keyed(fps: DataFrame, masks: Column) -> DataFrame:
    rows = fps.select("fp", F.explode(masks).alias("mask"))
    return rows.select("fp", "mask", F.col("mask").bitwiseAND(F.col("fp")).alias("value"))


def _forest(fps: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Edges of a spanning forest of the links among distinct fingerprints (each to its root)."""
    fps = np.sort(fps)
    table = popcount(fps[:, None] ^ _PIVOTS[None, :]).astype(np.int8)
    order = np.argsort(table[:, 0], kind="stable")
    fps, table = fps[order], table[order]
    n, root = len(fps), np.arange(len(fps))
    ends = np.searchsorted(table[:, 0], table[:, 0] + RADIUS, side="right")
    step = max(1, (1 << 20) // max(1, n))
    for a in range(0, n, step):
        b = min(n, a + step)
        hi = int(ends[b - 1])
        near = np.ones((b - a, hi - a), bool)
        for p in range(PIVOTS):  # each coordinate discards pairs
            near &= np.abs(table[a:b, p, None] - table[None, a:hi, p]) <= RADIUS
        i, j = np.nonzero(near)
        i, j = i[i < j] + a, j[i < j] + a
        good = popcount(fps[i] ^ fps[j]) <= RADIUS
        i, j = i[good], j[good]
        while len(i):  # hook the larger root to the smaller until the pairs agree
            ri, rj = root[i], root[j]
            apart = ri != rj
            if not apart.any():
                break
            i, j, ri, rj = i[apart], j[apart], ri[apart], rj[apart]
            np.minimum.at(root, np.maximum(ri, rj), np.minimum(ri, rj))
            while (root[root] != root).any():
                root = root[root]
    linked = np.flatnonzero(root != np.arange(n))
    return fps[linked], fps[root[linked]]


def _links_in_groups(keyed: DataFrame) -> DataFrame:
    groups = keyed.groupBy("mask", "value").agg(F.collect_list("fp").alias("fps")).where(F.size("fps") > 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [_forest(np.unique(x.values.to_numpy(zero_copy_only=False).view(np.uint64))) for x in batch.column("fps")]
            if found:
                a, b = (np.concatenate(x).view(np.int64) for x in zip(*found, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])

    return groups.select("fps").mapInArrow(run, "a bigint, b bigint")


def near_links(fps: DataFrame, hot: int = HOT) -> DataFrame:
    """Links (a, b) between distinct fingerprints that connect all pairs within RADIUS bits."""
    level = _masks(ALL, BLOCKS)
    keyed = _keyed(fps, F.array(*(F.lit(_signed(m)) for m in level)))
    crowded = checkpointed(keyed.groupBy("mask", "value").count().where(F.col("count") > hot).drop("count"))
    if crowded.isEmpty():
        return _links_in_groups(keyed).distinct()
    within = keyed.join(crowded, ["mask", "value"], "left_semi")
    finer = F.create_map(*(x for m in level for x in (F.lit(_signed(m)), F.array(*(F.lit(_signed(s)) for s in _masks(ALL & ~m, SPLIT_BLOCKS))))))
    split = within.select("fp", F.explode(finer[F.col("mask")]).alias("mask"))
    split = split.select("fp", "mask", F.col("mask").bitwiseAND(F.col("fp")).alias("value"))
    calm = keyed.join(crowded, ["mask", "value"], "left_anti")
    return _links_in_groups(calm).union(_links_in_groups(split)).distinct()


def components(links: DataFrame) -> DataFrame:
    """(node, root) of every node that has a link; root is the smallest node of its component. A node with a large share
    of the links is dealt over several tasks. Labels only fall, so the rounds end."""
    both = links.select("a", "b").union(links.select("b", "a")).where("a <> b").distinct()
    both = checkpointed(both)
    hot = checkpointed(dealt(both.groupBy("b").agg(F.count("*").alias("n")), "b", both.count()))
    both = checkpointed(salted(both, hot, "b", F.col("a")))
    label = checkpointed(both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("root")).withColumnRenamed("a", "node"))
    while True:
        seen = both.join(repeated(label.withColumnRenamed("node", "b"), hot, "b"), ["b", "__salt"]).groupBy("a").agg(F.min("root").alias("seen"))
        moved = label.join(seen.withColumnRenamed("a", "node"), "node").select("node", F.col("root").alias("old"), F.least("root", "seen").alias("root"))
        up = label.select(F.col("node").alias("root"), F.col("root").alias("up"))
        new = checkpointed(moved.join(up, "root", "left").select("node", "old", F.least("root", F.coalesce("up", "root")).alias("root")))
        label = new.select("node", "root")
        if new.where("root <> old").isEmpty():
            return label


def pivot_counts(fps: np.ndarray) -> list[int]:
    """Pairs of the distinct fingerprints given: all, those that each further pivot leaves, and those within RADIUS.
    For reports on how much the pivots discard; quadratic."""
    i, j = np.triu_indices(len(fps), 1)
    out, table = [len(i)], popcount(fps[:, None] ^ _PIVOTS[None, :]).astype(np.int16)
    for p in range(PIVOTS):
        near = np.abs(table[i, p] - table[j, p]) <= RADIUS
        i, j = i[near], j[near]
        out.append(len(i))
    return [*out, int((popcount(fps[i] ^ fps[j]) <= RADIUS).sum())]


def near_duplicate_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", hot: int = HOT, size: int = 3) -> DataFrame:
    """id, fingerprint (16 hex digits) and component_id (smallest id reachable) for every row."""
    marked = checkpointed(fingerprints(docs.select(F.col(id_col).cast("bigint").alias(id_col), F.col(text_col).alias(text_col)), None, id_col, text_col, size))
    nodes = checkpointed(marked.groupBy("fp").agg(F.min(id_col).alias("first"), F.count("*").alias("n")))
    roots = components(near_links(nodes.select("fp"), hot))
    placed = nodes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    names = placed.groupBy("root").agg(F.min("first").alias("component_id"))
    by_fp = placed.join(names, "root").select("fp", "component_id")
    # copies of one text, or empty texts, may be a third of all rows
    many = checkpointed(dealt(nodes, "fp", nodes.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]))
    rows = salted(marked, many, "fp", F.col(id_col)).join(repeated(by_fp, many, "fp"), ["fp", "__salt"])
    return rows.select(id_col, F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
