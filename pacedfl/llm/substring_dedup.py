"""Substring deduplication over a de Bruijn graph of words.

Nodes are runs of WINDOW - 1 words, edges are windows of WINDOW words, and an edge is repeated when two or more
documents hold it. Its source coordinate is where the smallest document holds it first. A node with one repeated
edge in and one out is a through node; paths of repeated edges whose inner nodes are all through nodes do not
branch. Runs of a path that lie together at the source are segments; segments that follow each other across
documents are compacted by Spark joins with pointer doubling. What a document shares with the source is cut at the
nodes that branch, so that every span lies on one path, and a span counts when the digests of its words here and
at its source coordinates are equal.

How it runs. Texts are packed in compressed slices of a few MB, written once as a table bucketed by slice, so that
no later join moves a text.
1. Sieve: every window stands for the smallest hash of its 9-word grams. Slices send each such hash once, 4 bytes, to
   hash bins; bins answer with a bit a hash: seen in two slices, or in two documents of one.
2. Windows that pass are folded within their slice (a later document of the slice points to the first), and the
   rest goes as packed nodes, with the words before and after, to the bins of the nodes.
3. A bin has all edges of its nodes: it finds repeated edges and their sources, in- and out-degrees, and the links
   across through nodes. Answers go back by slice and are cut to spans and segments.
4. Linked segments are compacted; spans, claims on source words and segments meet the slices in one join.
A passage that a third of all documents hold reaches a bin once a slice, not once a document.

Edge cases: null text has no words; texts of fewer than WINDOW words keep all of them; repeats within one
document, and rows with the same doc_id, do not count against each other (rows that share a doc_id are one
document: the same spans are removed from each); rows without doc_id keep all
their words and are no source; words are separated by ASCII white space only.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Callable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, functions as F

from pacedfl.llm.common import WordHash, checkpointed, mix, multipliers, new_path, raw, slices, window_hashes, written

WINDOW = 13
GRAM = 9  # words of the grams that the sieve looks at
SLICE_TEXT = 4 << 20
BUCKET_TEXT = 256 << 20  # a bucket is read by one task, slice after slice
MOST_BUCKETS = 100_000  # Spark's own limit
BIN_BYTES = 16 << 20
_EDGE, _NODE, _GRAM = multipliers(WINDOW, 9), multipliers(WINDOW - 1, 10), multipliers(GRAM, 11)
HAS_NEXT, HAS_PREV, MANY_NEXT, MANY_PREV = 1, 2, 4, 8
HIT = np.dtype([("at", "<i4"), ("slice", "<i8"), ("from", "<i4"), ("through", "u1")])
OWN = np.dtype([("at", "<i4"), ("through", "u1")])
LINK = np.dtype([("at", "<i4"), ("slice", "<i8"), ("to", "<i4")])
PIECE = np.dtype([("at", "<i4"), ("size", "<i4"), ("from", "<i4")])
SPAN, SEGMENT = 0, 1
_WORD = np.uint64((1 << 48) - 1)  # of a neighbour's hash: a node may have a new neighbour in every document


def _runs(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and lengths of runs of equal values."""
    cut = np.flatnonzero(x[1:] != x[:-1]) + 1
    start = np.concatenate([[0], cut]) if len(x) else np.empty(0, np.int64)
    return start.astype(np.int64), np.diff(np.append(start, len(x))).astype(np.int64)


def _bin_of(h: np.ndarray, bits: int) -> np.ndarray:
    return (h >> np.uint64(64 - bits)).astype(np.int64)


def _batch(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], f.type) for i, f in enumerate(schema)], schema=schema)


# ---- slices


def blocks(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(slice, ids, sizes, block): texts of a slice as one compressed block. A table bucketed by slice."""
    spark = docs.sparkSession
    schema = pa.schema([("slice", pa.int64()), ("ids", pa.list_(pa.int64())), ("sizes", pa.list_(pa.int32())), ("block", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=3)
        name = TaskContext.get().partitionId() << 32
        for batch in batches:
            for part in slices(batch, text_col, SLICE_TEXT):
                texts = raw(part, text_col)
                yield _batch([(name, part.column(id_col).to_pylist(), list(map(len, texts)), pack.compress(b"".join(texts)))], schema)
                name += 1

    packed = docs.select(id_col, text_col).mapInArrow(run, "slice bigint, ids array<bigint>, sizes array<int>, block binary")
    table = f"pacedfl_blocks_{uuid.uuid4().hex}"
    size = docs.agg(F.coalesce(F.sum(F.octet_length(text_col)), F.lit(0))).first()[0]
    buckets = min(MOST_BUCKETS, max(int(spark.conf.get("spark.sql.shuffle.partitions")), size // BUCKET_TEXT))
    packed.write.bucketBy(buckets, "slice").option("path", new_path(spark, "blocks")).option("compression", "none").format("parquet").saveAsTable(table)
    found = spark.table(table)
    found.schema  # resolved: the files stay when the name is given back
    spark.sql(f"DROP TABLE {table}")
    return found


class Slice:
    """The texts of a slice; rows that have an identifier, in its order, are one run of word hashes."""

    def __init__(self, ids: list[int | None], sizes: list[int], block: bytes, cache: WordHash | None = None):
        text, end, self.ids, self.words = zstandard.ZstdDecompressor().decompress(block, max_output_size=max(1, sum(sizes))), 0, ids, []
        for n in sizes:
            self.words.append(text[end : end + n].split())
            end += n
        self.rows = sorted((i for i, x in enumerate(ids) if x is not None), key=lambda i: ids[i])
        count = np.array([len(self.words[i]) for i in self.rows], np.int64)
        self.ends = np.cumsum(count)
        self.total = int(count.sum())
        if cache is not None:
            self.hash = np.concatenate([np.empty(0, np.uint64), *(cache.of(self.words[i]) for i in self.rows)])
            self.doc = np.repeat(np.array([ids[i] for i in self.rows], np.int64), count)
            self.edges = np.flatnonzero(np.repeat(self.ends, count) - np.arange(self.total) >= WINDOW)

    def flat(self) -> list[bytes]:
        return list(chain.from_iterable(self.words[i] for i in self.rows))

    def sieve(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(smallest gram hashes, sorted and distinct; held by several documents; place of each edge's hash)."""
        grams = window_hashes(self.hash, _GRAM)
        n = self.total - WINDOW + 1
        if n <= 0 or not len(self.edges):
            return np.empty(0, np.uint64), np.empty(0, bool), np.empty(0, np.int64)
        low = np.minimum.reduce([grams[j : j + n] for j in range(WINDOW - GRAM + 1)])[self.edges]
        order = np.argsort(low, kind="stable")
        start, size = _runs(low[order])
        place = np.empty(len(low), np.int64)
        place[order] = np.repeat(np.arange(len(start)), size)
        doc = self.doc[self.edges]
        return low[order[start]], doc[order[start]] != doc[order[start + size - 1]], place


def _slices_of(batches: Iterator[pa.RecordBatch], hashed: bool = True) -> Iterator[tuple[pa.RecordBatch, int, Slice]]:
    cache = WordHash() if hashed else None
    for batch in batches:
        for i in range(batch.num_rows):
            yield batch, i, Slice(*(batch.column(c)[i].as_py() for c in ("ids", "sizes", "block")), cache)


# ---- 1. the sieve


def passing(packed: DataFrame, bits: int) -> DataFrame:
    """(slice, found): per bin of the slice, a bit for each of its hashes: another document has it too."""
    schema = pa.schema([("bin", pa.int32()), ("slice", pa.int64()), ("n", pa.int32()), ("payload", pa.binary())])

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, i, s in _slices_of(batches):
            low, many, _ = s.sieve()
            start, size = _runs(_bin_of(low, bits))
            short = ((low >> np.uint64(32 - bits)) & np.uint64(0xFFFFFFFF)).astype("<u4")
            name = batch.column("slice")[i].as_py()
            yield _batch([(int(low[a]) >> (64 - bits), name, n, short[a : a + n].tobytes() + np.packbits(many[a : a + n]).tobytes()) for a, n in zip(start.tolist(), size.tolist(), strict=True)], schema)

    answer = pa.schema([("slice", pa.int64()), ("bin", pa.int32()), ("bits", pa.binary())])

    def meet(group: pa.Table) -> pa.Table:
        sizes, rows = group.column("n").to_pylist(), [p.as_buffer() for p in group.column("payload")]
        low = np.concatenate([np.frombuffer(p, "<u4", n) for p, n in zip(rows, sizes, strict=True)])
        many = np.concatenate([np.unpackbits(np.frombuffer(p, np.uint8, offset=4 * n))[:n] for p, n in zip(rows, sizes, strict=True)])
        _, place, count = np.unique(low, return_inverse=True, return_counts=True)
        shared = count > 1
        shared[place[many.astype(bool)]] = True
        out, end = [], 0
        for name, bin_, n in zip(group.column("slice").to_pylist(), group.column("bin").to_pylist(), sizes, strict=True):
            own, end = shared[place[end : end + n]], end + n
            if own.any():
                out.append((name, bin_, np.packbits(own).tobytes()))
        return pa.Table.from_batches([_batch(out, answer)])

    sent = packed.mapInArrow(send, "bin int, slice bigint, n int, payload binary")
    return sent.groupBy("bin").applyInArrow(meet, "slice bigint, bin int, bits binary").groupBy("slice").agg(F.collect_list(F.struct("bin", "bits")).alias("found"))


# ---- 2. nodes


def _pieces(at: np.ndarray, source: np.ndarray) -> bytes:
    """Runs of edges (at ascending) whose sources follow each other, packed."""
    cut = np.append(0, np.cumsum((np.diff(at) != 1) | (np.diff(source) != 1)))[: len(at)]
    start, size = _runs(cut)
    out = np.empty(len(start), PIECE)
    out["at"], out["size"], out["from"] = at[start], size, source[start]
    return out.tobytes()


def _low(x: np.ndarray, n: int) -> bytes:
    """The low n bytes of each number."""
    return np.ascontiguousarray(x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :n]).tobytes()


def _wide(b: bytes, at: int, count: int, n: int) -> np.ndarray:
    out = np.zeros((count, 8), np.uint8)
    out[:, :n] = np.frombuffer(b, np.uint8, n * count, at).reshape(count, n)
    return out.view("<u8").ravel()


def _pack(node: np.ndarray, after: np.ndarray, before: np.ndarray, flags: np.ndarray, at: np.ndarray, doc: np.ndarray) -> bytes:
    """Nodes of one bin and slice: 7 bytes of hash (the bin implies the rest), 6 of each neighbour word, flags, place and
    document."""
    base = int(doc.min())
    wide = 4 if int(doc.max()) - base < 1 << 32 else 8
    return b"".join((np.array([len(node), wide, base], "<i8").tobytes(), _low(node, 7), _low(after, 6), _low(before, 6), flags.astype(np.uint8).tobytes(), at.astype("<i4").tobytes(), (doc - base).astype(f"<u{wide}").tobytes()))


def _unpack(b: bytes) -> tuple[np.ndarray, ...]:
    """(node, after, before, flags, at, doc)."""
    n, wide, base = np.frombuffer(b, "<i8", 3).tolist()
    o = 24 + n * np.cumsum([0, 7, 6, 6, 1, 4])
    doc = np.frombuffer(b, f"<u{wide}", n, o[5]).astype(np.int64) + base
    return _wide(b, o[0], n, 7), _wide(b, o[1], n, 6), _wide(b, o[2], n, 6), np.frombuffer(b, np.uint8, n, o[3]), np.frombuffer(b, "<i4", n, o[4]), doc


def _nodes_of(s: Slice, candidates: np.ndarray) -> tuple[tuple[np.ndarray, ...], bytes]:
    """Nodes to send (node, after, before, flags, at, doc), and pieces that a smaller document of the slice has."""
    edge, node = window_hashes(s.hash, _EDGE), window_hashes(s.hash, _NODE)
    at = s.edges[candidates]
    order = np.argsort(edge[at], kind="stable")
    start, size = _runs(edge[at][order])
    here, lead = at[order], np.repeat(at[order[start]], size)
    later = (s.doc[here] > s.doc[lead]) & (s.hash[here] == s.hash[lead]) & (node[here + 1] == node[lead + 1])
    several = np.repeat(np.logical_or.reduceat(later, start), size) if len(start) else later
    keep, many = np.zeros(s.total + 1, bool), np.zeros(s.total + 1, bool)
    keep[here[~later]] = True
    many[here[several]] = True
    follows = np.append(False, keep[:-1])
    q = np.flatnonzero(keep | follows)
    has_next, has_prev = keep[q], follows[q]
    flags = has_next * HAS_NEXT + has_prev * HAS_PREV + (has_next & many[q]) * MANY_NEXT + (has_prev & many[q - 1]) * MANY_PREV
    word = lambda k: s.hash[np.clip(k, 0, s.total - 1)] & _WORD
    sent = (node[q], word(q + WINDOW - 1), word(q - 1), flags, q, s.doc[q])
    by = np.argsort(here[later], kind="stable")
    return sent, _pieces(here[later][by], lead[later][by])


def graph_answers(packed: DataFrame, found: DataFrame, bits: int) -> DataFrame:
    """(slice, hits, owned, links, pieces): packed arrays for the slice; pieces are those resolved within it."""
    schema = pa.schema([("bin", pa.int32()), ("slice", pa.int64()), ("payload", pa.binary()), ("pieces", pa.binary())])

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, i, s in _slices_of(batches):
            low, _, place = s.sieve()
            first, size = _runs(_bin_of(low, bits))
            bounds = dict(zip((low[first] >> np.uint64(64 - bits)).tolist(), zip(first.tolist(), size.tolist(), strict=True), strict=True))
            good = np.zeros(len(low), bool)
            for x in batch.column("found")[i].as_py():
                a, n = bounds[x["bin"]]
                good[a : a + n] = np.unpackbits(np.frombuffer(x["bits"], np.uint8))[:n]
            (node, *others), pieces = _nodes_of(s, np.flatnonzero(good[place]))
            name = batch.column("slice")[i].as_py()
            rows = [(name % (1 << bits), name, None, pieces)] if pieces else []
            bins = _bin_of(node, bits)
            order = np.argsort(bins, kind="stable")
            for a, n in zip(*(x.tolist() for x in _runs(bins[order])), strict=True):
                k = order[a : a + n]
                rows.append((int(bins[k[0]]), name, _pack(node[k], *(x[k] for x in others)), None))
            yield _batch(rows, schema)

    answer = pa.schema([("slice", pa.int64()), *((c, pa.binary()) for c in ("hits", "owned", "links", "pieces"))])

    def meet(group: pa.Table) -> pa.Table:
        out, names, held = [], [], []
        for name, payload, pieces in zip(group.column("slice").to_pylist(), group.column("payload"), group.column("pieces").to_pylist(), strict=True):
            if pieces is not None:
                out.append((name, None, None, None, pieces))
            else:
                held.append(_unpack(payload.as_buffer()))
                names.append(name)
        if held:
            sizes = [len(x[0]) for x in held]
            columns = [np.concatenate(x) for x in zip(*held, strict=True)]
            held.clear()
            out += _bin_answers(np.repeat(np.array(names, np.int64), sizes), *columns)
        return pa.Table.from_batches([_batch(out, answer)])

    sent = packed.join(found, "slice").select("slice", "ids", "sizes", "block", "found").mapInArrow(send, "bin int, slice bigint, payload binary, pieces binary")
    return sent.groupBy("bin").applyInArrow(meet, "slice bigint, hits binary, owned binary, links binary, pieces binary")


# ---- 3. edges, degrees, sources


def _edge_keys(node: np.ndarray, word: np.ndarray) -> np.ndarray:
    return mix(node.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + mix(word * np.uint64(0xD6E8FEB86659FD93)))


def _edges_at(key: np.ndarray, doc: np.ndarray, many: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of occurrences in order of coordinates: (order by edge, starts, sizes, repeated) of the distinct edges."""
    order = np.argsort(key, kind="stable")
    start, size = _runs(key[order])
    if not len(start):
        return order, start, size, np.empty(0, bool)
    return order, start, size, (doc[order[start]] != doc[order[start + size - 1]]) | np.logical_or.reduceat(many[order], start)


def _bin_answers(names, node, after, before, flags, at, doc) -> list[tuple]:
    """Answers of one bin: a row for each slice that has any."""
    order = np.lexsort((at, names, doc))
    names, node, after, before, flags, at, doc = (x[order] for x in (names, node, after, before, flags, at, doc))
    distinct, node = np.unique(node, return_inverse=True)
    out_of = np.flatnonzero(flags & HAS_NEXT)
    o, start, size, repeated = _edges_at(_edge_keys(node[out_of], after[out_of]), doc[out_of], (flags[out_of] & MANY_NEXT) > 0)
    o = out_of[o]
    source = o[start]
    into = np.flatnonzero(flags & HAS_PREV)
    i, start_in, _, repeated_in = _edges_at(_edge_keys(node[into], before[into]), doc[into], (flags[into] & MANY_PREV) > 0)
    source_in = into[i][start_in][repeated_in]
    degree = np.bincount(node[source[repeated]], minlength=len(distinct)), np.bincount(node[source_in], minlength=len(distinct))
    through = (degree[0] == 1) & (degree[1] == 1)
    # occurrences that a smaller document has
    lead = np.repeat(source, size)
    hit = np.flatnonzero(np.repeat(repeated, size) & (doc[o] > doc[lead]))
    hit, lead = o[hit], lead[hit]
    hits = np.empty(len(hit), HIT)
    hits["at"], hits["slice"], hits["from"], hits["through"] = at[hit], names[lead], at[lead], through[node[hit]]
    owner = source[repeated]
    owned = np.empty(len(owner), OWN)
    owned["at"], owned["through"] = at[owner], through[node[owner]]
    # where the path goes on at another place than its edge before
    ends, begins = np.full(len(distinct), -1), np.full(len(distinct), -1)
    ends[node[source_in]], begins[node[owner]] = source_in, owner
    moved = np.flatnonzero(through & (ends != begins))
    links = np.empty(len(moved), LINK)
    links["at"], links["slice"], links["to"] = at[ends[moved]] - 1, names[begins[moved]], at[begins[moved]]
    rows: dict[int, list] = {}
    for k, (who, what) in enumerate(((names[hit], hits), (names[owner], owned), (names[ends[moved]], links))):
        by = np.argsort(who, kind="stable")
        for a, n in zip(*(x.tolist() for x in _runs(who[by])), strict=True):
            rows.setdefault(int(who[by[a]]), [None, None, None, None])[k] = what[by[a : a + n]].tobytes()
    return [(name, *x) for name, x in rows.items()]


def cut_to_paths(answers: DataFrame) -> DataFrame:
    """(kind, slice, at, size, from_slice, from_at): spans with their source, segments with what follows them."""
    schema = pa.schema([("kind", pa.int32()), ("slice", pa.int64()), ("at", pa.int32()), ("size", pa.int32()), ("from_slice", pa.int64()), ("from_at", pa.int32())])
    names = ("hits", "owned", "links", "pieces")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                name = batch.column("slice")[i].as_py()
                hits, owned, links, pieces = (np.frombuffer(b"".join(batch.column(c)[i].as_py()), t) for c, t in zip(names, (HIT, OWN, LINK, PIECE), strict=True))
                hits, owned = hits[np.argsort(hits["at"])], owned[np.argsort(owned["at"])]
                follows = (np.diff(hits["at"]) == 1) & (np.diff(hits["from"]) == 1) & (np.diff(hits["slice"]) == 0) & (hits["through"][1:] == 1)
                start, size = _runs(np.append(0, np.cumsum(~follows))[: len(hits)])
                spans = [np.concatenate(x) for x in ((hits["at"][start], pieces["at"]), (size, pieces["size"]), (hits["slice"][start], np.full(len(pieces), name)), (hits["from"][start], pieces["from"]))]
                follows = (np.diff(owned["at"]) == 1) & (owned["through"][1:] == 1)
                start, size = _runs(np.append(0, np.cumsum(~follows))[: len(owned)])
                last = owned["at"][start] + size - 1
                links = links[np.argsort(links["at"])]
                k = np.minimum(np.searchsorted(links["at"], last), max(0, len(links) - 1))
                linked = links["at"][k] == last if len(links) else np.zeros(len(last), bool)
                follow = [pa.array(links[c][k] if len(links) else np.zeros(len(last), np.int64), t, mask=~linked) for c, t in (("slice", pa.int64()), ("to", pa.int32()))]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(spans[0]), SPAN), pa.int32()), pa.array(np.full(len(spans[0]), name), pa.int64()), *(pa.array(x, t) for x, t in zip(spans, (pa.int32(), pa.int32(), pa.int64(), pa.int32()), strict=True))], schema=schema)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(start), SEGMENT), pa.int32()), pa.array(np.full(len(start), name), pa.int64()), pa.array(owned["at"][start], pa.int32()), pa.array(size, pa.int32()), *follow], schema=schema)

    grouped = answers.groupBy("slice").agg(*(F.collect_list(c).alias(c) for c in names))
    return grouped.mapInArrow(run, "kind int, slice bigint, at int, size int, from_slice bigint, from_at int")


# ---- 4. compaction and verification


def path_heads(segments: DataFrame) -> DataFrame:
    """(slice, at, head, before): of every segment that continues another, the first segment of its path and the
    number of edges from there; pointers to the segment before double their reach in each join. A path that closes
    on itself begins at its smallest coordinate."""
    here, done = F.struct("slice", "at"), None
    step = segments.where("from_slice is not null").select(F.col("from_slice").alias("slice"), F.col("from_at").alias("at"), here.alias("head"), F.col("size").cast("bigint").alias("before"))
    step = checkpointed(step.withColumn("least", F.least("head", here)))
    while n := step.count():
        known, reach = step, 1
        while True:
            up = known.select(here.alias("head"), F.col("head").alias("further"), F.col("before").alias("more"), F.col("least").alias("other"))
            known = checkpointed(known.join(up, "head", "left").select("slice", "at", F.coalesce("further", "head").alias("head"), (F.col("before") + F.coalesce("more", F.lit(0))).alias("before"), F.least("least", "other").alias("least"), F.col("further").isNotNull().alias("moved")))
            reach *= 2
            if reach > 2 * n or known.where("moved").isEmpty():
                break
        settled = known.where("not moved").select("slice", "at", "head", "before")
        done = settled if done is None else done.union(settled)
        rounds = known.where("moved").select("slice", "at", "least")
        step = checkpointed(step.drop("least").join(rounds, ["slice", "at"]).where(here != F.col("least")).select("slice", "at", "head", "before", "least"))
    return done if done is not None else step.select("slice", "at", "head", "before")


def paths(segments: DataFrame) -> DataFrame:
    """(slice, at, size, head, before) of every segment: the head of its path and how many edges of it come before."""
    heads = path_heads(segments)
    return segments.select("slice", "at", "size").join(heads, ["slice", "at"], "left").select("slice", "at", "size", F.coalesce("head", F.struct("slice", "at")).alias("head"), F.coalesce("before", F.lit(0)).alias("before"))


def _digest(words: list[bytes]) -> bytes:
    return hashlib.blake2b(b" ".join(words), digest_size=16).digest()


def kept_words(words: list[bytes], gone: np.ndarray) -> list[bytes]:
    return [w for w, g in zip(words, gone.tolist(), strict=True) if not g]


def _applied(packed: DataFrame, spans: DataFrame, segments: DataFrame, id_col: str) -> DataFrame:
    """Rows of two kinds. Per document (slice null): id, n_words, n_removed, kept_sha256 with its spans applied.
    Per span, and per claim on source words that lies on one path: source slice, at, size, digest, and where the span is
    (null for the source itself). Spans within a slice are compared there."""
    nothing = F.lit(None).cast("bigint"), F.lit(None).cast("int")
    own = spans.select("slice", F.struct(F.lit("own").alias("role"), "at", "size", "from_slice", "from_at").alias("x"))
    asked = spans.where("from_slice <> slice").select(F.col("from_slice").alias("slice"), F.struct(F.lit("asked").alias("role"), F.col("from_at").alias("at"), "size", nothing[0].alias("from_slice"), nothing[1].alias("from_at")).alias("x")).distinct()
    laid = segments.select("slice", F.struct(F.lit("path").alias("role"), "at", "size", nothing[0].alias("from_slice"), nothing[1].alias("from_at")).alias("x"))
    wanted = own.union(asked).union(laid).groupBy("slice").agg(F.collect_list("x").alias("wanted"))
    schema = pa.schema([(id_col, pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string()), ("slice", pa.int64()), ("at", pa.int32()), ("size", pa.int32()), ("digest", pa.binary()), ("own_slice", pa.int64()), ("own_at", pa.int32())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, i, s in _slices_of(batches, hashed=False):
            name, flat, rows = batch.column("slice")[i].as_py(), s.flat(), []
            wanted = batch.column("wanted")[i].as_py() or []
            laid = np.array(sorted((x["at"], x["at"] + x["size"]) for x in wanted if x["role"] == "path"), np.int64).reshape(-1, 2)
            gone = np.zeros(s.total + 1, np.int64)
            for x in wanted:
                a, b = x["at"], x["at"] + x["size"] + WINDOW - 1
                if x["role"] == "own":
                    if x["from_slice"] == name:
                        if flat[a:b] != flat[x["from_at"] : x["from_at"] + b - a]:
                            continue
                    else:
                        rows.append((None, None, None, None, x["from_slice"], x["from_at"], x["size"], _digest(flat[a:b]), name, a))
                    gone[a] += 1
                    gone[b] -= 1
                elif x["role"] == "asked" and (k := int(np.searchsorted(laid[:, 0], a, "right")) - 1) >= 0 and a + x["size"] <= laid[k, 1]:
                    rows.append((None, None, None, None, name, a, x["size"], _digest(flat[a:b]), None, None))
            covered, end = np.cumsum(gone[:-1]) > 0, dict(zip(s.rows, s.ends.tolist(), strict=True))
            for r, words in enumerate(s.words):
                mask = covered[end[r] - len(words) : end[r]] if r in end else np.zeros(0, bool)
                kept = kept_words(words, mask) if mask.any() else words
                rows.append((s.ids[r], len(words), len(words) - len(kept), hashlib.sha256(b" ".join(kept)).hexdigest(), *[None] * 6))
            yield _batch(rows, schema)

    kinds = f"{id_col} bigint, n_words bigint, n_removed bigint, kept_sha256 string, slice bigint, at int, size int, digest binary, own_slice bigint, own_at int"
    return packed.join(wanted, "slice", "left").select("slice", "ids", "sizes", "block", "wanted").mapInArrow(run, kinds)


def bin_bits(packed: DataFrame, bin_bytes: int = BIN_BYTES) -> int:
    """Bits of hash that name a bin, so that a bin holds the windows of about bin_bytes of text; 8 to 24."""
    size = packed.select(F.explode("sizes").alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    return min(24, max(8, int(size // bin_bytes).bit_length()))


def repeated_spans(packed: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(spans, segments) of a table of slices; segments are those of the compacted paths."""
    bits = bin_bits(packed)
    found = written(cut_to_paths(graph_answers(packed, passing(packed, bits), bits)), "spans")
    return found.where(F.col("kind") == SPAN).drop("kind"), written(paths(found.where(F.col("kind") == SEGMENT)), "paths")


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", find: Callable = repeated_spans) -> DataFrame:
    """id, n_words, n_removed and kept_sha256 of every row, after removing words of repeated windows."""
    packed = blocks(docs.select(F.col(id_col).cast("bigint").alias(id_col), F.col(text_col).alias(text_col)), id_col, text_col)
    spans, segments = find(packed)
    done = written(_applied(packed, spans, segments, id_col), "kept")
    claim = ["slice", "at", "size", "digest"]
    claims = done.where("own_slice is not null").groupBy(*claim).agg(F.count("*").alias("n")).drop("n")
    wrong = written(claims.join(done.where("slice is not null and own_slice is null").select(*claim), claim, "left_anti"), "unverified")
    rows = done.where("slice is null").select(id_col, "n_words", "n_removed", "kept_sha256")
    if wrong.isEmpty():
        return rows
    # hash collisions: everything again with verified spans only
    bad = written(done.where("own_slice is not null").join(wrong, claim, "left_semi").select(F.col("own_slice").alias("slice"), F.col("own_at").alias("at"), "size").distinct(), "bad")
    again = _applied(packed, spans.join(bad, ["slice", "at", "size"], "left_anti"), segments, id_col)
    return again.where("slice is null").select(id_col, "n_words", "n_removed", "kept_sha256")


def repeated_paths(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, start_word, words, path, before) for each segment of each repeated path: where its words lie in the source
    document, the path as text `slice:offset` of its head, and the edges of the path before this segment."""
    packed = blocks(docs.select(F.col(id_col).cast("bigint").alias(id_col), F.col(text_col).alias(text_col)), id_col, text_col)
    segments = repeated_spans(packed)[1]
    laid = segments.select("slice", F.struct("at", "size", F.concat_ws(":", "head.slice", "head.at").alias("path"), "before").alias("x")).groupBy("slice").agg(F.collect_list("x").alias("laid"))
    schema = pa.schema([(id_col, pa.int64()), ("start_word", pa.int64()), ("words", pa.int64()), ("path", pa.string()), ("before", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, i, s in _slices_of(batches, hashed=False):
            rows = []
            for x in batch.column("laid")[i].as_py():
                r = int(np.searchsorted(s.ends, x["at"], "right"))
                start = int(s.ends[r - 1]) if r else 0
                rows.append((s.ids[s.rows[r]], x["at"] - start, x["size"] + WINDOW - 1, x["path"], x["before"]))
            yield _batch(rows, schema)

    return packed.join(laid, "slice").select("slice", "ids", "sizes", "block", "laid").mapInArrow(run, f"{id_col} bigint, start_word bigint, words bigint, path string, before bigint")
