"""Benchmark decontamination: SimHash over item-sized windows, a multi-index, and an exact check.

For every item length there is a multi-index over the items' 64-bit SimHash fingerprints: of BLOCKS blocks, two
fingerprints within RADIUS have one that differs in at most RADIUS // BLOCKS bits, and such a block is found by
flipping half of these bits on either side: sorted lists hold the items' blocks under HALF flips, and a window looks its
own blocks up under HALF flips. So every fingerprint within RADIUS is found; of unrelated ones a seventh is. A pair at
the similarity differs in 10 bits on average, with a deviation of 3. Windows of that many words slide over each whole text, and
windows found in the index are verified by the weighted Jaccard similarity of their word shingles (weights
are multiplicities). Windows that share fewer shingles with an item than the similarity asks for are skipped
before hashing; that loses nothing, as they could not pass the check.

Edge cases: items without words are never found, and null texts hold nothing; items shorter than a shingle
match where the same words follow each other; a text shorter than the item is one window; equal items are
all reported; items without identifier are looked for like any other and reported with a null one. The
benchmark is broadcast in slices of at most SLICE_ITEMS items and SLICE_TEXT bytes; a larger benchmark is
handled slice after slice.
"""

from __future__ import annotations

from collections import Counter, defaultdict
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from pacedfl.llm.common import WordHash, multipliers, popcount, slices, texts, window_hashes

SHINGLE = 5
SIMILARITY = 0.8
RADIUS = 19
BLOCKS = 4
HALF = -(-(RADIUS // BLOCKS) // 2)
SLICE_ITEMS = 5000
SLICE_TEXT = 8 << 20
_CONSTANTS = multipliers(SHINGLE, 3)
_WHOLE = multipliers(SHINGLE, 4)  # for items shorter than a shingle
_SIEVE_BITS = 20


def words_of(text: str) -> list[bytes]:
    return text.lower().encode().split()


def shingles_of(h: np.ndarray) -> np.ndarray:
    """Hashes of the word shingles; of the whole sequence where there are fewer words."""
    return window_hashes(h, _CONSTANTS) if len(h) >= SHINGLE else window_hashes(h, _WHOLE[: len(h)]) if len(h) else h


def simhash_windows(shingles: np.ndarray, starts: np.ndarray, size: int) -> np.ndarray:
    """Fingerprints of the runs of size shingles that begin at starts."""
    lo, hi = int(starts.min()), int(starts.max()) + size
    bits = np.unpackbits(shingles[lo:hi].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).astype(np.int32)
    sums = np.zeros((hi - lo + 1, 64), np.int32)
    np.cumsum(bits, axis=0, out=sums[1:])
    on = 2 * (sums[starts - lo + size] - sums[starts - lo]) > size
    return np.packbits(on, axis=1).view(">u8").ravel().astype(np.uint64)


def similarity(a: np.ndarray, b: np.ndarray) -> float:
    """Weighted Jaccard similarity of two multisets of shingles."""
    x, y = Counter(a.tolist()), Counter(b.tolist())
    return (x & y).total() / max(1, (x | y).total())


_WIDTH = 64 // BLOCKS
_FLIPS = np.array([sum(1 << b for b in c) for n in range(HALF + 1) for c in combinations(range(_WIDTH), n)], np.uint64)


def _blocks(fingerprints: np.ndarray, k: int) -> np.ndarray:
    """Block k of each fingerprint under all flips, row by row."""
    part = (fingerprints >> np.uint64(_WIDTH * k)) & np.uint64((1 << _WIDTH) - 1)
    return (part[:, None] ^ _FLIPS).astype(np.uint16).ravel()


class MultiIndex:
    """Positions of fingerprints within RADIUS bits, found by blocks."""

    def __init__(self, fingerprints: np.ndarray):
        self.fingerprints, self.lists = fingerprints, []
        for k in range(BLOCKS):
            value = _blocks(fingerprints, k)
            order = np.argsort(value, kind="stable")
            self.lists.append((value[order], (order // len(_FLIPS)).astype(np.int32)))

    def candidates(self, found: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(window, item) pairs that have a block within HALF flips of each other's, each once."""
        pairs = []
        for k, (value, item) in enumerate(self.lists):
            asked = _blocks(found, k)
            lo, hi = np.searchsorted(value, asked), np.searchsorted(value, asked, side="right")
            n = hi - lo
            at = np.repeat(lo - np.cumsum(n) + n, n) + np.arange(n.sum())
            pairs.append(np.unique(np.repeat(np.arange(len(asked)) // len(_FLIPS), n) * len(self.fingerprints) + item[at]))
        both = np.unique(np.concatenate(pairs))
        return both // len(self.fingerprints), both % len(self.fingerprints)

    def within(self, found: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(window, item, distance) for all pairs within RADIUS."""
        w, i = self.candidates(found)
        d = popcount(found[w] ^ self.fingerprints[i])
        good = d <= RADIUS
        return w[good], i[good], d[good]


class BenchmarkIndex:
    """A slice of benchmark items, ready to be looked for in texts."""

    def __init__(self, items: list[tuple[int | None, str]], threshold: float = SIMILARITY):
        cache = WordHash()
        self.threshold = threshold
        hashed = [(i, cache.of(words_of(t or ""))) for i, t in items]
        hashed = sorted(((i, h) for i, h in hashed if len(h)), key=lambda x: (len(x[1]), x[0] is None, x[0] or 0))
        self.ids = np.array([i for i, _ in hashed], object)
        self.sizes = [len(h) for _, h in hashed]
        self.shingles = [shingles_of(h) for _, h in hashed]
        self.index: dict[int, tuple[int, MultiIndex]] = {}
        for size in sorted(set(self.sizes)):
            own = [k for k, s in enumerate(self.sizes) if s == size]
            prints = [simhash_windows(self.shingles[k], np.array([0]), len(self.shingles[k]))[0] for k in own]
            self.index[size] = (own[0], MultiIndex(np.array(prints, np.uint64)))
        pairs = sorted({(int(s), k) for k, sh in enumerate(self.shingles) for s in sh.tolist()})
        self.keys, first = np.unique(np.array([s for s, _ in pairs], np.uint64), return_index=True)
        self.owner, self.bounds = np.array([k for _, k in pairs], np.int64), np.append(first, len(pairs))
        self.sieve = np.zeros(1 << _SIEVE_BITS, bool)
        self.sieve[(self.keys & np.uint64((1 << _SIEVE_BITS) - 1)).astype(np.int64)] = True
        self.short = sorted({s for s in self.sizes if s < SHINGLE})

    def _known(self, shingles: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions of shingles that some item has, and their places in keys."""
        at = np.flatnonzero(self.sieve[(shingles & np.uint64((1 << _SIEVE_BITS) - 1)).astype(np.int64)])
        place = np.minimum(np.searchsorted(self.keys, shingles[at]), max(0, len(self.keys) - 1))
        good = self.keys[place] == shingles[at] if len(self.keys) else np.zeros(len(at), bool)
        return at[good], place[good]

    def find(self, h: np.ndarray) -> list[tuple[int | None, float, int, int, int]]:
        """Of word hashes of a text: (item id, similarity, first word, words, distance), best window of each item."""
        best: dict[int, tuple[float, int, int, int]] = {}
        if not len(h) or not len(self.ids):
            return []
        for size in self.short:
            if len(h) >= size:
                self._look(window_hashes(h, _WHOLE[:size]), len(h), size, best)
        if len(h) >= SHINGLE:
            self._look(shingles_of(h), len(h), None, best)
        return [(self.ids[k], s, a, n, d) for k, (s, a, n, d) in sorted(best.items())]

    def _look(self, shingles: np.ndarray, n_words: int, short: int | None, best: dict) -> None:
        at, place = self._known(shingles)
        if not len(at):
            return
        hits: dict[int, list[int]] = defaultdict(list)
        for p, k in zip(at.tolist(), place.tolist(), strict=True):
            for item in self.owner[self.bounds[k] : self.bounds[k + 1]].tolist():
                hits[item].append(p)
        sizes = set()
        for item, where in hits.items():
            if (self.sizes[item] == short if short else self.sizes[item] >= SHINGLE) and len(where) >= self.threshold * len(self.shingles[item]):
                sizes.add(self.sizes[item])
        for size in sizes:
            span = 1 if short else min(size, n_words) - SHINGLE + 1
            first, index = self.index[size]
            marked = np.zeros(len(shingles) + 1, np.int64)
            seen = sorted({p for item, where in hits.items() if self.sizes[item] == size for p in where})
            marked[np.array(seen) + 1] = 1
            inside = np.cumsum(marked)
            starts = np.flatnonzero(inside[span:] - inside[:-span] >= self.threshold * (1 if short else size - SHINGLE + 1))
            for k in range(0, len(starts), 1 << 10):
                part = starts[k : k + (1 << 10)]
                for w, i, d in zip(*index.within(simhash_windows(shingles, part, span)), strict=True):
                    a, item = int(part[w]), first + int(i)
                    s = similarity(shingles[a : a + span], self.shingles[item])
                    if s >= self.threshold and (item not in best or (s, -int(d), -a) > (best[item][0], -best[item][3], -best[item][1])):
                        best[item] = (s, a, min(size, n_words), int(d))


def benchmark_slices(benchmark: DataFrame, id_col: str = "item_id", text_col: str = "text", max_items: int = SLICE_ITEMS, max_bytes: int = SLICE_TEXT) -> Iterator[BenchmarkIndex]:
    """The benchmark as indexes of bounded size; its size is checked before anything is gathered."""
    rows = benchmark.select(F.col(id_col).cast("bigint").alias("item"), F.col(text_col).alias("text")).where(F.col(text_col).isNotNull())
    n, size = rows.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    parts = max(1, -(-n // max_items), -(-size // max_bytes))
    if parts == 1:
        yield BenchmarkIndex([(r.item, r.text) for r in rows.collect()])
        return
    for k in range(2 * parts):  # by hash: about half a slice each
        yield BenchmarkIndex([(r.item, r.text) for r in rows.where(F.pmod(F.xxhash64("item", "text"), F.lit(2 * parts)) == k).toLocalIterator()])


def find_leaks(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, item_id, similarity, start_word, n_words, hamming) for every item found in a document."""
    schema = f"{id_col} bigint, item_id bigint, similarity double, start_word bigint, n_words bigint, hamming int"
    kinds = (pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64(), pa.int32())
    out = None
    for index in benchmark_slices(benchmark):
        shared = docs.sparkSession.sparkContext.broadcast(index)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            cache = WordHash()
            for batch in batches:
                for part in slices(batch, text_col):
                    rows = [(doc, *x) for doc, t in zip(part.column(id_col).to_pylist(), texts(part, text_col), strict=True) for x in shared.value.find(cache.of(words_of(t)))]
                    if rows:
                        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=[x.split()[0] for x in schema.split(", ")])

        found = docs.select(id_col, text_col).mapInArrow(run, schema)
        out = found if out is None else out.union(found)
    return out


def without_leaks(docs: DataFrame, benchmark: DataFrame, text_col: str = "text") -> DataFrame:
    """The rows of docs, with all their columns, in which no item is found."""
    for index in benchmark_slices(benchmark):
        shared = docs.sparkSession.sparkContext.broadcast(index)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            cache = WordHash()
            for batch in batches:
                for part in slices(batch, text_col):
                    yield part.filter(pa.array([not shared.value.find(cache.of(words_of(t))) for t in texts(part, text_col)], pa.bool_()))

        docs = docs.mapInArrow(run, docs.schema)
    return docs
