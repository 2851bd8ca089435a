"""Byte-level BPE encoding and decoding in length-bucketed padded numpy matrices.

Every row of a matrix is one pre-token. In each round every row merges its leftmost pair of minimum
rank; pair ranks come from an open-addressing hash table held in numpy arrays, and rows are compacted
after the merge. Rows that have no pair left leave the matrix. Results equal the tiktoken library's.

A row of more than WIDE bytes has a matrix of its own, and merges all places of its minimum-rank pair in one round where
no pair of such a rank or a lower one can come up beside them, so that its rounds are as many as the ranks it uses, not
as its bytes.

Edge cases: null text is an empty text and gives no ids; pre-tokens may be as long as the text.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from pacedfl.llm.common import slices, texts

WIDE = 256
PIECE_CACHE = 200_000
NONE = np.int32(2**31 - 1)


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


class PairTable:
    """(left id, right id) -> id of the joined token, by linear probing."""

    def __init__(self, ranks: dict[bytes, int]):
        pairs = [(ranks[t[:i]], ranks[t[i:]], r) for t, r in ranks.items() for i in range(1, len(t)) if t[:i] in ranks and t[i:] in ranks]
        a = np.array(pairs, dtype=np.int64).reshape(-1, 3)
        self.bits = max(4, int(np.ceil(np.log2(len(a) * 2 + 2))))
        self.mask = np.int64((1 << self.bits) - 1)
        self.keys = np.full(1 << self.bits, -1, np.int64)
        self.joined = np.full(1 << self.bits, NONE, np.int32)
        key, value = (a[:, 0] << 32) | a[:, 1], a[:, 2].astype(np.int32)
        at, left = self._home(key), np.arange(len(a))
        while len(left):
            free = self.keys[at[left]] == -1
            spots, first = np.unique(at[left[free]], return_index=True)
            placed = left[free][first]
            self.keys[spots], self.joined[spots] = key[placed], value[placed]
            left = np.setdiff1d(left, placed, assume_unique=True)
            at[left] = np.where(self.keys[at[left]] != key[left], (at[left] + 1) & self.mask, at[left])

    def _home(self, key: np.ndarray) -> np.ndarray:
        h = key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        return (h >> np.uint64(64 - self.bits)).astype(np.int64)

    def ranks_of(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Rank of each pair, NONE where it cannot merge or a side is padding (-1)."""
        shape = left.shape
        key = ((left.astype(np.int64) << 32) | (right.astype(np.int64) & 0xFFFFFFFF)).ravel()
        out = np.full(key.shape, NONE, np.int32)
        todo = np.flatnonzero((left.ravel() >= 0) & (right.ravel() >= 0))
        at = self._home(key[todo])
        while len(todo):
            seen = self.keys[at]
            hit = seen == key[todo]
            out[todo[hit]] = self.joined[at[hit]]
            go = ~hit & (seen != -1)
            todo, at = todo[go], (at[go] + 1) & self.mask
        return out.reshape(shape)


class ByteBpe:
    """Encoder and decoder for one rank file and one pre-token pattern."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks, self.split = ranks, regex.compile(pattern)
        self.byte_id = np.array([ranks[bytes([b])] for b in range(256)], dtype=np.int32)
        self.pairs = PairTable(ranks)
        self.vocab = [b""] * (max(ranks.values()) + 1)
        for t, r in ranks.items():
            self.vocab[r] = t
        self.alone = [r.to_bytes(4, "little") for r in range(len(self.vocab))]
        self.known: dict[str, bytes] = {}

    def encode_pieces(self, pieces: list[bytes]) -> list[bytes]:
        """Ids of each pre-token, as little-endian unsigned 32-bit integers."""
        out = [b""] * len(pieces)
        buckets: dict[int, list[int]] = {}
        for i, p in enumerate(pieces):
            if (whole := self.ranks.get(p)) is not None:
                out[i] = self.alone[whole]
            elif len(p) > WIDE:
                out[i] = self._wide(p)
            elif p:
                buckets.setdefault(1 << (len(p) - 1).bit_length(), []).append(i)
        for width, members in buckets.items():
            step = max(1, (1 << 20) // width)
            for k in range(0, len(members), step):
                part = members[k : k + step]
                for i, ids in zip(part, self._matrix([pieces[i] for i in part], width), strict=True):
                    out[i] = ids
        return out

    def _matrix(self, pieces: list[bytes], width: int) -> list[bytes]:
        n = len(pieces)
        size = np.fromiter(map(len, pieces), np.int64, n)
        ids = np.full((n, width), -1, np.int32)
        ids[np.arange(width) < size[:, None]] = self.byte_id[np.frombuffer(b"".join(pieces), np.uint8)]
        done = [b""] * n

        def leave(which: np.ndarray) -> None:
            flat, step = ids[which].astype("<u4").tobytes(), 4 * ids.shape[1]
            for k, (r, m) in enumerate(zip(row[which].tolist(), size[row[which]].tolist(), strict=True)):
                done[r] = flat[k * step : k * step + 4 * m]

        row = np.arange(n)
        rank = self.pairs.ranks_of(ids[:, :-1], ids[:, 1:]) if width > 1 else np.full((n, 0), NONE)
        while len(row):
            best = rank.argmin(axis=1) if rank.shape[1] else np.zeros(len(row), np.int64)
            low = rank[np.arange(len(row)), best] if rank.shape[1] else np.full(len(row), NONE)
            stays = low != NONE
            if not stays.all():
                leave(np.flatnonzero(~stays))
            ids, rank, row, best, low = ids[stays], rank[stays], row[stays], best[stays], low[stays]
            if not len(row):
                break
            size[row] -= 1
            at = np.arange(len(row))
            column = np.arange(ids.shape[1] - 1)
            moved = column[None, :] > best[:, None]
            ids = np.where(moved, ids[:, 1:], ids[:, :-1])
            ids[at, best] = low
            ids = ids[:, : max(1, int(size[row].max()))]
            if ids.shape[1] == 1:
                leave(np.arange(len(row)))
                break
            rank = np.where(moved, rank[:, np.minimum(column + 1, rank.shape[1] - 1)], rank)[:, : ids.shape[1] - 1]
            for side in (best - 1, best):
                ok = np.flatnonzero((side >= 0) & (side < ids.shape[1] - 1))
                rank[ok, side[ok]] = self.pairs.ranks_of(ids[ok, side[ok]], ids[ok, side[ok] + 1])
            rank[np.arange(rank.shape[1])[None, :] >= (size[row] - 1)[:, None]] = NONE
        return done

    def _wide(self, piece: bytes) -> bytes:
        """A matrix of one row. Merging the leftmost place first can only matter to the others of that rank if a merged
        token makes a pair of that rank or lower with a neighbour, as it was or as it becomes; then one place is merged."""
        ids = self.byte_id[np.frombuffer(piece, np.uint8)]
        rank = self.pairs.ranks_of(ids[:-1], ids[1:])
        while len(rank) and (low := rank.min()) != NONE:
            at = np.flatnonzero(rank == low)
            run = np.maximum.accumulate(np.where(np.diff(at, prepend=-2) != 1, np.arange(len(at)), 0))
            at = at[(np.arange(len(at)) - run) % 2 == 0]  # of places that overlap, the leftmost first
            if len(at) > 1:
                beside = np.concatenate([ids[at[at > 0] - 1], ids[at[at + 2 < len(ids)] + 2]])
                left = np.arange(len(beside)) < (at > 0).sum()
                made = self.pairs.ranks_of(np.where(left, beside, low), np.where(left, low, beside))
                both = self.pairs.ranks_of(np.array([low]), np.array([low]))[0]
                if (made <= low).any() or both <= low:
                    at = at[:1]
            ids[at] = low
            stays = np.ones(len(ids), bool)
            stays[at + 1] = False
            ids, rank = ids[stays], np.delete(rank, at)
            at = at - np.arange(len(at))
            for side in (at - 1, at):
                side = side[(side >= 0) & (side < len(rank))]
                rank[side] = self.pairs.ranks_of(ids[side], ids[side + 1])
        return ids.astype("<u4").tobytes()

    def encode_batch(self, batch: list[str]) -> list[bytes]:
        """Of each text, its ids as little-endian unsigned 32-bit integers."""
        split = [self.split.findall(t) for t in batch]
        new = list({p for pieces in split for p in pieces} - self.known.keys())
        if len(self.known) + len(new) > PIECE_CACHE:
            self.known.clear()
            new = list({p for pieces in split for p in pieces})
        self.known.update(zip(new, self.encode_pieces([p.encode() for p in new]), strict=True))
        get = self.known.__getitem__
        return [b"".join(map(get, pieces)) for pieces in split]

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.vocab.__getitem__, np.frombuffer(ids, "<u4").tolist()))


_LOADED: dict[tuple[str, str], ByteBpe] = {}


def loaded(path: str, pattern: str) -> ByteBpe:
    """One encoder per Python worker."""
    if (path, pattern) not in _LOADED:
        _LOADED[path, pattern] = ByteBpe(load_ranks(path), pattern)
    return _LOADED[path, pattern]


def bpe_documents(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """Encode every whole text, decode the ids again; one row per input row, no shuffle.

    path: a tiktoken rank file that each executor can read (installed with the tokenizers).
    with_ids: also return the ids themselves (array<int>) beside their digest.
    """
    schema = f"{id_col} bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = loaded(path, pattern)
        for batch in batches:
            for part in slices(batch, text_col, 2 << 20):
                ids = bpe.encode_batch(texts(part, text_col))
                out = {
                    id_col: part.column(id_col).cast(pa.int64()),
                    "n_tokens": pa.array([len(x) // 4 for x in ids], pa.int64()),
                    "ids_sha256": pa.array([hashlib.sha256(x).hexdigest() for x in ids], pa.string()),
                    "decoded_sha256": pa.array([hashlib.sha256(bpe.decode(x)).hexdigest() for x in ids], pa.string()),
                }
                if with_ids:
                    ends = np.cumsum([0] + [len(x) // 4 for x in ids]).astype(np.int32)
                    out["ids"] = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.frombuffer(b"".join(ids), "<i4")))
                yield pa.RecordBatch.from_pydict(out)

    return docs.select(id_col, text_col).mapInArrow(run, schema)
