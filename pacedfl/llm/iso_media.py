"""ISO base media files: a writer for byte payloads and a reader that never decodes them.

The reader walks nested boxes (32-bit, 64-bit and to-the-end sizes), decodes the sample tables of every
track (stts, stsc, stsz or stz2 of 4, 8 or 16 bits, stco or co64, stss) and the runs of movie fragments (trex, tfhd,
trun), and gives codec, timescale, duration and the byte range of each key frame. A fragmented track whose header
declares no duration has the sum of its samples'. The writer stores a payload as samples of UNIT bytes in one track.

Edge cases: a null payload is an empty one, and as a container has an error; malformed or truncated containers and
containers without tracks give one row with an error and no track; an absent stss means that every sample of the
sample tables is a key frame, as the format says, and a fragment's samples are where their flags do not deny it.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from pacedfl.llm.common import raw, slices

UNIT = 576
KEY_EVERY = 8
TIMESCALE = 8000
# Fixed values of the format: boxes that hold boxes, and bytes before the first child.
PARENTS = {b"moov": 0, b"trak": 0, b"edts": 0, b"mdia": 0, b"minf": 0, b"dinf": 0, b"stbl": 0, b"mvex": 0, b"moof": 0, b"traf": 0, b"udta": 0, b"meta": 4}


class Malformed(ValueError):
    pass


def _box(kind: bytes, *parts: bytes) -> bytes:
    body = b"".join(parts)
    return struct.pack(">I", len(body) + 8) + kind + body if len(body) < 2**32 - 8 else struct.pack(">I", 1) + kind + struct.pack(">Q", len(body) + 16) + body


def _full(kind: bytes, *parts: bytes, version: int = 0, flags: int = 0) -> bytes:
    return _box(kind, struct.pack(">I", version << 24 | flags), *parts)


MATRIX = struct.pack(">9I", 0x10000, 0, 0, 0, 0x10000, 0, 0, 0, 0x40000000)


def padded(data: bytes, unit: int = UNIT) -> bytes:
    """data with bytes 255 up to a positive multiple of unit."""
    return data + b"\xff" * (max(1, -(-len(data) // unit)) * unit - len(data))


def mux(payload: bytes, unit: int = UNIT, key_every: int = KEY_EVERY) -> bytes:
    """A container whose one track stores the payload as 8-bit PCM in samples of unit bytes."""
    n = len(payload) // unit
    if n * unit != len(payload) or not n:
        raise ValueError("the payload must be a positive multiple of the unit")
    per_chunk = key_every
    n_chunks, last = -(-n // per_chunk), n - (-(-n // per_chunk) - 1) * per_chunk
    entry = _box(b"raw ", b"\0" * 6, struct.pack(">H", 1), b"\0" * 8, struct.pack(">HHHHI", 1, 8, 0, 0, TIMESCALE << 16))
    runs = [(1, per_chunk, 1)] if last == per_chunk or n_chunks == 1 else [(1, per_chunk, 1), (n_chunks, last, 1)]
    if n_chunks == 1:
        runs = [(1, last, 1)]
    keys = np.arange(1, n + 1, key_every, dtype=">u4")
    ftyp = _box(b"ftyp", b"isom", struct.pack(">I", 512), b"isomiso2mp41")

    def moov(first: int) -> bytes:
        at = first + np.arange(n_chunks, dtype=np.uint64) * np.uint64(per_chunk * unit)
        offsets = _full(b"stco", struct.pack(">I", n_chunks), at.astype(">u4").tobytes()) if first + len(payload) < 2**32 else _full(b"co64", struct.pack(">I", n_chunks), at.astype(">u8").tobytes())
        table = _box(
            b"stbl",
            _full(b"stsd", struct.pack(">I", 1), entry),
            _full(b"stts", struct.pack(">III", 1, n, unit)),
            _full(b"stss", struct.pack(">I", len(keys)), keys.tobytes()),
            _full(b"stsc", struct.pack(">I", len(runs)), *(struct.pack(">III", *r) for r in runs)),
            _full(b"stsz", struct.pack(">II", unit, n)),
            offsets,
        )
        url = _full(b"url ", flags=1)
        media = _box(b"mdia", _full(b"mdhd", struct.pack(">IIIIHH", 0, 0, TIMESCALE, n * unit, 0x55C4, 0)), _full(b"hdlr", struct.pack(">I4s12x", 0, b"soun"), b"payload\0"), _box(b"minf", _full(b"smhd", b"\0" * 4), _box(b"dinf", _full(b"dref", struct.pack(">I", 1), url)), table))
        track = _full(b"tkhd", struct.pack(">IIIII", 0, 0, 1, 0, n * unit), b"\0" * 8, struct.pack(">hhhH", 0, 0, 0x100, 0), MATRIX, struct.pack(">II", 0, 0), flags=7)
        head = _full(b"mvhd", struct.pack(">IIIIIH", 0, 0, TIMESCALE, n * unit, 0x10000, 0x100), b"\0" * 10, MATRIX, b"\0" * 24, struct.pack(">I", 2))
        return _box(b"moov", head, _box(b"trak", track, media))

    first = len(ftyp) + len(moov(0)) + 8
    return ftyp + moov(first) + _box(b"mdat", payload)


def boxes(data: bytes, start: int = 0, end: int | None = None, path: tuple[bytes, ...] = ()) -> Iterator[tuple[tuple[bytes, ...], int, int]]:
    """(path, body start, body end) of each box, parents before their children."""
    end = len(data) if end is None else end
    while start < end:
        if end - start < 8:
            raise Malformed("truncated box header")
        size, kind = struct.unpack_from(">I4s", data, start)
        head = 8
        if size == 1:
            if end - start < 16:
                raise Malformed("truncated box header")
            size, head = struct.unpack_from(">Q", data, start + 8)[0], 16
        elif size == 0:
            size = end - start
        if size < head or start + size > end:
            raise Malformed(f"box {kind!r} leaves its parent")
        here = (*path, kind)
        yield here, start + head, start + size
        if kind in PARENTS and len(path) < 16:
            yield from boxes(data, start + head + PARENTS[kind], start + size, here)
        start += size


def _numbers(data: bytes, at: int, end: int, count: int, kind: str) -> np.ndarray:
    if count * np.dtype(kind).itemsize > end - at:
        raise Malformed("truncated table")
    return np.frombuffer(data, kind, count, at).astype(np.int64)


def _nibbles(data: bytes, at: int, end: int, count: int) -> np.ndarray:
    packed = _numbers(data, at, end, (count + 1) // 2, ">u1")
    return np.stack([packed >> 4, packed & 15], axis=1).ravel()[:count]


# Fixed values of the format: flags of a fragment's header and runs, and the sample flag that denies a key frame.
BASE_OFFSET, DESCRIPTION, DURATION, SIZE, FLAGS, BASE_IS_MOOF = 0x1, 0x2, 0x8, 0x10, 0x20, 0x20000
RUN_OFFSET, RUN_FIRST, RUN_DURATION, RUN_SIZE, RUN_FLAGS, RUN_SHIFT = 0x1, 0x4, 0x100, 0x200, 0x400, 0x800
NO_KEY = 0x10000


class _Fragments:
    """Samples of movie fragments by track; boxes come in file order."""

    def __init__(self, data: bytes):
        self.data, self.defaults, self.runs = data, {}, {}
        self.moof, self.end, self.now = 0, 0, {}

    def _u32(self, at: int) -> int:
        return struct.unpack_from(">I", self.data, at)[0]

    def box(self, kind: bytes, a: int, b: int) -> None:
        if kind == b"trex":
            self.defaults[self._u32(a + 4)] = tuple(self._u32(a + o) for o in (12, 16, 20))
        elif kind == b"moof":
            self.moof = self.end = a - (8 if self.data[a - 4 : a] == b"moof" else 16)
        elif kind == b"tfhd":
            flags, track, at = self._u32(a) & 0xFFFFFF, self._u32(a + 4), a + 8
            duration, size, sample_flags = self.defaults.get(track, (0, 0, 0))
            base = self.moof if flags & BASE_IS_MOOF else self.end
            if flags & BASE_OFFSET:
                base, at = struct.unpack_from(">Q", self.data, at)[0], at + 8
            at += 4 * bool(flags & DESCRIPTION)
            values = [duration, size, sample_flags]
            for i, bit in enumerate((DURATION, SIZE, FLAGS)):
                if flags & bit:
                    values[i], at = self._u32(at), at + 4
            self.now = {"track": track, "base": base, "next": base, "values": values}
        elif kind == b"trun":
            self._run(a, b)

    def _run(self, a: int, b: int) -> None:
        if not self.now:
            raise Malformed("run without a fragment header")
        flags, n, at, first = self._u32(a) & 0xFFFFFF, self._u32(a + 4), a + 8, None
        start = self.now["next"]
        if flags & RUN_OFFSET:
            start, at = self.now["base"] + struct.unpack_from(">i", self.data, at)[0], at + 4
        if flags & RUN_FIRST:
            first, at = self._u32(at), at + 4
        given = [bit for bit in (RUN_DURATION, RUN_SIZE, RUN_FLAGS, RUN_SHIFT) if flags & bit]
        table = _numbers(self.data, at, b, n * len(given), ">u4").reshape(n, -1)
        column = {bit: table[:, i] for i, bit in enumerate(given)}
        duration, size, sample_flags = (column.get(bit, np.full(n, v, np.int64)) for bit, v in zip((RUN_DURATION, RUN_SIZE, RUN_FLAGS), self.now["values"], strict=True))
        if first is not None and n and RUN_FLAGS not in column:
            sample_flags = np.append(first, sample_flags[1:])
        if start < 0:
            raise Malformed("run before the file")
        self.runs.setdefault(self.now["track"], []).append((start + np.cumsum(size) - size, size, (sample_flags & NO_KEY) == 0, int(duration.sum())))
        self.now["next"] = self.end = start + int(size.sum())


def probe(data: bytes) -> list[dict]:
    """Of each track: codec, handler, timescale, duration, sample offsets and sizes, key frame numbers."""
    tracks: list[dict] = []
    fragments = _Fragments(data)
    try:
        for path, a, b in boxes(data):
            kind = path[-1]
            if kind == b"trak":
                tracks.append({})
                continue
            fragments.box(kind, a, b)
            if not tracks or b"trak" not in path:
                continue
            t, u32 = tracks[-1], lambda o, a=a: struct.unpack_from(">I", data, a + o)[0]
            if kind == b"tkhd":
                t["id"] = u32(20 if data[a] == 1 else 12)
            elif kind == b"mdhd":
                t["timescale"], t["duration"] = struct.unpack_from(">IQ", data, a + 20) if data[a] == 1 else struct.unpack_from(">II", data, a + 12)
            elif kind == b"hdlr":
                t["handler"] = data[a + 8 : a + 12].decode("latin-1")
            elif kind == b"stsd":
                t["codec"] = data[a + 12 : a + 16].decode("latin-1") if u32(4) else ""
            elif kind == b"stts":
                t["stts"] = _numbers(data, a + 8, b, 2 * u32(4), ">u4").reshape(-1, 2)
            elif kind == b"stsc":
                t["stsc"] = _numbers(data, a + 8, b, 3 * u32(4), ">u4").reshape(-1, 3)
            elif kind == b"stss":
                t["stss"] = _numbers(data, a + 8, b, u32(4), ">u4")
            elif kind == b"stco":
                t["chunks"] = _numbers(data, a + 8, b, u32(4), ">u4")
            elif kind == b"co64":
                t["chunks"] = _numbers(data, a + 8, b, u32(4), ">u8")
            elif kind == b"stsz":
                t["sizes"] = np.full(u32(8), u32(4), np.int64) if u32(4) else _numbers(data, a + 12, b, u32(8), ">u4")
            elif kind == b"stz2":
                if data[a + 7] not in (4, 8, 16):
                    raise Malformed("sample sizes of unknown width")
                t["sizes"] = _nibbles(data, a + 12, b, u32(8)) if data[a + 7] == 4 else _numbers(data, a + 12, b, u32(8), ">u1" if data[a + 7] == 8 else ">u2")
    except (struct.error, IndexError) as e:
        raise Malformed(str(e)) from e
    for t in tracks:
        _locate(t)
        _with_fragments(t, fragments.runs.get(t.get("id"), []))
    return tracks


def _with_fragments(t: dict, runs: list[tuple]) -> None:
    """The track's own samples, then those of its runs."""
    own = int((t["stts"][:, 0] * t["stts"][:, 1]).sum()) if "stts" in t else 0
    if runs:
        offsets, sizes, keys, durations = zip(*runs, strict=True)
        n = len(t["offsets"])
        t["keys"] = np.concatenate([t["keys"], n + np.flatnonzero(np.concatenate(keys))])
        t["offsets"], t["sizes"] = np.concatenate([t["offsets"], *offsets]), np.concatenate([t["sizes"], *sizes])
        if not t.get("duration"):
            t["duration"] = own + sum(durations)


def _locate(t: dict) -> None:
    """Sample offsets from chunks, runs of chunks and sizes."""
    sizes, chunks = t.get("sizes", np.empty(0, np.int64)), t.get("chunks", np.empty(0, np.int64))
    runs, n = t.pop("stsc", np.empty((0, 3), np.int64)), len(t.get("sizes", ()))
    if n and (not len(runs) or not len(chunks)):
        raise Malformed("samples without chunks")
    if n:
        ends = np.append(runs[1:, 0], len(chunks) + 1)
        if (runs[:, 0] < 1).any() or (ends < runs[:, 0]).any():
            raise Malformed("chunk runs out of order")
        per = np.repeat(runs[:, 1], ends - runs[:, 0])
        if per.sum() < n:
            raise Malformed("fewer places than samples")
        chunk = np.repeat(np.arange(len(per)), per)[:n]
        before = np.cumsum(sizes) - sizes
        first = np.flatnonzero(np.diff(chunk, prepend=-1))
        t["offsets"] = chunks[chunk] + before - np.repeat(before[first], np.diff(np.append(first, n)))
    else:
        t["offsets"] = np.empty(0, np.int64)
    t["sizes"] = sizes
    t["keys"] = t.pop("stss", np.arange(1, n + 1)) - 1
    if len(t["keys"]) and (t["keys"].min() < 0 or t["keys"].max() >= n):
        raise Malformed("key frame outside the samples")


def key_ranges(track: dict) -> np.ndarray:
    """(start, end) bytes of each key frame."""
    k = track["keys"]
    return np.stack([track["offsets"][k], track["offsets"][k] + track["sizes"][k]], axis=1) if len(k) else np.empty((0, 2), np.int64)


RANGES = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))


def _as_ranges(x: np.ndarray) -> list[dict]:
    return [{"start": a, "end": b} for a, b in x.tolist()]


def stored_bytes(data: bytes, track: dict) -> bytes:
    """The samples of a track, in order."""
    if len(track["offsets"]) and int((track["offsets"] + track["sizes"]).max()) > len(data):
        raise Malformed("sample outside the file")
    if len(track["offsets"]) and (np.diff(track["offsets"]) == track["sizes"][:-1]).all():
        return data[int(track["offsets"][0]) : int(track["offsets"][-1] + track["sizes"][-1])]
    return b"".join(data[o : o + s] for o, s in zip(track["offsets"].tolist(), track["sizes"].tolist(), strict=True))


def feature_of(track: dict) -> str:
    """Codec, duration, counts, and first, last and digest of the key frames' byte ranges."""
    ranges = key_ranges(track)
    ends = [f"{a}-{b}" for a, b in (ranges[:1].tolist() + ranges[-1:].tolist())]
    digest = hashlib.sha256(ranges.astype("<i8").tobytes()).hexdigest()[:16]
    return f"codec={track.get('codec', '').strip()};timescale={track.get('timescale', 0)};duration={track.get('duration', 0)};samples={len(track['offsets'])};keys={len(ranges)};first={ends[0] if ends else ''};last={ends[-1] if ends else ''};ranges={digest}"


def text_media(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", unit: int = UNIT) -> DataFrame:
    """Store every whole text in a container, read it back and describe it; one row per input row."""
    names = [id_col, "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "key_ranges"]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), RANGES]
    schema = f"{id_col} bigint, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string, key_ranges array<struct<start:bigint,end:bigint>>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, text_col):
                rows = []
                for data in raw(part, text_col):
                    media = mux(padded(data, unit), unit)
                    track = probe(media)[0]
                    back = stored_bytes(media, track)
                    rows.append((len(data), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-32:]), len(media), hashlib.sha256(media).hexdigest(), feature_of(track), _as_ranges(key_ranges(track))))
                yield pa.RecordBatch.from_arrays([part.column(id_col).cast(pa.int64()), *(pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds[1:], strict=True))], names=names)

    return docs.select(id_col, text_col).mapInArrow(run, schema)


def probe_media(files: DataFrame, id_col: str = "path", content_col: str = "content") -> DataFrame:
    """Describe containers held in a binary column: one row per track, with the key frames' byte ranges.

    Payloads are never decoded. A null or malformed file, or one without tracks, gives one row with its error.
    """
    schema = f"{id_col} string, track int, codec string, handler string, timescale bigint, duration bigint, duration_s double, n_samples bigint, key_ranges array<struct<start:bigint,end:bigint>>, error string"
    kinds = [pa.string(), pa.int32(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.float64(), pa.int64(), RANGES, pa.string()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for name, data in zip(batch.column(id_col).cast(pa.string()).to_pylist(), batch.column(content_col).to_pylist(), strict=True):
                try:
                    found = probe(data) if data is not None else []
                    for i, t in enumerate(found):
                        scale = t.get("timescale", 0)
                        rows.append((name, i, t.get("codec"), t.get("handler"), scale, t.get("duration"), t["duration"] / scale if scale and "duration" in t else None, len(t["offsets"]), _as_ranges(key_ranges(t)), None))
                    error = None if found else "no content" if data is None else "no tracks"
                except Malformed as e:
                    error = str(e)
                if error:
                    rows.append((name, None, None, None, None, None, None, None, None, error))
            columns = list(zip(*rows, strict=True)) or [[] for _ in kinds]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=[x.split()[0] for x in schema.split(", ")])

    return files.select(id_col, content_col).mapInArrow(run, schema)
