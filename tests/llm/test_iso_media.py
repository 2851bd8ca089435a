import hashlib
import struct
import zlib

import pytest

from pacedfl.llm import iso_media as m
from pacedfl.llm.queries import op1_media


@pytest.mark.parametrize("n", [0, 1, 576, 577, 576 * 8, 576 * 9, 300_000])
def test_roundtrip(n):
    data = bytes(i * 31 % 256 for i in range(n))
    payload = m.padded(data)
    assert len(payload) % 576 == 0 and len(payload) >= 576 and payload.startswith(data) and set(payload[n:]) <= {255}
    media = m.mux(payload)
    (track,) = m.probe(media)
    assert m.stored_bytes(media, track) == payload
    assert (track["codec"], track["timescale"], track["duration"]) == ("raw ", 8000, len(payload))
    for k in track["keys"].tolist():
        a, s = int(track["offsets"][k]), int(track["sizes"][k])
        assert media[a : a + s] == payload[k * 576 : k * 576 + s]


def test_reader_knows_other_layouts():
    """64-bit box sizes, co64, a size table, version 1 times, no stss, two tracks, unknown boxes."""
    def full(kind, *parts, version=0):
        return m._box(kind, struct.pack(">I", version << 24), *parts)

    def track(offsets, sizes, codec):
        table = m._box(b"stbl", full(b"stsd", struct.pack(">I", 1), m._box(codec, b"\0" * 8)), full(b"stts", struct.pack(">III", 1, len(sizes), 10)),
                       full(b"stsc", struct.pack(">IIIIIII", 2, 1, 2, 1, 2, 1, 1)), full(b"stsz", struct.pack(">II", 0, len(sizes)), struct.pack(f">{len(sizes)}I", *sizes)),
                       full(b"co64", struct.pack(">I", len(offsets)), struct.pack(f">{len(offsets)}Q", *offsets)))
        return m._box(b"trak", m._box(b"mdia", full(b"mdhd", struct.pack(">QQIQI", 0, 0, 600, 30, 0), version=1), full(b"hdlr", b"\0" * 4, b"vide", b"\0" * 13), m._box(b"minf", table)))

    body = b"AAABBCCCC"
    free = m._box(b"free", b"zz")
    head = struct.pack(">I4sQ", 1, b"mdat", 16 + len(body)) + body
    media = free + head + m._box(b"moov", track([28 - 2 + 0, 31], [3, 2, 4], b"avc1"), m._box(b"uuid", b"?" * 16), track([26, 31], [3, 2, 4], b"mp4a"))
    first = media.index(body)
    one, two = m.probe(media.replace(struct.pack(">QQ", 26, 31), struct.pack(">QQ", first, first + 5)))
    assert one["codec"] == "avc1" and two["codec"] == "mp4a" and one["handler"] == "vide" and one["duration"] == 30
    assert m.stored_bytes(media, one) == body and one["keys"].tolist() == [0, 1, 2]


def full(kind, *parts, version=0, flags=0):
    return m._box(kind, struct.pack(">I", version << 24 | flags), *parts)


def small_track(table, number=7):
    head = full(b"tkhd", struct.pack(">IIIII", 0, 0, number, 0, 0))
    return m._box(b"trak", head, m._box(b"mdia", full(b"mdhd", struct.pack(">IIIII", 0, 0, 1000, 0, 0)), full(b"hdlr", b"\0" * 4, b"vide", b"\0" * 13), m._box(b"minf", m._box(b"stbl", full(b"stsd", struct.pack(">I", 1), m._box(b"avc1", b"\0" * 8)), *table))))


def test_fragments():
    """Defaults from trex and tfhd, sizes and flags in the run, runs that go on where the last one ended, an explicit base."""
    empty = [full(b"stts", struct.pack(">I", 0)), full(b"stsc", struct.pack(">I", 0)), full(b"stsz", struct.pack(">II", 0, 0)), full(b"stco", struct.pack(">I", 0))]
    moov = m._box(b"moov", small_track(empty), m._box(b"mvex", full(b"trex", struct.pack(">IIIII", 7, 1, 40, 5, m.NO_KEY))))

    def moof(shift):
        header = full(b"tfhd", struct.pack(">I", 7), flags=m.BASE_IS_MOOF)
        one = full(b"trun", struct.pack(">IiI", 3, shift, 0), flags=m.RUN_OFFSET | m.RUN_FIRST)
        two = full(b"trun", struct.pack(">I", 2), struct.pack(">IIIIII", 25, 4, 0, 25, 6, m.NO_KEY), flags=m.RUN_DURATION | m.RUN_SIZE | m.RUN_FLAGS)
        return m._box(b"moof", full(b"mfhd", struct.pack(">I", 1)), m._box(b"traf", header, one, two))

    first = moof(len(moof(0)) + 8) + m._box(b"mdat", b"aaaaabbbbbcccccddddeeeeee")
    tail = m._box(b"mdat", b"ffffff")
    at = len(moov) + len(first) + 8
    last = m._box(b"moof", m._box(b"traf", full(b"tfhd", struct.pack(">IQI", 7, at, 3), flags=m.BASE_OFFSET | m.SIZE), full(b"trun", struct.pack(">I", 2), flags=0)))
    (track,) = m.probe(moov + first + tail + last)
    assert m.stored_bytes(moov + first + tail + last, track) == b"aaaaabbbbbcccccddddeeeeeeffffff"
    assert track["sizes"].tolist() == [5, 5, 5, 4, 6, 3, 3] and track["keys"].tolist() == [0, 3]
    assert track["duration"] == 3 * 40 + 50 + 2 * 40 and track["codec"] == "avc1"


@pytest.mark.parametrize("width, packed", [(4, b"\x35\x10"), (8, b"\3\5\1"), (16, b"\0\3\0\5\0\1")])
def test_compact_sizes(width, packed):
    tables = [full(b"stts", struct.pack(">III", 1, 3, 10)), full(b"stsc", struct.pack(">IIII", 1, 1, 3, 1)), full(b"stz2", struct.pack(">II", width, 3), packed), full(b"stco", struct.pack(">II", 1, 8))]
    (track,) = m.probe(m._box(b"mdat", b"aaabbbbbc") + m._box(b"moov", small_track(tables)))
    assert track["sizes"].tolist() == [3, 5, 1] and m.key_ranges(track).tolist() == [[8, 11], [11, 16], [16, 17]]


def test_unknown_width_is_an_error():
    with pytest.raises(m.Malformed):
        m.probe(m._box(b"moov", small_track([full(b"stz2", struct.pack(">II", 5, 1), b"\0")])))


@pytest.mark.parametrize("bad", [b"abc", b"\0\0\0\x09mdat", m.mux(m.padded(b"x"))[:700][:100], struct.pack(">I4s", 4, b"moov")])
def test_malformed(bad):
    with pytest.raises(m.Malformed):
        list(m.boxes(bad))


def test_probe_operator(spark):
    good = m.mux(m.padded(b"x" * 6000))
    rows = m.probe_media(spark.createDataFrame([("a", bytearray(good)), ("b", bytearray(b"junk junk")), ("c", None), ("d", bytearray(m._box(b"free", b"x")))], "path string, content binary")).collect()
    by = {r.path: r for r in rows}
    assert set(by) == {"a", "b", "c", "d"} and by["b"].error and by["c"].error == "no content" and by["d"].error == "no tracks" and by["d"].track is None and by["a"].codec == "raw " and by["a"].duration_s == pytest.approx(6336 / 8000)
    assert [r.end - r.start for r in by["a"].key_ranges] == [576, 576]


def test_query(spark, small):
    rows = op1_media(spark, small).collect()
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    assert len(rows) == len(texts)
    for r in rows:
        p = m.padded((texts[r.doc_id] or "").encode())
        assert (r.n_bytes, r.payload_bytes) == (len((texts[r.doc_id] or "").encode()), len(p))
        assert r.payload_sha256 == hashlib.sha256(p).hexdigest() and r.tail_crc32 == zlib.crc32(p[-32:])
        media = m.mux(p)
        assert r.media_sha256 == hashlib.sha256(media).hexdigest()
        assert [(x.start, x.end) for x in r.key_ranges] == [tuple(x) for x in m.key_ranges(m.probe(media)[0]).tolist()] and r.key_ranges


def test_nulls_and_clashing_columns(spark):
    docs = spark.createDataFrame([(1, None, "x"), (None, "", "y"), (1, None, "z")], "doc_id long, text string, feature string")
    rows = m.text_media(docs).collect()
    assert [(r.n_bytes, r.payload_bytes) for r in rows] == [(0, 576)] * 3 and len({r.media_sha256 for r in rows}) == 1
    assert m.text_media(docs.limit(0)).count() == 0
