import gzip
import io
import zlib

import pytest
from conftest import same_rows

from pacedfl.llm import common, web_archive as w
from pacedfl.llm.queries import ORACLE, op2_warc


@pytest.mark.parametrize("version", [1, 2])
def test_arc_roundtrip(version):
    records = [("http://a/", b"HTTP/1.0 200 OK\r\n\r\nbody\n\nmore"), ("http://b c/", b""), ("http://d/", b"\nhttp://x 1 2 3 4\n")]
    got = list(w.read_arc(w.write_arc(records, version)))
    assert [r.body for r in got] == [b for _, b in records]
    assert got[1].fields["url"] == "http://b%20c/" and all(r.version == version for r in got)
    assert ("result" in got[0].fields) == (version == 2)


def test_arc_errors():
    data = w.write_arc([("http://a/", b"0123456789")])
    with pytest.raises(w.ArchiveError):
        list(w.read_arc(data[:-4]))
    assert list(w.read_arc(data[:-4], lenient=True))[0].body == b"0123456"
    with pytest.raises(w.ArchiveError):
        list(w.read_arc(b"http://a/ 1.2.3.4 20200101000000 text/html 4\nabcd"))
    with pytest.raises(w.ArchiveError):
        list(w.read_arc(data + b"http://b/ 0.0.0.0 2020 text/html\nabcd"))
    assert list(w.read_arc(b"")) == []


def test_conversion():
    r = w.ArcRecord(1, {"url": "http://a/", "ip": "1.2.3.4", "date": "20230405060708", "type": "text/html", "length": "9"}, b"HTTP/1.1 200 OK\r\nContent-Length: 3\r\n\r\nabc")
    out = w.arc_to_warc(r, w.record_id(7))
    assert out.headers["WARC-Date"] == "2023-04-05T06:07:08Z" and out.headers["WARC-Type"] == "response" and out.headers["WARC-IP-Address"] == "1.2.3.4"
    again = w.arc_to_warc(r, w.record_id(8), w.record_id(7))
    assert again.kind == "revisit" and again.block.endswith(b"\r\n\r\n") and w.page_of(again.headers["WARC-Refers-To"]) == 7
    assert w.arc_to_warc(w.ArcRecord(1, r.fields, b"plain"), w.record_id(9)).kind == "resource"
    blob = b"".join(x.head().encode() + x.block + b"\r\n\r\n" for x in (out, again))
    assert [x.kind for x in w.read_warc(io.BufferedReader(io.BytesIO(blob)))] == ["response", "revisit"]
    with pytest.raises(w.ArchiveError):
        list(w.read_warc(io.BufferedReader(io.BytesIO(blob[:-40]))))


@pytest.mark.parametrize("page", [0, 1, -1, 2**63 - 1, -(2**63), 2**60])
def test_identifier_carries_the_page(page):
    assert w.page_of(w.record_id(page)) == page


def test_edge_rows(spark, tmp_path):
    big = "x" * 200
    rows = [(1, None, None, "e"), (2, "u", big, "e"), (3, "u", big, "e"), (3, "u", big, "e"), (4, "u", "y" * 99, "e"), (5, "u", "y" * 99, "e"), (None, "u", big, "e"), (6, "http://a\tb", "é\r\n\r\n" * 40, "e"), (7, "u", "é\r\n\r\n" * 40, "e")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, first string")
    path = f"file://{tmp_path}/warc"
    got = w.archive_pages(pages, path).collect()
    assert len(got) == len(rows)
    kind = sorted(((r.page_id, r.record_type, r.refers_to, r.payload_bytes) for r in got), key=repr)
    assert kind == sorted([(1, "response", None, 0), (2, "response", None, 200), (3, "revisit", 2, 200), (3, "revisit", 2, 200), (4, "response", None, 99), (5, "response", None, 99), (None, "response", None, 200), (6, "response", None, 240), (7, "revisit", 6, 240)], key=repr)
    files = list((tmp_path / "warc").glob("*.gz"))
    assert files and sum(1 for f in files for _ in w.read_warc(io.BufferedReader(gzip.open(f)))) == len(rows)
    for f in files:  # each record can be read from its member alone
        data, seen = f.read_bytes(), []
        while data:
            one = zlib.decompressobj(31)
            text, data = one.decompress(data), one.unused_data
            if text:
                seen += w.read_warc(io.BufferedReader(io.BytesIO(text)))
                assert text.startswith(b"WARC/1.1") and text.count(b"WARC-Record-ID") == 1
        assert len(seen) == sum(1 for _ in w.read_warc(io.BufferedReader(gzip.open(f))))
    assert w.archive_pages(pages.limit(0)).count() == 0


def test_files_are_bounded_and_hot_payloads_dealt(spark, tmp_path, monkeypatch):
    """Small slices and files, one payload on most pages, a very long one; the same rows come back."""
    monkeypatch.setattr(w, "SLICE_PAGES", 1000)
    monkeypatch.setattr(w, "FILE_ROWS", 2)
    monkeypatch.setattr(common, "HOT_SHARE", 3)
    rows = [(i, f"u{i}", "same " * 40 if i % 3 else f"{i} " * (200_000 if i == 9 else 60)) for i in range(60)]
    path = f"file://{tmp_path}/warc"
    got = {r.page_id: r for r in w.archive_pages(spark.createDataFrame(rows, "page_id long, url string, html string"), path).collect()}
    assert len(got) == 60 and len(list((tmp_path / "warc").glob("*.warc.gz"))) > 5
    assert all(got[i].refers_to == (1 if i % 3 and i != 1 else None) and got[i].payload_bytes == len(html) for i, _, html in rows)


def test_query_equals_sql(spark, duck, small):
    assert same_rows(op2_warc(spark, small).toPandas(), duck.sql(ORACLE["op2_warc"]).df())
