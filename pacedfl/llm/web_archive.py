"""Web archives: read legacy ARC files, convert them to WARC, write and read WARC through Spark.

ARC headers are one line whose fields depend on the version that the file's first record declares:
version 1 has URL, address, date, type, length; version 2 adds result code, checksum, location, offset
and file name before the length. The declared length, not any delimiter, ends a record. From these the
converter makes WARC identifiers, ISO timestamps, types and payload digests.

Every record is a gzip member of its own, so that a reader can seek to it. Archives are written by Spark's own text
writer, so they go to any file system that Spark can write: a row is a run of members, and what the writer puts after
each row is an empty member. A file holds at most FILE_ROWS rows, each the records of about SLICE_PAGES bytes of pages;
so one file is small enough to be read whole with the binaryFile source, and is unpacked as a stream.

Edge cases: null html is an empty payload; a null url becomes a urn; equal payloads below MIN_REVISIT
bytes are always stored; rows without page_id are stored as responses and read back without one; rows
that repeat a page_id with the same payload are all responses; truncated ARC records raise ArchiveError
unless lenient.
"""

from __future__ import annotations

import gzip
import hashlib
import io
import re
import uuid
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from pacedfl.llm.common import checkpointed, dealt, new_path, repeated, salted, slices

MIN_REVISIT = 100
FILE_ROWS = 32
SLICE_PAGES = 4 << 20
DATE = "20240101000000"
EMPTY_MEMBER = gzip.compress(b"", mtime=0)
# Fixed values of the formats.
ARC_FIELDS = {1: ("url", "ip", "date", "type", "length"), 2: ("url", "ip", "date", "type", "result", "checksum", "location", "offset", "filename", "length")}
ARC_NAMES = {"url": "URL", "ip": "IP-address", "date": "Archive-date", "type": "Content-type", "result": "Result-code", "checksum": "Checksum", "location": "Location", "offset": "Offset", "filename": "Filename", "length": "Archive-length"}
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
HTTP_OK = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n"


class ArchiveError(ValueError):
    pass


@dataclass
class ArcRecord:
    version: int
    fields: dict[str, str]
    body: bytes


@dataclass
class WarcRecord:
    kind: str
    headers: dict[str, str] = field(default_factory=dict)
    block: bytes = b""

    def head(self) -> str:
        return "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in self.headers.items()) + "\r\n"


def write_arc(records: list[tuple[str, bytes]], version: int = 1, name: str = "pages.arc", date: str = DATE) -> bytes:
    """An ARC file of (url, body) records."""
    about = f"{version} 0 pacedfl\n{' '.join(ARC_NAMES[f] for f in ARC_FIELDS[version])}\n\n".encode()
    out = io.BytesIO()

    def put(url: str, kind: str, body: bytes) -> None:
        values = {"url": re.sub(r"\s", lambda m: f"%{ord(m[0]):02X}", url), "ip": "0.0.0.0", "date": date, "type": kind, "result": "200", "checksum": hashlib.md5(body).hexdigest(), "location": "-", "offset": str(out.tell()), "filename": name, "length": str(len(body))}
        out.write(" ".join(values[f] for f in ARC_FIELDS[version]).encode() + b"\n" + body + b"\n")

    put(f"filedesc://{name}", "text/plain", about)
    for url, body in records:
        put(url, "text/html", body)
    return out.getvalue()


def read_arc(data: bytes, lenient: bool = False) -> Iterator[ArcRecord]:
    """Records of an ARC file, the version record left out."""
    at, version = 0, None
    while at < len(data):
        if data[at : at + 1] in (b"\n", b"\r"):
            at += 1
            continue
        end = data.find(b"\n", at)
        words = data[at : end if end >= 0 else len(data)].decode("utf-8", "replace").split()
        if version is None:
            if len(words) not in (5, 10) or not words[0].startswith("filedesc://"):
                raise ArchiveError("no version record")
            declared = data[end + 1 : end + 3].decode("latin-1").strip()
            version = int(declared) if declared in ("1", "2") else {5: 1, 10: 2}[len(words)]
            names = ARC_FIELDS[{5: 1, 10: 2}[len(words)]]
        else:
            names = ARC_FIELDS[version]
        if len(words) != len(names) or not words[-1].isdigit():
            raise ArchiveError(f"header line does not fit version {version}: {words[:3]}")
        fields = dict(zip(names, words, strict=True))
        size = int(fields["length"])
        if end < 0 or end + 1 + size > len(data):
            if not lenient:
                raise ArchiveError("record is shorter than it declares")
            size = max(0, len(data) - end - 1)
        if not fields["url"].startswith("filedesc://"):
            yield ArcRecord(version, fields, data[end + 1 : end + 1 + size])
        at = end + 1 + size


def record_id(page_id: int | None, tag: str = "") -> str:
    """A version 8 UUID that carries the page id, so that the id can be read back."""
    if page_id is None:
        return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, tag)}>"
    n = page_id & (2**64 - 1)
    return f"<urn:uuid:{uuid.UUID(int=(0x9A6E << 112) | ((n >> 60) << 80) | (8 << 76) | (0x5AF << 64) | (2 << 62) | (n & (2**60 - 1)))}>"


def page_of(identifier: str) -> int | None:
    u = uuid.UUID(identifier.strip("<>")).int
    if (u >> 76) & 15 != 8:
        return None
    n = (((u >> 80) & 15) << 60) | (u & (2**60 - 1))
    return n - 2**64 if n >= 2**63 else n


def split_http(block: bytes) -> tuple[bytes, bytes]:
    """HTTP head and payload; a block without a head is all payload."""
    if block.startswith(b"HTTP/"):
        head, gap, rest = block.partition(b"\r\n\r\n")
        if gap:
            return head + gap, rest
    return b"", block


def arc_to_warc(record: ArcRecord, identifier: str, refers_to: str | None = None) -> WarcRecord:
    """The WARC record for an ARC record: response (or resource without an HTTP head), or revisit of another."""
    head, payload = split_http(record.body)
    d = record.fields["date"].ljust(14, "0")
    stamp = f"{d[:4]}-{d[4:6]}-{d[6:8]}T{d[8:10]}:{d[10:12]}:{d[12:14]}Z"
    kind = "revisit" if refers_to else "response" if head else "resource"
    block = head if refers_to else record.body
    headers = {"WARC-Type": kind, "WARC-Record-ID": identifier, "WARC-Date": stamp, "WARC-Target-URI": record.fields["url"]}
    if record.fields["ip"] != "0.0.0.0":
        headers["WARC-IP-Address"] = record.fields["ip"]
    headers["WARC-Payload-Digest"] = f"sha256:{hashlib.sha256(payload).hexdigest()}"
    if refers_to:
        headers |= {"WARC-Profile": REVISIT_PROFILE, "WARC-Refers-To": refers_to}
    headers |= {"Content-Type": "application/http; msgtype=response" if head else record.fields["type"], "Content-Length": str(len(block))}
    return WarcRecord(kind, headers, block)


def read_warc(stream: io.BufferedIOBase) -> Iterator[WarcRecord]:
    """Records of an open WARC file, one at a time."""
    while line := stream.readline():
        if line == b"\r\n":
            continue
        if not line.startswith(b"WARC/1."):
            raise ArchiveError(f"not a WARC record: {line[:40]!r}")
        headers: dict[str, str] = {}
        while (line := stream.readline()) not in (b"\r\n", b""):
            name, _, value = line.decode("utf-8", "replace").partition(":")
            headers[name.strip()] = value.strip()
        size = int(headers["Content-Length"])
        block = stream.read(size)
        if len(block) != size:
            raise ArchiveError("record is shorter than it declares")
        yield WarcRecord(headers.get("WARC-Type", ""), headers, block)


def with_first_copy(pages: DataFrame) -> DataFrame:
    """pages (page_id, url, html) and `first`: the smallest page_id with the same payload of MIN_REVISIT bytes or more.

    Digests are aggregated before the join; only payloads that occur more than once take part in it, the pages of a
    payload with a large share of all are dealt over several tasks, and pages without a digest by their hash.
    """
    rows = pages.select(F.col("page_id").cast("bigint").alias("page_id"), "url", F.coalesce("html", F.lit("")).alias("html"))
    alone = F.xxhash64("page_id", "url", "html").cast("string")
    rows = rows.withColumn("__digest", F.when(F.octet_length("html") >= MIN_REVISIT, F.sha2("html", 256)).otherwise(alone))
    counts = rows.where(F.octet_length("html") >= MIN_REVISIT).groupBy("__digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n"))
    copies = checkpointed(counts.where("n > 1"))
    hot = checkpointed(dealt(copies, "__digest", copies.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]))
    copies = repeated(copies.drop("n"), hot, "__digest")
    rows = salted(rows, hot, "__digest", F.struct("page_id", "url"))
    return rows.join(copies, ["__digest", "__salt"], "left").select("page_id", "url", "html", "first")


def member(record: WarcRecord) -> bytes:
    """The record as a gzip member."""
    return gzip.compress(record.head().encode() + record.block + b"\r\n\r\n", 6, mtime=0)


def arc_warc_members(pages: DataFrame) -> DataFrame:
    """(members) rows: WARC records, each a gzip member. The pages of a slice go into ARC files (version 1 or 2 by the
    id's parity), the files are parsed, and the records found there are converted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "html", SLICE_PAGES):
                rows = list(zip(*(part.column(c).to_pylist() for c in ("page_id", "url", "html", "first")), strict=True))
                out = []
                for version in (1, 2):
                    own = [r for r in rows if (r[0] or 0) % 2 == version - 1]
                    bodies = [(url or f"urn:page:{page}", HTTP_OK % len(data := (html or "").encode()) + data) for page, url, html, _ in own]
                    for (page, url, _, first), record in zip(own, read_arc(write_arc(bodies, version)), strict=True):
                        other = record_id(first) if first is not None and page is not None and first != page else None
                        out.append(member(arc_to_warc(record, record_id(page, url or ""), other)))
                yield pa.RecordBatch.from_arrays([pa.array([b"".join(out)], pa.binary())], names=["members"])

    return pages.mapInArrow(run, "members binary")


def write_warc(members: DataFrame, path: str) -> None:
    """A folder of .warc.gz files. The text writer copies bytes as they are; it names files .txt, so they are renamed, one
    call a file."""
    rows = members.select(F.col("members").cast("string").alias("value"))
    rows.write.option("lineSep", EMPTY_MEMBER.decode("latin-1")).option("encoding", "ISO-8859-1").option("compression", "none").option("maxRecordsPerFile", FILE_ROWS).text(path)
    spark = members.sparkSession
    folder = spark._jvm.org.apache.hadoop.fs.Path(path)
    fs = folder.getFileSystem(spark._jsc.hadoopConfiguration())
    for found in fs.globStatus(spark._jvm.org.apache.hadoop.fs.Path(folder, "part-*.txt")):
        fs.rename(found.getPath(), found.getPath().suffix(".warc.gz"))


def read_warc_files(spark, path: str) -> DataFrame:
    """What the archives in a folder hold: one row per record, digests of responses computed anew."""
    schema = "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint, url string, warc_date string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in batch.column("content"):
                rows = []
                with gzip.open(io.BytesIO(content.as_buffer())) as f:
                    for r in read_warc(io.BufferedReader(f, 1 << 20)):
                        head, payload = split_http(r.block)
                        digest, size = r.headers["WARC-Payload-Digest"].removeprefix("sha256:"), len(payload)
                        if r.kind == "revisit":
                            size = int(re.search(rb"(?i)\r\ncontent-length: *(\d+)", head)[1])
                        elif hashlib.sha256(payload).hexdigest() != digest:
                            raise ArchiveError("payload does not fit its digest")
                        refers = r.headers.get("WARC-Refers-To")
                        rows.append((page_of(r.headers["WARC-Record-ID"]), size, digest, r.kind, page_of(refers) if refers else None, r.headers["WARC-Target-URI"], r.headers["WARC-Date"]))
                columns = list(zip(*rows, strict=True)) or [()] * 7
                kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.string())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=[x.split()[0] for x in schema.split(", ")])

    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.warc.gz").load(path)
    return files.select("content").mapInArrow(run, schema)


def archive_pages(pages: DataFrame, path: str | None = None) -> DataFrame:
    """Write the pages to WARC archives in a folder (by default in the shared one) and read them back."""
    spark = pages.sparkSession
    path = path or new_path(spark, "warc")
    write_warc(arc_warc_members(with_first_copy(pages)), path)
    return read_warc_files(spark, path)
