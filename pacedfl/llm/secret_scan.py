"""Secret scan: three fixed kinds of span, and random strings found by their token efficiency.

A run of key characters that the tiktoken vocabulary can only spell in short tokens is likely random.
Candidates are runs of at least MIN_RUN characters with letters and digits; runs that are known digests
(hexadecimal of a digest's length), UUIDs, dates, or identifiers made of ordinary words are excluded
before the ratio of characters to tokens is tested.

Edge cases: null text is an empty text with no spans; spans are code points, end exclusive; texts of any
length are scanned whole.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from pacedfl.llm.byte_bpe import ByteBpe, loaded
from pacedfl.llm.common import slices, texts

# Fixed values of the result contract: kinds in their order, and their patterns.
KINDS = ("assign", "access", "hex", "random")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"(?<![0-9a-f])[0-9a-f]{32,}")

MIN_RUN = 20
MAX_RATIO = 2.2
RUN = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{%d,}" % MIN_RUN)
DIGEST = re.compile(r"(?:[0-9a-f]+|[0-9A-F]+)")
DIGEST_SIZES = (32, 40, 48, 56, 64, 96, 128)
UUID = re.compile(r"[0-9A-Fa-f]{8}(?:-[0-9A-Fa-f]{4}){3}-[0-9A-Fa-f]{12}")
PART = re.compile(r"[_\-/=+]+")
WORDS = re.compile(r"(?:[A-Z]?[a-z]+|[A-Z]+|[0-9]+)")
ASSIGN_KEYS = ("password", "passwd", "secret", "token", "apikey", "api_key")


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of the three fixed kinds."""
    found = []
    low = text.lower()
    if any(k in low for k in ASSIGN_KEYS):
        found += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 8]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 16]
    found += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(found)


def is_known(run: str) -> bool:
    """A digest, a UUID, or an identifier: parts that are words or numbers of a few characters a switch."""
    if not (any(c.isdigit() for c in run) and any(c.isalpha() for c in run)):
        return True
    if len(run) in DIGEST_SIZES and DIGEST.fullmatch(run) or UUID.fullmatch(run):
        return True
    parts = [w for p in PART.split(run) if p for w in WORDS.findall(p)]
    return len(run) / max(1, len(parts)) >= 5


def random_spans(text: str, taken: list[tuple[int, int, int]], bpe: ByteBpe, max_ratio: float = MAX_RATIO) -> list[tuple[int, int, int]]:
    """Spans of random strings that no other span touches."""
    runs = [m for m in RUN.finditer(text) if not is_known(m[0]) and not any(a < m.end() and m.start() < b for a, _, b in taken)]
    if not runs:
        return []
    return [(m.start(), 3, m.end()) for m, ids in zip(runs, bpe.encode_batch([m[0] for m in runs]), strict=True) if len(m[0]) < max_ratio * (len(ids) // 4)]


def show(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


def redacted(text: str, spans: list[tuple[int, int, int]], mark: str) -> str:
    """The text with each stretch that spans cover replaced by the mark."""
    out, end = [], 0
    for a, _, b in spans:
        if a >= end:
            out += [text[end:a], mark]
        end = max(end, b)
    return "".join(out) + text[end:]


def scan_secrets(docs: DataFrame, vocabulary: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", max_ratio: float = MAX_RATIO) -> DataFrame:
    """Counts, digest and spans of every document; one row per input row, no shuffle."""
    schema = f"{id_col} bigint, n_assign bigint, n_access bigint, n_hex bigint, n_random bigint, base_sha256 string, spans string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = loaded(vocabulary, pattern)
        for batch in batches:
            for part in slices(batch, text_col):
                rows = []
                for text in texts(part, text_col):
                    base = base_spans(text)
                    more = random_spans(text, base, bpe, max_ratio)
                    rows.append((*(sum(k == i for _, k, _ in base) for i in range(3)), len(more), hashlib.sha256(show(base).encode()).hexdigest(), show(sorted(base + more))))
                columns = zip(*rows, strict=True)
                types = [pa.int64()] * 4 + [pa.string()] * 2
                yield pa.RecordBatch.from_arrays([part.column(id_col).cast(pa.int64()), *(pa.array(c, t) for c, t in zip(columns, types, strict=True))], names=[x.split()[0] for x in schema.split(", ")])

    return docs.select(id_col, text_col).mapInArrow(run, schema)


def redact_secrets(docs: DataFrame, vocabulary: str, pattern: str, text_col: str = "text", mark: str = "[secret]", max_ratio: float = MAX_RATIO) -> DataFrame:
    """docs with every secret replaced by the mark; all other columns and clean texts stay as they are.

    A column n_chars, where there is one, follows the changed text.
    """
    names = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = loaded(vocabulary, pattern)
        for batch in batches:
            for part in slices(batch, text_col):
                clean = []
                for text in part.column(text_col).to_pylist():
                    spans = base_spans(text or "")
                    spans = sorted(spans + random_spans(text or "", spans, bpe, max_ratio))
                    clean.append(redacted(text, spans, mark) if spans else text)
                yield part.set_column(part.schema.get_field_index(text_col), part.schema.field(text_col), pa.array(clean, part.schema.field(text_col).type))

    out = docs.mapInArrow(run, docs.schema)
    if "n_chars" in names and text_col in names:
        kind = docs.schema["n_chars"].dataType
        out = out.withColumn("n_chars", F.when(F.col(text_col).contains(mark), F.length(text_col)).otherwise(F.col("n_chars")).cast(kind))
    return out.select(*names)
