"""Ordinal quality grading: a cumulative-link (proportional odds) model over hashed text.

Grades are 0 (toxic), 1 (poor) and 2 (good). All grades share one weight vector over hashed features;
ordered thresholds cut the score: P(grade <= k) = sigmoid(threshold_k - score). The model gives the
expected grade and the tail probability P(grade >= SELECT_GRADE) by which documents are selected.

Features: presence of each word (lower case, outer punctuation removed) and of its prefixes of 5 to 7
characters in 2^17 buckets, and the share of each word shape (case and punctuation pattern) in 2^10 more.

Edge cases: null or empty text has no features and is graded by the thresholds alone; documents without
a label are not learned from; several labels of a document count as the lowest; with fewer than two
grades in the sample everything is selected.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F

from pacedfl.llm.common import WORD_CACHE, raw, slices

WORD_BITS, SHAPE_BITS = 17, 10
WIDTH = (1 << WORD_BITS) + (1 << SHAPE_BITS)
SAMPLE_ROWS = 6000  # labelled documents that the fit reads at most
SCREEN = 5.0  # standard deviations
SELECT_GRADE = 2
SELECT_TAIL = 0.3
PREFIXES = (5, 6, 7)
DIGIT = re.compile(rb"[0-9]")
PUNCTUATION = b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"


class WordFeatures(dict):
    """word -> (shape bucket, buckets of the word and of its prefixes), of the live buckets where they are given."""

    def __init__(self, live: np.ndarray | None = None):
        super().__init__()
        self.live = None if live is None else set(np.flatnonzero(live).tolist())
        self.buckets: dict[str, int] = {}
        self.shapes: dict[bytes, int] = {}

    def __missing__(self, word: bytes) -> tuple[int, tuple[int, ...]]:
        core = word.strip(PUNCTUATION)
        head, _, tail = word.partition(core) if core else (word, b"", b"")
        case = b"-" if not core else b"U" if core.isupper() and len(core) > 1 else b"T" if core[:1].isupper() else b"l"
        name = head[-2:] + case + (b"9" if DIGIT.search(core) else b"") + tail[:2]
        if (shape := self.shapes.get(name)) is None:
            shape = self.shapes[name] = (1 << WORD_BITS) + (xxhash.xxh64_intdigest(name, 8) & ((1 << SHAPE_BITS) - 1))
        low = core.decode("utf-8", "replace").lower()
        n, known = len(low), self.buckets
        if len(self) >= WORD_CACHE:
            self.clear()
        if len(known) >= WORD_CACHE:
            known.clear()
        found = []
        for part in (low, *(low[:k] + "*" for k in PREFIXES if n > k)):
            if (bucket := known.get(part)) is None:
                bucket = xxhash.xxh64_intdigest(part.encode(), 7) & ((1 << WORD_BITS) - 1)
                if self.live is not None and bucket not in self.live:
                    bucket = -1
                if len(part) < 9:  # whole words rarely come back once their own entry is gone
                    known[part] = bucket
            if bucket >= 0:
                found.append(bucket)
        self[word] = out = (shape, tuple(found))
        return out


def features(text: bytes, cache: WordFeatures) -> tuple[np.ndarray, np.ndarray]:
    """Sorted feature indexes of a text and their values."""
    count = Counter(text.split())
    if not count:
        return np.empty(0, np.int32), np.empty(0, np.float32)
    shapes: dict[int, int] = {}
    words: set[int] = set()
    for word, n in count.items():
        shape, buckets = cache[word]
        shapes[shape] = shapes.get(shape, 0) + n
        if buckets:
            words.update(buckets)
    known = np.fromiter(words, np.int32, len(words))
    known.sort()
    share = np.array(sorted(shapes.items()), dtype=np.float64).reshape(-1, 2)
    return np.concatenate([known, share[:, 0].astype(np.int32)]), np.concatenate([np.ones(len(known), np.float32), (10 * share[:, 1] / count.total()).astype(np.float32)])


@dataclass
class OrdinalModel:
    weights: np.ndarray
    thresholds: np.ndarray

    def tails(self, score: float) -> np.ndarray:
        """P(grade >= k) for k = 1 .. number of grades - 1."""
        return 1 / (1 + np.exp(np.clip(self.thresholds - score, -60, 60)))


def _screened(row: np.ndarray, column: np.ndarray, grades: np.ndarray, width: int, screen: float) -> np.ndarray:
    """Features whose presence and a grade go together beyond chance, given how common both are."""
    n, live = len(grades), np.zeros(width, bool)
    seen = np.bincount(column, minlength=width)
    p = seen / n
    for k in np.unique(grades):
        inside = (grades == k)[row].astype(np.float64)
        share = (grades == k).mean()
        z = (np.bincount(column, inside, minlength=width) - seen * share) / np.sqrt(np.maximum(n * p * (1 - p) * share * (1 - share), 0.25))
        live |= (np.abs(z) > screen) & (seen >= 3)
    return live


def ordinal_loss(params: np.ndarray, row: np.ndarray, column: np.ndarray, value: np.ndarray, grades: np.ndarray, weight_of: np.ndarray, ridge: float) -> tuple[float, np.ndarray]:
    """Mean weighted negative log likelihood with a ridge, and its gradient.

    params: a weight of each column, the lowest threshold, logarithms of the steps to the others. Entries of a row's
    features are (row, column, value).
    """
    n_grades = int(grades.max()) + 1
    n = len(params) - n_grades + 1
    sig = lambda x: 1 / (1 + np.exp(-np.clip(x, -60, 60)))
    w, theta = params[:n], np.cumsum(np.concatenate([params[n : n + 1], np.exp(params[n + 1 :])]))
    score = np.bincount(row, w[column] * value, minlength=len(grades))
    edges = np.concatenate([[-np.inf], theta, [np.inf]])
    upper, lower = sig(edges[grades + 1] - score), sig(edges[grades] - score)
    p = np.maximum(upper - lower, 1e-12)
    du, dl = upper * (1 - upper) / p, lower * (1 - lower) / p
    g_score = weight_of * (du - dl) / len(grades)
    g_theta = np.zeros(n_grades + 1)
    np.add.at(g_theta, grades + 1, -weight_of * du / len(grades))
    np.add.at(g_theta, grades, weight_of * dl / len(grades))
    g_theta = g_theta[1:-1]
    grad = np.concatenate([np.bincount(column, g_score[row] * value, minlength=n) + ridge * w, [g_theta.sum()], np.exp(params[n + 1 :]) * np.cumsum(g_theta[::-1])[::-1][1:]])
    return float((weight_of * -np.log(p)).sum() / len(grades) + ridge * (w @ w) / 2), grad


def fit_ordinal(indexes: list[np.ndarray], values: list[np.ndarray], grades: np.ndarray, steps: int = 300, rate: float = 0.05, ridge: float = 3e-4, screen: float = SCREEN) -> OrdinalModel:
    """Maximum likelihood with a ridge by full-batch adaptive gradient steps."""
    n_grades = int(grades.max()) + 1 if len(grades) else 0
    if n_grades < 2 or len(np.unique(grades)) < 2:
        return OrdinalModel(np.zeros(WIDTH, np.float32), np.full(max(1, n_grades - 1), -60.0))
    sizes = np.fromiter(map(len, indexes), np.int64)
    at, value = np.concatenate(indexes), np.concatenate(values)
    used, column = np.unique(at, return_inverse=True)
    row = np.repeat(np.arange(len(sizes)), sizes)
    live = _screened(row, column, grades, len(used), screen)
    keep = live[column]  # the rest carries noise only
    row, column, value = row[keep], column[keep], value[keep]
    share = np.array([(grades <= k).mean() for k in range(n_grades - 1)]).clip(1e-3, 1 - 1e-3)
    cut = np.log(share / (1 - share))
    params = np.concatenate([np.zeros(len(used)), [cut[0]], np.log(np.maximum(np.diff(cut), 1e-2))])
    m, v = np.zeros_like(params), np.zeros_like(params)
    weight_of = len(grades) / (len(np.unique(grades)) * np.maximum(np.bincount(grades, minlength=n_grades), 1))[grades]
    weight_of = np.sqrt(weight_of)
    for step in range(1, steps + 1):
        _, grad = ordinal_loss(params, row, column, value, grades, weight_of, ridge)
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
        params = params - rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-9)
    weights = np.zeros(WIDTH, np.float32)
    weights[used] = params[: len(used)]
    return OrdinalModel(weights, np.cumsum(np.concatenate([params[len(used) : len(used) + 1], np.exp(params[len(used) + 1 :])])))


def graded_labels(labels: DataFrame) -> DataFrame:
    """(doc_id, grade): 0 toxic, 1 poor, 2 good; the lowest of several labels; nulls in either column drop the row."""
    grade = F.when(F.col("toxic") == 1, 0).when(F.col("quality") == 0, 1).otherwise(2)
    rows = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & F.col("quality").isNotNull())
    return rows.groupBy("doc_id").agg(F.min(grade).alias("grade"))


def fit_quality_model(docs: DataFrame, grades: DataFrame, id_col: str = "doc_id", text_col: str = "text", sample_rows: int = SAMPLE_ROWS, seed: int = 1) -> OrdinalModel:
    """Fit on at most sample_rows labelled documents, picked by a hash of their identifier.

    The sample bounds what is broadcast (identifiers and grades) and what the driver gathers (features).
    """
    sample = grades.orderBy(F.xxhash64("doc_id", F.lit(seed)), "doc_id").limit(sample_rows)
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).join(F.broadcast(sample), "doc_id").select("grade", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = WordFeatures()
        for batch in batches:
            for part in slices(batch, "text"):
                pairs = [features(t, cache) for t in raw(part, "text")]
                yield pa.RecordBatch.from_arrays([part.column("grade").cast(pa.int32()), pa.array([a.astype("<i4").tobytes() for a, _ in pairs], pa.binary()), pa.array([b.astype("<f4").tobytes() for _, b in pairs], pa.binary())], names=["grade", "at", "value"])

    got = rows.mapInArrow(run, "grade int, at binary, value binary").toArrow().to_pydict()
    # one order whatever the partitions: sums of floats then agree from run to run
    got = sorted(zip(got["grade"], got["at"], got["value"], strict=True))
    return fit_ordinal([np.frombuffer(a, "<i4") for _, a, _ in got], [np.frombuffer(b, "<f4") for _, _, b in got], np.array([g for g, _, _ in got], dtype=np.int64))


def _graded(part: pa.RecordBatch, text_col: str, model: OrdinalModel, cache: WordFeatures) -> tuple[list[float], list[float]]:
    expected, tail = [], []
    for text in raw(part, text_col):
        at, value = features(text, cache)
        t = model.tails(float((model.weights[at].astype(np.float64) * value).sum()))
        expected.append(float(t.sum()))
        tail.append(float(t[min(SELECT_GRADE, len(t)) - 1]))
    return expected, tail


def grade_documents(docs: DataFrame, model: OrdinalModel, id_col: str = "doc_id", text_col: str = "text", select_tail: float = SELECT_TAIL) -> DataFrame:
    """(id, expected_grade, tail_probability, selected) for every input row; no shuffle."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = WordFeatures(shared.value.weights)
        for batch in batches:
            for part in slices(batch, text_col):
                expected, tail = _graded(part, text_col, shared.value, cache)
                yield pa.RecordBatch.from_arrays([part.column(id_col).cast(pa.int64()), pa.array(expected, pa.float64()), pa.array(tail, pa.float64()), pa.array([x >= select_tail for x in tail], pa.bool_())], names=[id_col, "expected_grade", "tail_probability", "selected"])

    return docs.select(id_col, text_col).mapInArrow(run, f"{id_col} bigint, expected_grade double, tail_probability double, selected boolean")


def select_documents(docs: DataFrame, model: OrdinalModel, text_col: str = "text", select_tail: float = SELECT_TAIL) -> DataFrame:
    """The rows of docs, with all their columns, that the model selects."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = WordFeatures(shared.value.weights)
        for batch in batches:
            for part in slices(batch, text_col):
                _, tail = _graded(part, text_col, shared.value, cache)
                yield part.filter(pa.array([x >= select_tail for x in tail], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
