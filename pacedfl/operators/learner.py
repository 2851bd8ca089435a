"""Local training: models over flat parameter vectors, mini-batch steps in Arrow, full-batch gradients in SQL.

A client's steps follow one another, so a client is one stream of rows: rows are clustered and sorted by
(client, epoch, hash order) and read in Arrow batches, mini-batch after mini-batch, in memory that does
not grow with the client; all runs of the client take each mini-batch. Full-batch steps have no such order and are partial sums (gradient_sql).
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from typing import Protocol

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from pacedfl.functions.portable import uniform, uniform_py
from pacedfl.sources.features import to_numpy

MAX_BROADCAST_BYTES = 256 << 20


class Model(Protocol):
    n_params: int

    def start(self, seed: int, at: np.ndarray) -> np.ndarray: ...
    def layers(self) -> np.ndarray: ...
    def grad(self, w: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray: ...
    def predict(self, w: np.ndarray, x: np.ndarray) -> np.ndarray: ...
    def loss(self, w: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray: ...


def _one(x: np.ndarray) -> np.ndarray:
    return np.concatenate([x, np.ones((len(x), 1))], axis=1)


def _softmax(z: np.ndarray) -> np.ndarray:
    z = np.exp(z - z.max(axis=1, keepdims=True))
    return z / z.sum(axis=1, keepdims=True)


def _normal(seed: int, at: np.ndarray, tag: str) -> np.ndarray:
    u = np.array([(uniform_py(seed, f"{tag}.a", i), uniform_py(seed, f"{tag}.b", i)) for i in at.tolist()]).reshape(-1, 2)
    return np.sqrt(-2 * np.log((u[:, 0] * 4294967296.0 + 1) / 4294967297.0)) * np.cos(2 * math.pi * u[:, 1])


@dataclass(frozen=True)
class Softmax:
    """Softmax regression with a constant; weights class by class."""

    n_features: int
    n_classes: int

    @property
    def n_params(self) -> int:
        return self.n_classes * (self.n_features + 1)

    def start(self, seed: int, at: np.ndarray) -> np.ndarray:
        return np.zeros(len(at))

    def layers(self) -> np.ndarray:
        return np.repeat(np.arange(self.n_classes), self.n_features + 1)

    def _scores(self, w, x):
        return _one(x) @ w.reshape(self.n_classes, -1).T

    def grad(self, w, x, y):
        p = _softmax(self._scores(w, x))
        p[np.arange(len(y)), y] -= 1
        return (p.T @ _one(x)).ravel() / len(y)

    def predict(self, w, x):
        return self._scores(w, x).argmax(axis=1)

    def loss(self, w, x, y):
        return -np.log(np.maximum(_softmax(self._scores(w, x))[np.arange(len(y)), y], 1e-300))


@dataclass(frozen=True)
class Perceptron:
    """One hidden layer of tanh units: a non-convex objective."""

    n_features: int
    n_classes: int
    hidden: int = 16

    @property
    def n_params(self) -> int:
        return self.hidden * (self.n_features + 1) + self.n_classes * (self.hidden + 1)

    def start(self, seed: int, at: np.ndarray) -> np.ndarray:
        first = at < self.hidden * (self.n_features + 1)
        return _normal(seed, at, "init") / np.sqrt(np.where(first, self.n_features + 1, self.hidden + 1))

    def layers(self) -> np.ndarray:
        return np.repeat([0, 1], [self.hidden * (self.n_features + 1), self.n_classes * (self.hidden + 1)])

    def _parts(self, w):
        cut = self.hidden * (self.n_features + 1)
        return w[:cut].reshape(self.hidden, -1), w[cut:].reshape(self.n_classes, -1)

    def _forward(self, w, x):
        a, b = self._parts(w)
        h = np.tanh(_one(x) @ a.T)
        return h, _one(h) @ b.T

    def grad(self, w, x, y):
        _, b = self._parts(w)
        h, z = self._forward(w, x)
        p = _softmax(z)
        p[np.arange(len(y)), y] -= 1
        p /= len(y)
        back = (p @ b[:, :-1]) * (1 - h * h)
        return np.concatenate([(back.T @ _one(x)).ravel(), (p.T @ _one(h)).ravel()])

    def predict(self, w, x):
        return self._forward(w, x)[1].argmax(axis=1)

    def loss(self, w, x, y):
        return -np.log(np.maximum(_softmax(self._forward(w, x)[1])[np.arange(len(y)), y], 1e-300))


@dataclass(frozen=True)
class Linear:
    """Least squares; x brings its own constant."""

    n_features: int
    n_classes: int = 1

    @property
    def n_params(self) -> int:
        return self.n_features

    def start(self, seed: int, at: np.ndarray) -> np.ndarray:
        return np.zeros(len(at))

    def layers(self) -> np.ndarray:
        return np.zeros(self.n_features, np.int64)

    def grad(self, w, x, y):
        return 2 * x.T @ (x @ w - y) / len(y)

    def predict(self, w, x):
        return x @ w

    def loss(self, w, x, y):
        return (x @ w - y) ** 2


MODELS = {"softmax": Softmax, "perceptron": Perceptron, "linear": Linear}


def sample_order(seed: int, sample: str = "sample_id") -> Column:
    """Order of a client's samples within an epoch: by hash of seed, round, epoch and sample."""
    return uniform(seed, "order", "round", "epoch", sample)


def sgd(model: Model, w: np.ndarray, batches, lr: float) -> np.ndarray:
    for x, y in batches:
        g = model.grad(w, x, y)
        if not np.isfinite(g).all():
            raise FloatingPointError("gradient is not finite")
        w = w - lr * g
    return w


def start_weights(spark: SparkSession, model: Model, runs: dict[str, int]) -> DataFrame:
    """(run_id, param_idx, w) of each run at its seed, made where it is stored."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = b.column("id").to_numpy()
            for run_id, seed in runs.items():
                yield pa.RecordBatch.from_arrays([pa.array([run_id] * len(at), pa.string()), pa.array(at, pa.int64()), pa.array(model.start(seed, at), pa.float64())], names=["run_id", "param_idx", "w"])

    return spark.range(model.n_params).mapInArrow(run, "run_id string, param_idx bigint, w double")


def packed_weights(weights: DataFrame) -> DataFrame:
    """(run_id, w): one row a run, coordinates in order; as large as the model that a client has to hold."""
    rows = weights.groupBy("run_id").agg(F.array_sort(F.collect_list(F.struct("param_idx", "w"))).alias("__w"))
    return rows.select("run_id", F.col("__w.w").alias("w"))


def vectors(weights: DataFrame, max_bytes: int = MAX_BROADCAST_BYTES, n: int | None = None) -> dict[str, np.ndarray]:
    """Weights by run, on the driver; their number, counted where it is not given, is checked first."""
    n = weights.count() if n is None else n
    if 8 * n > max_bytes:
        raise ValueError(f"{n} weights are too many for the driver")
    return {r.run_id: np.array(r.w, np.float64) for r in packed_weights(weights).collect()}


def local_update(samples: DataFrame, picked: DataFrame, weights: DataFrame, model: Model, lr: float, epochs: int = 1, batch: int | None = 64, seed: int = 42, partitions: int | None = None) -> DataFrame:
    """(run_id, client_id, param_idx, delta): start weights less trained ones, non-zero entries only.

    samples: (sample_id, client_id, x, y), training rows. picked: (run_id, round, client_id), the round's clients
    of each run. weights: (run_id, param_idx, w). A client's samples are moved and sorted once, whatever the number
    of runs; the weights of its runs come before them in the same stream, so nothing is broadcast. batch None makes a
    whole epoch one step.
    """
    label = samples.schema["y"].dataType
    rows = samples.select("sample_id", "client_id", "x", "y").join(picked.select("round", "client_id").distinct(), "client_id")
    rows = rows.withColumn("epoch", F.explode(F.sequence(F.lit(1), F.lit(epochs)))).withColumn("__o", sample_order(seed)).drop("round").withColumn("run_id", F.lit(None).cast("string"))
    heads = picked.select("run_id", "client_id").join(packed_weights(weights), "run_id")
    heads = heads.select(F.lit(None).cast("bigint").alias("sample_id"), "client_id", F.col("w").alias("x"), F.lit(0).cast(label).alias("y"), F.lit(0).alias("epoch"), F.lit(0.0).alias("__o"), "run_id")
    rows = rows.unionByName(heads)
    rows = rows.repartition(partitions, "client_id") if partitions else rows.repartition("client_id")
    rows = rows.sortWithinPartitions("client_id", "epoch", "__o", "sample_id", "run_id").select("client_id", "epoch", "run_id", "x", "y")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        client, epoch, start, now, xs, ys, held = None, 0, {}, {}, [], [], 0

        def step(force: bool):
            nonlocal xs, ys, held
            if not held or not force and (batch is None or held < batch):
                return
            x, y = np.concatenate(xs), np.concatenate(ys)
            n = len(y) if batch is None else batch
            ends = len(y) if force else len(y) // n * n
            parts = [(x[a : a + n], y[a : a + n]) for a in range(0, ends, n)]
            for run_id, w in now.items():
                now[run_id] = sgd(model, w, parts, lr)
            xs, ys, held = [x[ends:]], [y[ends:]], len(y) - ends

        def done() -> Iterator[pa.RecordBatch]:
            step(True)
            for run_id, w in now.items():
                d = start[run_id] - w
                at = np.flatnonzero(d)
                yield pa.RecordBatch.from_arrays([pa.array([run_id] * len(at), pa.string()), pa.array(np.full(len(at), client, np.int32)), pa.array(at.astype(np.int64)), pa.array(d[at])], names=["run_id", "client_id", "param_idx", "delta"])

        for b in batches:
            if not b.num_rows:
                continue
            ids, eps = b.column("client_id").to_numpy(), b.column("epoch").to_numpy()
            cuts = np.flatnonzero((ids[1:] != ids[:-1]) | (eps[1:] != eps[:-1])) + 1
            for a, z in zip([0, *cuts.tolist()], [*cuts.tolist(), len(ids)], strict=True):
                if ids[a] != client:
                    yield from done()
                    client, epoch, start, now, xs, ys, held = int(ids[a]), 0, {}, {}, [], [], 0
                x = to_numpy(b.column("x").slice(a, z - a))
                if not eps[a]:
                    start |= zip(b.column("run_id").slice(a, z - a).to_pylist(), x, strict=True)
                    now = dict(start)
                    continue
                if eps[a] != epoch:
                    step(True)
                    epoch = eps[a]
                xs.append(x)
                ys.append(b.column("y").slice(a, z - a).to_numpy(zero_copy_only=False))
                held += z - a
                step(False)
        yield from done()

    return rows.mapInArrow(run, "run_id string, client_id int, param_idx bigint, delta double")


def gradient_sql(samples: DataFrame, weights: list[float]) -> DataFrame:
    """(client_id, param_idx, grad, n): mean gradient of the squared error, one full-batch step, no Python.

    One shuffle with partial sums: (clients x parameters) rows from each task.
    """
    w = F.array(*(F.lit(float(v)) for v in weights))
    error = F.aggregate(F.zip_with("x", w, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v) - F.col("y")
    rows = samples.select("client_id", error.alias("e"), F.posexplode("x").alias("param_idx", "v"))
    return rows.groupBy("client_id", F.col("param_idx").cast("long").alias("param_idx")).agg((2 * F.avg(F.col("e") * F.col("v"))).alias("grad"), F.count("*").alias("n"))


_SCORES = "run_id string, y int, n bigint, correct bigint, loss double"


def _scored(model: Model, start: dict[str, np.ndarray], x: np.ndarray, y: np.ndarray) -> pa.RecordBatch:
    rows = []
    for run_id, w in start.items():
        right, loss = model.predict(w, x) == y, model.loss(w, x, y)
        group = np.zeros(len(y), np.int64) if isinstance(model, Linear) else y
        for c in np.unique(group).tolist():
            k = group == c
            rows.append((run_id, int(c), int(k.sum()), int(right[k].sum()), float(loss[k].sum())))
    kinds = (pa.string(), pa.int32(), pa.int64(), pa.int64(), pa.float64())
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds)], names=["run_id", "y", "n", "correct", "loss"])


def evaluate(test: DataFrame, weights: DataFrame, model: Model, n_runs: int, max_bytes: int = MAX_BROADCAST_BYTES) -> DataFrame:
    """(run_id, y, n, correct, loss) summed over test rows by run and class: counts leave a task, never rows.

    Weights of up to max_bytes are broadcast; larger ones go to the parts that the test rows are dealt to.
    """
    if 8 * n_runs * model.n_params <= max_bytes:
        shared = test.sparkSession.sparkContext.broadcast(vectors(weights, max_bytes, n_runs * model.n_params))

        def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if b.num_rows:
                    yield _scored(model, shared.value, to_numpy(b.column("x")), b.column("y").to_numpy(zero_copy_only=False))

        rows = test.select("x", "y").mapInArrow(whole, _SCORES)
    else:
        parts = int(test.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        heads = packed_weights(weights).select(F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"), "run_id", F.col("w").alias("x"), F.lit(0).cast(test.schema["y"].dataType).alias("y"))
        dealt = test.select(F.pmod(F.xxhash64("sample_id"), F.lit(parts)).cast("int").alias("part"), F.lit(None).cast("string").alias("run_id"), "x", "y").unionByName(heads)

        def dealt_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            part, start = None, {}
            for b in batches:
                if not b.num_rows:
                    continue
                key, head = b.column("part").to_numpy(), b.column("run_id").is_valid().to_numpy(zero_copy_only=False)
                cuts = np.flatnonzero((key[1:] != key[:-1]) | (head[1:] != head[:-1])) + 1
                for a, z in zip([0, *cuts.tolist()], [*cuts.tolist(), len(key)], strict=True):
                    if key[a] != part:
                        part, start = key[a], {}
                    x = to_numpy(b.column("x").slice(a, z - a))
                    if head[a]:
                        start |= zip(b.column("run_id").slice(a, z - a).to_pylist(), x, strict=True)
                    else:
                        yield _scored(model, start, x, b.column("y").slice(a, z - a).to_numpy(zero_copy_only=False))

        rows = dealt.repartition("part").sortWithinPartitions("part", F.col("run_id").asc_nulls_last()).mapInArrow(dealt_out, _SCORES)
    return rows.groupBy("run_id", "y").agg(F.sum("n").alias("n"), F.sum("correct").alias("correct"), F.sum("loss").alias("loss"))


def predictions(test: DataFrame, w: np.ndarray, model: Model) -> DataFrame:
    """(sample_id, y, pred) of one run."""
    shared = test.sparkSession.sparkContext.broadcast((w, model))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w_, m = shared.value
        for b in batches:
            pred = m.predict(w_, to_numpy(b.column("x"))) if b.num_rows else np.empty(0)
            yield pa.RecordBatch.from_arrays([b.column("sample_id"), b.column("y"), pa.array(pred.astype(np.int32))], names=["sample_id", "y", "pred"])

    return test.select("sample_id", F.col("y").cast("int").alias("y"), "x").mapInArrow(run, "sample_id bigint, y int, pred int")


def objective(samples: DataFrame, w: np.ndarray, model: Model) -> DataFrame:
    """(client_id, n, risk, weighted): each client's mean loss, and its share of the global objective."""
    shared = samples.sparkSession.sparkContext.broadcast((w, model))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w_, m = shared.value
        for b in batches:
            loss = m.loss(w_, to_numpy(b.column("x")), b.column("y").to_numpy(zero_copy_only=False)) if b.num_rows else np.empty(0)
            yield pa.RecordBatch.from_arrays([b.column("client_id"), pa.array(loss, pa.float64())], names=["client_id", "loss"])

    rows = samples.select("client_id", "x", "y").mapInArrow(run, "client_id int, loss double").groupBy("client_id").agg(F.count("*").alias("n"), F.avg("loss").alias("risk"))
    total = rows.agg(F.sum("n").alias("__n"))
    return rows.crossJoin(F.broadcast(total)).select("client_id", "n", "risk", (F.col("risk") * F.col("n") / F.col("__n")).alias("weighted"))
