"""Vectorised Python functions for packed updates and predictions, where built-in functions do not reach."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, functions as F, types as T


def predictor(model, w: np.ndarray):
    """A scalar pandas UDF: features array -> predicted class."""

    @F.pandas_udf("int")
    def predict(x: pd.Series) -> pd.Series:
        return pd.Series(model.predict(w, np.stack(x.to_numpy())).astype(np.int32) if len(x) else np.empty(0, np.int32))

    return predict


def merged(packed: DataFrame, weight: str, by: tuple[str, ...] = ("shard",)) -> DataFrame:
    """Weighted sum of packed updates (idx, val) within each shard, as one packed update with degrees.

    A shard holds one stretch of coordinates of all clients of a round, so a group is bounded by clients
    times stretch; choose the number of shards for that.
    """
    names = list(by)

    def merge(frame: pd.DataFrame) -> pd.DataFrame:
        idx = np.concatenate([np.asarray(i, np.int64) for i in frame["idx"]])
        val = np.concatenate([np.asarray(v, np.float64) * p for v, p in zip(frame["val"], frame[weight], strict=True)])
        at, place = np.unique(idx, return_inverse=True)
        out = {n: [frame[n].iloc[0]] for n in names}
        return pd.DataFrame(out | {"idx": [at.tolist()], "step": [np.bincount(place, val, len(at)).tolist()], "degree": [np.bincount(place, minlength=len(at)).tolist()]})

    kinds = {f.name: f.dataType.simpleString() for f in packed.schema}
    schema = ", ".join(f"{n} {kinds[n]}" for n in names) + ", idx array<bigint>, step array<double>, degree array<bigint>"
    return packed.select(*names, "idx", "val", weight).groupBy(*names).applyInPandas(merge, schema)


@F.pandas_udf(T.DoubleType())
def packed_norm(val: pd.Series) -> float:
    """Grouped aggregate: norm of all values of packed updates."""
    return float(np.sqrt(sum(float(np.square(np.asarray(v, np.float64)).sum()) for v in val)))


@F.udtf(returnType=T.StructType([T.StructField("param_idx", T.LongType()), T.StructField("delta", T.DoubleType())]))
class UnpackUpdate:
    """Table function: a packed update's entries as rows."""

    def eval(self, idx, val):
        for i, v in zip(idx or (), val or (), strict=True):
            yield int(i), float(v)


def feedback_cogroup(delta: DataFrame, residual: DataFrame, k: int) -> DataFrame:
    """Error feedback by cogrouping update and residual on the client: (client_id, param_idx, sent, residual).

    For updates that fit a task; the join in `compress.ef_topk` has no such bound.
    """

    def step(d: pd.DataFrame, r: pd.DataFrame) -> pd.DataFrame:
        both = pd.concat([d[["client_id", "param_idx", "delta"]], r.rename(columns={"residual": "delta"})[["client_id", "param_idx", "delta"]]])
        total = both.groupby(["client_id", "param_idx"], as_index=False)["delta"].sum()
        total = total[total["delta"] != 0]
        order = total.assign(m=-total["delta"].abs()).sort_values(["m", "param_idx"]).index[:k]
        sent = np.where(total.index.isin(order), total["delta"], 0.0)
        return pd.DataFrame({"client_id": total["client_id"], "param_idx": total["param_idx"], "sent": sent, "residual": total["delta"] - sent})

    own, old = (df.select(*(F.col(c).alias(f"__{n}_{c}").alias(c) for c in df.columns)) for n, df in enumerate((delta, residual)))
    return own.groupBy("client_id").cogroup(old.groupBy("client_id")).applyInPandas(step, "client_id int, param_idx bigint, sent double, residual double")


def clipped(delta: DataFrame, limit: float) -> DataFrame:
    """Entries clipped to a magnitude, batch by batch (mapInPandas); the built-in form is a projection."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            yield f.assign(delta=f["delta"].clip(-limit, limit))

    return delta.mapInPandas(run, delta.schema)


def clip(c: Column | str, limit: float) -> Column:
    c = F.col(c) if isinstance(c, str) else c
    return F.greatest(F.lit(-limit), F.least(F.lit(limit), c))
