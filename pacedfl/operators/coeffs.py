"""Averaging weights of a round's clients."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from pacedfl.operators.schedule import per_round


def with_share(selected: DataFrame, weighting: str = "samples") -> DataFrame:
    """Adds f: the client's share of the round's samples, or 1/K. Clients without samples get 0."""
    if weighting == "uniform":
        return selected.withColumn("f", 1.0 / F.count("*").over(per_round()))
    n = F.coalesce(F.col("n_samples"), F.lit(0))
    return selected.withColumn("f", F.coalesce(n / F.nullif(F.sum(n).over(per_round()), F.lit(0)), F.lit(0.0)))


def normalised(ratio: Column, norm: str = "sum") -> Column:
    """A round's keep-ratios on the scale of shares."""
    if norm == "sum":
        return ratio / F.sum(ratio).over(per_round())
    if norm == "max":
        return ratio / F.max(ratio).over(per_round())
    if norm == "minmax":
        lo, hi = F.min(ratio).over(per_round()), F.max(ratio).over(per_round())
        return F.coalesce((ratio - lo) / F.nullif(hi - lo, F.lit(0.0)), F.lit(0.0))
    if norm == "none":
        return ratio
    raise ValueError(norm)


def with_adjusted(selected: DataFrame, alpha: float = 0.3, norm: str = "sum", renormalize: bool = False) -> DataFrame:
    """Adds norm_ratio and p_adj = alpha * f / max(f, normalised ratio): at most alpha, and less where a client sends much.

    renormalize: scale the round's coefficients so that they sum to alpha.
    """
    rows = selected.withColumn("norm_ratio", normalised(F.col("keep_ratio"), norm))
    p = F.coalesce(F.col("f") / F.nullif(F.greatest("f", "norm_ratio"), F.lit(0.0)), F.lit(0.0)) * alpha
    rows = rows.withColumn("p_adj", p)
    return rows.withColumn("p_adj", F.col("p_adj") * alpha / F.sum("p_adj").over(per_round())) if renormalize else rows


def coef_stats(selected: DataFrame, column: str = "p_adj") -> DataFrame:
    """Per round: sum, largest, and largest over mean of the coefficients."""
    return selected.groupBy("round").agg(F.sum(column).alias("coef_sum"), F.max(column).alias("coef_max"), (F.max(column) / F.avg(column)).alias("coef_skew"))
