"""Who takes part in a round, and how much each may send.

Everything is per round and stays in one plan: the pace is a window maximum over the round's clients.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, WindowSpec, functions as F

from pacedfl.functions.portable import uniform
from pacedfl.operators.links import V_MBIT, sparse_time


def per_round() -> WindowSpec:
    return Window.partitionBy("round")


def n_selected(n_clients: int, fraction: float) -> int:
    return max(1, int(n_clients * fraction + 1e-9))


def _in_rounds(clients: DataFrame, rounds: int) -> DataFrame:
    return clients.withColumn("round", F.explode(F.sequence(F.lit(0), F.lit(rounds - 1))))


def select_by_threshold(clients: DataFrame, rounds: int, fraction: float = 0.5, seed: int = 42) -> DataFrame:
    """Each client takes part in each round with probability fraction, by its hash: no exchange, no ranking. The
    number of clients differs from round to round."""
    return _in_rounds(clients, rounds).where(uniform(seed, "select", "round", "client_id") < fraction)


def select_clients(clients: DataFrame, rounds: int, n_clients: int, fraction: float = 0.5, seed: int = 42) -> DataFrame:
    """The clients of each round: those of smallest hash. Adds `round`, keeps the clients' columns.

    The literal bound lets Spark cut each partition's candidates before the exchange. With millions of clients and a
    fraction that makes thousands of them, select_by_threshold ranks nothing.
    """
    order = Window.partitionBy("round").orderBy("__u", "client_id")
    rows = _in_rounds(clients, rounds).withColumn("__u", uniform(seed, "select", "round", "client_id"))
    return rows.withColumn("__r", F.row_number().over(order)).where(F.col("__r") <= n_selected(n_clients, fraction)).drop("__r", "__u")


def with_pace(selected: DataFrame, base_ratio: float, v: float = V_MBIT, factor: float = 2.0) -> DataFrame:
    """Adds t_base and t_bench, the time of the slowest client of the round at the base ratio."""
    rows = selected.withColumn("t_base", sparse_time(v, base_ratio, "bandwidth_mbps", "latency_s", factor))
    return rows.withColumn("t_bench", F.max("t_base").over(per_round()))


def pace_time(selected: DataFrame, base_ratio: float, v: float = V_MBIT, factor: float = 2.0) -> DataFrame:
    """(round, t_bench, pace_client); ties go to the lowest id."""
    rows = selected.withColumn("t_base", sparse_time(v, base_ratio, "bandwidth_mbps", "latency_s", factor))
    slowest = F.max_by("client_id", F.struct("t_base", -F.col("client_id")))
    return rows.groupBy("round").agg(F.max("t_base").alias("t_bench"), slowest.alias("pace_client"))


def pace_time_argmin(selected: DataFrame, base_ratio: float, v: float = V_MBIT, factor: float = 2.0) -> DataFrame:
    """Diagnostic: the other reading of the pace, the fastest client's time."""
    rows = selected.withColumn("t_base", sparse_time(v, base_ratio, "bandwidth_mbps", "latency_s", factor))
    return rows.groupBy("round").agg(F.min("t_base").alias("t_bench"), F.min_by("client_id", F.struct("t_base", "client_id")).alias("pace_client"))


def kept_count(ratio: Column, n_params: Column | int) -> Column:
    """k of a ratio; the small constant undoes the rounding of a divide and multiply round trip."""
    p = n_params if isinstance(n_params, Column) else F.lit(n_params)
    return F.greatest(F.lit(1), F.floor(ratio * p + 1e-9)).cast("long")


def paced_ratios(selected: DataFrame, base_ratio: float, n_params: int, v: float = V_MBIT, clamp: bool = True, dense_fallback: bool = False, factor: float = 2.0) -> DataFrame:
    """Adds keep_ratio_raw, keep_ratio, k and t_after so that all uploads of a round end with the slowest.

    clamp: no ratio above 1. dense_fallback: a ratio above one half is billed as a dense upload.
    """
    rows = with_pace(selected, base_ratio, v, factor)
    raw = (F.col("t_bench") - F.col("latency_s")) * F.col("bandwidth_mbps") / (factor * v)
    rows = rows.withColumn("keep_ratio_raw", raw)
    ratio = F.least(F.lit(1.0), F.col("keep_ratio_raw")) if clamp else F.col("keep_ratio_raw")
    rows = rows.withColumn("keep_ratio", ratio)
    billed = F.least(factor * F.col("keep_ratio"), F.lit(1.0)) / factor if dense_fallback else F.col("keep_ratio")
    rows = rows.withColumn("k", kept_count(F.least(F.lit(1.0), F.col("keep_ratio")), n_params))
    return rows.withColumn("t_after", sparse_time(v, billed, "bandwidth_mbps", "latency_s", factor))


def uniform_ratios(selected: DataFrame, base_ratio: float, n_params: int, v: float = V_MBIT, factor: float = 2.0) -> DataFrame:
    """The same columns when every client keeps the base ratio."""
    rows = with_pace(selected, base_ratio, v, factor)
    rows = rows.withColumns({"keep_ratio_raw": F.lit(float(base_ratio)), "keep_ratio": F.lit(float(base_ratio)), "k": kept_count(F.lit(float(base_ratio)), n_params)})
    return rows.withColumn("t_after", F.col("t_base"))
