"""The server's step: a weighted sum of kept updates, with or without the boost, in one shuffle.

The mask depends on the coordinate alone, so it can multiply the sum: degree and weighted sum come from the
same aggregate, and no second pass or join over the kept rows is needed.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from pacedfl.operators.overlap import boost_mask, overlap_degree

MAX_BROADCAST_CLIENTS = 1_000_000


def weighted(kept: DataFrame, coef: DataFrame, column: str, n_clients: int | None = None, by: tuple[str, ...] = ()) -> DataFrame:
    """kept with its client's coefficient. coef has a row per selected client (and by); it is broadcast only where
    the number of clients is given and bounded, otherwise Spark chooses by size."""
    side = coef.select(*by, "client_id", F.col(column).alias("__p"))
    return kept.join(F.broadcast(side) if n_clients is not None and n_clients <= MAX_BROADCAST_CLIENTS else side, [*by, "client_id"])


def server_step(kept: DataFrame, coef: DataFrame, column: str = "f", gamma: Column | float = 1.0, max_degree: Column | int = 1, n_clients: int | None = None, coord: str = "param_idx", by: tuple[str, ...] = ()) -> DataFrame:
    """(by, coordinate, degree, step): the boosted weighted sum of what was kept. by: columns that tell runs apart;
    boost and rarity limit may be columns of them."""
    rows = weighted(kept, coef, column, n_clients, by).groupBy(*by, coord).agg(F.count_if(F.col("delta") != 0).alias("degree"), F.sum(F.col("__p") * F.col("delta")).alias("step"))
    return rows.select(*by, coord, "degree", (F.col("step") * boost_mask("degree", gamma, max_degree)).alias("step"))


def server_step_two_pass(kept: DataFrame, coef: DataFrame, column: str = "f", gamma: float = 1.0, max_degree: int = 1, coord: str = "param_idx") -> DataFrame:
    """The same by counting first and joining the mask onto every kept row; for comparison."""
    degree = overlap_degree(kept, coord=coord)
    rows = weighted(kept, coef, column).join(degree.withColumn("__m", boost_mask("degree", gamma, max_degree)), coord)
    return rows.groupBy(coord).agg(F.max("degree").alias("degree"), F.sum(F.col("__p") * F.col("delta") * F.col("__m")).alias("step"))


def gamma_grid(kept: DataFrame, coef: DataFrame, column: str, gammas: list[float], degrees: list[int], n_clients: int | None = None) -> DataFrame:
    """(gamma, max_degree, coordinate, degree, step) for a grid of boosts: one shuffle serves them all."""
    spark = kept.sparkSession
    grid = spark.createDataFrame([(float(g), int(d)) for g in gammas for d in degrees], "gamma double, max_degree int")
    base = server_step(kept, coef, column, n_clients=n_clients)
    return base.crossJoin(F.broadcast(grid)).select("gamma", "max_degree", "param_idx", "degree", (F.col("step") * boost_mask("degree", F.col("gamma"), F.col("max_degree"))).alias("step"))


def apply_step(weights: DataFrame, step: DataFrame, server_lr: Column | float = 1.0, by: tuple[str, ...] = ()) -> DataFrame:
    """New weights; coordinates that nobody kept stay as they are."""
    rate = server_lr if isinstance(server_lr, Column) else F.lit(float(server_lr))
    rows = weights.join(step.select(*by, "param_idx", "step"), [*by, "param_idx"], "left")
    return rows.select(*[c for c in weights.columns if c != "w"], (F.col("w") - rate * F.coalesce("step", F.lit(0.0))).alias("w"))
