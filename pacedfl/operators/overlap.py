"""How many of a round's clients kept a coordinate, and the boost of those that few kept."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F


def overlap_degree(kept: DataFrame, by: tuple[str, ...] = (), coord: str = "param_idx") -> DataFrame:
    """(by, coordinate, degree). An update has a coordinate once, so no distinct is needed."""
    return kept.groupBy(*by, coord).agg(F.count_if(F.col("delta") != 0).alias("degree")).where("degree > 0")


def overlap_histogram(degree: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, degree, n_coords, share of the kept coordinates)."""
    rows = degree.groupBy(*by, "degree").agg(F.count("*").alias("n_coords"))
    w = Window.partitionBy(*by) if by else Window.partitionBy(F.lit(0))
    return rows.withColumn("share", F.col("n_coords") / F.sum("n_coords").over(w))


def pairwise_overlap(kept: DataFrame, coord: str = "param_idx") -> DataFrame:
    """(c1, c2, both, either, jaccard) for pairs of clients that share a coordinate.

    The pairs of one coordinate are bounded by the clients of a round, not by the data.
    """
    own = kept.where("delta <> 0").select("client_id", coord)
    size = own.groupBy("client_id").agg(F.count("*").alias("n"))
    sets = own.groupBy(coord).agg(F.array_sort(F.collect_list("client_id")).alias("c"))
    pairs = sets.select(F.explode("c").alias("c1"), "c").select("c1", F.explode(F.filter("c", lambda x: x > F.col("c1"))).alias("c2"))
    both = pairs.groupBy("c1", "c2").agg(F.count("*").alias("both"))
    rows = both.join(F.broadcast(size.select(F.col("client_id").alias("c1"), F.col("n").alias("n1"))), "c1").join(F.broadcast(size.select(F.col("client_id").alias("c2"), F.col("n").alias("n2"))), "c2")
    either = F.col("n1") + F.col("n2") - F.col("both")
    return rows.select("c1", "c2", "both", either.alias("either"), (F.col("both") / either).alias("jaccard"))


def boost_mask(degree: Column | str, gamma: Column | float, max_degree: Column | int = 1) -> Column:
    """gamma where at most max_degree clients kept the coordinate, else 1."""
    d = F.col(degree) if isinstance(degree, str) else degree
    g, m = (x if isinstance(x, Column) else F.lit(x) for x in (gamma, max_degree))
    return F.when(d <= m, g.cast("double")).otherwise(F.lit(1.0))
