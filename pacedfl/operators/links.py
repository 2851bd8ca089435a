"""Client links and the time an upload takes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from pacedfl.functions.portable import gaussian, r6, uniform
from pacedfl.sources.tables import table

V_MBIT = 357.0
FLOOR_MBPS = 0.05


def gaussian_links(spark: SparkSession, n_clients: int, seed: int = 42) -> DataFrame:
    """Bandwidth: normal, mean 1, sd 0.2 Mbit/s, floored; latency: uniform in (0.05, 0.2] seconds."""
    return drawn_links(spark.range(n_clients).select(F.col("id").cast("int").alias("client_id")), seed)


def drawn_links(clients: DataFrame, seed: int = 42) -> DataFrame:
    """The same for each row of clients (client_id)."""
    return clients.select("client_id", F.greatest(F.lit(FLOOR_MBPS), 1 + 0.2 * gaussian(seed, "bw", "client_id")).alias("bandwidth_mbps"), (0.2 - 0.15 * uniform(seed, "lat", "client_id")).alias("latency_s"))


def round_links(clients: DataFrame, rounds: int, seed: int = 42) -> DataFrame:
    """Links drawn anew in every round: (round, client_id, bandwidth_mbps, latency_s)."""
    each = clients.select("client_id", F.explode(F.sequence(F.lit(0), F.lit(rounds - 1))).alias("round"))
    return each.select("round", "client_id", F.greatest(F.lit(FLOOR_MBPS), 1 + 0.2 * gaussian(seed, "bw", "round", "client_id")).alias("bandwidth_mbps"), (0.2 - 0.15 * uniform(seed, "lat", "round", "client_id")).alias("latency_s"))


def supplier_links(spark: SparkSession, sf_dir: str, n_clients: int | None = 10) -> DataFrame:
    """Links read off the supplier table; the first n_clients suppliers, or all."""
    s = table(spark, sf_dir, "supplier")
    ends = s.agg(F.min("s_acctbal").alias("lo"), F.max("s_acctbal").alias("hi"))
    bw = 0.4 + 1.2 * (F.col("s_acctbal") - F.col("lo")) / (F.col("hi") - F.col("lo"))
    rows = s.crossJoin(F.broadcast(ends)).select(F.col("s_suppkey").cast("int").alias("client_id"), r6(bw).alias("bandwidth_mbps"), r6(0.05 + 0.15 * (F.col("s_suppkey") % 100 + 1) / 100).alias("latency_s"), F.col("s_nationkey"))
    return rows if n_clients is None else rows.where(F.col("client_id") < n_clients)


def traced_links(spark: SparkSession, sf_dir: str, n_clients: int = 10) -> DataFrame:
    """Mean throughput of each client and day in the telemetry: (client_id, day, bandwidth_mbps, n)."""
    e = table(spark, sf_dir, "events").where("value is not null and ts is not null and user_id is not null")
    rows = e.groupBy((F.col("user_id") % n_clients).cast("int").alias("client_id"), F.date_trunc("DAY", "ts").alias("day"))
    return rows.agg(F.greatest(F.lit(FLOOR_MBPS), F.avg("value") / 50).alias("bandwidth_mbps"), F.count("*").alias("n"))


def newest_link(rounds: DataFrame, trace: DataFrame) -> DataFrame:
    """As-of: for each (client_id, at) the newest trace row (client_id, day, bandwidth_mbps) not after it.

    One shuffle of the union on the client, and a running last value; no range join.
    """
    both = rounds.select("client_id", "at", F.lit(None).cast("double").alias("bandwidth_mbps"), F.lit(1).alias("ask")).unionByName(trace.select("client_id", F.col("day").alias("at"), "bandwidth_mbps", F.lit(0).alias("ask")))
    seen = Window.partitionBy("client_id").orderBy("at", "ask").rowsBetween(Window.unboundedPreceding, 0)
    return both.select("client_id", "at", F.last("bandwidth_mbps", ignorenulls=True).over(seen).alias("bandwidth_mbps"), "ask").where("ask = 1").drop("ask")


def dense_time(v: Column | float, bw: Column | str, lat: Column | str) -> Column:
    v = v if isinstance(v, Column) else F.lit(v)
    return _c(lat) + v / _c(bw)


def sparse_time(v: Column | float, ratio: Column | float, bw: Column | str, lat: Column | str, factor: float = 2.0) -> Column:
    """Value and index are both sent, hence the factor."""
    v, ratio = (x if isinstance(x, Column) else F.lit(x) for x in (v, ratio))
    return _c(lat) + factor * v * ratio / _c(bw)


def _c(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c
