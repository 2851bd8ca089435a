"""Splitting labelled samples over clients: by skewed label shares, evenly, or by a column."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window, functions as F

from pacedfl.functions.portable import uniform


STRETCHES = 256


def dirichlet_shares(classes: list, n_clients: int, beta: float, seed: int = 42) -> dict:
    """class -> each client's share of it, from a symmetric Dirichlet; low beta is severe skew."""
    rng = np.random.default_rng(seed)
    out = {}
    for c in classes:
        g = rng.standard_gamma(beta, n_clients)
        if not np.isfinite(g.sum()) or g.sum() <= 0:
            g = np.eye(n_clients)[rng.integers(n_clients)]
        out[c] = np.round(g / g.sum(), 9)
    return out


def cumulative(shares: dict) -> dict:
    """class -> upper ends of the clients' stretches of [0, 1], rounded; the last is 1."""
    return {c: [*(round(float(x), 9) for x in np.cumsum(s)[:-1]), 1.0] for c, s in shares.items()}


def _locate(label: Column, position: Column, cum: dict) -> Column:
    """Number of ends at or below the position: a lookup in a literal map of arrays, no range join."""
    ends = F.create_map(*(x for c, e in cum.items() for x in (F.lit(c), F.array(*map(F.lit, e)))))[label]
    return F.least(F.size(F.filter(ends, lambda b: b <= position)), F.size(ends) - 1).cast("int")


def assign_clients(samples: DataFrame, label: str = "y", n_clients: int = 10, beta: float = 0.5, seed: int = 42, mode: str = "quota", key: str = "sample_id", shares: dict | None = None, column: str | None = None) -> DataFrame:
    """samples with client_id.

    quota: positions in each class's hash order, so that shares are met within one sample (one shuffle by
    class and stretch of the hash). hashed: each sample's own hash as position, no shuffle. iid: hash modulo clients. column: as given.
    shares: class -> shares; by default drawn for the classes found in the data (one small aggregate).
    """
    if mode == "iid":
        return samples.withColumn("client_id", F.floor(uniform(seed, "iid", key) * n_clients).cast("int"))
    if mode == "column":
        return samples.withColumn("client_id", F.col(column or "client_id").cast("int"))
    if shares is None:
        classes = sorted(r[0] for r in samples.select(label).where(F.col(label).isNotNull()).distinct().collect())
        shares = dirichlet_shares(classes, n_clients, beta, seed)
    cum = cumulative(shares)
    u = uniform(seed, "assign", key)
    if mode == "hashed":
        return samples.withColumn("client_id", _locate(F.col(label), u, cum))
    if mode == "quota":
        # a class may hold a large part of all rows: rank within stretches of the hash, and add what lies below.
        # The counts have a row per class and stretch; classes are a parameter's size (shares has one entry each).
        rows = samples.withColumn("__u", u).withColumn("__b", F.floor(F.col("__u") * STRETCHES).cast("int"))
        below = Window.partitionBy("__c").orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)
        counts = rows.where(F.col(label).isin(list(cum))).groupBy(F.col(label).alias("__c"), "__b").agg(F.count("*").alias("__n"))
        counts = counts.select("__c", F.col("__b").alias("__s"), F.coalesce(F.sum("__n").over(below), F.lit(0)).alias("__below"), F.sum("__n").over(Window.partitionBy("__c")).alias("__all"))
        order = Window.partitionBy(label, "__b").orderBy("__u", key)
        rows = rows.withColumn("__r", F.row_number().over(order)).join(F.broadcast(counts), (F.col(label) == F.col("__c")) & (F.col("__b") == F.col("__s")), "left")
        position = (F.col("__below") + F.col("__r") - 0.5) / F.col("__all")
        return rows.withColumn("client_id", _locate(F.col(label), position, cum)).drop("__u", "__b", "__r", "__c", "__s", "__below", "__all")
    raise ValueError(mode)


def label_matrix(assigned: DataFrame, label: str = "label") -> DataFrame:
    return assigned.groupBy("client_id", label).agg(F.count("*").alias("n"))


def label_cube(assigned: DataFrame, label: str = "label") -> DataFrame:
    """Counts by client and label with all subtotals; gid tells a subtotal's null from a label's."""
    return assigned.cube("client_id", label).agg(F.grouping_id().cast("int").alias("gid"), F.count("*").alias("n"))


def skew_of(assigned: DataFrame, label: str = "label") -> DataFrame:
    """(client_id, n, max_share): how far the largest label dominates each client."""
    rows = label_matrix(assigned, label)
    return rows.groupBy("client_id").agg(F.sum("n").alias("n"), (F.max("n") / F.sum("n")).alias("max_share"))
