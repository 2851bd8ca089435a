"""Compressors of client updates, rows (client_id, param_idx, delta) plus any grouping columns.

`keys` names the columns that identify one update (client, and round or run where there are several). k is a
column: each update has its own. Zeros are never kept. Ties in magnitude go to the lower coordinate.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from pacedfl.functions.portable import uniform

KEYS = ("client_id",)


def topk(delta: DataFrame, keys: tuple[str, ...] = KEYS, k: str = "k", k_max: int | None = None, scope: str | None = None, coord: str = "param_idx") -> DataFrame:
    """The k entries of largest magnitude of each update (of each layer of it with scope=column); adds rank.

    k_max: a literal that no k exceeds; rows past it are dropped. With it Spark cuts every partition before the
    exchange (where the session's window group limit allows a bound that large); k alone, being a column, does not.
    """
    group = [*keys, *([scope] if scope else [])]
    w = Window.partitionBy(*group).orderBy(F.abs("delta").desc(), coord)
    rows = delta.where("delta <> 0").withColumn("rank", F.row_number().over(w))
    rows = rows.where(F.col("rank") <= F.col(k))
    return rows.where(F.col("rank") <= k_max) if k_max else rows


def magnitude_bucket(v: Column) -> Column:
    """A bucket that grows with |v|: eight to each power of two. Continuous at the powers, so that a
    logarithm that is off by a bit there does not matter."""
    a = F.abs(v)
    e = F.floor(F.log2(a))
    return (e * 8 + F.floor(a / F.pow(F.lit(2.0), e) * 8)).cast("int")


def topk_marked(delta: DataFrame, keys: tuple[str, ...] = KEYS, k: str = "k", coord: str = "param_idx") -> DataFrame:
    """All non-zero rows with kept: whether topk keeps the row. No task sorts a whole update.

    Counts of magnitude buckets give, by a running sum from the top, the bucket that k cuts; what lies above is kept,
    and only rows of the cut bucket are ranked. The count table has a few hundred rows an update; one row an update
    is joined to its entries. A null k keeps nothing.
    """
    rows = delta.where("delta <> 0").withColumn("__b", magnitude_bucket(F.col("delta")))
    top = Window.partitionBy(*keys).orderBy(F.col("__b").desc())
    counts = rows.groupBy(*keys, "__b").agg(F.count("*").alias("__n"), F.max(k).alias("__k"))
    counts = counts.withColumn("__over", F.sum("__n").over(top) - F.col("__n")).where("__over < __k")
    cuts = counts.groupBy(*keys).agg(F.min("__b").alias("__cut"), F.max("__over").alias("__above"))
    both = rows.join(cuts, list(keys), "left")
    sure = both.where("__b is distinct from __cut").withColumn("kept", F.coalesce(F.col("__b") > F.col("__cut"), F.lit(False)))
    w = Window.partitionBy(*keys).orderBy(F.abs("delta").desc(), coord)
    cut = both.where("__b = __cut").withColumn("kept", F.row_number().over(w) <= F.col(k) - F.col("__above"))
    return sure.unionByName(cut).select(*delta.columns, "kept")


def topk_select(delta: DataFrame, keys: tuple[str, ...] = KEYS, k: str = "k", coord: str = "param_idx") -> DataFrame:
    """Exactly the rows of topk without sorting whole updates."""
    return topk_marked(delta, keys, k, coord).where("kept").drop("kept")


def topk_bounded(delta: DataFrame, k_max: int, keys: tuple[str, ...] = KEYS, k: str = "k", coord: str = "param_idx") -> DataFrame:
    """The rows of topk, k_max being a bound of every k: ranked where Spark cuts partitions at such a rank before the
    exchange, selected by buckets where k_max is past the session's limit for that."""
    limit = int(delta.sparkSession.conf.get("spark.sql.optimizer.windowGroupLimitThreshold", "1000"))
    return topk(delta, keys, k, k_max, coord=coord).drop("rank") if k_max <= limit else topk_select(delta, keys, k, coord)


def topk_approx(delta: DataFrame, ratio: float, keys: tuple[str, ...] = KEYS, accuracy: int = 10_000) -> DataFrame:
    """Entries above an approximate quantile of the magnitudes: one aggregate and a filter."""
    rows = delta.where("delta <> 0")
    cut = rows.groupBy(*keys).agg(F.percentile_approx(F.abs("delta"), F.lit(1.0 - ratio), F.lit(accuracy)).alias("__cut"))
    return rows.join(cut, list(keys)).where(F.abs("delta") >= F.col("__cut")).drop("__cut")


def randomk(delta: DataFrame, keys: tuple[str, ...] = KEYS, k: str = "k", seed: int = 42, n_params: int | None = None, coord: str = "param_idx") -> DataFrame:
    """k entries chosen by hash. With n_params the values are scaled by n_params / k, which keeps their expectation."""
    w = Window.partitionBy(*keys).orderBy(uniform(seed, "randk", *keys, coord), coord)
    rows = delta.where("delta <> 0").withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= F.col(k))
    return rows.withColumn("delta", F.col("delta") * n_params / F.col(k)) if n_params else rows


def hard_threshold(delta: DataFrame, tau: float) -> DataFrame:
    return delta.where(F.abs("delta") >= tau).where("delta <> 0")


def quantize(delta: DataFrame, bits: int = 8, keys: tuple[str, ...] = KEYS, seed: int | None = None, coord: str = "param_idx") -> DataFrame:
    """Adds q, step and restored: uniform levels up to each update's largest magnitude; seed adds hash dither."""
    levels = 2 ** (bits - 1) - 1
    rows = delta.withColumn("step", F.max(F.abs("delta")).over(Window.partitionBy(*keys)) / levels)
    shift = F.lit(0.5) if seed is None else uniform(seed, "dither", *keys, coord)
    q = F.coalesce(F.floor(F.col("delta") / F.nullif("step", F.lit(0.0)) + shift), F.lit(0)).cast("int")
    return rows.withColumn("q", q).withColumn("restored", F.col("q") * F.col("step"))


def sign_compress(delta: DataFrame, keys: tuple[str, ...] = KEYS) -> DataFrame:
    """Adds restored: the sign of each entry times the update's mean magnitude."""
    return delta.withColumn("restored", F.signum("delta") * F.avg(F.abs("delta")).over(Window.partitionBy(*keys)))


def ef_topk(delta: DataFrame, residual: DataFrame | None, k: DataFrame, keys: tuple[str, ...] = KEYS, coord: str = "param_idx") -> DataFrame:
    """Error feedback: (keys, coordinate, sent, residual) of top-k over update plus carried residual.

    k: the clients that take part, (keys or some of them, k). Others send nothing and carry what they have. Both big
    sides are joined on (keys, coordinate); no update is sorted whole.
    """
    on = [*keys, coord]
    rows = delta.select(*on, "delta")
    if residual is not None:
        old = residual.where("residual <> 0").select(*on, F.col("residual").alias("__old"))
        rows = rows.join(old, on, "full").select(*on, (F.coalesce("delta", F.lit(0.0)) + F.coalesce("__old", F.lit(0.0))).alias("delta"))
    rows = topk_marked(rows.join(k, [c for c in k.columns if c != "k"], "left"), keys, "k", coord)
    sent = F.when(F.col("kept"), F.col("delta")).otherwise(0.0)
    return rows.select(*on, sent.alias("sent"), (F.col("delta") - sent).alias("residual"))


def energy_kept(delta: DataFrame, kept: DataFrame, keys: tuple[str, ...] = KEYS) -> DataFrame:
    """Per update: squared norm of what is kept over that of the whole."""
    all_ = delta.groupBy(*keys).agg(F.sum(F.col("delta") * F.col("delta")).alias("__all"))
    some = kept.groupBy(*keys).agg(F.sum(F.col("delta") * F.col("delta")).alias("__kept"))
    return all_.join(some, list(keys), "left").select(*keys, F.coalesce(F.col("__kept") / F.nullif("__all", F.lit(0.0)), F.lit(0.0)).alias("energy"))


def energy_marked(marked: DataFrame, keys: tuple[str, ...] = KEYS) -> DataFrame:
    """The same from rows that say whether they are kept: one pass."""
    square = F.col("delta") * F.col("delta")
    return marked.groupBy(*keys).agg(F.coalesce(F.sum(F.when(F.col("kept"), square)) / F.nullif(F.sum(square), F.lit(0.0)), F.lit(0.0)).alias("energy"))


def pack(kept: DataFrame, keys: tuple[str, ...] = KEYS, coord: str = "param_idx", shards: int = 1) -> DataFrame:
    """One row an update (and shard of coordinates): idx and val arrays sorted by coordinate."""
    shard = F.pmod(F.xxhash64(coord), F.lit(shards)).cast("int")
    rows = kept.groupBy(*keys, shard.alias("shard")).agg(F.array_sort(F.collect_list(F.struct(F.col(coord).cast("long").alias("i"), F.col("delta").cast("float").alias("v")))).alias("__e"))
    return rows.select(*keys, "shard", F.col("__e.i").alias("idx"), F.col("__e.v").alias("val"))


def unpack(packed: DataFrame, keys: tuple[str, ...] = KEYS, coord: str = "param_idx") -> DataFrame:
    rows = packed.select(*keys, F.explode(F.arrays_zip("idx", "val")).alias("__e"))
    return rows.select(*keys, F.col("__e.idx").alias(coord), F.col("__e.val").cast("double").alias("delta"))
