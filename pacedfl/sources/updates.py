"""Client updates made from the given tables, for one-round studies without training.

Every frame has client_id, a coordinate and delta. lineitem gives a wide vector per client (coordinates are
parts), documents a sparse one with heavy ties (coordinates are words), embeddings a dense short one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from pacedfl.sources.tables import table

SPLIT_DATE = "1995-06-17"


def money(c: str) -> Column:
    return F.col(c).cast("decimal(12,2)")


def _lineitem(spark: SparkSession, sf_dir: str, n_clients: int) -> DataFrame:
    value = money("l_quantity") * (money("l_discount") - F.lit("0.05").cast("decimal(12,2)"))
    return table(spark, sf_dir, "lineitem").select((F.col("l_suppkey") % n_clients).cast("int").alias("client_id"), F.col("l_partkey").alias("param_idx"), "l_shipdate", value.alias("value"))


def update_lineitem(spark: SparkSession, sf_dir: str, n_clients: int = 10) -> DataFrame:
    """Change of each part's coordinate by client: exact decimals summed, given as double."""
    rows = _lineitem(spark, sf_dir, n_clients).groupBy("client_id", "param_idx").agg(F.sum("value").alias("delta"))
    return rows.select("client_id", "param_idx", F.col("delta").cast("decimal(18,4)").cast("double").alias("delta"))


def update_lineitem_rounds(spark: SparkSession, sf_dir: str, n_clients: int = 10, split: str = SPLIT_DATE) -> DataFrame:
    """The same in two rounds: rows shipped before the date, and the others."""
    rows = _lineitem(spark, sf_dir, n_clients).withColumn("round", (F.col("l_shipdate") >= F.lit(split).cast("timestamp_ntz")).cast("int"))
    rows = rows.groupBy("round", "client_id", "param_idx").agg(F.sum("value").alias("delta"))
    return rows.select("round", "client_id", "param_idx", F.col("delta").cast("decimal(18,4)").cast("double").alias("delta"))


def update_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Word counts of each source: naturally twenty clients, most values tied."""
    words = table(spark, sf_dir, "documents").where(F.col("source").isNotNull() & F.col("text").isNotNull())
    words = words.select(F.regexp_extract("source", r"(\d+)$", 1).cast("int").alias("client_id"), F.explode(F.split(F.lower("text"), r"[^a-zäöüßàâçéèêëîïôûùñáíóú]+")).alias("token"))
    return words.where("token <> ''").groupBy("client_id", "token").agg(F.count("*").cast("double").alias("delta"))


def update_embeddings(spark: SparkSession, sf_dir: str, n_clients: int = 10) -> DataFrame:
    """Mean of each embedding component by client: every coordinate is in every client."""
    rows = table(spark, sf_dir, "embeddings").select((F.col("vec_id") % n_clients).cast("int").alias("client_id"), F.posexplode("embedding").alias("param_idx", "v"))
    rows = rows.groupBy("client_id", "param_idx").agg(F.avg(F.col("v").cast("double")).alias("delta"))
    return rows.select("client_id", F.col("param_idx").cast("long").alias("param_idx"), "delta")


def n_params(spark: SparkSession, sf_dir: str) -> int:
    """Coordinates of the lineitem fixture: the parts."""
    return table(spark, sf_dir, "part").count()


def layers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Layer of each coordinate: the part's brand."""
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("param_idx"), F.col("p_brand").alias("layer"))
