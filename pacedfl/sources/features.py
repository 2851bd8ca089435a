"""Labelled samples from the given tables: sample_id, x, y, is_test."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from pacedfl.functions.portable import uniform
from pacedfl.sources.tables import table

LANGS = ("de", "en", "es", "fr")
LETTERS = "abcdefghijklmnopqrstuvwxyz "
TEST_SHARE = 0.2


def is_test(key: str, seed: int = 42) -> Column:
    return uniform(seed, "split", key) < TEST_SHARE


def letter_rates(low: Column) -> Column:
    """Share of each letter and of blanks in a lower-case text, times ten."""
    return F.array(*((F.length(low) - F.length(F.replace(low, F.lit(c), F.lit("")))) * 10.0 / F.greatest(F.length(low), F.lit(1)) for c in LETTERS))


def language_samples(spark: SparkSession, sf_dir: str, seed: int = 42) -> DataFrame:
    """Documents by letter rates, labelled with their language."""
    docs = table(spark, sf_dir, "documents").where(F.col("lang").isin(*LANGS) & F.col("text").isNotNull())
    y = F.array_position(F.array(*map(F.lit, LANGS)), F.col("lang")).cast("int") - 1
    docs = docs.select("doc_id", F.lower("text").alias("low"), y.alias("y"))
    return docs.select(F.col("doc_id").alias("sample_id"), letter_rates(F.col("low")).alias("x"), "y", is_test("doc_id", seed).alias("is_test"))


def quality_samples(spark: SparkSession, sf_dir: str, seed: int = 42) -> DataFrame:
    """Documents with letter rates and four more features, labelled with their quality."""
    labels = table(spark, sf_dir, "labels").where("quality is not null").groupBy("doc_id").agg(F.min("quality").alias("y"))
    docs = table(spark, sf_dir, "documents").where(F.col("text").isNotNull()).join(labels, "doc_id")
    words = F.split(F.col("text"), r"\s+")
    more = F.array(F.log1p(F.length("text").cast("double")) / 5, F.size(F.array_distinct(words)) / F.size(words), F.regexp_count("text", F.lit(r"[0-9]")) * 10.0 / F.greatest(F.length("text"), F.lit(1)), F.lit(1.0))
    docs = docs.withColumn("low", F.lower("text"))
    return docs.select(F.col("doc_id").alias("sample_id"), F.concat(letter_rates(F.col("low")), more).alias("x"), F.col("y").cast("int").alias("y"), is_test("doc_id", seed).alias("is_test"))


def walsh_signs(first: int, last: int, width: int = 64) -> list[list[int]]:
    return [[1 - 2 * (int(j & k).bit_count() % 2) for j in range(width)] for k in range(first, last + 1)]


def embedding_samples(spark: SparkSession, sf_dir: str, planted: str = "walsh10", seed: int = 42) -> DataFrame:
    """Embeddings times eight with planted labels: walsh10 and walsh63 (dense sign patterns) or largest10 (sparse)."""
    rows = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("sample_id"), F.transform("embedding", lambda v: v.cast("double") * 8.0).alias("x"))
    if planted == "largest10":
        head = F.slice("x", 1, 10)
        y = F.array_position(head, F.array_max(head)).cast("int") - 1
    else:
        signs = walsh_signs(1, 10 if planted == "walsh10" else 63)
        scores = F.array(*(F.aggregate(F.zip_with("x", F.array(*map(F.lit, s)), lambda a, b: a * b), F.lit(0.0), lambda acc, v: acc + v) for s in signs))
        y = F.array_position(F.col("scores"), F.array_max("scores")).cast("int") - 1
        rows = rows.withColumn("scores", scores)
    return rows.select("sample_id", "x", y.alias("y"), is_test("sample_id", seed).alias("is_test"))


def conversation_samples(spark: SparkSession, sf_dir: str, seed: int = 42) -> DataFrame:
    """Turns of conversations by letter rates, labelled with their role; a second text set."""
    rows = table(spark, sf_dir, "conversations").where("role is not null and text is not null and conv_id is not null")
    roles = F.array(F.lit("assistant"), F.lit("system"), F.lit("user"))
    y = F.array_position(roles, F.col("role")).cast("int") - 1
    key = F.col("conv_id") * 1000 + F.coalesce("turn", F.lit(0))
    rows = rows.withColumn("low", F.lower("text"))
    return rows.select(key.alias("sample_id"), "conv_id", letter_rates(F.col("low")).alias("x"), y.alias("y")).where("y >= 0").withColumn("is_test", is_test("sample_id", seed))


def regression_rows(spark: SparkSession, sf_dir: str, n_clients: int = 10) -> DataFrame:
    """lineitem as a regression: client_id, x (constant, quantity, discount, tax), y (price)."""
    x = F.array(F.lit(1.0), F.col("l_quantity") / 50, F.col("l_discount") * 10, F.col("l_tax") * 10)
    return table(spark, sf_dir, "lineitem").select((F.col("l_suppkey") % n_clients).cast("int").alias("client_id"), x.alias("x"), (F.col("l_extendedprice") / 100000).alias("y"))


def regression_samples(spark: SparkSession, sf_dir: str, n_clients: int = 10, seed: int = 42) -> DataFrame:
    """The same rows as samples with a split by hash; the table has no key, so a row's hash stands for one."""
    rows = table(spark, sf_dir, "lineitem").withColumn("sample_id", F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice"))
    x = F.array(F.lit(1.0), F.col("l_quantity") / 50, F.col("l_discount") * 10, F.col("l_tax") * 10)
    return rows.select("sample_id", (F.col("l_suppkey") % n_clients).cast("int").alias("client_id"), x.alias("x"), (F.col("l_extendedprice") / 100000).alias("y"), is_test("sample_id", seed).alias("is_test"))


def without_benchmark(spark: SparkSession, sf_dir: str, samples: DataFrame, words: int = 8) -> DataFrame:
    """Samples whose document shares no run of words with a benchmark item (an equi anti-join on runs)."""

    def runs(df: DataFrame, key: str) -> DataFrame:
        w = F.filter(F.split(F.lower("text"), r"\s+"), lambda x: x != "")
        rows = df.where("text is not null").select(key, w.alias("w")).where(F.size("w") >= words)
        return rows.select(key, F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - words + 1), lambda i: F.xxhash64(F.array_join(F.slice("w", i, words), " ")))).alias("h"))

    hit = runs(table(spark, sf_dir, "documents"), "doc_id").join(runs(table(spark, sf_dir, "benchmark"), "item_id").select("h").distinct(), "h", "left_semi").select("doc_id").distinct()
    return samples.join(hit, samples["sample_id"] == hit["doc_id"], "left_anti")


def to_numpy(batch_x) -> np.ndarray:
    """An Arrow list column of equal lengths as a matrix."""
    values = batch_x.flatten().to_numpy(zero_copy_only=False)
    return values.reshape(len(batch_x), -1)
