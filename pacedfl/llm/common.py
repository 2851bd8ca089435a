"""What the operators of this subpackage share: tables, the shared work folder, Arrow slices, word hashes.

Conventions that hold for every operator here unless its docstring says otherwise:

* a null text counts as an empty text; an empty table gives an empty result with the same schema;
* repeated rows give repeated results, one per input row;
* only the named columns are read, so extra columns, whatever they are called, do no harm.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession, functions as F

SLICE_BYTES = 8 << 20
WORD_CACHE = 150_000
HOT_SHARE = 1000  # a key of over one in so many rows is dealt over several tasks


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def work_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. Where the session names none, a fresh local one, but only if
    driver and executors are one machine."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    current = spark.sparkContext._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get().rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("name a folder that all machines share in spark.checkpoint.dir")
    spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="pacedfl-"))
    return spark.sparkContext._jsc.sc().getCheckpointDir().get().rstrip("/")


def new_path(spark: SparkSession, tag: str) -> str:
    return f"{work_dir(spark)}/pacedfl-{tag}-{uuid.uuid4().hex}"


def written(df: DataFrame, tag: str) -> DataFrame:
    """df as a Parquet table in the shared folder: cuts the lineage and survives lost executors."""
    spark, path = df.sparkSession, new_path(df.sparkSession, tag)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def checkpointed(df: DataFrame) -> DataFrame:
    work_dir(df.sparkSession)
    if not df.sparkSession.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        df.sparkSession.sparkContext.setCheckpointDir(work_dir(df.sparkSession))
    return df.checkpoint()


def dealt(counts: DataFrame, key: str, total: int) -> DataFrame:
    """(key, parts) of keys (with count n) that hold over one in HOT_SHARE of total: fewer than HOT_SHARE rows, whatever
    the data, so the table may be broadcast."""
    most = -(-total // HOT_SHARE)
    return counts.where(F.col("n") > most).select(key, F.ceil(F.col("n") / most).cast("int").alias("parts"))


def salted(rows: DataFrame, hot: DataFrame, key: str, salt: Column) -> DataFrame:
    """rows with __salt: below the parts of a hot key, by the hash given; 0 for others."""
    if hot.isEmpty():
        return rows.withColumn("__salt", F.lit(0))
    side = hot.select(F.col(key).alias("__hot"), F.col("parts").alias("__parts"))
    rows = rows.join(F.broadcast(side), F.col(key) == F.col("__hot"), "left")
    return rows.withColumn("__salt", F.coalesce(F.pmod(F.xxhash64(salt), F.col("__parts")), F.lit(0)).cast("int")).drop("__hot", "__parts")


def repeated(rows: DataFrame, hot: DataFrame, key: str) -> DataFrame:
    """rows once for each __salt of their key."""
    if hot.isEmpty():
        return rows.withColumn("__salt", F.lit(0))
    side = hot.select(F.col(key).alias("__hot"), F.col("parts").alias("__parts"))
    rows = rows.join(F.broadcast(side), F.col(key) == F.col("__hot"), "left")
    return rows.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.coalesce("__parts", F.lit(1)) - 1))).drop("__hot", "__parts")


def slices(batch: pa.RecordBatch, column: str, max_bytes: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Pieces of a batch with about max_bytes of the column each, at least one row."""
    n = batch.num_rows
    if not n:
        return
    size = np.asarray(pc.fill_null(pc.binary_length(batch.column(column)), 0), dtype=np.int64)
    part = (np.cumsum(size) - size) // max_bytes
    cuts = np.flatnonzero(np.diff(part)) + 1
    for a, b in zip([0, *cuts], [*cuts, n], strict=True):
        yield batch.slice(a, b - a)


def raw(batch: pa.RecordBatch, column: str) -> list[bytes]:
    """UTF-8 bytes of a string column; null as empty."""
    return pc.fill_null(batch.column(column).cast(pa.binary()), b"").to_pylist()


def texts(batch: pa.RecordBatch, column: str) -> list[str]:
    return pc.fill_null(batch.column(column), "").to_pylist()


class WordHash(dict):
    """word bytes -> XXH64 as Python int; emptied when it holds WORD_CACHE words."""

    def __missing__(self, word: bytes) -> int:
        h = xxhash.xxh64_intdigest(word, 42)
        if len(self) >= WORD_CACHE:
            self.clear()
        self[word] = h
        return h

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), dtype=np.uint64, count=len(words))


def mix(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser over an array of unsigned hashes."""
    h = h ^ (h >> np.uint64(31))
    h = h * np.uint64(0x9E3779B97F4A7C15)
    return h ^ (h >> np.uint64(29))


def multipliers(n: int, seed: int) -> np.ndarray:
    """n odd 64-bit constants made from a seed."""
    return np.array([xxhash.xxh64_intdigest(b"%d:%d" % (seed, i)) | 1 for i in range(n)], dtype=np.uint64)


def window_hashes(h: np.ndarray, constants: np.ndarray) -> np.ndarray:
    """A hash of each run of len(constants) consecutive word hashes."""
    n = len(h) - len(constants) + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for j, c in enumerate(constants):
        out += h[j : j + n] * c
    return mix(out)


def popcount(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x)
