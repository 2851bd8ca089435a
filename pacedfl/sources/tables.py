"""Session settings, given tables, engine schemas and the shared work folder."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession, types as T

CLIENTS = T.StructType([T.StructField("client_id", T.IntegerType()), T.StructField("bandwidth_mbps", T.DoubleType()), T.StructField("latency_s", T.DoubleType()), T.StructField("n_samples", T.LongType())])
SAMPLES = T.StructType([T.StructField("sample_id", T.LongType()), T.StructField("client_id", T.IntegerType()), T.StructField("x", T.ArrayType(T.DoubleType())), T.StructField("y", T.IntegerType()), T.StructField("is_test", T.BooleanType())])
DELTAS = T.StructType([T.StructField("round", T.IntegerType()), T.StructField("client_id", T.IntegerType()), T.StructField("param_idx", T.LongType()), T.StructField("delta", T.DoubleType())])
WEIGHTS = T.StructType([T.StructField("param_idx", T.LongType()), T.StructField("layer", T.IntegerType()), T.StructField("w", T.DoubleType())])
ROUND_LOG = T.StructType([T.StructField(n, t) for n, t in (("run_id", T.StringType()), ("round", T.IntegerType()), ("accuracy", T.DoubleType()), ("loss", T.DoubleType()), ("t_actual", T.DoubleType()), ("t_max", T.DoubleType()), ("t_min", T.DoubleType()), ("coef_sum", T.DoubleType()), ("sent_rows", T.LongType()))])


def session(app: str = "pacedfl", master: str | None = None, **conf: str) -> SparkSession:
    """A session with the settings the plans are written for; on a cluster the submit settings win."""
    b = SparkSession.builder.appName(app).config("spark.sql.session.timeZone", "UTC").config("spark.sql.adaptive.enabled", "true")
    b = b.config("spark.sql.optimizer.windowGroupLimitThreshold", "100000")
    if master:
        b = b.master(master)
    for k, v in conf.items():
        b = b.config(k, v)
    return b.getOrCreate()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def work_dir(spark: SparkSession) -> str:
    """The folder driver and executors share. Where the session names none, a fresh local one, but only if driver and
    executors are one machine."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    current = spark.sparkContext._jsc.sc().getCheckpointDir()
    if not current.isDefined():
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("name a folder that all machines share in spark.checkpoint.dir")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="pacedfl-"))
        current = spark.sparkContext._jsc.sc().getCheckpointDir()
    return current.get().rstrip("/")


def new_path(spark: SparkSession, tag: str) -> str:
    return f"{work_dir(spark)}/pacedfl-{tag}-{uuid.uuid4().hex}"


def written(df: DataFrame, path: str, *partition: str) -> DataFrame:
    """df as a new Parquet table: cuts the lineage and survives lost executors."""
    df.write.mode("errorifexists").partitionBy(*partition).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def exists(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)


def is_folder(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def removed(spark: SparkSession, path: str) -> None:
    """Delete a table of ours that nothing reads any more."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
