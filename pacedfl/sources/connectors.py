"""Other ways in and out: client logs as CSV or JSON lines, generated link profiles, bucketed tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from pacedfl.functions.portable import uniform_py

CLIENT_LOG = "client_id INT, round INT, started_at TIMESTAMP, bandwidth_mbps DOUBLE, latency_s DOUBLE, sent_entries BIGINT"


def read_client_log(spark: SparkSession, path: str, kind: str = "json") -> DataFrame:
    """Client logs with a fixed schema; rows that do not fit it are kept in `_bad` instead of failing the read."""
    reader = spark.read.schema(f"{CLIENT_LOG}, _bad STRING").option("columnNameOfCorruptRecord", "_bad").option("mode", "PERMISSIVE")
    return reader.option("header", "true").csv(path) if kind == "csv" else reader.json(path)


def write_client_log(df: DataFrame, path: str, kind: str = "json") -> None:
    w = df.write.mode("errorifexists")
    w.option("header", "true").csv(path) if kind == "csv" else w.json(path)


class _Range(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _LinkReader(DataSourceReader):
    def __init__(self, options):
        self.n, self.seed, self.parts = int(options.get("clients", 10)), int(options.get("seed", 42)), int(options.get("partitions", 4))

    def partitions(self):
        step = -(-self.n // max(1, self.parts))
        return [_Range(a, min(self.n, a + step)) for a in range(0, self.n, max(1, step))] or [_Range(0, 0)]

    def read(self, part):
        import math

        for i in range(part.first, part.last):
            u, v = uniform_py(self.seed, "bw.a", i), uniform_py(self.seed, "bw.b", i)
            z = math.sqrt(-2 * math.log((u * 4294967296.0 + 1) / 4294967297.0)) * math.cos(2 * math.pi * v)
            yield (i, max(0.05, 1 + 0.2 * z), 0.2 - 0.15 * uniform_py(self.seed, "lat", i))


class LinkProfiles(DataSource):
    """spark.read.format("link_profiles").option("clients", n): the Gaussian profile as a data source."""

    @classmethod
    def name(cls) -> str:
        return "link_profiles"

    def schema(self) -> str:
        return "client_id INT, bandwidth_mbps DOUBLE, latency_s DOUBLE"

    def reader(self, schema) -> DataSourceReader:
        return _LinkReader(self.options)


def register_link_profiles(spark: SparkSession) -> None:
    spark.dataSource.register(LinkProfiles)


def write_bucketed(df: DataFrame, name: str, buckets: int, *keys: str) -> DataFrame:
    """A table clustered and sorted by the keys: joins and aggregates on them with a table of as many
    buckets need no exchange. For samples by client, and for residuals by client and coordinate."""
    df.repartition(buckets, *keys).write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(name)
    return df.sparkSession.table(name)
