"""Structured Streaming forms of link telemetry and uploads, each with a batch twin.

events.ts has no time zone, and watermarks need one: it is cast under the session's zone.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from pacedfl.operators.links import FLOOR_MBPS, V_MBIT
from pacedfl.operators.schedule import paced_ratios
from pacedfl.sources.tables import is_folder, new_path, table

EVENTS = "event_id BIGINT, ts TIMESTAMP_NTZ, user_id BIGINT, event_type STRING, value DOUBLE, props STRING"


def read_events(spark: SparkSession, sf_dir: str, files_per_trigger: int = 4) -> DataFrame:
    """The events table as a stream: of its folder, or of the one file."""
    path = f"{sf_dir}/events.parquet"
    reader = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(path) if is_folder(spark, path) else reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir)


def observations(events: DataFrame, n_clients: int = 10) -> DataFrame:
    """(client_id, at timestamp, mbps, k): one throughput sample per event; k is read from its JSON."""
    rows = events.where("ts is not null and value is not null and user_id is not null")
    return rows.select("event_id", (F.col("user_id") % n_clients).cast("int").alias("client_id"), F.col("ts").cast("timestamp").alias("at"), (F.col("value") / 50).alias("mbps"), F.from_json("props", "k INT").getField("k").alias("k"))


def _summary(grouped) -> DataFrame:
    rows = grouped.agg(F.avg("mbps").alias("bandwidth_mbps"), F.count("*").alias("n"))
    return rows.select("client_id", F.col("w.start").alias("w_start"), F.col("w.end").alias("w_end"), "bandwidth_mbps", "n")


def tumbling(obs: DataFrame, size: str = "1 day") -> DataFrame:
    return _summary(obs.groupBy("client_id", F.window("at", size).alias("w")))


def sliding(obs: DataFrame, size: str = "1 day", slide: str = "6 hours") -> DataFrame:
    return _summary(obs.groupBy("client_id", F.window("at", size, slide).alias("w")))


def sessions(obs: DataFrame, gap: str = "2 hours") -> DataFrame:
    return _summary(obs.groupBy("client_id", F.session_window("at", gap).alias("w")))


def window_ratios(windows: DataFrame, latencies: DataFrame, base_ratio: float = 0.1, n_params: int = 1000, v: float = V_MBIT) -> DataFrame:
    """Paced ratios of all clients in each window, from the window's throughput."""
    rows = windows.join(F.broadcast(latencies.select("client_id", "latency_s")), "client_id")
    rows = rows.withColumn("bandwidth_mbps", F.greatest(F.lit(FLOOR_MBPS), "bandwidth_mbps")).withColumn("round", F.col("w_start"))
    return paced_ratios(rows, base_ratio, n_params, v).select("w_start", "client_id", "bandwidth_mbps", "t_bench", "keep_ratio", "k", "t_after")


def run_to_table(stream: DataFrame, tag: str, mode: str = "append", timeout: int | None = None) -> DataFrame:
    """Run a stream over all that is there and give what it wrote, as a table in the shared folder. It ends by itself,
    so there is no time limit unless one is asked for."""
    spark, out = stream.sparkSession, new_path(stream.sparkSession, tag)
    q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", f"{out}-state").outputMode(mode).trigger(availableNow=True).start()
    finish(q, timeout)
    return spark.read.schema(stream.schema).parquet(out)


def finish(q, timeout: int | None) -> None:
    if q.awaitTermination(timeout) is False:
        q.stop()
        raise TimeoutError("the stream did not end in time")


def ratios_per_window(obs: DataFrame, latencies: DataFrame, out: str, size: str = "1 day", lateness: str = "1 day", **more):
    """foreachBatch: finished windows are paced and written under their batch number, so a repeated batch
    overwrites itself. Returns the query."""

    def put(batch: DataFrame, number: int) -> None:
        window_ratios(batch, latencies, **more).write.mode("overwrite").parquet(f"{out}/batch={number}")

    windows = tumbling(obs.withWatermark("at", lateness), size)
    return windows.writeStream.foreachBatch(put).option("checkpointLocation", f"{out}-state").outputMode("append").trigger(availableNow=True).start()


def deadline_sums(uploads: DataFrame, deadline: str, round_length: str = "1 day") -> DataFrame:
    """Uploads (client_id, at, param_idx, value) summed per round; those later than the deadline are dropped
    by the watermark and counted in the query's progress."""
    w = F.window("at", round_length).alias("w")
    rows = uploads.withWatermark("at", deadline).groupBy(w, "param_idx").agg(F.sum("value").alias("step"), F.count("*").alias("degree"))
    return rows.select(F.col("w.start").alias("w_start"), "param_idx", "step", "degree")


def late_rows(progress: list) -> int:
    """Rows that the watermark dropped, over all progress reports of a query."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in progress for op in p["stateOperators"])


def once(uploads: DataFrame, lateness: str = "1 day") -> DataFrame:
    """At-least-once clients: one upload per (client_id, round) within the watermark."""
    return uploads.withWatermark("at", lateness).dropDuplicatesWithinWatermark(["client_id", "round"])


def with_links(uploads: DataFrame, links: DataFrame) -> DataFrame:
    """Stream-static join: each upload with its client's link."""
    return uploads.join(F.broadcast(links.select("client_id", "bandwidth_mbps", "latency_s")), "client_id", "left")


def matched(starts: DataFrame, ends: DataFrame, within: str = "1 hour", lateness: str = "1 day") -> DataFrame:
    """Stream-stream interval join: upload starts with the ends that follow within the interval.

    The state is keyed by client and slot of time, a slot as long as the interval: an end lies in one slot, a start in
    all that its interval touches, so each pair meets once and a row is held against its own slot only.
    """
    slot = lambda at: F.expr(f"unix_micros({at}) div greatest(1L, unix_micros(timestamp_micros(0) + INTERVAL {within}))")
    s = starts.select("client_id", F.col("at").alias("start_at")).withWatermark("start_at", lateness)
    s = s.select("client_id", "start_at", F.explode(F.sequence(slot("start_at"), slot(f"(start_at + INTERVAL {within})"))).alias("slot"))
    e = ends.select(F.col("client_id").alias("__c"), F.col("at").alias("end_at")).withWatermark("end_at", lateness)
    e = e.select("__c", "end_at", slot("end_at").alias("__slot"))
    on = F.expr(f"client_id = __c AND slot = __slot AND end_at >= start_at AND end_at <= start_at + INTERVAL {within}")
    return s.join(e, on).select("client_id", "start_at", "end_at")


def batch_table(spark: SparkSession, sf_dir: str, n_clients: int = 10) -> DataFrame:
    return observations(table(spark, sf_dir, "events"), n_clients)
