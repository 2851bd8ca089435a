import datetime as dt
from collections import Counter

import pytest
from pyspark.sql import functions as F

from pacedfl.operators import links
from pacedfl.streaming import residual_state, telemetry

SCHEMA = "client_id int, at timestamp, param_idx long, value double, round int"


def at(day, hour=0, minute=0):
    return dt.datetime(2024, 1, day, hour, minute)


@pytest.fixture()
def files(spark, tmp_path):
    """Micro-batches from files, one each; returns a stream over them."""

    def make(batches, schema=SCHEMA):
        for i, rows in enumerate(batches):
            spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in{i}")
        folder = tmp_path / "all"
        folder.mkdir()
        for i in range(len(batches)):
            for p in (tmp_path / f"in{i}").glob("part-*.parquet"):
                p.rename(folder / f"{i:03d}-{p.name}")
                import os
                os.utime(folder / f"{i:03d}-{p.name}", (1_700_000_000 + i * 10,) * 2)
        return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(folder))

    return make


def drive(df, mode="append"):
    out = f"t{abs(hash(df)) % 10**9}"
    q = df.writeStream.format("memory").queryName(out).outputMode(mode).trigger(availableNow=True).start()
    telemetry.finish(q, 120)
    return df.sparkSession.table(out), q


@pytest.mark.parametrize("windows", [telemetry.tumbling, telemetry.sliding, telemetry.sessions])
def test_windows_equal_batch_twin(spark, small, windows):
    """All windows that the watermark has closed are those of the batch query."""
    stream = telemetry.observations(telemetry.read_events(spark, small)).withWatermark("at", "1 hour")
    got = telemetry.run_to_table(windows(stream), "twin")
    key = lambda r: (r.client_id, r.w_start, r.w_end, round(r.bandwidth_mbps, 9), r.n)
    mine, batch = set(map(key, got.collect())), set(map(key, windows(telemetry.batch_table(spark, small)).collect()))
    # a stream that ends leaves open what the watermark has not passed
    assert mine and mine <= batch
    edge = max(r[2] for r in batch) - dt.timedelta(days=3)
    assert {r for r in batch if r[2] <= edge} <= mine


def test_late_uploads_are_dropped_and_counted(spark, files):
    stream = files([
        [(1, at(1, 1), 0, 1.0, 0), (2, at(1, 2), 0, 2.0, 0)],
        [(1, at(3, 1), 0, 5.0, 2)],
        [(1, at(3, 1), 2, 1.0, 2)],  # the mark reaches the late filter one batch later
        [(3, at(1, 3), 0, 100.0, 0), (1, at(3, 2), 1, 1.0, 2)],
        [(1, at(6, 0), 0, 1.0, 5)],
    ])
    got, q = drive(telemetry.deadline_sums(stream, "6 hours"))
    rows = {(r.w_start.day, r.param_idx): (r.step, r.degree) for r in got.collect()}
    assert rows[1, 0] == (3.0, 2) and rows[3, 0] == (5.0, 1)
    assert telemetry.late_rows(q.recentProgress) == 1


def test_duplicate_uploads_count_once(files):
    stream = files([[(1, at(1, 1), 0, 1.0, 0), (1, at(1, 1), 0, 1.0, 0)], [(1, at(1, 2), 0, 1.0, 0), (2, at(1, 2), 0, 1.0, 0)]])
    got, _ = drive(telemetry.once(stream))
    assert sorted((r.client_id, r["round"]) for r in got.collect()) == [(1, 0), (2, 0)]


def test_stream_static_and_interval_joins(spark, files, tmp_path):
    stream = files([[(1, at(1, 1), 0, 1.0, 0), (77, at(1, 1), 0, 1.0, 0)]])
    got, _ = drive(telemetry.with_links(stream, links.gaussian_links(spark, 3)))
    assert {r.client_id: r.bandwidth_mbps is None for r in got.collect()} == {1: False, 77: True}


def test_interval_join(files, spark, tmp_path):
    starts = files([[(1, at(1, 1), 0, 1.0, 0), (2, at(1, 1), 0, 1.0, 0)]])
    ends = spark.createDataFrame([(1, at(1, 1, 30), 0, 1.0, 0), (2, at(1, 3), 0, 1.0, 0)], SCHEMA)
    ends.coalesce(1).write.parquet(f"{tmp_path}/ends")
    got, _ = drive(telemetry.matched(starts, spark.readStream.schema(SCHEMA).parquet(f"{tmp_path}/ends")))
    assert [(r.client_id, r.end_at) for r in got.collect()] == [(1, at(1, 1, 30))]


def test_interval_join_holds_rows_against_their_slot_only(spark, tmp_path):
    """One client, 16,000 starts and ends a minute apart: held against all of its rows, they take over a minute."""
    n, each = 16_000, spark.range(16_000).coalesce(1)
    each.selectExpr("1 AS client_id", "timestamp_seconds(60 * id + 300000) AS at").write.parquet(f"{tmp_path}/starts")
    each.selectExpr("1 AS client_id", "timestamp_seconds(60 * id + 300000 + 60 * (id % 2)) AS at").write.parquet(f"{tmp_path}/ends")
    starts, ends = (spark.readStream.schema("client_id int, at timestamp").parquet(f"{tmp_path}/{x}") for x in ("starts", "ends"))
    got = telemetry.run_to_table(telemetry.matched(starts, ends, "10 minutes", "40 days"), "slots", timeout=60)
    a, b = (spark.read.parquet(f"{tmp_path}/{x}") for x in ("starts", "ends"))
    a, b = ([int(r.s) for r in x.selectExpr("unix_seconds(at) AS s").collect()] for x in (a, b))
    many = Counter(b)
    want = {(s, s + d): many[s + d] for s in a for d in range(0, 601, 60) if many[s + d]}
    found = {(int(r.s), int(r.e)): r["n"] for r in got.groupBy(F.unix_seconds("start_at").alias("s"), F.unix_seconds("end_at").alias("e")).agg(F.count("*").alias("n")).collect()}
    assert len(a) == n and found == want


def test_residual_state_equals_batch_by_batch(files):
    batches = [[(1, at(1), i, float(v), 0) for i, v in enumerate(b)] for b in ([5, -4, 3, 1], [0, 1, 3, 1], [1, 0, 0, 1])]
    stream = files(batches).select("client_id", "param_idx", F.col("value").alias("delta"))
    got, _ = drive(residual_state.stream_error_feedback(stream, 2))
    sent = [(r.param_idx, r.sent) for r in got.collect()]
    assert sent == [(0, 5.0), (1, -4.0), (2, 6.0), (3, 2.0), (0, 1.0), (1, 1.0)]


def test_ratios_per_window_are_idempotent(spark, small, tmp_path):
    out = f"{tmp_path}/ratios"
    obs = telemetry.observations(telemetry.read_events(spark, small))
    lat = links.supplier_links(spark, small, 10)
    telemetry.finish(telemetry.ratios_per_window(obs, lat, out), 120)
    n = spark.read.parquet(out).count()
    telemetry.finish(telemetry.ratios_per_window(obs, lat, out), 120)
    assert n > 0 and spark.read.parquet(out).count() == n
