import numpy as np
import pytest
from pyspark.sql import functions as F

from pacedfl import queries as q
from pacedfl.functions import sqlfuncs, udfs
from pacedfl.operators import compress, learner, links
from pacedfl.sources import connectors, features


@pytest.mark.parametrize("kind", ["json", "csv"])
def test_client_log_roundtrip(spark, tmp_path, kind):
    rows = spark.sql("SELECT 1 AS client_id, 0 AS round, timestamp'2024-01-01 00:00:00' AS started_at, 1.5D AS bandwidth_mbps, 0.1D AS latency_s, 7L AS sent_entries")
    connectors.write_client_log(rows, f"{tmp_path}/log", kind)
    got = connectors.read_client_log(spark, f"{tmp_path}/log", kind)
    assert got.drop("_bad").collect() == rows.collect()


def test_bad_lines_are_kept(spark, tmp_path):
    (tmp_path / "x.json").write_text('{"client_id": 1, "round": 2}\n{oops\n')
    rows = connectors.read_client_log(spark, str(tmp_path / "x.json")).cache()
    assert rows.count() == 2 and rows.where("_bad is not null").count() == 1


def test_generated_links_equal_columns(spark):
    connectors.register_link_profiles(spark)
    got = {r.client_id: (r.bandwidth_mbps, r.latency_s) for r in spark.read.format("link_profiles").option("clients", 25).option("partitions", 3).load().collect()}
    want = {r.client_id: (r.bandwidth_mbps, r.latency_s) for r in links.gaussian_links(spark, 25).collect()}
    assert got.keys() == want.keys() and all(got[c] == pytest.approx(want[c], abs=1e-12) for c in want)


def test_bucketed_join_needs_no_exchange(spark):
    keep = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        df = spark.range(1000).select((F.col("id") % 7).cast("int").alias("client_id"), F.col("id").alias("param_idx"), F.rand(1).alias("v"))
        a = connectors.write_bucketed(df, "bucket_a", 4, "client_id", "param_idx")
        b = connectors.write_bucketed(df.withColumnRenamed("v", "u"), "bucket_b", 4, "client_id", "param_idx")
        both = a.join(b, ["client_id", "param_idx"])
        assert "Exchange" not in both._jdf.queryExecution().executedPlan().toString() and both.count() == 1000
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", keep)


def test_predict_udf(spark, small):
    model, w = learner.Softmax(27, 4), np.linspace(-1, 1, 112)
    rows = features.language_samples(spark, small)
    a = {r.sample_id: r.p for r in rows.select("sample_id", udfs.predictor(model, w)("x").alias("p")).collect()}
    assert a == {r.sample_id: r.pred for r in learner.predictions(rows, w, model).collect()}


def test_packed_functions(spark):
    rows = spark.createDataFrame([(c, i, float(c + i)) for c in (1, 2) for i in range(5)], "client_id int, param_idx long, delta double")
    packed = compress.pack(rows.where("delta <> 0"))
    assert packed.agg(udfs.packed_norm("val")).first()[0] == pytest.approx(float(np.sqrt(sum((c + i) ** 2 for c in (1, 2) for i in range(5)))))
    packed.createOrReplaceTempView("packed_rows")
    spark.udtf.register("unpack_update", udfs.UnpackUpdate)
    got = spark.sql("SELECT client_id, u.* FROM packed_rows, LATERAL unpack_update(idx, val) u")
    assert sorted(got.collect()) == sorted(rows.collect())


def test_clip_forms_agree(spark):
    rows = spark.createDataFrame([(1, i, float(i - 3)) for i in range(7)], "client_id int, param_idx long, delta double")
    a = udfs.clipped(rows, 1.5).collect()
    assert sorted(a) == sorted(rows.withColumn("delta", udfs.clip("delta", 1.5)).collect())


def test_sql_functions(spark):
    sqlfuncs.register(spark)
    r = spark.sql("SELECT dense_time(10D, 2D, 0.1D) a, sparse_time(10D, 0.1D, 2D, 0.1D) b, paced_ratio(4.2D, 10D, 2D, 0.1D) c, adjusted_coef(0.5D, 0.573427D, 1D) d, boost_factor(1L, 5D, 1) e, boost_factor(2L, 5D, 1) f, kept_count(0.0999999999999D, 1000L) g").first()
    assert [round(x, 6) for x in r] == [5.1, 1.1, 0.41, 0.871951, 5.0, 1.0, 100]


def test_registry_runs_everywhere_once(spark, small):
    """Rows-only queries give rows."""
    for name in sorted(set(q.QUERIES) - set(q.ORACLE)):
        if name.startswith(("eval_", "topk_", "stream_")):
            assert q.QUERIES[name](spark, small).count() > 0, name
