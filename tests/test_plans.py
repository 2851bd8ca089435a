import contextlib
import io
import re

from pyspark.sql import functions as F

from pacedfl import queries as q
from pacedfl.operators import compress, partition, server
from pacedfl.sources import updates


def plan(df) -> str:
    with contextlib.redirect_stdout(io.StringIO()) as out:
        df.explain("formatted")
    return out.getvalue()


def tree(df) -> str:
    return plan(df).split("\n\n")[0]


def test_fused_boost_shuffles_kept_rows_once(spark, small):
    kept = spark.createDataFrame([(c, c * i, 1.0) for c in range(3) for i in range(5)], "client_id int, param_idx long, delta double")
    coef = spark.createDataFrame([(c, 0.1) for c in range(3)], "client_id int, p double")
    fused = tree(server.server_step(kept, coef, "p", 5.0, n_clients=3))
    assert len(re.findall(r"\bExchange \(", fused)) == 1 and "BroadcastHashJoin" in fused
    two = tree(server.server_step_two_pass(kept, coef, "p", 5.0))
    assert len(re.findall(r"\bExchange \(", two)) >= 2


def test_hashed_assignment_has_no_join_and_no_shuffle(spark, small):
    e = spark.read.parquet(f"{small}/embeddings.parquet").select(F.col("vec_id").alias("sample_id"), F.col("label").alias("y"))
    text = tree(partition.assign_clients(e, mode="hashed", shares=q.SHARES))
    assert "Join" not in text and "Exchange" not in text


def test_literal_bound_cuts_before_the_exchange(spark, small):
    rows = updates.update_lineitem(spark, small, 10).withColumn("k", F.lit(20).cast("long") + F.col("client_id"))
    assert "WindowGroupLimit" in tree(compress.topk(rows, k_max=40))
    assert "WindowGroupLimit" not in tree(compress.topk(rows))


def test_scans_read_what_they_need(spark, small):
    text = plan(q.QUERIES["update_lineitem"](spark, small))
    assert re.search(r"ReadSchema: struct<l_partkey:bigint,l_suppkey:bigint,l_quantity:double,l_discount:double>", text)
    text = plan(spark.read.parquet(f"{small}/events.parquet").where("user_id = 3").select("value"))
    assert "EqualTo(user_id,3)" in text


def test_sql_paths_have_no_python(spark, small):
    for name in q.ORACLE:
        if name in ("eval_confusion", "server_packed", "ef_cogroup") or name.startswith("stream_"):  # a stream has run by then
            continue
        text = tree(q.QUERIES[name](spark, small))
        assert not re.search("Python|Pandas|Arrow", text), name
        assert "CartesianProduct" not in text, name


def test_nested_loops_meet_only_tiny_tables(spark, small):
    """Where a plan has a nested loop, one side is a broadcast of grids or single rows."""
    for name in (n for n in q.ORACLE if not n.startswith("stream_")):
        text = tree(q.QUERIES[name](spark, small))
        assert text.count("BroadcastNestedLoopJoin") <= text.count("BroadcastExchange"), name


def test_no_literal_cuts_an_update_of_many_parts(spark, small, tmp_path):
    """A tenth of 1,100,000 parts is more than the 100,000 rows that a group limit may have."""
    n, cut = 1_100_000, 110_000
    sf, parts = str(tmp_path), spark.range(1, n + 1)
    client = q.first_round(spark, small).orderBy(F.desc("k")).first().client_id
    parts.select(F.col("id").alias("p_partkey"), F.lit("b").alias("p_brand")).write.parquet(f"{sf}/part.parquet")
    lines = parts.select(F.lit(client).cast("long").alias("l_suppkey"), F.col("id").alias("l_partkey"), F.lit(1.0).alias("l_quantity"), F.lit(0.06).alias("l_discount"))
    lines.withColumn("l_shipdate", F.lit("1995-01-01").cast("timestamp_ntz")).write.parquet(f"{sf}/lineitem.parquet")
    spark.read.parquet(f"{small}/supplier.parquet").write.parquet(f"{sf}/supplier.parquet")
    assert q.QUERIES["topk_global"](spark, sf).count() == cut
    assert q.QUERIES["topk_layer"](spark, sf).count() == cut
    paced = q.first_round(spark, sf).where(F.col("client_id") == client).first().k
    assert paced >= cut and q.kept(spark, sf).count() == cut and q.kept(spark, sf, "paced").count() == paced
