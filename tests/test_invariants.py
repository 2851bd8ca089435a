import pytest
from pyspark.sql import functions as F

from pacedfl.operators import compress, links, partition, schedule, server
from pacedfl.operators.coeffs import with_adjusted, with_share
from pacedfl.operators.overlap import overlap_degree
from pacedfl.plans import metrics
from pacedfl.sources import updates


@pytest.fixture(scope="module", params=[1, 2])
def round_(request, spark):
    reg = links.gaussian_links(spark, 12, request.param).withColumn("n_samples", (F.col("client_id") * 7 % 5 + 1).cast("long"))
    return schedule.select_clients(reg, 6, 12, 0.5, request.param).cache()


@pytest.fixture(scope="module")
def delta(spark, small):
    return updates.update_lineitem(spark, small, 5).cache()


def test_pace(round_):
    rows = schedule.paced_ratios(round_, 0.1, 1000, clamp=False).collect()
    assert len(rows) == 36
    for t in range(6):
        own = [r for r in rows if r.round == t]
        assert len(own) == 6
        assert all(r.keep_ratio >= 0.1 - 1e-12 for r in own) and min(abs(r.keep_ratio - 0.1) for r in own) < 1e-12
        assert max(r.t_after for r in own) - min(r.t_after for r in own) < 1e-9
    clamped = schedule.paced_ratios(round_, 0.45, 1000).collect()
    assert all(r.keep_ratio <= 1 and r.t_after <= r.t_bench + 1e-9 and r.k <= 1000 for r in clamped)


def test_paced_and_uniform_rounds_last_equally(round_):
    a = metrics.time_account(metrics.simulated_uploads(round_, 0.1, 1000)).toPandas().pivot(index="round", columns="run_id", values="t_actual")
    assert (a["paced"] - a["topk"]).abs().max() < 1e-9
    b = metrics.time_account(metrics.simulated_uploads(round_, 0.1, 1000)).toPandas()
    assert (b.t_min <= b.t_max).all() and (b.t_actual <= b.t_max + 1e-9).all()
    assert (b.sort_values("round").groupby("run_id").cum_actual.diff().dropna() >= 0).all()


def test_latency_dominated_payload_saturates(round_):
    rows = schedule.paced_ratios(round_, 0.1, 1000, v=0.02).collect()
    assert sum(r.keep_ratio == 1 for r in rows) > len(rows) / 3


@pytest.mark.parametrize("norm", ["sum", "max", "minmax", "none"])
def test_coefficients(round_, norm):
    rows = with_adjusted(with_share(schedule.paced_ratios(round_, 0.1, 1000)), 0.3, norm).collect()
    for t in range(6):
        assert abs(sum(r.f for r in rows if r.round == t) - 1) < 1e-12
    for r in rows:
        assert 0 < r.p_adj <= 0.3 + 1e-12
        assert (abs(r.p_adj - 0.3) < 1e-12) == (r.f >= r.norm_ratio - 1e-15)


def test_clients_without_samples_get_no_weight(spark):
    reg = spark.createDataFrame([(0, 1, 0.2, 5), (0, 2, 0.1, 0), (0, 3, 0.1, None)], "round int, client_id int, keep_ratio double, n_samples long")
    rows = {r.client_id: r for r in with_adjusted(with_share(reg)).collect()}
    assert rows[1].f == 1 and rows[2].p_adj == 0 and rows[3].p_adj == 0


def test_topk(delta):
    k = 15
    rows = compress.topk(delta.withColumn("k", F.lit(k)))
    own, all_ = rows.toPandas(), delta.where("delta <> 0").toPandas()
    for c, g in all_.groupby("client_id"):
        kept = own[own.client_id == c]
        assert len(kept) == min(k, len(g))
        rest = g[~g.param_idx.isin(kept.param_idx)]
        assert kept.delta.abs().min() >= rest.delta.abs().max()
    for k in (1, 15, 60, 10**6):
        with_k = delta.withColumn("k", F.lit(k))
        a = {(r.client_id, r.param_idx) for r in compress.topk(with_k).collect()}
        b = {(r.client_id, r.param_idx) for r in compress.topk_select(with_k).collect()}
        assert a == b


def test_topk_select_with_all_magnitudes_tied(spark):
    rows = spark.createDataFrame([(c, i, (-1.0) ** i * 4) for c in range(3) for i in range(50)], "client_id int, param_idx long, delta double").withColumn("k", F.col("client_id") * 10 + 1)
    a = {(r.client_id, r.param_idx) for r in compress.topk(rows).collect()}
    assert a == {(r.client_id, r.param_idx) for r in compress.topk_select(rows).collect()}
    assert a == {(c, i) for c in range(3) for i in range(c * 10 + 1)}


def test_zero_updates_are_never_sent(spark):
    rows = spark.createDataFrame([(1, 0, 0.0), (1, 1, 0.0)], "client_id int, param_idx long, delta double").withColumn("k", F.lit(2))
    assert not compress.topk(rows).count() and not compress.topk_select(rows).count()
    assert [r.q for r in compress.quantize(rows).collect()] == [0, 0]


def test_error_feedback_loses_nothing(spark, small):
    u = updates.update_lineitem_rounds(spark, small, 5)
    k = spark.range(5).select(F.col("id").cast("int").alias("client_id"), F.lit(7).alias("k"))
    one = compress.ef_topk(u.where("round = 0"), None, k)
    two = compress.ef_topk(u.where("round = 1"), one, k)
    total = u.groupBy("client_id", "param_idx").agg(F.sum("delta").alias("d"))
    sent = one.select("client_id", "param_idx", "sent").union(two.select("client_id", "param_idx", "sent")).union(two.select("client_id", "param_idx", "residual"))
    # residuals of the first round that met nothing in the second are part of the second's rows
    got = sent.groupBy("client_id", "param_idx").agg(F.sum("sent").alias("s"))
    assert got.join(total, ["client_id", "param_idx"], "full").where(F.abs(F.coalesce("s", F.lit(0.0)) - F.coalesce("d", F.lit(0.0))) > 1e-9).count() == 0
    assert two.where("sent <> 0").groupBy("client_id").count().agg(F.max("count")).first()[0] <= 7


def test_overlap_and_boost(delta):
    info = delta.select("client_id").distinct().withColumn("p", F.lit(0.2))
    kept = compress.topk(delta.withColumn("k", F.lit(20))).cache()
    degree = overlap_degree(kept)
    assert degree.agg(F.min("degree"), F.max("degree"), F.sum("degree")).first() == (1, degree.agg(F.max("degree")).first()[0], kept.count())
    step = lambda **o: {r.param_idx: r.step for r in server.server_step(kept, info, "p", **o).collect()}
    plain = step()
    assert step(gamma=5.0, max_degree=0) == pytest.approx(plain)
    assert step(gamma=5.0, max_degree=5) == pytest.approx({k: 5 * v for k, v in plain.items()})
    grid = server.gamma_grid(kept, info, "p", [1, 5], [1])
    assert {r.param_idx: r.step for r in grid.where("gamma = 5").collect()} == pytest.approx(step(gamma=5.0))


def test_full_ratio_is_dense(delta):
    info = delta.select("client_id").distinct().withColumn("f", F.lit(0.2))
    all_ = compress.topk(delta.withColumn("k", F.lit(10**6)))
    a, b = ({r.param_idx: r.step for r in server.server_step(x, info, "f").where("degree > 0").collect()} for x in (all_, delta))
    assert a == pytest.approx(b)


@pytest.mark.parametrize("mode", ["quota", "hashed", "iid"])
def test_partition_keeps_every_sample(spark, small, mode):
    e = spark.read.parquet(f"{small}/embeddings.parquet").select(F.col("vec_id").alias("sample_id"), F.col("label").alias("y"))
    got = partition.assign_clients(e, n_clients=7, beta=0.3, mode=mode)
    assert got.count() == e.count() == got.select("sample_id").distinct().count()
    assert got.agg(F.min("client_id") >= 0, F.max("client_id") < 7).first() == (True, True)


def test_quota_meets_shares_and_beta_orders_skew(spark, small):
    e = spark.read.parquet(f"{small}/embeddings.parquet").select(F.col("vec_id").alias("sample_id"), F.col("label").alias("y"))
    shares = partition.dirichlet_shares(list(range(10)), 5, 0.5, 3)
    got = partition.assign_clients(e, n_clients=5, shares=shares).groupBy("y", "client_id").count().collect()
    size = {r.y: r["count"] for r in e.groupBy("y").count().collect()}
    count = {(r.y, r.client_id): r["count"] for r in got}
    for y, n in size.items():
        for c in range(5):
            assert abs(count.get((y, c), 0) - n * shares[y][c]) <= 1.0001
    skew = [partition.skew_of(partition.assign_clients(e, n_clients=5, beta=b, seed=4), "y").agg(F.avg("max_share")).first()[0] for b in (0.05, 0.5, 1000.0)]
    assert skew[0] > skew[1] > skew[2]


def test_target_never_reached(spark):
    log = spark.createDataFrame([("a", t, 0.1 * t, 1.0, 2.0, 0.5) for t in range(5)], "run_id string, round int, accuracy double, t_actual double, t_max double, t_min double")
    assert metrics.time_to_target(log, 0.9).first().round_hit is None
    r = metrics.time_to_target(log, 0.3).first()
    assert (r.round_hit, r.time_actual, r.time_max) == (3, 4.0, 8.0)


def test_pack_roundtrip(delta):
    kept = compress.topk(delta.withColumn("k", F.lit(20)))
    back = compress.unpack(compress.pack(kept, shards=3))
    a = {(r.client_id, r.param_idx): r.delta for r in kept.collect()}
    assert {(r.client_id, r.param_idx): r.delta for r in back.collect()} == pytest.approx(a, rel=1e-6)
