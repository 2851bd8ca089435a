"""A three-client round worked out by hand: V = 10 Mbit, base ratio 0.1, ten coordinates."""

import pytest
from pyspark.sql import functions as F

from pacedfl.operators import compress, schedule, server
from pacedfl.operators.coeffs import with_adjusted, with_share
from pacedfl.operators.overlap import overlap_degree, overlap_histogram

UPDATES = {1: [5, -4, 3, -2, 1, 0.5, 0, 0, 0.25, -0.1], 2: [0.5, 4, -0.2, 0, 3, 1, -2, 0.1, 0, 0], 3: [-0.3, 0, 0.2, 1, 0, 0, -6, 2, 0.5, 0.1]}


@pytest.fixture(scope="module")
def registry(spark):
    return spark.createDataFrame([(0, 1, 2.0, 0.1, 50), (0, 2, 1.0, 0.1, 30), (0, 3, 0.5, 0.2, 20)], "round int, client_id int, bandwidth_mbps double, latency_s double, n_samples long").cache()


@pytest.fixture(scope="module")
def delta(spark):
    return spark.createDataFrame([(c, i, float(v)) for c, u in UPDATES.items() for i, v in enumerate(u)], "client_id int, param_idx long, delta double").cache()


def paced(registry, norm="sum"):
    return with_adjusted(with_share(schedule.paced_ratios(registry, 0.1, 10, 10.0)), 1.0, norm)


def test_schedule(registry):
    rows = {r.client_id: r for r in paced(registry).collect()}
    assert [round(rows[c].t_base, 6) for c in (1, 2, 3)] == [1.1, 2.1, 4.2]
    assert [round(rows[c].keep_ratio, 6) for c in (1, 2, 3)] == [0.41, 0.205, 0.1]
    assert [rows[c].k for c in (1, 2, 3)] == [4, 2, 1]
    assert all(abs(rows[c].t_after - 4.2) < 1e-9 for c in rows)
    pace = schedule.pace_time(registry, 0.1, 10.0).first()
    assert pace.pace_client == 3 and abs(pace.t_bench - 4.2) < 1e-9
    assert abs(schedule.pace_time_argmin(registry, 0.1, 10.0).first().t_bench - 1.1) < 1e-9


@pytest.mark.parametrize("norm, want", [("sum", [0.871951, 1, 1]), ("max", [0.5, 0.6, 0.82]), ("minmax", [0.5, 0.885714, 1]), ("none", [1, 1, 1])])
def test_coefficients(registry, norm, want):
    rows = {r.client_id: r for r in paced(registry, norm).collect()}
    if norm == "max":
        want = [0.5, 0.6, 0.2 / max(0.2, 0.1 / 0.41)]
    assert [round(rows[c].p_adj, 5) for c in (1, 2, 3)] == [round(x, 5) for x in want]


def step_of(df):
    out = [0.0] * 10
    for r in df.collect():
        out[r.param_idx] = round(r.step, 6)
    return out


def test_steps(spark, registry, delta):
    info = paced(registry)
    assert step_of(server.server_step(delta, info, "f")) == pytest.approx([2.59, -0.8, 1.48, -0.8, 1.4, 0.55, -1.8, 0.43, 0.225, -0.03])
    top = compress.topk(delta.withColumn("k", F.lit(1)))
    assert step_of(server.server_step(top, info, "f")) == pytest.approx([2.5, 1.2, 0, 0, 0, 0, -1.2, 0, 0, 0])
    sent = compress.topk(delta.join(info.select("client_id", "k"), "client_id"))
    assert {(r.client_id, r.param_idx) for r in sent.collect()} == {(1, 0), (1, 1), (1, 2), (1, 3), (2, 1), (2, 4), (3, 6)}
    plain = [4.359756, 0.512195, 2.615854, -1.743902, 3, 0, -6, 0, 0, 0]
    assert step_of(server.server_step(sent, info, "p_adj")) == pytest.approx(plain, abs=2e-6)
    for gamma in (3.0, 5.0):
        want = [v if i == 1 else gamma * v for i, v in enumerate(plain)]
        assert step_of(server.server_step(sent, info, "p_adj", gamma)) == pytest.approx(want, abs=1e-5)
        assert step_of(server.server_step_two_pass(sent, info, "p_adj", gamma)) == pytest.approx(want, abs=1e-5)
    degree = overlap_degree(sent)
    assert {r.param_idx: r.degree for r in degree.collect()} == {0: 1, 1: 2, 2: 1, 3: 1, 4: 1, 6: 1}
    assert {r.degree: r.share for r in overlap_histogram(degree).collect()} == {1: pytest.approx(5 / 6), 2: pytest.approx(1 / 6)}
    weights = spark.createDataFrame([(i, 0, 1.0) for i in range(10)], "param_idx long, layer int, w double")
    new = {r.param_idx: r.w for r in server.apply_step(weights, server.server_step(sent, info, "p_adj"), 1.0).collect()}
    assert new[0] == pytest.approx(1 - 4.359756, abs=1e-5) and new[5] == 1.0
