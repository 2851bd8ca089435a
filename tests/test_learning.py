import numpy as np
import pytest
from pyspark.sql import functions as F

from pacedfl.functions.portable import uniform_py
from pacedfl.operators import learner
from pacedfl.plans import experiments
from pacedfl.plans.rounds import run_cohort
from pacedfl.plans.spec import METHODS, method
from pacedfl.sources import features


@pytest.fixture(scope="module")
def samples(spark, small):
    return features.embedding_samples(spark, small).cache()


def twin(samples, spec, picked_by_round, n_classes):
    """The whole loop in numpy, from the same draws."""
    rows = samples.collect()
    model = learner.MODELS[spec.model](64, n_classes, **({"hidden": spec.hidden} if spec.model == "perceptron" else {}))
    w, residual = model.start(spec.seed, np.arange(model.n_params)), {}
    for t in range(spec.rounds):
        kept, info = {}, picked_by_round[t]
        for c, p in info.items():
            own = sorted((r for r in rows if r.client_id == c), key=lambda r: (uniform_py(spec.seed, "order", t, 1, r.sample_id), r.sample_id))
            x, y, u = np.array([r.x for r in own]), np.array([r.y for r in own]), w
            for a in range(0, len(own), spec.batch_size):
                u = u - spec.lr * model.grad(u, x[a : a + spec.batch_size], y[a : a + spec.batch_size])
            d = w - u + (residual.get(c, 0) if spec.error_feedback else 0)
            if spec.compressor == "none":
                kept[c] = d
                continue
            order = sorted(np.flatnonzero(d), key=lambda i: (-abs(d[i]), i))[: p.k]
            kept[c] = np.zeros_like(d)
            kept[c][order] = d[order]
            residual[c] = d - kept[c]
        degree = sum((v != 0).astype(int) for v in kept.values())
        step = sum(info[c].weight * v for c, v in kept.items())
        w = w - step * np.where(degree <= spec.max_degree, spec.gamma, 1.0)
    return w


@pytest.mark.parametrize("name", ["dense", "topk", "ef_topk", "boosted"])
def test_loop_equals_numpy_twin(spark, samples, tmp_path, name):
    spec = method(name, rounds=3, n_clients=4, batch_size=32, beta=0.5)
    out = f"file://{tmp_path}/run"
    log, weights = run_cohort([spec], samples, 10, out_dir=out)
    picked = {}
    for r in spark.read.parquet(f"{out}/plan").collect():
        picked.setdefault(r["round"], {})[r.client_id] = r
    assert all(len(p) == 2 for p in picked.values())
    train = spark.read.parquet(f"{out}/samples").where("not is_test")
    want = twin(train, spec, picked, 10)
    assert np.allclose(learner.vectors(weights)[name], want, rtol=1e-9, atol=1e-12)
    assert log.count() == 3


def test_run_resumes_from_last_round(spark, samples, tmp_path):
    out = f"file://{tmp_path}/run"
    spec = method("ef_boosted", rounds=3, n_clients=4, beta=0.5)
    _, whole = run_cohort([spec], samples, 10)
    jvm_path = spark._jvm.org.apache.hadoop.fs.Path
    run_cohort([spec], samples, 10, out_dir=out)
    fs = jvm_path(out).getFileSystem(spark._jsc.hadoopConfiguration())
    fs.delete(jvm_path(f"{out}/log/round=2"), True)  # as if the last round had broken off
    _, again = run_cohort([spec], samples, 10, out_dir=out)
    assert np.allclose(learner.vectors(whole)["ef_boosted"], learner.vectors(again)["ef_boosted"], rtol=1e-9)


def test_a_round_reads_only_its_clients(spark, samples, tmp_path):
    out = f"file://{tmp_path}/run"
    run_cohort([method("dense", rounds=1, n_clients=6, fraction=0.34, beta=5.0)], samples, 10, out_dir=out)
    rows = spark.read.parquet(f"{out}/samples")
    plan = rows.where("not is_test").where(F.col("bucket").isin(1, 2))._jdf.queryExecution().executedPlan().toString()
    assert "bucket" in plan.split("PartitionFilters")[1].split("]")[0]
    assert rows.count() == samples.count() and rows.where("not is_test and client_id <> bucket").count() == 0


def test_every_method_runs_in_one_cohort(samples):
    specs = [method(m, rounds=1, beta=0.5, n_clients=4) for m in METHODS]
    log, weights = run_cohort(specs, samples, 10)
    rows = {r.run_id: r for r in log.collect()}
    assert set(rows) == set(METHODS) == set(learner.vectors(weights))
    assert rows["topk"].sent_rows < rows["dense"].sent_rows
    assert rows["dense"].t_actual == pytest.approx(rows["dense"].t_max)


def test_one_client_full_batch_is_gradient_descent(samples):
    spec = method("dense", rounds=2, n_clients=1, fraction=1.0, batch_size=None, partition="iid")
    _, weights = run_cohort([spec], samples, 10)
    rows = samples.where("not is_test").collect()
    model, w = learner.Softmax(64, 10), np.zeros(650)
    for _ in range(2):
        w = w - spec.lr * model.grad(w, np.array([r.x for r in rows]), np.array([r.y for r in rows]))
    assert np.allclose(learner.vectors(weights)["dense"], w, rtol=1e-9)


@pytest.mark.parametrize("model, y", [(learner.Softmax(5, 3), [0, 2, 1, 1]), (learner.Perceptron(5, 3, 4), [0, 2, 1, 1]), (learner.Linear(5), [0.5, 1.0, -1.0, 2.0])])
def test_gradients_by_differences(model, y):
    rng = np.random.default_rng(0)
    x, y, w = rng.normal(size=(4, 5)), np.array(y), rng.normal(size=model.n_params)
    g = model.grad(w, x, y)
    for i in range(model.n_params):
        e = np.zeros_like(w)
        e[i] = 1e-6
        assert g[i] == pytest.approx((model.loss(w + e, x, y).mean() - model.loss(w - e, x, y).mean()) / 2e-6, abs=1e-6)


def test_sql_gradient_equals_numpy(spark, small):
    rows = features.regression_rows(spark, small, 3)
    got = {(r.client_id, r.param_idx): r.grad for r in learner.gradient_sql(rows, [0.1, 0.2, -0.3, 0.4]).collect()}
    own = [r for r in rows.collect() if r.client_id == 1]
    want = learner.Linear(4).grad(np.array([0.1, 0.2, -0.3, 0.4]), np.array([r.x for r in own]), np.array([r.y for r in own]))
    assert [got[1, i] for i in range(4)] == pytest.approx(want.tolist())


def test_boosted_beats_topk_on_planted_classes(spark):
    finals = experiments.accuracy_grid(spark, "/root/testdata/sf0.01", ("W3",), methods=("dense", "topk", "boosted"), betas=(0.5,), ratios=(0.01,), rounds=8)
    by = {r.method: r.accuracy for r in finals.collect()}
    assert by["boosted"] > by["topk"] and by["dense"] >= by["topk"]


def test_benchmark_documents_can_be_left_out(spark, small):
    s = features.language_samples(spark, small)
    left = features.without_benchmark(spark, small, s)
    docs, items = (spark.read.parquet(f"{small}/{t}.parquet") for t in ("documents", "benchmark"))
    hit = docs.join(items.withColumnRenamed("text", "item"), F.expr("contains(text, item)")).select("doc_id").distinct()
    assert hit.count() > 0 and left.join(hit, left.sample_id == hit.doc_id, "left_semi").count() == 0 and left.count() > 0.8 * s.count()


def test_early_stop_sampled_evaluation_and_traced_links(spark, small, samples):
    from pacedfl.operators import links

    log, _ = run_cohort([method("dense", rounds=6, n_clients=4, beta=0.5, target_accuracy=0.0)], samples, 10)
    assert log.count() == 1
    log, _ = run_cohort([method("dense", rounds=1, n_clients=4, beta=0.5, eval_share=0.5)], samples, 10)
    assert 0 <= log.first().accuracy <= 1
    log, _ = run_cohort([method("paced", rounds=2, n_clients=4, beta=0.5, link_mode="trace")], samples, 10, trace=links.traced_links(spark, small, 4))
    assert log.agg(F.countDistinct("t_max")).first()[0] == 2


def test_regression_loss_falls(spark, small):
    rows = {(r.run_id, r["round"]): r.loss for r in experiments.regression(spark, small, 3, ("dense", "boosted")).collect()}
    assert rows["dense", 2] < rows["dense", 0] and rows["boosted", 2] < rows["boosted", 0]


def test_rarer_overlap_at_smaller_ratio(spark):
    rows = experiments.overlap_distribution(spark, "/root/testdata/sf0.01", "W1", betas=(0.1,)).collect()
    alone = {r.base_ratio: r.share for r in rows if r.degree == 1}
    assert alone[0.01] > alone[0.1]


@pytest.mark.parametrize("name, changes", [("paced", {}), ("coef_only", {}), ("boost_only", {}), ("ef_boosted", {"fraction": 0.34, "n_clients": 6}), ("topk", {"model": "perceptron", "hidden": 4}), ("topk", {"epochs": 1, "batch_size": 7})])
def test_more_loops_equal_numpy_twin(spark, samples, tmp_path, name, changes):
    """Pacing, coefficients, absent clients' residuals, another model, another batch."""
    spec = method(name, **({"rounds": 3, "n_clients": 4, "batch_size": 32, "beta": 0.5} | changes))
    out = f"file://{tmp_path}/run"
    _, weights = run_cohort([spec], samples, 10, out_dir=out)
    picked = {}
    for r in spark.read.parquet(f"{out}/plan").collect():
        picked.setdefault(r["round"], {})[r.client_id] = r
    want = twin(spark.read.parquet(f"{out}/samples").where("not is_test"), spec, picked, 10)
    assert np.allclose(learner.vectors(weights)[name], want, rtol=1e-9, atol=1e-12)


def test_randomk_and_traced_loops_equal_numpy_twin(spark, small, samples, tmp_path):
    from pacedfl.operators import compress, links

    out = f"file://{tmp_path}/run"
    specs = [method("paced", rounds=2, n_clients=4, beta=0.5, link_mode="trace"), method("randomk_boosted", rounds=1, n_clients=4, beta=0.5, link_mode="trace")]
    _, weights = run_cohort([specs[0]], samples, 10, out_dir=out, trace=links.traced_links(spark, small, 4))
    picked = {}
    for r in spark.read.parquet(f"{out}/plan").collect():
        picked.setdefault(r["round"], {})[r.client_id] = r
    assert np.allclose(learner.vectors(weights)["paced"], twin(spark.read.parquet(f"{out}/samples").where("not is_test"), specs[0], picked, 10), rtol=1e-9, atol=1e-12)
    out = f"file://{tmp_path}/other"
    _, weights = run_cohort([specs[1]], samples, 10, out_dir=out, trace=links.traced_links(spark, small, 4), keep_updates=True)
    plan, delta = spark.read.parquet(f"{out}/plan"), spark.read.parquet(f"{out}/delta/round=0")
    kept = compress.randomk(delta.join(plan.select("run_id", "client_id", "k", "weight"), ["run_id", "client_id"]), ("run_id", "client_id"), seed=specs[1].seed).toPandas()
    step = kept.assign(s=kept.weight * kept.delta).groupby("param_idx").agg(s=("s", "sum"), n=("delta", "size"))
    want = np.zeros(650)
    want[step.index] -= step.s * np.where(step.n <= 1, specs[1].gamma, 1.0)
    assert np.allclose(learner.vectors(weights)["randomk_boosted"], want, rtol=1e-9, atol=1e-12)


def test_large_weights_reach_the_test_rows_without_broadcast(spark, samples):
    """The same scores when the weights are dealt with the rows."""
    model = learner.Softmax(64, 10)
    weights = spark.range(2 * model.n_params).selectExpr("concat('r', id % 2) AS run_id", "id div 2 AS param_idx", "cos(cast(id as double)) AS w")
    a, b = (sorted((r.run_id, r.y, r.n, r.correct, round(r.loss, 9)) for r in learner.evaluate(samples.where("is_test"), weights, model, 2, limit).collect()) for limit in (1 << 20, 1))
    assert a == b and len(a) == 20


def test_parts_of_a_round_are_timed(spark, samples):
    log, _ = run_cohort([method("paced", rounds=2, n_clients=4, beta=0.5)], samples, 10, timed=True)
    for r in log.collect():
        assert min(r.train_s, r.compress_s, r.server_s) > 0.01


def test_nothing_of_a_model_is_gathered_in_a_round(spark, samples, tmp_path):
    """Updates are sent, summed and applied as tables; selections by bucket give the same weights as by sorting."""
    from pacedfl.plans import rounds

    spec = method("boosted", rounds=2, n_clients=4, beta=0.5)
    _, a = run_cohort([spec], samples, 10)
    limit, rounds.SORT_LIMIT = rounds.SORT_LIMIT, 10
    try:
        _, b = run_cohort([spec], samples, 10)
    finally:
        rounds.SORT_LIMIT = limit
    assert np.allclose(learner.vectors(a)["boosted"], learner.vectors(b)["boosted"], rtol=1e-9)
    with pytest.raises(ValueError):
        learner.vectors(a, max_bytes=100)
