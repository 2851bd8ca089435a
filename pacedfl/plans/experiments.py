"""The experiment workloads on the given tables, as DataFrames of results.

Workloads: W1 language of documents, W2 quality of labelled documents, W3 ten planted classes of embeddings,
W3s its counter-workload (sparse true weights), W5 sixty-three planted classes, WC roles of conversations.
Means and spreads over seeds are reported; tuning uses a validation third of the training rows, and the
number of settings tried is a column of its result.
"""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, functions as F

from pacedfl.functions.portable import uniform
from pacedfl.operators import compress, overlap
from pacedfl.plans import metrics
from pacedfl.plans.rounds import run_all, run_cohort
from pacedfl.plans.spec import RunSpec, method
from pacedfl.sources import features
from pacedfl.sources.tables import new_path

MAIN = ("dense", "topk", "ef_topk", "paced", "boosted")
WORKLOADS = {
    "W1": (features.language_samples, 4),
    "W2": (features.quality_samples, 2),
    "W3": (lambda s, d: features.embedding_samples(s, d, "walsh10"), 10),
    "W3s": (lambda s, d: features.embedding_samples(s, d, "largest10"), 10),
    "W5": (lambda s, d: features.embedding_samples(s, d, "walsh63"), 63),
    "WC": (lambda s, d: features.conversation_samples(s, d).drop("conv_id"), 3),
}
ALPHAS = (0.01, 0.03, 0.1, 0.3, 1.0)
BETAS, RATIOS = (0.1, 0.5), (0.1, 0.01)


def grid_specs(methods=MAIN, betas=BETAS, ratios=RATIOS, seeds=(42,), rounds: int = 20, **changes) -> list[RunSpec]:
    return [method(m, run_id=f"{m}|b{b}|r{r}|s{s}", beta=b, base_ratio=r, seed=s, rounds=rounds, **changes) for b in betas for r in ratios for s in seeds for m in methods]


def labelled(log: DataFrame, workload: str) -> DataFrame:
    """The log with the columns that the run's name holds."""
    part = F.split("run_id", r"\|")
    number = lambda i: F.regexp_extract(part[i], r"([0-9.]+)$", 1)
    return log.select(F.lit(workload).alias("workload"), part[0].alias("method"), number(1).cast("double").alias("beta"), number(2).cast("double").alias("base_ratio"), number(3).cast("int").alias("seed"), *[c for c in log.columns])


def accuracy_grid(spark: SparkSession, sf_dir: str, workloads=("W1", "W2", "W3", "W5"), **more) -> DataFrame:
    """Main comparison: final held-out accuracy of every method and cell, one row a run."""
    out = None
    for w in workloads:
        make, n = WORKLOADS[w]
        log = labelled(run_all(grid_specs(**more), make(spark, sf_dir), n), w)
        rows = log.groupBy("workload", "method", "beta", "base_ratio", "seed").agg(F.max_by("accuracy", "round").alias("accuracy"), F.sum("t_actual").alias("t_actual"), F.sum("t_max").alias("t_max"), F.sum("t_min").alias("t_min"))
        out = rows if out is None else out.unionByName(rows)
    return out


def with_spread(finals: DataFrame) -> DataFrame:
    return finals.groupBy("workload", "beta", "base_ratio", "method").agg(F.avg("accuracy").alias("accuracy"), F.stddev("accuracy").alias("sd"), F.count("*").alias("runs"))


def curves(spark: SparkSession, sf_dir: str, workload: str = "W1", **more) -> DataFrame:
    make, n = WORKLOADS[workload]
    return metrics.curve(run_all(grid_specs(**more), make(spark, sf_dir), n))


def alpha_tuning(spark: SparkSession, sf_dir: str, workload: str = "W3", betas=BETAS, ratios=RATIOS, rounds: int = 20, methods=("paced", "boosted", "topk", "ef_topk"), seeds=(42,)) -> DataFrame:
    """Server factor of each method and cell, chosen on a validation third by mean accuracy over the seeds; baselines get
    the same budget through server_lr. tried: settings of each method and cell."""
    make, n = WORKLOADS[workload]
    logs = []
    for seed in seeds:
        samples = make(spark, sf_dir).where("not is_test").withColumn("is_test", uniform(seed, "valid", "sample_id") < 1 / 3)
        specs = []
        for m in methods:
            for b in betas:
                for r in ratios:
                    for a in ALPHAS:
                        s = method(m, run_id=f"{m}@{a}|b{b}|r{r}|s{seed}", beta=b, base_ratio=r, rounds=rounds, seed=seed)
                        specs.append(replace(s, alpha=a) if s.coef == "adjusted" else replace(s, server_lr=a / 0.3))
        logs.append(labelled(metrics.final_accuracy(run_all(specs, samples, n)), workload))
    rows = reduce(DataFrame.unionByName, logs)
    part = F.split("method", "@")
    means = rows.groupBy(part[0].alias("method"), part[1].cast("double").alias("alpha"), "beta", "base_ratio").agg(F.avg("accuracy").alias("accuracy"))
    best = F.max_by("alpha", F.struct("accuracy", -F.col("alpha")))
    return means.groupBy("method", "beta", "base_ratio").agg(best.alias("best_alpha"), F.max("accuracy").alias("accuracy"), F.count("*").alias("tried"))


def gamma_sweep(spark: SparkSession, sf_dir: str, workload: str = "W1", n_clients: int = 10, betas=BETAS, ratios=RATIOS, gammas=None, rounds: int = 20, seed: int = 42) -> DataFrame:
    """Final accuracy by boost for every cell; all boosts of a cell train in the same jobs."""
    make, n = WORKLOADS[workload]
    specs = [method("boosted", run_id=f"g{g}|b{b}|r{r}|s{seed}", gamma=float(g), beta=b, base_ratio=r, n_clients=n_clients, rounds=rounds, seed=seed) for b in betas for r in ratios for g in gammas or range(1, n_clients + 1)]
    log = labelled(run_all(specs, make(spark, sf_dir), n), workload)
    rows = log.groupBy("method", "beta", "base_ratio").agg(F.max_by("accuracy", "round").alias("accuracy"))
    return rows.select(F.lit(n_clients).alias("n_clients"), F.expr("cast(substring(method, 2) as double)").alias("gamma"), "beta", "base_ratio", "accuracy")


def client_scaling(spark: SparkSession, sf_dir: str, workload: str = "W1", counts=(10, 16, 20), **more) -> DataFrame:
    """Best boost by number of clients and cell."""
    rows = None
    for n in counts:
        one = gamma_sweep(spark, sf_dir, workload, n, **more)
        rows = one if rows is None else rows.unionByName(one)
    return rows.groupBy("n_clients", "beta", "base_ratio").agg(F.max_by("gamma", F.struct("accuracy", -F.col("gamma"))).alias("best_gamma"), F.max("accuracy").alias("accuracy"))


def time_to_accuracy(spark: SparkSession, sf_dir: str, workload: str = "W1", targets=(0.4, 0.6), rounds: int = 20, seed: int = 42, beta: float = 0.1) -> DataFrame:
    """Communication seconds to each target, and the speed-up over uniform top-k at the same ratio. Error feedback is
    billed twice: with its indexes, and (ef_topk_values) by its values alone."""
    make, n = WORKLOADS[workload]
    specs = grid_specs(betas=(beta,), seeds=(seed,), rounds=rounds) + [method("ef_topk", run_id=f"ef_topk_values|b{beta}|r{r}|s{seed}", beta=beta, base_ratio=r, seed=seed, rounds=rounds, payload_factor=1.0) for r in RATIOS]
    log = run_all(specs, make(spark, sf_dir), n)
    rows = reduce(DataFrame.unionByName, [labelled(metrics.time_to_target(log, t), workload).drop("run_id").withColumn("target", F.lit(float(t))) for t in targets])
    ref = rows.where("method = 'topk'").select("base_ratio", "target", F.col("time_actual").alias("__ref"))
    return rows.join(ref, ["base_ratio", "target"]).select("workload", "target", "method", "base_ratio", "round_hit", "time_actual", "time_max", "time_min", (F.col("__ref") / F.col("time_actual")).alias("speedup"))


def overlap_distribution(spark: SparkSession, sf_dir: str, workload: str = "W1", betas=BETAS, ratios=RATIOS, seed: int = 42) -> DataFrame:
    """Degrees of overlap of what clients keep of a trained first round, by cell: (beta, base_ratio, degree, n_coords, share)."""
    make, n = WORKLOADS[workload]
    out = None
    for b in betas:
        folder = new_path(spark, "overlap")
        specs = [method("topk", run_id=f"r{r}", beta=b, base_ratio=r, seed=seed, rounds=1) for r in ratios]
        run_cohort(specs, make(spark, sf_dir), n, out_dir=folder, keep_updates=True)
        sent = spark.read.parquet(f"{folder}/delta/round=0").join(spark.read.parquet(f"{folder}/plan").where("round = 0").select("run_id", "client_id", "k"), ["run_id", "client_id"])
        kept = compress.topk(sent, ("run_id", "client_id"))
        rows = overlap.overlap_histogram(overlap.overlap_degree(kept, ("run_id",)), ("run_id",))
        rows = rows.select(F.lit(b).alias("beta"), F.expr("cast(substring(run_id, 2) as double)").alias("base_ratio"), "degree", "n_coords", "share")
        out = rows if out is None else out.unionByName(rows)
    return out


def regression(spark: SparkSession, sf_dir: str, rounds: int = 5, methods=MAIN, n_clients: int = 10, **changes) -> DataFrame:
    """W4: prices of lineitem by least squares, clients by supplier; held-out loss by round."""
    specs = [method(m, n_clients=n_clients, rounds=rounds, partition="column", model="linear", lr=0.1, base_ratio=0.5, **changes) for m in methods]
    log, _ = run_cohort(specs, features.regression_samples(spark, sf_dir, n_clients), 1)
    return log.select("run_id", "round", "loss", "sent_rows", "t_actual")


def round_breakdown(spark: SparkSession, sf_dir: str, workload: str = "W1", rounds: int = 5, methods=MAIN, beta: float = 0.1, ratio: float = 0.1) -> DataFrame:
    """Mean seconds of a round by part; every method runs alone, and each part is written before the next begins."""
    make, n = WORKLOADS[workload]
    logs = [run_cohort([method(m, beta=beta, base_ratio=ratio, rounds=rounds)], make(spark, sf_dir), n, timed=True)[0] for m in methods]
    return metrics.breakdown(reduce(DataFrame.unionByName, logs))


def accuracy_over_time(spark: SparkSession, sf_dir: str, workload: str = "W1", step_s: float = 100.0, steps: int = 40, **more) -> DataFrame:
    make, n = WORKLOADS[workload]
    log = run_all(grid_specs(**more), make(spark, sf_dir), n)
    return metrics.accuracy_at(log, spark.range(1, steps + 1).select((F.col("id") * step_s).alias("t_grid")))
