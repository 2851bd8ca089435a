"""The round loop. Runs of one cohort go through every round together, in the same jobs.

State of a round, in the run's folder: weights by coordinate, residuals of the round's clients, then the log, which is
there only when the round is complete. Selections, links and sample order are functions of (seed, round), so a run
resumes from its last complete round. The driver holds the log's numbers, a few for each run and round; updates, steps
and weights stay in tables.
"""

from __future__ import annotations

import time
from functools import reduce
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F, types as T

from pacedfl.functions.portable import uniform
from pacedfl.operators import compress, schedule, server
from pacedfl.operators.coeffs import with_adjusted, with_share
from pacedfl.operators.learner import MODELS, Model, evaluate, local_update, start_weights
from pacedfl.operators.links import dense_time, gaussian_links, round_links
from pacedfl.operators.partition import assign_clients
from pacedfl.plans.spec import RunSpec
from pacedfl.sources.tables import ROUND_LOG, exists, new_path, removed, written

LOG = T.StructType([*ROUND_LOG.fields, *(T.StructField(n, T.DoubleType()) for n in ("train_s", "compress_s", "server_s"))])
LOG_NAMES = [n for n in LOG.names if n != "round"]
LOG_KINDS = [pa.int64() if n == "sent_rows" else pa.string() if n == "run_id" else pa.float64() for n in LOG_NAMES]
KEYS = ("run_id", "client_id")
SORT_LIMIT = 100_000  # coordinates of an update that a task may sort; the same rows are selected beyond it
BUCKETS = 64  # folders of clients: a round reads only those of its clients


def plan_rounds(spark: SparkSession, spec: RunSpec, sizes: DataFrame, n_params: int, links: DataFrame | None = None, trace: DataFrame | None = None) -> DataFrame:
    """All rounds' clients of a run in one plan: round, client_id, k, weight, t_own, t_dense, keep_ratio.

    sizes: (client_id, n_samples); clients without samples are never selected.
    """
    if links is None:
        links = gaussian_links(spark, spec.n_clients, spec.seed)
    registry = links.select("client_id", "bandwidth_mbps", "latency_s").join(sizes, "client_id").where("n_samples > 0")
    rows = schedule.select_clients(registry, spec.rounds, spec.n_clients, spec.fraction, spec.seed)
    if spec.link_mode == "per_round":
        rows = rows.drop("bandwidth_mbps", "latency_s").join(round_links(sizes.select("client_id"), spec.rounds, spec.seed), ["round", "client_id"])
    if spec.link_mode == "trace":
        # a day of telemetry is a round; a client without an observation that day keeps its own link
        order = trace.select("day").distinct().select("day", (F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("day")) - 1).alias("round"))
        day = trace.join(order, "day").select("client_id", "round", F.col("bandwidth_mbps").alias("__seen"))
        days = order.count() or 1
        rows = rows.withColumn("__day", F.col("round") % days).join(day.withColumnRenamed("round", "__day"), ["client_id", "__day"], "left")
        rows = rows.withColumn("bandwidth_mbps", F.coalesce("__seen", "bandwidth_mbps")).drop("__seen", "__day")
    if spec.schedule == "paced":
        rows = schedule.paced_ratios(rows, spec.base_ratio, n_params, spec.v_mbit, spec.clamp, spec.dense_fallback, spec.payload_factor)
    else:
        rows = schedule.uniform_ratios(rows, 1.0 if spec.compressor == "none" else spec.base_ratio, n_params, spec.v_mbit, spec.payload_factor)
    rows = with_adjusted(with_share(rows, spec.weighting), spec.alpha, spec.norm, spec.renormalize)
    full = dense_time(spec.v_mbit, "bandwidth_mbps", "latency_s")
    own = full if spec.compressor == "none" else F.col("t_after")
    return rows.select(F.lit(spec.run_id).alias("run_id"), "round", "client_id", "k", F.col("p_adj" if spec.coef == "adjusted" else "f").alias("weight"), "keep_ratio", own.alias("t_own"), full.alias("t_dense"))


def compressed(delta: DataFrame, spec: RunSpec, layers: np.ndarray) -> DataFrame:
    """What one run's clients send of (run_id, client_id, param_idx, delta, k)."""
    c = spec.compressor
    if c == "none":
        return delta
    if c == "topk":
        if spec.scope == "layer":
            size = np.bincount(layers)
            each = F.array(*(F.lit(int(x)) for x in layers))
            counts = F.array(*(F.lit(max(1, int(spec.base_ratio * n + 1e-9))) for n in size))
            rows = delta.withColumn("__l", each[F.col("param_idx").cast("int")]).withColumn("k", counts[F.col("__l")])
            return compress.topk(rows, KEYS, scope="__l").drop("__l")
        return compress.topk(delta, KEYS).drop("rank") if len(layers) <= SORT_LIMIT else compress.topk_select(delta, KEYS)
    if c == "randomk":
        return compress.randomk(delta, KEYS, seed=spec.seed)
    if c == "threshold":
        return compress.hard_threshold(delta, spec.tau)
    if c == "quantize":
        return compress.quantize(delta, spec.bits, KEYS).withColumn("delta", F.col("restored"))
    if c == "sign":
        return compress.sign_compress(delta, KEYS).withColumn("delta", F.col("restored"))
    raise ValueError(c)


def _union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def _by_run(specs: list[RunSpec], value) -> Column:
    """A setting of each run, as a column."""
    return F.create_map(*chain.from_iterable((F.lit(s.run_id), F.lit(value(s))) for s in specs))[F.col("run_id")]


def _fresh(df: DataFrame, path: str) -> DataFrame:
    """df written anew (a round that broke off may have left parts)."""
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def _stored_samples(samples: DataFrame, spec: RunSpec, out_dir: str, spread: int) -> DataFrame:
    """Samples with their client, in folders of clients; test rows have client -1."""
    samples = samples.select("sample_id", "x", "y", "is_test", *[c for c in samples.columns if c == "client_id"])
    if exists(samples.sparkSession, f"{out_dir}/samples/_SUCCESS"):
        schema = samples.select("sample_id", "x", "y", "is_test").schema.add("client_id", "integer").add("bucket", "integer")
        return samples.sparkSession.read.schema(schema).parquet(f"{out_dir}/samples")
    mode = {"mode": spec.partition, "column": "client_id"} if spec.partition == "column" else {"mode": spec.partition}
    train = assign_clients(samples.where("not is_test"), "y", spec.n_clients, spec.beta, spec.seed, **mode)
    both = _union([train.withColumn("is_test", F.lit(False)), samples.where("is_test").withColumn("client_id", F.lit(-1))]).select("sample_id", "x", "y", "is_test", "client_id")
    both = both.withColumn("bucket", F.pmod("client_id", F.lit(BUCKETS)).cast("int"))
    # rows of a folder come from `spread` tasks: a client may hold a large part of all rows
    return written(both.repartition("bucket", F.pmod(F.xxhash64("sample_id"), F.lit(spread))), f"{out_dir}/samples", "is_test", "bucket")


def _stored_plan(specs: list[RunSpec], train: DataFrame, n_params: int, links: DataFrame | None, trace: DataFrame | None, out_dir: str) -> DataFrame:
    """All rounds' clients of all runs, with the round in which each client took part before and next."""
    spark, plan = train.sparkSession, f"{out_dir}/plan"
    if exists(spark, f"{plan}/_SUCCESS"):
        return spark.read.parquet(plan)
    sizes = _fresh(train.groupBy("client_id").agg(F.count("*").alias("n_samples")), f"{out_dir}/sizes")
    own = Window.partitionBy("run_id", "client_id").orderBy("round")
    rows = _union([plan_rounds(spark, s, sizes, n_params, links, trace) for s in specs])
    return written(rows.withColumns({"before": F.lag("round").over(own), "after": F.lead("round").over(own)}), plan)


def run_cohort(specs: list[RunSpec], samples: DataFrame, n_classes: int, links: DataFrame | None = None, out_dir: str | None = None, partitions: int | None = None, keep_updates: bool = False, spread: int = 1, trace: DataFrame | None = None, timed: bool = False) -> tuple[DataFrame, DataFrame]:
    """Run the specs (of one cohort) over samples (sample_id, x, y, is_test); (log, final weights by run and coordinate).

    keep_updates: leave every round's updates in the folder (else they go once the round is written).
    spread: files of each folder of samples; raise it with the size of the largest client.
    trace: (client_id, day, bandwidth_mbps) for runs whose links follow telemetry, a day a round.
    timed: write what is sent before the server's step, so that the log's seconds are those of the parts; without
    it compression runs in the same job as the step, and its seconds are null.
    """
    spark, first = samples.sparkSession, specs[0]
    if len({s.cohort() for s in specs}) != 1 or len({s.run_id for s in specs}) != len(specs):
        raise ValueError("specs must share a cohort and differ in run_id")
    out_dir = out_dir or new_path(spark, "run")
    assigned = _stored_samples(samples, first, out_dir, spread)
    train, test = assigned.where("not is_test"), assigned.where("is_test")
    n_features = len(assigned.select("x").first().x)
    extra = {"hidden": first.hidden} if first.model == "perceptron" else {}
    model: Model = MODELS[first.model](n_features, n_classes, **extra)
    rounds = _stored_plan(specs, train, model.n_params, links, trace, out_dir)
    account = {(r.run_id, r.round): r for r in rounds.groupBy("run_id", "round").agg(F.max("t_own").alias("t_actual"), F.max("t_dense").alias("t_max"), F.min("t_dense").alias("t_min"), F.sum("weight").alias("coef_sum")).collect()}
    by_round = {r["round"]: r for r in rounds.groupBy("round").agg(F.collect_set(F.pmod("client_id", F.lit(BUCKETS))).alias("folders"), F.collect_set("before").alias("before"), F.max(F.coalesce("after", F.lit(first.rounds))).alias("needed_till")).collect()}
    alike: dict[tuple, list[RunSpec]] = {}
    for s in specs:
        alike.setdefault(_compression(s), []).append(s)
    groups = list(alike.values())
    begin = 0
    while exists(spark, f"{out_dir}/log/round={begin}/_SUCCESS"):
        begin += 1
    weights = spark.read.parquet(f"{out_dir}/weights/round={begin - 1}") if begin else _fresh(start_weights(spark, model, {s.run_id: s.seed for s in specs}), f"{out_dir}/weights/round=-1")
    for t in range(begin, first.rounds):
        picked, took = rounds.where(F.col("round") == t), {"train_s": None, "compress_s": None, "server_s": None}
        now = time.time()
        folders = by_round[t].folders if t in by_round else []
        delta = _fresh(local_update(train.where(F.col("bucket").isin(*folders)), picked, weights, model, first.lr, first.epochs, first.batch_size, first.seed, partitions), f"{out_dir}/delta/round={t}")
        took["train_s"], now = time.time() - now, time.time()
        kept = []
        for n, group in enumerate(groups):  # one pass over the updates for all runs that compress alike
            runs = [s.run_id for s in group]
            own, mine = (df.where(F.col("run_id").isin(runs)) if len(groups) > 1 else df for df in (delta, picked))
            if group[0].error_feedback:
                kept.append(_with_feedback(own, mine, group[0], model, f"{out_dir}/residual/{n}", t, by_round[t].before if t in by_round else []))
            else:
                kept.append(compressed(own.join(mine.select(*KEYS, "k"), list(KEYS)), group[0], model.layers()).select(*KEYS, "param_idx", "delta"))
        sent = _union(kept)
        if timed:
            sent = _fresh(sent, f"{out_dir}/sent/round={t}")
            took["compress_s"], now = time.time() - now, time.time()
        step = server.server_step(sent, picked, "weight", _by_run(specs, lambda s: float(s.gamma)), _by_run(specs, lambda s: s.max_degree), by=("run_id",))
        step = _fresh(step, f"{out_dir}/step/round={t}")
        weights = _fresh(server.apply_step(weights, step, _by_run(specs, lambda s: float(s.step_size)), ("run_id",)), f"{out_dir}/weights/round={t}")
        took["server_s"] = time.time() - now
        count = {r.run_id: r.n for r in step.groupBy("run_id").agg(F.sum("degree").alias("n")).collect()}
        scores = {}
        if (t + 1) % first.eval_every == 0 or t == first.rounds - 1:
            seen = test if first.eval_share >= 1 else test.where(uniform(first.seed, "eval", "sample_id") < first.eval_share)
            for r in evaluate(seen, weights, model, len(specs)).groupBy("run_id").agg((F.sum("correct") / F.sum("n")).alias("accuracy"), (F.sum("loss") / F.sum("n")).alias("loss")).collect():
                scores[r.run_id] = (r.accuracy, r.loss)
        log = []
        for s in specs:
            a = account.get((s.run_id, t))
            log.append((s.run_id, *scores.get(s.run_id, (None, None)), a and a.t_actual, a and a.t_max, a and a.t_min, a and a.coef_sum, int(count.get(s.run_id, 0)), *took.values()))
        columns = [pa.array(c, k) for c, k in zip(zip(*log, strict=True), LOG_KINDS, strict=True)]
        spark.createDataFrame(pa.table(columns, names=LOG_NAMES)).coalesce(1).write.mode("overwrite").parquet(f"{out_dir}/log/round={t}")
        # what no later round reads
        for part in (f"weights/round={t - 2}", f"step/round={t}", *([] if keep_updates else [f"delta/round={t}", f"sent/round={t}"])):
            removed(spark, f"{out_dir}/{part}")
        for p in [p for p, r in by_round.items() if p < t and r.needed_till < t]:
            for n in range(len(groups)):
                removed(spark, f"{out_dir}/residual/{n}/round={p}")
            del by_round[p]
        goals = [(s.target_accuracy, scores.get(s.run_id, (0, 0))[0]) for s in specs]
        if all(goal is not None and reached is not None and reached >= goal for goal, reached in goals):
            break
    return spark.read.schema(LOG).parquet(f"{out_dir}/log").where(F.col("round") < first.rounds), weights


def _compression(s: RunSpec) -> tuple:
    """Runs with equal values are compressed in one pass; how much each client keeps is in its k."""
    return (s.compressor, s.scope, s.error_feedback, s.tau if s.compressor == "threshold" else 0, s.bits if s.compressor == "quantize" else 0, s.base_ratio if s.scope == "layer" else 0)


def _with_feedback(delta: DataFrame, picked: DataFrame, spec: RunSpec, model: Model, where: str, t: int, before: list[int]) -> DataFrame:
    """Send what is kept of update plus residual; what is left becomes the residual of the round's clients.

    A client's residual lies in the table of the round in which it took part before, so that absent clients' residuals
    stay where they are.
    """
    spark, on = delta.sparkSession, [*KEYS, "param_idx"]
    tables = [spark.read.parquet(f"{where}/round={p}").select(*on, "residual", F.lit(p).alias("before")) for p in before]
    old = _union(tables).where("residual <> 0").join(picked.select(*KEYS, "before"), [*KEYS, "before"]).select(*on, "residual") if tables else None
    if spec.compressor == "topk" and spec.scope == "global":
        rows = compress.ef_topk(delta, old, picked.select(*KEYS, "k"), KEYS)
    else:
        total = delta.select(*on, "delta")
        if old is not None:
            total = total.join(old, on, "full").select(*on, (F.coalesce("delta", F.lit(0.0)) + F.coalesce("residual", F.lit(0.0))).alias("delta"))
        total = total.where("delta <> 0")
        kept = compressed(total.join(picked.select(*KEYS, "k"), list(KEYS)), spec, model.layers()).select(*on, F.col("delta").alias("sent"))
        sent = F.coalesce("sent", F.lit(0.0))
        rows = total.join(kept, on, "left").select(*on, sent.alias("sent"), (F.col("delta") - sent).alias("residual"))
    return _fresh(rows, f"{where}/round={t}").where("sent <> 0").select(*on, F.col("sent").alias("delta"))


def run_all(specs: list[RunSpec], samples: DataFrame, n_classes: int, **more) -> DataFrame:
    """Logs of any specs, cohort by cohort."""
    groups: dict[tuple, list[RunSpec]] = {}
    for s in specs:
        groups.setdefault(s.cohort(), []).append(s)
    return _union([run_cohort(g, samples, n_classes, **more)[0] for g in groups.values()])
