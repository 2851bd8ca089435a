"""Cost and accuracy measures as set queries over round logs and simulated uploads.

An upload row is (run_id, round, client_id, t_own, t_dense): what the client's upload took, and what an
uncompressed one would have taken. A log row is (run_id, round, accuracy, t_actual, t_max, t_min).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, WindowSpec, functions as F

from pacedfl.operators.links import V_MBIT, dense_time, sparse_time
from pacedfl.operators.schedule import paced_ratios

METHODS = ("dense", "topk", "ef_topk", "paced", "boosted")
ENTRY_BITS, DENSE_BITS = 64, 32


def _run() -> WindowSpec:
    return Window.partitionBy("run_id").orderBy("round")


def _so_far() -> WindowSpec:
    return _run().rowsBetween(Window.unboundedPreceding, Window.currentRow)


def simulated_uploads(selected: DataFrame, base_ratio: float, n_params: int, v: float = V_MBIT, methods=METHODS, ef_factor: float = 2.0) -> DataFrame:
    """Upload rows of every method for the same clients and links. ef_factor 1 bills error feedback by values alone."""
    rows = paced_ratios(selected, base_ratio, n_params, v).withColumn("t_dense", dense_time(v, "bandwidth_mbps", "latency_s"))
    own = {"dense": F.col("t_dense"), "topk": F.col("t_base"), "ef_topk": sparse_time(v, base_ratio, "bandwidth_mbps", "latency_s", ef_factor), "paced": F.col("t_after"), "boosted": F.col("t_after")}
    full = F.lit(n_params).cast("long")
    base_k = F.greatest(F.lit(1), F.floor(F.lit(base_ratio) * n_params + 1e-9)).cast("long")
    count = {"dense": full, "topk": base_k, "ef_topk": base_k, "paced": F.col("k"), "boosted": F.col("k")}
    each = F.explode(F.array(*(F.struct(F.lit(m).alias("run_id"), own[m].alias("t_own"), count[m].alias("sent")) for m in methods))).alias("u")
    return rows.select("round", "client_id", "t_dense", each).select("u.run_id", "round", "client_id", "u.t_own", "t_dense", "u.sent")


def time_account(uploads: DataFrame) -> DataFrame:
    """Per run and round: time really spent, the uncompressed slowest and fastest client, and running sums."""
    rows = uploads.groupBy("run_id", "round").agg(F.max("t_own").alias("t_actual"), F.max("t_dense").alias("t_max"), F.min("t_dense").alias("t_min"))
    return rows.withColumns({f"cum_{k}": F.sum(f"t_{k}").over(_so_far()) for k in ("actual", "max", "min")})


def time_to_target(log: DataFrame, target: float) -> DataFrame:
    """(run_id, round_hit, time_actual, time_max, time_min) up to the first round at the target; nulls if never."""
    rows = log.withColumns({f"cum_{k}": F.sum(f"t_{k}").over(_so_far()) for k in ("actual", "max", "min")})
    hit = F.when(F.col("accuracy") >= target, F.col("round"))
    return rows.groupBy("run_id").agg(F.min(hit).alias("round_hit"), *(F.min_by(f"cum_{k}", hit).alias(f"time_{k}") for k in ("actual", "max", "min")))


def speedup(reached: DataFrame, reference: str) -> DataFrame:
    """Time of the reference over each run's time; null where either never got there."""
    ref = reached.where(F.col("run_id") == reference).select(F.col("run_id").alias("reference"), F.col("time_actual").alias("__ref"))
    return reached.crossJoin(F.broadcast(ref)).select("run_id", "reference", (F.col("__ref") / F.col("time_actual")).alias("ratio"))


def final_accuracy(log: DataFrame) -> DataFrame:
    return log.groupBy("run_id").agg(F.max_by("accuracy", "round").alias("accuracy"))


def gain(log: DataFrame, reference: str) -> DataFrame:
    """Final accuracy against a reference run: difference and ratio less one."""
    last = final_accuracy(log)
    ref = last.where(F.col("run_id") == reference).select(F.col("run_id").alias("reference"), F.col("accuracy").alias("__ref"))
    return last.crossJoin(F.broadcast(ref)).select("run_id", "reference", "accuracy", (F.col("accuracy") - F.col("__ref")).alias("gain_abs"), (F.col("accuracy") / F.col("__ref") - 1).alias("gain_rel"))


def accuracy_interval(log: DataFrame, n_test: int, z: float = 1.96) -> DataFrame:
    """Accuracy with its binomial interval when it was measured on n_test rows."""
    half = z * F.sqrt(F.col("accuracy") * (1 - F.col("accuracy")) / n_test)
    return log.select("run_id", "round", "accuracy", F.greatest(F.lit(0.0), F.col("accuracy") - half).alias("low"), F.least(F.lit(1.0), F.col("accuracy") + half).alias("high"))


def curve(log: DataFrame, width: int = 5) -> DataFrame:
    """Accuracy per round with its change and moving average."""
    near = _run().rowsBetween(1 - width, 0)
    return log.select("run_id", "round", "accuracy", (F.col("accuracy") - F.lag("accuracy").over(_run())).alias("change"), F.avg("accuracy").over(near).alias("smooth"))


def accuracy_at(log: DataFrame, grid: DataFrame) -> DataFrame:
    """(run_id, t_grid, accuracy): as-of join, the last round finished at or before each time of the grid."""
    ends = log.select("run_id", F.sum("t_actual").over(_so_far()).alias("t"), "accuracy", F.lit(0).alias("ask"))
    asked = log.select("run_id").distinct().crossJoin(F.broadcast(grid.select("t_grid"))).select("run_id", F.col("t_grid").cast("double").alias("t"), F.lit(None).cast("double").alias("accuracy"), F.lit(1).alias("ask"))
    seen = Window.partitionBy("run_id").orderBy("t", "ask").rowsBetween(Window.unboundedPreceding, 0)
    rows = ends.unionByName(asked).withColumn("accuracy", F.last("accuracy", ignorenulls=True).over(seen))
    return rows.where("ask = 1").select("run_id", F.col("t").alias("t_grid"), "accuracy")


def idle_time(uploads: DataFrame) -> DataFrame:
    """Seconds that a round's clients wait for its slowest upload, summed."""
    return uploads.groupBy("run_id", "round").agg((F.max("t_own") * F.count("*") - F.sum("t_own")).alias("idle_s"))


def traffic(uploads: DataFrame, n_params: int) -> DataFrame:
    """Megabits sent (value and index, or values alone when dense) against uncompressed uploads."""
    bits = F.when(F.col("sent") >= n_params, F.col("sent") * DENSE_BITS).otherwise(F.col("sent") * ENTRY_BITS)
    return uploads.groupBy("run_id", "round").agg((F.sum(bits) / 1e6).alias("mbit_sent"), (F.count("*") * float(n_params) * DENSE_BITS / 1e6).alias("mbit_dense"))


def client_drift(deltas: DataFrame) -> DataFrame:
    """(client_id, drift): distance of each client's update from the mean update."""
    n = deltas.select("client_id").distinct().agg(F.count("*").alias("__n"))
    mean = deltas.groupBy("param_idx").agg(F.sum("delta").alias("__s")).crossJoin(F.broadcast(n)).select("param_idx", (F.col("__s") / F.col("__n")).alias("__m"))
    total = mean.agg(F.sum(F.col("__m") * F.col("__m")).alias("__mm"))
    each = deltas.join(mean, "param_idx").groupBy("client_id").agg(F.sum(F.col("delta") * F.col("delta") - 2 * F.col("delta") * F.col("__m")).alias("__d"))
    return each.crossJoin(F.broadcast(total)).select("client_id", F.sqrt(F.greatest(F.col("__d") + F.col("__mm"), F.lit(0.0))).alias("drift"))


def time_rollup(times: DataFrame) -> DataFrame:
    """Sums and maxima of t by region, nation and client with subtotals; gid tells them apart."""
    return times.rollup("region", "nation", "client_id").agg(F.grouping_id().cast("int").alias("gid"), F.sum("t").alias("sum_t"), F.max("t").alias("max_t"))


def report(finals: DataFrame) -> DataFrame:
    """Accuracy grid (workload, beta, base_ratio by method): a pivot of mean accuracies."""
    return finals.groupBy("workload", "beta", "base_ratio").pivot("method", [*METHODS]).agg(F.round(F.avg("accuracy"), 4))


def summary_sets(finals: DataFrame) -> DataFrame:
    """Mean accuracy by method and beta, by method and ratio, by method, and over all."""
    finals.createOrReplaceTempView("pacedfl_finals")
    return finals.sparkSession.sql("SELECT method, beta, base_ratio, CAST(grouping_id() AS INT) AS gid, avg(accuracy) AS accuracy, count(*) AS n FROM pacedfl_finals GROUP BY GROUPING SETS ((method, beta), (method, base_ratio), (method), ())")


def breakdown(log: DataFrame) -> DataFrame:
    """Mean seconds of a round by part, from the timers of a timed run and the simulated uploads; round_s is the parts
    that were computed and the upload together."""
    parts = ("train_s", "compress_s", "server_s", "t_actual")
    rows = log.groupBy("run_id").agg(*(F.avg(c).alias(c) for c in (*parts, "t_max")))
    return rows.withColumn("round_s", sum((F.col(c) for c in parts[1:]), F.col(parts[0])))


def confusion(predicted: DataFrame) -> DataFrame:
    return predicted.groupBy("y", "pred").agg(F.count("*").alias("n"))


def balanced_accuracy(predicted: DataFrame) -> Column | DataFrame:
    """Mean of the classes' own accuracies."""
    each = predicted.groupBy("y").agg(F.avg((F.col("y") == F.col("pred")).cast("double")).alias("a"))
    return each.agg(F.avg("a").alias("balanced_accuracy"))
