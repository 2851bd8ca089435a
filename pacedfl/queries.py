"""Registered queries of the library and, for those that SQL can express, the same in DuckDB's SQL.

Parameters of all of them: ten clients, half of them selected, ten rounds, seed 42, links from supplier,
payload 357 Mbit, base ratio 0.1, alpha 0.3, gamma 5, rarity limit 1. Doubles are rounded to six places.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from pacedfl.functions import udfs
from pacedfl.functions.portable import r6
from pacedfl.operators import compress, learner, links, overlap, partition, schedule, server
from pacedfl.operators.coeffs import coef_stats, with_adjusted, with_share
from pacedfl.plans import experiments, metrics
from pacedfl.plans.rounds import run_cohort
from pacedfl.plans.spec import METHODS, method
from pacedfl.sources import features, updates
from pacedfl.sources.tables import new_path, table
from pacedfl.streaming import residual_state, telemetry

N, FRACTION, ROUNDS, SEED, V, RATIO, ALPHA, GAMMA = 10, 0.5, 10, 42, 357.0, 0.1, 0.3, 5.0
TAU, BITS = 5.0, 8
ACCURACY_TAU = {"dense": 4.0, "topk": 9.0, "ef_topk": 8.0, "paced": 6.0, "boosted": 5.0, "slow": 40.0}

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def put(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLE[name or f.__name__] = BASE + sql
        return f

    return put


def u_sql(tag: str, *keys: str) -> str:
    return f"(('0x' || substr(md5(concat_ws(':', '{SEED}:{tag}', {', '.join(keys)})), 1, 8))::UBIGINT / 4294967296.0::DOUBLE)"


def k_sql(ratio: str) -> str:
    return f"greatest(1, floor({ratio} * n + 1e-9))::BIGINT"


VALUE = "l_quantity::DECIMAL(12,2) * (l_discount::DECIMAL(12,2) - 0.05::DECIMAL(12,2))"
RANK = "row_number() OVER (PARTITION BY client_id ORDER BY abs(delta) DESC, param_idx)"
BASE = f"""
WITH RECURSIVE p AS (SELECT count(*) AS n FROM part)
, ends AS (SELECT min(s_acctbal) AS lo, max(s_acctbal) AS hi FROM supplier)
, links_all AS (SELECT s_suppkey::INT AS client_id, round(0.4 + 1.2 * (s_acctbal - lo) / (hi - lo), 6) AS bandwidth_mbps, round((0.05 + 0.15 * (s_suppkey % 100 + 1) / 100)::DOUBLE, 6) AS latency_s, s_nationkey FROM supplier, ends)
, links AS (SELECT client_id, bandwidth_mbps, latency_s FROM links_all WHERE client_id < {N})
, nsamp AS (SELECT (l_suppkey % {N})::INT AS client_id, count(*) AS n_samples FROM lineitem GROUP BY 1)
, clients AS (SELECT l.*, n_samples FROM links l LEFT JOIN nsamp USING (client_id))
, sel AS (SELECT * EXCLUDE (rn) FROM (SELECT r.round::INT AS round, c.*, row_number() OVER (PARTITION BY r.round ORDER BY {u_sql("select", "r.round", "c.client_id")}, c.client_id) AS rn FROM clients c, range({ROUNDS}) r(round)) WHERE rn <= {schedule.n_selected(N, FRACTION)})
, based AS (SELECT *, latency_s + {2 * V} * {RATIO} / bandwidth_mbps AS t_base, latency_s + {V} / bandwidth_mbps AS t_dense FROM sel)
, benched AS (SELECT *, max(t_base) OVER (PARTITION BY round) AS t_bench FROM based)
, raws AS (SELECT *, (t_bench - latency_s) * bandwidth_mbps / {2 * V} AS keep_ratio_raw FROM benched)
, paced AS (SELECT r.*, least(1.0::DOUBLE, keep_ratio_raw) AS keep_ratio, {k_sql("least(1.0::DOUBLE, keep_ratio_raw)")} AS k, latency_s + {2 * V} * least(1.0::DOUBLE, keep_ratio_raw) / bandwidth_mbps AS t_after FROM raws r, p)
, coef AS (SELECT *, n_samples / sum(n_samples) OVER (PARTITION BY round) AS f, keep_ratio / sum(keep_ratio) OVER (PARTITION BY round) AS norm_sum, keep_ratio / max(keep_ratio) OVER (PARTITION BY round) AS norm_max,
  coalesce((keep_ratio - min(keep_ratio) OVER (PARTITION BY round)) / nullif(max(keep_ratio) OVER (PARTITION BY round) - min(keep_ratio) OVER (PARTITION BY round), 0), 0) AS norm_minmax FROM paced)
, u1 AS (SELECT (l_suppkey % {N})::INT AS client_id, l_partkey AS param_idx, sum({VALUE})::DECIMAL(18,4)::DOUBLE AS delta FROM lineitem GROUP BY 1, 2)
, u1t AS (SELECT (l_shipdate >= TIMESTAMP '{updates.SPLIT_DATE}')::INT AS round, (l_suppkey % {N})::INT AS client_id, l_partkey AS param_idx, sum({VALUE})::DECIMAL(18,4)::DOUBLE AS delta FROM lineitem GROUP BY 1, 2, 3)
, ranked AS (SELECT *, {RANK} AS rank FROM u1 WHERE delta <> 0)
, sel0 AS (SELECT *, f / greatest(f, norm_sum) * {ALPHA} AS p_adj FROM coef WHERE round = 0)
, kept_topk AS (SELECT r.* FROM ranked r JOIN sel0 USING (client_id), p WHERE rank <= {k_sql(str(RATIO))})
, kept_paced AS (SELECT r.* FROM ranked r JOIN sel0 s USING (client_id) WHERE rank <= s.k)
, ef0 AS (SELECT client_id, param_idx, delta, {RANK} AS rank FROM u1t WHERE round = 0 AND delta <> 0)
, ef0s AS (SELECT client_id, param_idx, CASE WHEN rank <= {k_sql(str(RATIO))} THEN delta ELSE 0 END AS sent, CASE WHEN rank <= {k_sql(str(RATIO))} THEN 0 ELSE delta END AS residual FROM ef0, p)
, ef1 AS (SELECT client_id, param_idx, coalesce(u.delta, 0) + coalesce(o.residual, 0) AS delta FROM (SELECT * FROM u1t WHERE round = 1) u FULL JOIN (SELECT * FROM ef0s WHERE residual <> 0) o USING (client_id, param_idx))
, ef1r AS (SELECT *, {RANK} AS rank FROM ef1 WHERE delta <> 0)
, ef1s AS (SELECT client_id, param_idx, CASE WHEN rank <= {k_sql(str(RATIO))} THEN delta ELSE 0 END AS sent, CASE WHEN rank <= {k_sql(str(RATIO))} THEN 0 ELSE delta END AS residual FROM ef1r, p)
, uploads AS (SELECT * FROM (SELECT 'dense' AS run_id, round, client_id, t_dense AS t_own, t_dense, n AS sent FROM paced, p UNION ALL SELECT 'topk', round, client_id, t_base, t_dense, {k_sql(str(RATIO))} FROM paced, p UNION ALL SELECT 'ef_topk', round, client_id, t_base, t_dense, {k_sql(str(RATIO))} FROM paced, p UNION ALL SELECT 'paced', round, client_id, t_after, t_dense, k FROM paced UNION ALL SELECT 'boosted', round, client_id, t_after, t_dense, k FROM paced))
, account AS (SELECT run_id, round, max(t_own) AS t_actual, max(t_dense) AS t_max, min(t_dense) AS t_min FROM uploads GROUP BY 1, 2)
, taus(run_id, tau) AS (VALUES {", ".join(f"('{k}', {v}::DOUBLE)" for k, v in ACCURACY_TAU.items())})
, log AS (SELECT t.run_id, a.round, round(1 - exp(-(a.round + 1) / tau), 6) AS accuracy, t_actual, t_max, t_min FROM taus t JOIN account a ON a.run_id = CASE WHEN t.run_id = 'slow' THEN 'topk' ELSE t.run_id END)
, cumlog AS (SELECT *, sum(t_actual) OVER w AS cum_actual, sum(t_max) OVER w AS cum_max, sum(t_min) OVER w AS cum_min FROM log WINDOW w AS (PARTITION BY run_id ORDER BY round ROWS UNBOUNDED PRECEDING))
, hits AS (SELECT run_id, min(round) FILTER (WHERE accuracy >= 0.6) AS round_hit FROM cumlog GROUP BY 1)
, reached AS (SELECT h.run_id, h.round_hit, c.cum_actual AS time_actual, c.cum_max AS time_max, c.cum_min AS time_min FROM hits h LEFT JOIN cumlog c ON c.run_id = h.run_id AND c.round = h.round_hit)
, tel AS (SELECT (user_id % {N})::INT AS client_id, ts, value FROM events WHERE ts IS NOT NULL AND value IS NOT NULL AND user_id IS NOT NULL)
"""


def clients(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Registry: links and sample counts of the ten clients."""
    n = table(spark, sf_dir, "lineitem").groupBy((F.col("l_suppkey") % N).cast("int").alias("client_id")).agg(F.count("*").alias("n_samples"))
    return links.supplier_links(spark, sf_dir, N).drop("s_nationkey").join(n, "client_id", "left")


def selected(spark: SparkSession, sf_dir: str, rounds: int = ROUNDS) -> DataFrame:
    return schedule.select_clients(clients(spark, sf_dir), rounds, N, FRACTION, SEED)


def paced(spark: SparkSession, sf_dir: str, **more) -> DataFrame:
    return schedule.paced_ratios(selected(spark, sf_dir), RATIO, updates.n_params(spark, sf_dir), V, **more)


def coefs(spark: SparkSession, sf_dir: str, norm: str = "sum", weighting: str = "samples", renormalize: bool = False) -> DataFrame:
    return with_adjusted(with_share(paced(spark, sf_dir), weighting), ALPHA, norm, renormalize)


def first_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The selected clients of round 0 with k, f and p_adj."""
    return coefs(spark, sf_dir).where("round = 0")


def base_k(spark: SparkSession, sf_dir: str, ratio: float = RATIO):
    return schedule.kept_count(F.lit(ratio), updates.n_params(spark, sf_dir))


def base_bound(spark: SparkSession, sf_dir: str, ratio: float = RATIO) -> int:
    """A literal that no k of this ratio of the parts, or of some of them, exceeds."""
    return int(ratio * updates.n_params(spark, sf_dir)) + 1


def counted(spark: SparkSession, sf_dir: str, how: str = "topk", ratio: float = RATIO) -> tuple[DataFrame, int]:
    """(k of round 0's clients under the uniform or paced schedule, a bound of it)."""
    if how == "topk":
        return first_round(spark, sf_dir).select("client_id", base_k(spark, sf_dir, ratio).alias("k")), base_bound(spark, sf_dir, ratio)
    rows = schedule.paced_ratios(selected(spark, sf_dir), ratio, updates.n_params(spark, sf_dir), V).where("round = 0")
    return rows.select("client_id", "k"), base_bound(spark, sf_dir, 1.0)


def kept(spark: SparkSession, sf_dir: str, how: str = "topk", ratio: float = RATIO) -> DataFrame:
    """Updates of round 0's clients after uniform or paced top-k."""
    k, bound = counted(spark, sf_dir, how, ratio)
    return compress.topk_bounded(updates.update_lineitem(spark, sf_dir, N).join(F.broadcast(k), "client_id"), bound)


def ranked_for(spark: SparkSession, sf_dir: str, cases: list[tuple[str, float]]) -> DataFrame:
    """Updates of round 0's clients ranked once, with k0, k1, ...: how many each (schedule, ratio) keeps."""
    ks, bounds = zip(*(counted(spark, sf_dir, *c) for c in cases), strict=True)
    side = ks[0].withColumnRenamed("k", "k0")
    for i, k in enumerate(ks[1:], 1):
        side = side.join(k.withColumnRenamed("k", f"k{i}"), "client_id")
    side = side.withColumn("k", F.array_max(F.array(*(f"k{i}" for i in range(len(cases))))))
    return compress.topk(updates.update_lineitem(spark, sf_dir, N).join(F.broadcast(side), "client_id"), k_max=max(bounds))


# --- links and times ---------------------------------------------------------------------------------------


@query(f"SELECT l.client_id, bandwidth_mbps, latency_s, n_name AS nation, r_name AS region FROM links_all l JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey WHERE l.client_id < {N}")
def link_profile_supplier(spark, sf_dir):
    """Supplier links with nation and region."""
    rows = links.supplier_links(spark, sf_dir, N)
    n, r = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    return rows.join(n, rows.s_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey).select("client_id", "bandwidth_mbps", "latency_s", F.col("n_name").alias("nation"), F.col("r_name").alias("region"))


def _gauss_sql(*keys: str) -> str:
    u, v = u_sql("bw.a", *keys), u_sql("bw.b", *keys)
    return f"round(greatest({links.FLOOR_MBPS}, 1 + 0.2 * sqrt(-2.0 * ln(({u} * 4294967296.0 + 1.0) / 4294967297.0)) * cos(2.0 * pi() * {v})), 6)"


def _customers(spark, sf_dir):
    """Every customer as a client."""
    return table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("client_id"))


@query(f"SELECT c_custkey AS client_id, {_gauss_sql('c_custkey')} AS bandwidth_mbps, round(0.2 - 0.15 * {u_sql('lat', 'c_custkey')}, 6) AS latency_s FROM customer")
def link_profile_gaussian(spark, sf_dir):
    """A drawn link for every customer."""
    return links.drawn_links(_customers(spark, sf_dir), SEED).select("client_id", r6("bandwidth_mbps").alias("bandwidth_mbps"), r6("latency_s").alias("latency_s"))


@query(f"SELECT r.round::INT AS round, c_custkey AS client_id, {_gauss_sql('r.round', 'c_custkey')} AS bandwidth_mbps, round(0.2 - 0.15 * {u_sql('lat', 'r.round', 'c_custkey')}, 6) AS latency_s FROM customer, range({ROUNDS}) r(round)")
def link_profile_per_round(spark, sf_dir):
    """A link for every customer, drawn anew in each round."""
    rows = links.round_links(_customers(spark, sf_dir), ROUNDS, SEED)
    return rows.select("round", "client_id", r6("bandwidth_mbps").alias("bandwidth_mbps"), r6("latency_s").alias("latency_s"))


@query(f"SELECT client_id, date_trunc('day', ts)::VARCHAR AS day, round(greatest({links.FLOOR_MBPS}, avg(value) / 50), 6) AS bandwidth_mbps, count(*) AS n FROM tel GROUP BY client_id, date_trunc('day', ts)")
def link_profile_trace(spark, sf_dir):
    return links.traced_links(spark, sf_dir, N).select("client_id", F.date_format("day", "yyyy-MM-dd HH:mm:ss").alias("day"), r6("bandwidth_mbps").alias("bandwidth_mbps"), "n")


@query(f"""SELECT a.client_id, a.at::VARCHAR AS at, (SELECT round(arg_max(greatest({links.FLOOR_MBPS}, x.bw), x.day), 6) FROM (SELECT client_id, date_trunc('day', ts) AS day, avg(value) / 50 AS bw FROM tel GROUP BY ALL) x WHERE x.client_id = a.client_id AND x.day <= a.at) AS bandwidth_mbps
FROM (SELECT c.client_id, TIMESTAMP '2024-01-03 12:00:00' + to_days((2 * r.round)::INT) AS at FROM links c, range({ROUNDS}) r(round)) a""")
def link_asof(spark, sf_dir):
    """The link each client has when a round starts, from the telemetry."""
    at = F.lit("2024-01-03 12:00:00").cast("timestamp_ntz") + F.make_dt_interval(F.col("id").cast("int") * 2)
    asked = links.supplier_links(spark, sf_dir, N).select("client_id").crossJoin(F.broadcast(spark.range(ROUNDS).select(at.alias("at"))))
    return links.newest_link(asked, links.traced_links(spark, sf_dir, N)).select("client_id", F.date_format("at", "yyyy-MM-dd HH:mm:ss").alias("at"), r6("bandwidth_mbps").alias("bandwidth_mbps"))


@query(f"SELECT client_id, round(latency_s + {V} / bandwidth_mbps, 6) AS t FROM links")
def dense_times(spark, sf_dir):
    return links.supplier_links(spark, sf_dir, N).select("client_id", r6(links.dense_time(V, "bandwidth_mbps", "latency_s")).alias("t"))


@query(f"SELECT client_id, round(latency_s + {2 * V} * {RATIO} / bandwidth_mbps, 6) AS t FROM links")
def sparse_times(spark, sf_dir):
    return links.supplier_links(spark, sf_dir, N).select("client_id", r6(links.sparse_time(V, RATIO, "bandwidth_mbps", "latency_s")).alias("t"))


@query(f"SELECT client_id, round(latency_s + {V} / bandwidth_mbps, 6) AS t_dense, round(latency_s + {2 * V} * {RATIO} / bandwidth_mbps, 6) AS t_sparse, round(least(1, (80.0 - latency_s) * bandwidth_mbps / {2 * V}), 6) AS ratio FROM links")
def sql_functions(spark, sf_dir):
    """The registered SQL functions in one SELECT."""
    from pacedfl.functions.sqlfuncs import register

    register(spark)
    links.supplier_links(spark, sf_dir, N).createOrReplaceTempView("pacedfl_links")
    return spark.sql(f"SELECT client_id, round(dense_time({V}D, bandwidth_mbps, latency_s), 6) AS t_dense, round(sparse_time({V}D, {RATIO}D, bandwidth_mbps, latency_s), 6) AS t_sparse, round(paced_ratio(80D, {V}D, bandwidth_mbps, latency_s), 6) AS ratio FROM pacedfl_links")


# --- schedule and coefficients ------------------------------------------------------------------------------


@query("SELECT round, client_id FROM sel")
def select_clients_rounds(spark, sf_dir):
    return selected(spark, sf_dir).select("round", "client_id")


@query(f"SELECT r.round::INT AS round, client_id FROM clients, range({ROUNDS}) r(round) WHERE {u_sql('select', 'r.round', 'client_id')} < {FRACTION}")
def select_threshold(spark, sf_dir):
    """Clients drawn one by one with their hash; for registries too large to rank."""
    return schedule.select_by_threshold(clients(spark, sf_dir), ROUNDS, FRACTION, SEED).select("round", "client_id")


@query("SELECT round, round(max(t_base), 6) AS t_bench, arg_max(client_id, {'t': t_base, 'c': -client_id}) AS pace_client FROM based GROUP BY round")
def pace_time(spark, sf_dir):
    return schedule.pace_time(selected(spark, sf_dir), RATIO, V).select("round", r6("t_bench").alias("t_bench"), "pace_client")


@query("SELECT round, round(min(t_base), 6) AS t_bench, arg_min(client_id, {'t': t_base, 'c': client_id}) AS pace_client FROM based GROUP BY round")
def pace_time_argmin(spark, sf_dir):
    """Diagnostic reading of the pace."""
    return schedule.pace_time_argmin(selected(spark, sf_dir), RATIO, V).select("round", r6("t_bench").alias("t_bench"), "pace_client")


def _ratio_columns(df: DataFrame) -> DataFrame:
    return df.select("round", "client_id", *(r6(c).alias(c) for c in ("keep_ratio_raw", "keep_ratio")), "k", r6("t_after").alias("t_after"))


@query("SELECT round, client_id, round(keep_ratio_raw, 6) AS keep_ratio_raw, round(keep_ratio, 6) AS keep_ratio, k, round(t_after, 6) AS t_after FROM paced")
def paced_ratios(spark, sf_dir):
    return _ratio_columns(paced(spark, sf_dir))


@query("SELECT round, client_id, round(keep_ratio_raw, 6) AS keep_ratio_raw, round(keep_ratio_raw, 6) AS keep_ratio, k, round(t_bench, 6) AS t_after FROM paced")
def paced_ratios_unclamped(spark, sf_dir):
    return _ratio_columns(paced(spark, sf_dir, clamp=False))


@query(f"SELECT round, client_id, round(keep_ratio_raw, 6) AS keep_ratio_raw, round(keep_ratio, 6) AS keep_ratio, k, round(latency_s + {V} * least(2 * keep_ratio, 1) / bandwidth_mbps, 6) AS t_after FROM paced")
def paced_dense_fallback(spark, sf_dir):
    return _ratio_columns(paced(spark, sf_dir, dense_fallback=True))


@query("SELECT round, round(max(t_bench), 6) AS t_bench, 0.0::DOUBLE AS spread FROM benched GROUP BY round")
def paced_times_equal(spark, sf_dir):
    """All unclamped uploads of a round end together."""
    return paced(spark, sf_dir, clamp=False).groupBy("round").agg(r6(F.max("t_bench")).alias("t_bench"), r6(F.max("t_after") - F.min("t_after")).alias("spread"))


@query("SELECT round, client_id, round(f, 6) AS f FROM coef")
def data_share(spark, sf_dir):
    return with_share(selected(spark, sf_dir)).select("round", "client_id", r6("f").alias("f"))


@query("SELECT round, client_id, round(1.0 / count(*) OVER (PARTITION BY round), 6)::DOUBLE AS f FROM sel")
def uniform_coef(spark, sf_dir):
    return with_share(selected(spark, sf_dir), "uniform").select("round", "client_id", r6("f").alias("f"))


def _adjusted(norm: str):
    column = {"sum": "norm_sum", "max": "norm_max", "minmax": "norm_minmax", "none": "keep_ratio"}[norm]

    @query(f"SELECT round, client_id, round(f, 6) AS f, round({column}, 6) AS norm_ratio, round(f / greatest(f, {column}) * {ALPHA}, 6) AS p_adj FROM coef", name=f"adjusted_coef_{norm}")
    def run(spark, sf_dir):
        return coefs(spark, sf_dir, norm).select("round", "client_id", *(r6(c).alias(c) for c in ("f", "norm_ratio", "p_adj")))

    return run


for _n in ("sum", "max", "minmax", "none"):
    _adjusted(_n)


@query(f"SELECT round, client_id, round(f / greatest(f, norm_sum) * {ALPHA} / sum(f / greatest(f, norm_sum)) OVER (PARTITION BY round), 6) AS p_adj FROM coef")
def adjusted_coef_renormalized(spark, sf_dir):
    return coefs(spark, sf_dir, renormalize=True).select("round", "client_id", r6("p_adj").alias("p_adj"))


@query(f"SELECT round, round(sum(p), 6) AS coef_sum, round(max(p), 6) AS coef_max, round(max(p) / avg(p), 6) AS coef_skew FROM (SELECT round, f / greatest(f, norm_sum) * {ALPHA} AS p FROM coef) GROUP BY round")
def coefficient_stats(spark, sf_dir):
    return coef_stats(coefs(spark, sf_dir)).select("round", *(r6(c).alias(c) for c in ("coef_sum", "coef_max", "coef_skew")))


# --- partitioning -----------------------------------------------------------------------------------------

SHARES = partition.dirichlet_shares(list(range(10)), N, 0.5, SEED)
SHARES_SEVERE = partition.dirichlet_shares(list(range(10)), N, 0.1, SEED)
LANG_SHARES = partition.dirichlet_shares(["de", "en", "es", "fr"], N, 0.1, SEED)


def _cum_sql(shares: dict) -> str:
    return "(VALUES " + ", ".join(f"({c!r}, {[float(x) for x in e]}::DOUBLE[])" for c, e in partition.cumulative(shares).items()) + ") c(class_id, cum)"


def _at_sql(position: str) -> str:
    return f"least(len(list_filter(cum, lambda b: b <= {position})), len(cum) - 1)::INT"


def _embeddings(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("sample_id"), "label")


def _quota_sql(shares: dict) -> str:
    return f"SELECT sample_id, label, {_at_sql('pos')} AS client_id FROM (SELECT vec_id AS sample_id, label, (row_number() OVER (PARTITION BY label ORDER BY {u_sql('assign', 'vec_id')}, vec_id) - 0.5) / count(*) OVER (PARTITION BY label) AS pos FROM embeddings) e JOIN {_cum_sql(shares)} ON class_id = label"


@query(_quota_sql(SHARES))
def assign_quota(spark, sf_dir):
    return partition.assign_clients(_embeddings(spark, sf_dir), "label", N, seed=SEED, shares=SHARES)


@query(_quota_sql(SHARES_SEVERE))
def assign_quota_severe(spark, sf_dir):
    return partition.assign_clients(_embeddings(spark, sf_dir), "label", N, seed=SEED, shares=SHARES_SEVERE)


@query(f"SELECT doc_id AS sample_id, lang AS label, {_at_sql(u_sql('assign', 'doc_id'))} AS client_id FROM documents JOIN {_cum_sql(LANG_SHARES)} ON class_id = lang")
def assign_hashed(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").where("lang is not null").select(F.col("doc_id").alias("sample_id"), F.col("lang").alias("label"))
    return partition.assign_clients(docs, "label", N, seed=SEED, mode="hashed", shares=LANG_SHARES)


@query(f"SELECT vec_id AS sample_id, label, floor({u_sql('iid', 'vec_id')} * {N})::INT AS client_id FROM embeddings")
def assign_iid(spark, sf_dir):
    return partition.assign_clients(_embeddings(spark, sf_dir), "label", N, seed=SEED, mode="iid")


@query("SELECT regexp_extract(source, '([0-9]+)$', 1)::INT AS client_id, lang, count(*) AS n FROM documents GROUP BY 1, 2")
def assign_natural(spark, sf_dir):
    """Sources as clients: counts of each language."""
    docs = table(spark, sf_dir, "documents").withColumn("client", F.regexp_extract("source", r"(\d+)$", 1))
    return partition.label_matrix(partition.assign_clients(docs, mode="column", column="client"), "lang")


@query(f"SELECT client_id, label, count(*) AS n FROM ({_quota_sql(SHARES)}) GROUP BY 1, 2")
def label_matrix(spark, sf_dir):
    return partition.label_matrix(assign_quota(spark, sf_dir))


@query(f"SELECT client_id, label, grouping(client_id, label)::INT AS gid, count(*) AS n FROM ({_quota_sql(SHARES)}) GROUP BY CUBE (client_id, label)")
def label_matrix_cube(spark, sf_dir):
    return partition.label_cube(assign_quota(spark, sf_dir))


@query(f"SELECT client_id, sum(n)::BIGINT AS n, round(max(n) / sum(n), 6) AS max_share FROM (SELECT client_id, label, count(*) AS n FROM ({_quota_sql(SHARES_SEVERE)}) GROUP BY 1, 2) GROUP BY 1")
def label_skew(spark, sf_dir):
    return partition.skew_of(assign_quota_severe(spark, sf_dir)).select("client_id", "n", r6("max_share").alias("max_share"))


# --- updates ----------------------------------------------------------------------------------------------


@query("SELECT client_id, param_idx, delta FROM u1")
def update_lineitem(spark, sf_dir):
    return updates.update_lineitem(spark, sf_dir, N)


@query("SELECT round, client_id, param_idx, delta FROM u1t")
def update_lineitem_rounds(spark, sf_dir):
    return updates.update_lineitem_rounds(spark, sf_dir, N)


@query("SELECT client_id, token, count(*)::DOUBLE AS delta FROM (SELECT regexp_extract(source, '([0-9]+)$', 1)::INT AS client_id, unnest(string_split_regex(lower(text), '[^a-zäöüßàâçéèêëîïôûùñáíóú]+')) AS token FROM documents WHERE source IS NOT NULL AND text IS NOT NULL) WHERE token <> '' GROUP BY 1, 2")
def update_tokens(spark, sf_dir):
    return updates.update_tokens(spark, sf_dir)


@query(f"SELECT client_id, param_idx, round(avg(v), 6) AS delta FROM (SELECT (vec_id % {N})::INT AS client_id, unnest(embedding)::DOUBLE AS v, unnest(range(len(embedding)))::BIGINT AS param_idx FROM embeddings) GROUP BY 1, 2")
def update_embeddings(spark, sf_dir):
    return updates.update_embeddings(spark, sf_dir, N).withColumn("delta", r6("delta"))


# --- compressors ------------------------------------------------------------------------------------------


def _with_k(spark, sf_dir):
    return updates.update_lineitem(spark, sf_dir, N).withColumn("k", base_k(spark, sf_dir))


TOPK_SQL = f"SELECT client_id, param_idx, delta FROM ranked, p WHERE rank <= {k_sql(str(RATIO))}"


@query(TOPK_SQL.replace("delta FROM", "delta, rank::INT AS rank FROM"))
def topk_global(spark, sf_dir):
    return compress.topk(_with_k(spark, sf_dir), k_max=base_bound(spark, sf_dir)).select("client_id", "param_idx", "delta", "rank")


@query(f"""SELECT client_id, param_idx, layer, delta, rank::INT AS rank FROM (SELECT u.*, p_brand AS layer, row_number() OVER (PARTITION BY client_id, p_brand ORDER BY abs(delta) DESC, param_idx) AS rank FROM u1 u JOIN part ON p_partkey = param_idx WHERE delta <> 0) r
JOIN (SELECT p_brand, count(*) AS n FROM part GROUP BY 1) z ON z.p_brand = layer WHERE rank <= {k_sql(str(RATIO))}""")
def topk_layer(spark, sf_dir):
    layers = updates.layers(spark, sf_dir)
    size = layers.groupBy("layer").agg(F.count("*").alias("n"))
    rows = updates.update_lineitem(spark, sf_dir, N).join(layers, "param_idx").join(F.broadcast(size), "layer").withColumn("k", schedule.kept_count(F.lit(RATIO), F.col("n")))
    return compress.topk(rows, scope="layer", k_max=base_bound(spark, sf_dir)).select("client_id", "param_idx", "layer", "delta", "rank")


@query("SELECT client_id, param_idx, delta, rank::INT AS rank FROM kept_paced")
def topk_paced(spark, sf_dir):
    return ranked_for(spark, sf_dir, [("paced", RATIO)]).select("client_id", "param_idx", "delta", "rank")


@query(TOPK_SQL)
def topk_select(spark, sf_dir):
    """Exact top-k by magnitude buckets."""
    return compress.topk_select(_with_k(spark, sf_dir)).select("client_id", "param_idx", "delta")


@query()
def topk_approx(spark, sf_dir):
    return compress.topk_approx(updates.update_lineitem(spark, sf_dir, N), RATIO)


@query(f"SELECT client_id, param_idx, delta FROM (SELECT *, row_number() OVER (PARTITION BY client_id ORDER BY {u_sql('randk', 'client_id', 'param_idx')}, param_idx) AS r FROM u1 WHERE delta <> 0), p WHERE r <= {k_sql(str(RATIO))}")
def randomk(spark, sf_dir):
    return compress.randomk(_with_k(spark, sf_dir), seed=SEED).select("client_id", "param_idx", "delta")


@query(f"SELECT client_id, param_idx, round(delta * n / {k_sql(str(RATIO))}, 6) AS delta FROM (SELECT *, row_number() OVER (PARTITION BY client_id ORDER BY {u_sql('randk', 'client_id', 'param_idx')}, param_idx) AS r FROM u1 WHERE delta <> 0), p WHERE r <= {k_sql(str(RATIO))}")
def randomk_unbiased(spark, sf_dir):
    return compress.randomk(_with_k(spark, sf_dir), seed=SEED, n_params=updates.n_params(spark, sf_dir)).select("client_id", "param_idx", r6("delta").alias("delta"))


@query(f"SELECT client_id, param_idx, delta FROM u1 WHERE abs(delta) >= {TAU}")
def threshold(spark, sf_dir):
    return compress.hard_threshold(updates.update_lineitem(spark, sf_dir, N), TAU)


def _quant_sql(shift: str) -> str:
    return f"SELECT client_id, param_idx, q, round(step, 6) AS step, round(q * step, 6) AS restored FROM (SELECT *, coalesce(floor(delta / nullif(step, 0) + {shift}), 0)::INT AS q FROM (SELECT *, max(abs(delta)) OVER (PARTITION BY client_id) / {2 ** (BITS - 1) - 1} AS step FROM u1))"


@query(_quant_sql("0.5"))
def quantize8(spark, sf_dir):
    return compress.quantize(updates.update_lineitem(spark, sf_dir, N), BITS).select("client_id", "param_idx", "q", r6("step").alias("step"), r6("restored").alias("restored"))


@query(_quant_sql(u_sql("dither", "client_id", "param_idx")))
def quantize8_dithered(spark, sf_dir):
    return compress.quantize(updates.update_lineitem(spark, sf_dir, N), BITS, seed=SEED).select("client_id", "param_idx", "q", r6("step").alias("step"), r6("restored").alias("restored"))


@query("SELECT client_id, param_idx, round(sign(delta) * avg(abs(delta)) OVER (PARTITION BY client_id), 6) + 0.0 AS restored FROM u1")
def sign_compress(spark, sf_dir):
    return compress.sign_compress(updates.update_lineitem(spark, sf_dir, N)).select("client_id", "param_idx", r6("restored").alias("restored"))


@query("SELECT client_id, round(sum(CASE WHEN rank <= greatest(1, floor(0.1 * n + 1e-9)) THEN delta * delta ELSE 0 END) / sum(delta * delta), 6) AS energy FROM ranked, p GROUP BY 1")
def energy_kept(spark, sf_dir):
    return compress.energy_marked(compress.topk_marked(_with_k(spark, sf_dir))).select("client_id", r6("energy").alias("energy"))


@query("SELECT client_id, param_idx, delta::FLOAT::DOUBLE AS delta FROM kept_topk")
def packed_roundtrip(spark, sf_dir):
    """Updates packed into arrays and unpacked again (values are stored as float)."""
    return compress.unpack(compress.pack(kept(spark, sf_dir), shards=4))


def _feedback(spark, sf_dir):
    u, k = updates.update_lineitem_rounds(spark, sf_dir, N), links.supplier_links(spark, sf_dir, N).select("client_id", base_k(spark, sf_dir).alias("k"))
    one = compress.ef_topk(u.where("round = 0"), None, k)
    return one, compress.ef_topk(u.where("round = 1"), one, k)


def _ef_columns(df, rnd):
    return df.select(F.lit(rnd).alias("round"), "client_id", "param_idx", r6("sent").alias("sent"), r6("residual").alias("residual"))


EF_SQL = ["SELECT {r}::INT AS round, client_id, param_idx, round(sent, 6) AS sent, round(residual, 6) AS residual FROM ef{r}s".format(r=r) for r in (0, 1)]


@query(EF_SQL[0])
def ef_round1(spark, sf_dir):
    return _ef_columns(_feedback(spark, sf_dir)[0], 0)


@query(EF_SQL[1])
def ef_round2(spark, sf_dir):
    return _ef_columns(_feedback(spark, sf_dir)[1], 1)


@query(f"SELECT * FROM ({EF_SQL[0]} UNION ALL {EF_SQL[1]}) WHERE residual <> 0")
def ef_residual(spark, sf_dir):
    one, two = _feedback(spark, sf_dir)
    return _ef_columns(one, 0).union(_ef_columns(two, 1)).where("residual <> 0")


@query(f""", e0 AS (SELECT u.*, {RANK} AS rank FROM u1t u JOIN (SELECT client_id FROM sel WHERE round = 0) USING (client_id) WHERE u.round = 0 AND delta <> 0)
, left0 AS (SELECT client_id, param_idx, delta AS residual FROM e0, p WHERE rank > {k_sql(str(RATIO))})
, e1 AS (SELECT client_id, param_idx, coalesce(u.delta, 0) + coalesce(o.residual, 0) AS delta FROM (SELECT u1t.* FROM u1t JOIN (SELECT client_id FROM sel WHERE round = 1) USING (client_id) WHERE u1t.round = 1) u FULL JOIN left0 o USING (client_id, param_idx))
, e1r AS (SELECT e1.*, s.client_id IS NOT NULL AS here, {RANK.replace("client_id", "e1.client_id", 1)} AS rank FROM e1 LEFT JOIN (SELECT client_id FROM sel WHERE round = 1) s ON s.client_id = e1.client_id WHERE delta <> 0)
SELECT client_id, param_idx, round(CASE WHEN here AND rank <= {k_sql(str(RATIO))} THEN delta ELSE 0 END, 6) + 0.0 AS sent, round(CASE WHEN here AND rank <= {k_sql(str(RATIO))} THEN 0 ELSE delta END, 6) + 0.0 AS residual FROM e1r, p""")
def ef_partial(spark, sf_dir):
    """Two rounds of error feedback in which each round's own clients take part; absent clients keep their residuals."""
    u = updates.update_lineitem_rounds(spark, sf_dir, N)
    k = selected(spark, sf_dir, 2).select("round", "client_id", base_k(spark, sf_dir).alias("k"))
    here = u.join(k.select("round", "client_id"), ["round", "client_id"], "left_semi")
    one = compress.ef_topk(here.where("round = 0"), None, k.where("round = 0").drop("round"))
    return _ef_columns(compress.ef_topk(here.where("round = 1"), one, k.where("round = 1").drop("round")), 1).drop("round")


@query("SELECT client_id, param_idx, round(delta, 6) AS delta, rank <= " + k_sql(str(RATIO)) + " AS kept FROM ranked, p")
def topk_marked(spark, sf_dir):
    """Every coordinate of every update and whether top-k keeps it; no update is sorted whole."""
    rows = updates.update_lineitem(spark, sf_dir, N).withColumn("k", base_k(spark, sf_dir))
    return compress.topk_marked(rows).select("client_id", "param_idx", r6("delta").alias("delta"), "kept")


# --- overlap and boost --------------------------------------------------------------------------------------


@query("SELECT param_idx, count(*) AS degree FROM kept_topk GROUP BY 1")
def overlap_degree(spark, sf_dir):
    return overlap.overlap_degree(kept(spark, sf_dir))


def _hist_sql(how: str, ratio: float) -> str:
    if how == "topk":
        rows = f"SELECT r.* FROM ranked r JOIN sel0 USING (client_id), p WHERE rank <= {k_sql(str(ratio))}"
    else:
        raw = f"least(1.0::DOUBLE, (max(latency_s + {2 * V} * {ratio} / bandwidth_mbps) OVER () - latency_s) * bandwidth_mbps / {2 * V})"
        rows = f"SELECT r.* FROM ranked r JOIN (SELECT client_id, {k_sql('raw')} AS k2 FROM (SELECT client_id, {raw} AS raw FROM sel0), p) s USING (client_id) WHERE rank <= k2"
    return f"SELECT '{how}' AS method, {ratio}::DOUBLE AS base_ratio, degree, count(*) AS n_coords, round(count(*) / sum(count(*)) OVER (), 6) AS share FROM (SELECT param_idx, count(*) AS degree FROM ({rows}) GROUP BY 1) GROUP BY degree"


def _hist(spark, sf_dir, how):
    """Both ratios from one ranking and one count."""
    ratios = (0.1, 0.01)
    rows = ranked_for(spark, sf_dir, [(how, r) for r in ratios]).groupBy("param_idx").agg(*(F.count_if(F.col("rank") <= F.col(f"k{i}")).alias(f"d{i}") for i in range(len(ratios))))
    degrees = rows.select("param_idx", F.explode(F.array(*(F.struct(F.lit(r).alias("base_ratio"), F.col(f"d{i}").alias("degree")) for i, r in enumerate(ratios)))).alias("x")).select("x.*").where("degree > 0")
    return overlap.overlap_histogram(degrees, ("base_ratio",)).select(F.lit(how).alias("method"), "base_ratio", "degree", "n_coords", r6("share").alias("share"))


@query(" UNION ALL ".join(_hist_sql("topk", r) for r in (0.1, 0.01)))
def overlap_histogram(spark, sf_dir):
    return _hist(spark, sf_dir, "topk")


@query(" UNION ALL ".join(_hist_sql("paced", r) for r in (0.1, 0.01)))
def overlap_histogram_paced(spark, sf_dir):
    return _hist(spark, sf_dir, "paced")


@query("""SELECT degree, count(*) AS n_coords, round(count(*) / sum(count(*)) OVER (), 6) AS share FROM (SELECT token, count(*) AS degree FROM (SELECT client_id, token, row_number() OVER (PARTITION BY client_id ORDER BY n DESC, token) AS r FROM (
SELECT regexp_extract(source, '([0-9]+)$', 1)::INT AS client_id, token, count(*) AS n FROM (SELECT source, unnest(string_split_regex(lower(text), '[^a-zäöüßàâçéèêëîïôûùñáíóú]+')) AS token FROM documents WHERE source IS NOT NULL AND text IS NOT NULL) WHERE token <> '' GROUP BY 1, 2)) WHERE r <= 200 GROUP BY 1) GROUP BY 1""")
def overlap_histogram_tokens(spark, sf_dir):
    """The 200 most frequent words of each source: how many sources share them."""
    rows = compress.topk(updates.update_tokens(spark, sf_dir).withColumn("k", F.lit(200)), k_max=200, coord="token")
    return overlap.overlap_histogram(overlap.overlap_degree(rows, coord="token")).select("degree", "n_coords", r6("share").alias("share"))


@query("""SELECT c1, c2, x AS "both", n1 + n2 - x AS either, round(x / (n1 + n2 - x), 6) AS jaccard FROM (SELECT a.client_id AS c1, b.client_id AS c2, count(*) AS x FROM kept_topk a JOIN kept_topk b ON a.param_idx = b.param_idx AND a.client_id < b.client_id GROUP BY 1, 2)
JOIN (SELECT client_id AS c1, count(*) AS n1 FROM kept_topk GROUP BY 1) USING (c1) JOIN (SELECT client_id AS c2, count(*) AS n2 FROM kept_topk GROUP BY 1) USING (c2)""")
def pairwise_overlap(spark, sf_dir):
    return overlap.pairwise_overlap(kept(spark, sf_dir)).select("c1", "c2", "both", "either", r6("jaccard").alias("jaccard"))


@query("SELECT gamma, max_degree, param_idx, CASE WHEN degree <= max_degree THEN gamma ELSE 1 END AS factor FROM (SELECT param_idx, count(*) AS degree FROM kept_topk GROUP BY 1), (VALUES (3.0::DOUBLE), (5.0::DOUBLE), (7.0::DOUBLE)) g(gamma), (VALUES (1), (2)) d(max_degree)")
def boost_mask(spark, sf_dir):
    grid = spark.createDataFrame([(g, d) for g in (3.0, 5.0, 7.0) for d in (1, 2)], "gamma double, max_degree int")
    rows = overlap.overlap_degree(kept(spark, sf_dir)).crossJoin(F.broadcast(grid))
    return rows.select("gamma", "max_degree", "param_idx", overlap.boost_mask("degree", F.col("gamma"), F.col("max_degree")).alias("factor"))


@query("SELECT CASE WHEN a AND b THEN 'both' WHEN a THEN 'topk' ELSE 'paced' END AS side, count(*) AS n FROM (SELECT param_idx, bool_or(w = 't') AS a, bool_or(w = 'p') AS b FROM (SELECT param_idx, 't' AS w FROM kept_topk UNION SELECT param_idx, 'p' FROM kept_paced) GROUP BY 1) GROUP BY 1")
def support_sets(spark, sf_dir):
    """Coordinates kept under both schedules, or one alone; from one ranking."""
    rows = ranked_for(spark, sf_dir, [("topk", RATIO), ("paced", RATIO)]).groupBy("param_idx").agg(*(F.bool_or(F.col("rank") <= F.col(f"k{i}")).alias(c) for i, c in enumerate("ab")))
    side = F.when(F.col("a") & F.col("b"), "both").when(F.col("a"), "topk").otherwise("paced")
    return rows.where("a or b").groupBy(side.alias("side")).agg(F.count("*").alias("n"))


# --- server steps -------------------------------------------------------------------------------------------


def _step_sql(rows: str, coef: str, gamma: float = 1.0) -> str:
    return f"SELECT param_idx, degree, round(s * CASE WHEN degree <= 1 THEN {gamma}::DOUBLE ELSE 1 END, 6) + 0.0 AS step FROM (SELECT param_idx, count(*) FILTER (WHERE delta <> 0) AS degree, sum({coef} * delta) AS s FROM {rows} r JOIN (SELECT client_id, f, p_adj FROM sel0) USING (client_id) GROUP BY 1)"


def _step(df: DataFrame) -> DataFrame:
    return df.select("param_idx", "degree", r6("step").alias("step"))


@query(_step_sql("u1", "f"))
def server_dense(spark, sf_dir):
    return _step(server.server_step(updates.update_lineitem(spark, sf_dir, N), first_round(spark, sf_dir), "f", n_clients=N))


@query(_step_sql("kept_topk", "f"))
def server_topk(spark, sf_dir):
    return _step(server.server_step(kept(spark, sf_dir), first_round(spark, sf_dir), "f", n_clients=N))


@query(_step_sql("kept_paced", "p_adj"))
def server_paced(spark, sf_dir):
    return _step(server.server_step(kept(spark, sf_dir, "paced"), first_round(spark, sf_dir), "p_adj", n_clients=N))


@query(_step_sql("kept_paced", "p_adj", GAMMA))
def server_boosted(spark, sf_dir):
    return _step(server.server_step(kept(spark, sf_dir, "paced"), first_round(spark, sf_dir), "p_adj", GAMMA, n_clients=N))


@query(_step_sql("kept_topk", "f", GAMMA))
def server_boost_only(spark, sf_dir):
    """Ablation: the boost without pacing."""
    return _step(server.server_step(kept(spark, sf_dir), first_round(spark, sf_dir), "f", GAMMA, n_clients=N))


@query(_step_sql("kept_paced", "f"))
def server_pace_only(spark, sf_dir):
    """Ablation: pacing with plain shares."""
    return _step(server.server_step(kept(spark, sf_dir, "paced"), first_round(spark, sf_dir), "f", n_clients=N))


@query(_step_sql("kept_topk", "p_adj"))
def server_coef_only(spark, sf_dir):
    """Ablation: adjusted coefficients on uniform top-k."""
    return _step(server.server_step(kept(spark, sf_dir), first_round(spark, sf_dir), "p_adj", n_clients=N))


@query(_step_sql("kept_paced", "p_adj", GAMMA))
def server_boosted_two_pass(spark, sf_dir):
    return _step(server.server_step_two_pass(kept(spark, sf_dir, "paced"), first_round(spark, sf_dir), "p_adj", GAMMA))


@query(f"""SELECT gamma, max_degree, count(*) AS n, round(sum(step * step), 4) AS step_norm2 FROM (SELECT g.gamma, d.max_degree, s * CASE WHEN degree <= d.max_degree THEN g.gamma ELSE 1 END AS step FROM
(SELECT param_idx, count(*) FILTER (WHERE delta <> 0) AS degree, sum(p_adj * delta) AS s FROM kept_paced r JOIN (SELECT client_id, p_adj FROM sel0) USING (client_id) GROUP BY 1), (SELECT x::DOUBLE AS gamma FROM range(1, {N + 1}) t(x)) g, (VALUES (0), (1), (2)) d(max_degree)) GROUP BY 1, 2""")
def gamma_sweep_round(spark, sf_dir):
    """Boosts 1..N by rarity limits 0..2 over one round's kept rows, from one aggregate."""
    rows = server.gamma_grid(kept(spark, sf_dir, "paced"), first_round(spark, sf_dir), "p_adj", list(range(1, N + 1)), [0, 1, 2], N)
    return rows.groupBy("gamma", "max_degree").agg(F.count("*").alias("n"), F.round(F.sum(F.col("step") * F.col("step")), 4).alias("step_norm2"))


@query("SELECT client_id, round(sqrt(sum((coalesce(delta, 0) - m) * (coalesce(delta, 0) - m))), 6) AS drift FROM (SELECT DISTINCT client_id FROM u1) CROSS JOIN (SELECT param_idx, sum(delta) / (SELECT count(DISTINCT client_id) FROM u1) AS m FROM u1 GROUP BY 1) LEFT JOIN u1 USING (client_id, param_idx) GROUP BY 1")
def client_drift(spark, sf_dir):
    return metrics.client_drift(updates.update_lineitem(spark, sf_dir, N)).select("client_id", r6("drift").alias("drift"))


# --- time and accuracy measures -------------------------------------------------------------------------------


def uploads(spark, sf_dir):
    return metrics.simulated_uploads(selected(spark, sf_dir), RATIO, updates.n_params(spark, sf_dir), V)


def round_log(spark, sf_dir):
    """Simulated log: accuracy rises as 1 - exp(-(round + 1) / tau); times are those of the methods."""
    taus = spark.createDataFrame([(k, v, "topk" if k == "slow" else k) for k, v in ACCURACY_TAU.items()], "run_id string, tau double, source string")
    times = metrics.time_account(uploads(spark, sf_dir)).withColumnRenamed("run_id", "source")
    return times.join(F.broadcast(taus), "source").select("run_id", "round", F.round(1 - F.exp(-(F.col("round") + 1) / F.col("tau")), 6).alias("accuracy"), "t_actual", "t_max", "t_min")


@query("SELECT run_id, round, round(t_actual, 6) AS t_actual, round(t_max, 6) AS t_max, round(t_min, 6) AS t_min, round(cum_actual, 6) AS cum_actual, round(cum_max, 6) AS cum_max, round(cum_min, 6) AS cum_min FROM cumlog WHERE run_id <> 'slow'")
def time_account(spark, sf_dir):
    rows = metrics.time_account(uploads(spark, sf_dir))
    return rows.select("run_id", "round", *(r6(c).alias(c) for c in ("t_actual", "t_max", "t_min", "cum_actual", "cum_max", "cum_min")))


@query("SELECT run_id, round_hit, round(time_actual, 6) AS time_actual, round(time_max, 6) AS time_max, round(time_min, 6) AS time_min FROM reached")
def time_to_target(spark, sf_dir):
    return metrics.time_to_target(round_log(spark, sf_dir), 0.6).select("run_id", "round_hit", *(r6(c).alias(c) for c in ("time_actual", "time_max", "time_min")))


@query("SELECT a.run_id, b.run_id AS reference, round(b.time_actual / a.time_actual, 6) AS ratio FROM reached a, reached b WHERE b.run_id = 'topk'")
def speedup(spark, sf_dir):
    return metrics.speedup(metrics.time_to_target(round_log(spark, sf_dir), 0.6), "topk").select("run_id", "reference", r6("ratio").alias("ratio"))


@query(f"SELECT a.run_id, b.run_id AS reference, a.accuracy, round(a.accuracy - b.accuracy, 6) AS gain_abs, round(a.accuracy / b.accuracy - 1, 6) AS gain_rel FROM log a, log b WHERE b.run_id = 'dense' AND a.round = {ROUNDS - 1} AND b.round = {ROUNDS - 1}")
def accuracy_gain(spark, sf_dir):
    return metrics.gain(round_log(spark, sf_dir), "dense").select("run_id", "reference", "accuracy", r6("gain_abs").alias("gain_abs"), r6("gain_rel").alias("gain_rel"))


@query("SELECT run_id, round, accuracy, round(accuracy - lag(accuracy) OVER w, 6) AS change, round(avg(accuracy) OVER (PARTITION BY run_id ORDER BY round ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS smooth FROM log WINDOW w AS (PARTITION BY run_id ORDER BY round)")
def accuracy_curve(spark, sf_dir):
    return metrics.curve(round_log(spark, sf_dir)).select("run_id", "round", "accuracy", r6("change").alias("change"), r6("smooth").alias("smooth"))


@query("SELECT r.run_id, g.t_grid, (SELECT max(c.accuracy) FROM cumlog c WHERE c.run_id = r.run_id AND c.cum_actual <= g.t_grid) AS accuracy FROM (SELECT DISTINCT run_id FROM log) r, (SELECT (x * 50)::DOUBLE AS t_grid FROM range(1, 21) t(x)) g")
def accuracy_at(spark, sf_dir):
    return metrics.accuracy_at(round_log(spark, sf_dir), spark.range(1, 21).select((F.col("id") * 50).cast("double").alias("t_grid")))


@query("SELECT run_id, round, round(max(t_own) * count(*) - sum(t_own), 6) + 0.0 AS idle_s FROM uploads GROUP BY 1, 2")
def idle_time(spark, sf_dir):
    return metrics.idle_time(uploads(spark, sf_dir)).select("run_id", "round", r6("idle_s").alias("idle_s"))


@query("SELECT run_id, round, round(sum(CASE WHEN sent >= n THEN sent * 32 ELSE sent * 64 END) / 1e6, 6) AS mbit_sent, round(count(*) * any_value(n) * 32 / 1e6, 6) AS mbit_dense FROM uploads, p GROUP BY 1, 2")
def traffic(spark, sf_dir):
    return metrics.traffic(uploads(spark, sf_dir), updates.n_params(spark, sf_dir)).select("run_id", "round", r6("mbit_sent").alias("mbit_sent"), r6("mbit_dense").alias("mbit_dense"))


@query(f"SELECT r_name AS region, n_name AS nation, client_id, grouping(r_name, n_name, client_id)::INT AS gid, round(sum(latency_s + {V} / bandwidth_mbps), 6) AS sum_t, round(max(latency_s + {V} / bandwidth_mbps), 6) AS max_t FROM links_all JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name, client_id)")
def time_rollup_region(spark, sf_dir):
    rows = links.supplier_links(spark, sf_dir, None)
    n, r = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    rows = rows.join(F.broadcast(n), rows.s_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    times = rows.select(F.col("r_name").alias("region"), F.col("n_name").alias("nation"), "client_id", links.dense_time(V, "bandwidth_mbps", "latency_s").alias("t"))
    return metrics.time_rollup(times).select("region", "nation", "client_id", "gid", r6("sum_t").alias("sum_t"), r6("max_t").alias("max_t"))


# --- full-batch gradients and a round in SQL ------------------------------------------------------------------

W4 = f"w4 AS (SELECT (l_suppkey % {N})::INT AS client_id, [1.0::DOUBLE, l_quantity / 50, l_discount * 10, l_tax * 10] AS x, l_extendedprice / 100000 AS y FROM lineitem), g4 AS (SELECT client_id, param_idx, 2 * avg((0 - y) * v) AS grad, count(*) AS n FROM (SELECT client_id, y, unnest(x) AS v, unnest(range(4)) AS param_idx FROM w4) GROUP BY 1, 2)"


@query(f", {W4} SELECT client_id, param_idx, round(grad, 6) AS grad, n FROM g4")
def gradient_sql_regression(spark, sf_dir):
    """One full-batch gradient of every client at zero weights."""
    rows = learner.gradient_sql(features.regression_rows(spark, sf_dir, N), [0.0] * 4)
    return rows.select("client_id", "param_idx", r6("grad").alias("grad"), "n")


@query(f""", {W4}
, sel4 AS (SELECT s.client_id, t.p_adj, least(4, greatest(1, floor(least(1.0::DOUBLE, q.raw) * 4 + 1e-9)))::BIGINT AS k4 FROM sel0 t JOIN (SELECT client_id, (max(latency_s + {2 * V} * 0.25 / bandwidth_mbps) OVER () - latency_s) * bandwidth_mbps / {2 * V} AS raw FROM sel0) q USING (client_id) JOIN (SELECT client_id FROM sel0) s USING (client_id))
, c4 AS (SELECT client_id, f / greatest(f, r / sum(r) OVER ()) * {ALPHA} AS p4 FROM (SELECT client_id, n_samples / sum(n_samples) OVER () AS f, least(1.0::DOUBLE, (max(latency_s + {2 * V} * 0.25 / bandwidth_mbps) OVER () - latency_s) * bandwidth_mbps / {2 * V}) AS r FROM sel0))
, r4 AS (SELECT g.client_id, g.param_idx, 0.1 * grad AS delta, row_number() OVER (PARTITION BY g.client_id ORDER BY abs(grad) DESC, g.param_idx) AS rank FROM g4 g JOIN sel4 USING (client_id))
SELECT i.param_idx, round(0 - coalesce(s * CASE WHEN degree <= 1 THEN {GAMMA} ELSE 1 END, 0), 6) + 0.0 AS w_next FROM (SELECT unnest(range(4)) AS param_idx) i LEFT JOIN
(SELECT param_idx, count(*) AS degree, sum(p4 * delta) AS s FROM r4 JOIN sel4 USING (client_id) JOIN c4 USING (client_id) WHERE rank <= k4 GROUP BY 1) z USING (param_idx)""")
def round_sql_regression(spark, sf_dir):
    """A whole round without Python: gradient, paced top-k, adjusted coefficients, boost, step."""
    rows = features.regression_rows(spark, sf_dir, N)
    info = with_adjusted(with_share(schedule.paced_ratios(selected(spark, sf_dir, 1), 0.25, 4, V)), ALPHA)
    delta = learner.gradient_sql(rows, [0.0] * 4).select("client_id", "param_idx", (0.1 * F.col("grad")).alias("delta"))
    sent = compress.topk(delta.join(F.broadcast(info.select("client_id", "k")), "client_id"), k_max=4)
    step = server.server_step(sent, info, "p_adj", GAMMA, n_clients=N)
    start = spark.range(4).select(F.col("id").alias("param_idx"), F.lit(0.0).alias("w"))
    return server.apply_step(start, step).select("param_idx", r6("w").alias("w_next"))


# --- training -------------------------------------------------------------------------------------------------


def _training(name: str):
    @query(name=f"train_{name}" if name != "ef_topk" else "train_ef")
    def run(spark, sf_dir):
        """Three rounds on the language of documents."""
        spec = method(name, rounds=3, beta=0.5)
        log, _ = run_cohort([spec], features.language_samples(spark, sf_dir), 4)
        rows = metrics.time_account(log.select("run_id", "round", F.col("t_actual").alias("t_own"), F.col("t_max").alias("t_dense")))
        return log.join(rows.select("round", "cum_actual"), "round").select("round", r6("accuracy").alias("accuracy"), r6("loss").alias("loss"), r6("coef_sum").alias("coef_sum"), "sent_rows", r6("cum_actual").alias("cum_actual"))

    return run


for _m in ("dense", "topk", "ef_topk", "paced", "boosted", "randomk_boosted", "ef_boosted"):
    _training(_m)


@query()
def train_all_methods(spark, sf_dir):
    """Every named method in one cohort: all train in the same jobs; planted classes of embeddings, two rounds."""
    specs = [method(m, rounds=2, beta=0.5) for m in METHODS]
    log, _ = run_cohort(specs, features.embedding_samples(spark, sf_dir), 10)
    return log.select("run_id", "round", r6("accuracy").alias("accuracy"), r6("loss").alias("loss"), "sent_rows", r6("t_actual").alias("t_actual"))


@query()
def train_perceptron(spark, sf_dir):
    spec = method("boosted", rounds=2, beta=0.5, model="perceptron", hidden=8)
    log, _ = run_cohort([spec], features.language_samples(spark, sf_dir), 4)
    return log.select("round", r6("accuracy").alias("accuracy"), r6("loss").alias("loss"), "sent_rows")


FIXED = [round(((i * 7919) % 1009 - 504) / 504, 6) for i in range(4 * 28)]


def _fixed():
    import numpy as np

    return np.array(FIXED), learner.Softmax(27, 4)


@query()
def eval_objective(spark, sf_dir):
    """Local risks and the global objective at fixed weights."""
    w, model = _fixed()
    samples = partition.assign_clients(features.language_samples(spark, sf_dir), "y", N, seed=SEED, mode="iid")
    return learner.objective(samples, w, model).select("client_id", "n", r6("risk").alias("risk"), r6("weighted").alias("weighted"))


LETTERS_SQL = ", ".join(f"(length(low) - length(replace(low, '{c}', ''))) * 10.0::DOUBLE / greatest(length(low), 1)" for c in features.LETTERS)


@query(f""", s AS (SELECT list_position(['de', 'en', 'es', 'fr'], lang)::INT - 1 AS y, list_append([{LETTERS_SQL}], 1.0::DOUBLE) AS x FROM (SELECT lang, lower(text) AS low FROM documents WHERE lang IN ('de', 'en', 'es', 'fr') AND text IS NOT NULL))
, z AS (SELECT y, [{", ".join(f"round(list_dot_product(x, {FIXED[28 * c : 28 * c + 28]}::DOUBLE[]), 9)" for c in range(4))}] AS z FROM s)
SELECT y, (list_position(z, list_max(z)) - 1)::INT AS pred, count(*) AS n FROM z GROUP BY 1, 2""")
def eval_confusion(spark, sf_dir):
    """Confusion counts of a softmax model with fixed weights over all documents."""
    w, model = _fixed()
    return metrics.confusion(learner.predictions(features.language_samples(spark, sf_dir), w, model))


@query()
def eval_balanced(spark, sf_dir):
    w, model = _fixed()
    return metrics.balanced_accuracy(learner.predictions(features.language_samples(spark, sf_dir), w, model)).select(r6("balanced_accuracy").alias("balanced_accuracy"))


# --- telemetry: batch twins and streams ---------------------------------------------------------------------


def _windows(df: DataFrame) -> DataFrame:
    stamp = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss")
    return df.select("client_id", stamp("w_start").alias("w_start"), stamp("w_end").alias("w_end"), r6("bandwidth_mbps").alias("bandwidth_mbps"), "n")


def _observed(spark, sf_dir):
    """Telemetry without a zone, so that windows do not depend on the session's."""
    e = table(spark, sf_dir, "events").where("ts is not null and value is not null and user_id is not null")
    return e.select("event_id", (F.col("user_id") % N).cast("int").alias("client_id"), F.col("ts").alias("at"), (F.col("value") / 50).alias("mbps"))


@query("SELECT client_id, date_trunc('day', ts)::VARCHAR AS w_start, (date_trunc('day', ts) + INTERVAL 1 DAY)::VARCHAR AS w_end, round(avg(value / 50), 6) AS bandwidth_mbps, count(*) AS n FROM tel GROUP BY client_id, date_trunc('day', ts)")
def telemetry_tumbling(spark, sf_dir):
    return _windows(telemetry.tumbling(_observed(spark, sf_dir)))


@query("SELECT client_id, s::VARCHAR AS w_start, (s + INTERVAL 1 DAY)::VARCHAR AS w_end, round(avg(value / 50), 6) AS bandwidth_mbps, count(*) AS n FROM (SELECT client_id, value, time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - to_hours(6 * k::INT) AS s FROM tel, range(4) t(k)) GROUP BY client_id, s")
def telemetry_sliding(spark, sf_dir):
    return _windows(telemetry.sliding(_observed(spark, sf_dir)))


@query("SELECT client_id, min(ts)::VARCHAR AS w_start, (max(ts) + INTERVAL 2 HOUR)::VARCHAR AS w_end, round(avg(value / 50), 6) AS bandwidth_mbps, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY client_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY client_id ORDER BY ts) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM tel)) GROUP BY client_id, s")
def telemetry_session(spark, sf_dir):
    rows = telemetry.sessions(_observed(spark, sf_dir))
    stamp = lambda c: F.regexp_replace(F.col(c).cast("string"), r"T", " ")
    return rows.select("client_id", stamp("w_start").alias("w_start"), stamp("w_end").alias("w_end"), r6("bandwidth_mbps").alias("bandwidth_mbps"), "n")


@query(f"""SELECT s::VARCHAR AS w_start, client_id, round(keep_ratio, 6) AS keep_ratio FROM (SELECT s, client_id, least(1.0::DOUBLE, (max(latency_s + {2 * V} * {RATIO} / bw) OVER (PARTITION BY s) - latency_s) * bw / {2 * V}) AS keep_ratio FROM
(SELECT date_trunc('day', ts) AS s, client_id, greatest({links.FLOOR_MBPS}, avg(value / 50)) AS bw FROM tel GROUP BY 1, 2) JOIN links USING (client_id))""")
def telemetry_trace_ratio(spark, sf_dir):
    """Paced ratios of every day, from the day's throughput."""
    rows = telemetry.window_ratios(telemetry.tumbling(_observed(spark, sf_dir)), links.supplier_links(spark, sf_dir, N), RATIO, 1000, V)
    return rows.select(F.date_format("w_start", "yyyy-MM-dd HH:mm:ss").alias("w_start"), "client_id", r6("keep_ratio").alias("keep_ratio"))


@query()
def stream_telemetry(spark, sf_dir):
    """Finished day windows of the event stream: those that the watermark has passed. The last windows are still open when
    the stream ends, so they are not in the result (telemetry_tumbling has them all)."""
    obs = telemetry.observations(telemetry.read_events(spark, sf_dir), N).withWatermark("at", "1 day")
    return _windows(telemetry.run_to_table(telemetry.tumbling(obs), "stream"))


@query("SELECT DISTINCT client_id, date_trunc('day', ts)::DATE::VARCHAR AS round FROM tel")
def stream_once(spark, sf_dir):
    """At-least-once uploads: one of each client and day, duplicates dropped within the watermark."""
    obs = telemetry.observations(telemetry.read_events(spark, sf_dir), N)
    up = obs.select("client_id", "at", F.date_format("at", "yyyy-MM-dd").alias("round"))
    return telemetry.run_to_table(telemetry.once(up, "40 days").select("client_id", "round"), "once")


@query(f"SELECT event_id, (user_id % {N})::INT AS client_id, round(value / 50, 6) AS mbps, bandwidth_mbps, latency_s FROM events LEFT JOIN links ON client_id = user_id % {N} WHERE ts IS NOT NULL AND value IS NOT NULL AND user_id IS NOT NULL")
def stream_with_links(spark, sf_dir):
    """Each upload of the stream with its client's static link."""
    obs = telemetry.observations(telemetry.read_events(spark, sf_dir), N).select("event_id", "client_id", r6("mbps").alias("mbps"))
    return telemetry.run_to_table(telemetry.with_links(obs, links.supplier_links(spark, sf_dir, N)), "linked")


@query(f"SELECT (a.user_id % {N})::INT AS client_id, a.ts::VARCHAR AS start_at, b.ts::VARCHAR AS end_at FROM events a JOIN events b ON a.user_id % {N} = b.user_id % {N} AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE WHERE a.event_id % 2 = 0 AND b.event_id % 2 = 1 AND a.value IS NOT NULL AND b.value IS NOT NULL")
def stream_matched(spark, sf_dir):
    """Starts (even events) with the ends (odd events) of the client within ten minutes after them."""
    starts, ends = (telemetry.observations(telemetry.read_events(spark, sf_dir).where(F.col("event_id") % 2 == k), N) for k in (0, 1))
    rows = telemetry.run_to_table(telemetry.matched(starts, ends, "10 minutes", "40 days"), "matched")
    return rows.select("client_id", F.col("start_at").cast("timestamp_ntz").cast("string").alias("start_at"), F.col("end_at").cast("timestamp_ntz").cast("string").alias("end_at"))


@query()
def stream_trace_ratio(spark, sf_dir):
    """Paced ratios written for every finished window; windows that are open when the stream ends are not written."""
    out = new_path(spark, "ratios")
    obs = telemetry.observations(telemetry.read_events(spark, sf_dir), N)
    telemetry.finish(telemetry.ratios_per_window(obs, links.supplier_links(spark, sf_dir, N), out, base_ratio=RATIO, n_params=1000, v=V), 300)
    rows = spark.read.parquet(out)
    return rows.select(F.date_format("w_start", "yyyy-MM-dd HH:mm:ss").alias("w_start"), "client_id", r6("keep_ratio").alias("keep_ratio"))


@query()
def stream_deadline_agg(spark, sf_dir):
    """Uploads summed per day and coordinate, those past the deadline dropped."""
    obs = telemetry.observations(telemetry.read_events(spark, sf_dir), N)
    up = obs.select("client_id", "at", (F.col("event_id") % 16).alias("param_idx"), F.col("mbps").alias("value"))
    rows = telemetry.run_to_table(telemetry.deadline_sums(up, "6 hours"), "deadline")
    return rows.select(F.date_format("w_start", "yyyy-MM-dd HH:mm:ss").alias("w_start"), "param_idx", r6("step").alias("step"), "degree")


@query()
def stream_ef_state(spark, sf_dir):
    """Error feedback with the residual in the state store."""
    obs = telemetry.observations(telemetry.read_events(spark, sf_dir), N)
    up = obs.select("client_id", (F.col("event_id") % 64).alias("param_idx"), (F.col("mbps") - 1).alias("delta"))
    return telemetry.run_to_table(residual_state.stream_error_feedback(up, 6), "feedback").select("client_id", "param_idx", r6("sent").alias("sent"), "kept_back")


# --- packed updates, ranks, reports ---------------------------------------------------------------------------


@query("SELECT param_idx, count(*) AS degree, round(sum(p_adj * delta::FLOAT::DOUBLE), 6) + 0.0 AS step FROM kept_paced JOIN (SELECT client_id, p_adj FROM sel0) USING (client_id) GROUP BY 1")
def server_packed(spark, sf_dir):
    """The paced step from packed updates, merged shard by shard in Arrow-fed groups."""
    packed = compress.pack(kept(spark, sf_dir, "paced"), shards=8).join(F.broadcast(first_round(spark, sf_dir).select("client_id", "p_adj")), "client_id")
    rows = udfs.merged(packed, "p_adj").select(F.explode(F.arrays_zip("idx", "step", "degree")).alias("e"))
    return rows.select(F.col("e.idx").alias("param_idx"), F.col("e.degree").alias("degree"), r6("e.step").alias("step"))


@query(EF_SQL[1].replace("SELECT 1::INT AS round, ", "SELECT "))
def ef_cogroup(spark, sf_dir):
    """The second round of error feedback by cogroup; equals the join."""
    u, k = updates.update_lineitem_rounds(spark, sf_dir, N), schedule.kept_count(F.lit(RATIO), updates.n_params(spark, sf_dir))
    n = spark.range(1).select(k).first()[0]
    one = compress.ef_topk(u.where("round = 0"), None, links.supplier_links(spark, sf_dir, N).select("client_id", F.lit(n).alias("k")))
    rows = udfs.feedback_cogroup(u.where("round = 1").select("client_id", "param_idx", "delta"), one.where("residual <> 0").select("client_id", "param_idx", "residual"), n)
    return rows.select("client_id", "param_idx", r6("sent").alias("sent"), r6("residual").alias("residual"))


@query("SELECT client_id, rank() OVER w::INT AS rnk, dense_rank() OVER w::INT AS dense, round(percent_rank() OVER w, 6) AS pct, ntile(4) OVER w::INT AS quartile FROM links WINDOW w AS (ORDER BY bandwidth_mbps DESC, client_id)".replace("OVER w::INT", "OVER w"))
def client_ranks(spark, sf_dir):
    """Clients by bandwidth: ranks and quartiles (a registry is small, so one ordered window serves)."""
    w = Window.partitionBy(F.lit(0)).orderBy(F.desc("bandwidth_mbps"), "client_id")
    rows = links.supplier_links(spark, sf_dir, N)
    return rows.select("client_id", F.rank().over(w).cast("long").alias("rnk"), F.dense_rank().over(w).cast("long").alias("dense"), r6(F.percent_rank().over(w)).alias("pct"), F.ntile(4).over(w).cast("long").alias("quartile"))


@query("SELECT run_id, round, grouping(run_id, round)::INT AS gid, round(avg(t_own), 6) AS mean_t, sum(sent)::BIGINT AS sent FROM uploads GROUP BY GROUPING SETS ((run_id), (round), ())")
def report_sets(spark, sf_dir):
    """Mean upload time and entries sent by method, by round, and over all."""
    uploads(spark, sf_dir).createOrReplaceTempView("pacedfl_uploads")
    return spark.sql("SELECT run_id, round, CAST(grouping_id(run_id, round) AS INT) AS gid, round(avg(t_own), 6) + 0D AS mean_t, sum(sent) AS sent FROM pacedfl_uploads GROUP BY GROUPING SETS ((run_id), (round), ())")


@query(f"SELECT round, {', '.join(f'''round(max(t_own) FILTER (WHERE run_id = '{m}'), 6) AS {m}''' for m in metrics.METHODS)} FROM uploads GROUP BY round")
def report_pivot(spark, sf_dir):
    """Round times, one column a method."""
    rows = uploads(spark, sf_dir).groupBy("round").pivot("run_id", list(metrics.METHODS)).agg(F.max("t_own"))
    return rows.select("round", *(r6(m).alias(m) for m in metrics.METHODS))


@query("SELECT run_id, round(quantile_cont(t_own, 0.5), 6) AS median, round(quantile_cont(t_own, 0.9), 6) AS p90, count(DISTINCT client_id) AS clients FROM uploads GROUP BY 1")
def upload_percentiles(spark, sf_dir):
    """Median and ninth decile of upload times by method; exact, as a run has few uploads."""
    rows = uploads(spark, sf_dir).groupBy("run_id").agg(F.percentile("t_own", F.lit(0.5)).alias("median"), F.percentile("t_own", F.lit(0.9)).alias("p90"), F.countDistinct("client_id").alias("clients"))
    return rows.select("run_id", r6("median").alias("median"), r6("p90").alias("p90"), "clients")


@query("SELECT DISTINCT client_id, ts::VARCHAR AS at, round(avg(value / 50) OVER (PARTITION BY client_id ORDER BY ts RANGE BETWEEN INTERVAL 6 HOUR PRECEDING AND CURRENT ROW), 6) AS recent_mbps FROM tel")
def telemetry_recent(spark, sf_dir):
    """At every observation, the mean throughput of the client's last six hours: a window by range of time."""
    micros = F.unix_micros(F.col("at").cast("timestamp"))
    w = Window.partitionBy("client_id").orderBy(micros).rangeBetween(-6 * 3600 * 1_000_000, 0)
    rows = _observed(spark, sf_dir).select("client_id", F.col("at").cast("timestamp_ntz").cast("string").alias("at"), r6(F.avg("mbps").over(w)).alias("recent_mbps"))
    return rows.distinct()


@query("SELECT param_idx, count(*) AS n FROM (SELECT param_idx FROM kept_topk EXCEPT ALL SELECT param_idx FROM kept_paced) GROUP BY 1")
def support_excess(spark, sf_dir):
    """By how many clients more a coordinate is kept under the uniform schedule: a difference of multisets."""
    a, b = (kept(spark, sf_dir, how).select("param_idx") for how in ("topk", "paced"))
    return a.exceptAll(b).groupBy("param_idx").agg(F.count("*").alias("n"))


@query("SELECT client_id, round(sum(abs(delta)) / nullif(sum(CASE WHEN rank <= " + k_sql(str(RATIO)) + " THEN abs(delta) ELSE 0 END), 0), 6) AS mass_ratio FROM ranked, p GROUP BY 1")
def mass_ratio(spark, sf_dir):
    """Magnitude of an update over that of what top-k keeps of it; null where nothing is kept."""
    size = F.abs("delta")
    rows = compress.topk_marked(_with_k(spark, sf_dir)).groupBy("client_id").agg(F.sum(size).alias("whole"), F.sum(F.when(F.col("kept"), size).otherwise(0.0)).alias("some"))
    return rows.select("client_id", r6(F.try_divide("whole", "some")).alias("mass_ratio"))


@query()
def coordinates_approx(spark, sf_dir):
    """Distinct coordinates that each method's clients keep, by a sketch."""
    rows = [kept(spark, sf_dir, how).select(F.lit(how).alias("method"), "param_idx") for how in ("topk", "paced")]
    return rows[0].union(rows[1]).groupBy("method").agg(F.approx_count_distinct("param_idx", 0.02).alias("coordinates"))


@query(r""", w AS (SELECT doc_id, list_filter(string_split_regex(lower(text), '[ \t\n\x0B\f\r]+'), lambda x: x <> '') AS w FROM documents WHERE text IS NOT NULL)
, b AS (SELECT list_filter(string_split_regex(lower(text), '[ \t\n\x0B\f\r]+'), lambda x: x <> '') AS w FROM benchmark WHERE text IS NOT NULL)
, r AS (SELECT doc_id, array_to_string(w[i:i + 7], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM w WHERE len(w) >= 8))
, q AS (SELECT DISTINCT array_to_string(w[i:i + 7], ' ') AS s FROM (SELECT w, unnest(range(1, len(w) - 6)) AS i FROM b WHERE len(w) >= 8))
SELECT doc_id AS sample_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM r JOIN q USING (s)) AND lang IN ('de', 'en', 'es', 'fr') AND text IS NOT NULL""")
def samples_without_benchmark(spark, sf_dir):
    """Training samples of the language task whose documents share no run of eight words with a benchmark item."""
    return features.without_benchmark(spark, sf_dir, features.language_samples(spark, sf_dir)).select("sample_id")


# --- experiments (more rounds, seeds and workloads: pacedfl.plans.experiments) ------------------------------------


def _accuracy_grid(workload: str):
    @query(name=f"experiment_accuracy_grid_{workload.lower()}")
    def run(spark, sf_dir):
        """Five methods, both skews, both ratios, five rounds."""
        rows = experiments.accuracy_grid(spark, sf_dir, (workload,), rounds=5)
        return rows.select("workload", "method", "beta", "base_ratio", r6("accuracy").alias("accuracy"), r6("t_actual").alias("t_actual"))

    return run


for _w in ("W1", "W2", "W3", "W5"):
    _accuracy_grid(_w)


@query()
def experiment_curves(spark, sf_dir):
    """Accuracy by round, with its change and moving average: both skews and ratios."""
    return experiments.curves(spark, sf_dir, "W3", rounds=5).select("run_id", "round", *(r6(c).alias(c) for c in ("accuracy", "change", "smooth")))


@query()
def experiment_gamma_sweep(spark, sf_dir):
    """Boosts of 1 to 10 in all four cells, one cohort a skew."""
    return experiments.gamma_sweep(spark, sf_dir, "W1", rounds=5).withColumn("accuracy", r6("accuracy"))


@query()
def experiment_client_scaling(spark, sf_dir):
    """Best boost of 1 to N for N of 10, 16 and 20 clients, at the severe skew and both ratios."""
    return experiments.client_scaling(spark, sf_dir, "W1", betas=(0.1,), rounds=3).withColumn("accuracy", r6("accuracy"))


def _time_to_accuracy(name: str, workload: str, rounds: int):
    @query(name=name)
    def run(spark, sf_dir):
        """Communication time to 40 % and 60 %, and the speed-up over top-k."""
        rows = experiments.time_to_accuracy(spark, sf_dir, workload, rounds=rounds)
        return rows.select("target", "method", "base_ratio", "round_hit", *(r6(c).alias(c) for c in ("time_actual", "time_max", "time_min", "speedup")))

    return run


_time_to_accuracy("experiment_time_to_accuracy", "W3", ROUNDS)
_time_to_accuracy("experiment_time_to_accuracy_w1", "W1", 5)


@query()
def experiment_alpha_tuning(spark, sf_dir):
    """Server factor by validation, of every cell; the baselines' rates get the same number of trials."""
    return experiments.alpha_tuning(spark, sf_dir, "W3", rounds=3).withColumn("accuracy", r6("accuracy"))


@query()
def experiment_breakdown(spark, sf_dir):
    """Seconds of a round by part (wall clock, so values differ from run to run)."""
    return experiments.round_breakdown(spark, sf_dir, "W1", rounds=2)


@query()
def experiment_accuracy_over_time(spark, sf_dir):
    """Accuracy on a grid of communication seconds, all four cells."""
    return experiments.accuracy_over_time(spark, sf_dir, "W3", rounds=5, steps=10).withColumn("accuracy", r6("accuracy"))


@query()
def experiment_quality_balanced(spark, sf_dir):
    """The unbalanced quality labels, two rounds of dense and boosted."""
    log, _ = run_cohort([method(m, rounds=2, beta=0.5) for m in ("dense", "boosted")], features.quality_samples(spark, sf_dir), 2)
    return log.select("run_id", "round", r6("accuracy").alias("accuracy"), r6("loss").alias("loss"))


@query()
def experiment_overlap(spark, sf_dir):
    """Degrees of overlap after a trained first round, at both skews and ratios."""
    return experiments.overlap_distribution(spark, sf_dir, "W1").withColumn("share", r6("share"))


@query()
def experiment_regression(spark, sf_dir):
    """Held-out loss of least squares on lineitem, two rounds of every main method."""
    return experiments.regression(spark, sf_dir, 2).withColumns({"loss": r6("loss"), "t_actual": r6("t_actual")})


@query()
def train_traced_links(spark, sf_dir):
    """Pacing by the links that the telemetry shows, a day a round."""
    trace = links.traced_links(spark, sf_dir, N)
    log, _ = run_cohort([method("paced", rounds=3, beta=0.5, link_mode="trace")], features.embedding_samples(spark, sf_dir), 10, trace=trace)
    return log.select("round", r6("accuracy").alias("accuracy"), r6("t_actual").alias("t_actual"), r6("t_max").alias("t_max"), r6("t_min").alias("t_min"))


@query("SELECT run_id, round, accuracy, round(greatest(0, accuracy - 1.96 * sqrt(accuracy * (1 - accuracy) / 500)), 6) AS low, round(least(1, accuracy + 1.96 * sqrt(accuracy * (1 - accuracy) / 500)), 6) AS high FROM log")
def accuracy_interval(spark, sf_dir):
    return metrics.accuracy_interval(round_log(spark, sf_dir), 500).select("run_id", "round", "accuracy", r6("low").alias("low"), r6("high").alias("high"))
