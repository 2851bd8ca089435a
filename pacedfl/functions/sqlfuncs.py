"""The cost and weight formulas as temporary SQL functions; Catalyst inlines them into the plan."""

from __future__ import annotations

from pyspark.sql import SparkSession

# name -> (parameters, expression)
DEFINITIONS = {
    "dense_time": ("v DOUBLE, bw DOUBLE, lat DOUBLE", "lat + v / bw"),
    "sparse_time": ("v DOUBLE, r DOUBLE, bw DOUBLE, lat DOUBLE", "lat + 2 * v * r / bw"),
    "paced_ratio": ("t_bench DOUBLE, v DOUBLE, bw DOUBLE, lat DOUBLE", "least(1D, (t_bench - lat) * bw / (2 * v))"),
    "adjusted_coef": ("f DOUBLE, norm_ratio DOUBLE, alpha DOUBLE", "f / greatest(f, norm_ratio) * alpha"),
    "boost_factor": ("degree BIGINT, gamma DOUBLE, max_degree INT", "CASE WHEN degree <= max_degree THEN gamma ELSE 1D END"),
    "kept_count": ("r DOUBLE, p BIGINT", "greatest(1L, CAST(floor(r * p + 1e-9) AS BIGINT))"),
}


def register(spark: SparkSession) -> list[str]:
    for name, (params, body) in DEFINITIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({params}) RETURNS {'BIGINT' if name == 'kept_count' else 'DOUBLE'} RETURN {body}")
    return list(DEFINITIONS)
