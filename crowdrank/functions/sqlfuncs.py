"""SQL functions over vectors and scores, as temporary SQL functions (no Python at run time)."""

from __future__ import annotations

from pyspark.sql import SparkSession

BODIES = {
    "vec_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "vec_add(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE>": "zip_with(a, b, (x, y) -> x + y)",
    "vec_scale(a ARRAY<DOUBLE>, s DOUBLE) RETURNS ARRAY<DOUBLE>": "transform(a, x -> x * s)",
    "sigmoid(x DOUBLE) RETURNS DOUBLE": "CASE WHEN x >= 0 THEN 1 / (1 + exp(-x)) ELSE exp(x) / (1 + exp(x)) END",
    "init_vec(id BIGINT, d INT, salt INT) RETURNS ARRAY<DOUBLE>": "transform(sequence(0, d - 1), k -> pmod(id * 7919 + k * 104729 + salt * 1299709, 1000003) / 1000003D - 0.5D)",
}


def register(spark: SparkSession) -> None:
    for head, body in BODIES.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
