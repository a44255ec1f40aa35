"""SQL names of the vector functions. They are SQL functions, so Catalyst inlines them."""

from __future__ import annotations

from pyspark.sql import SparkSession

# Name, parameters, result type, body.
SQL_FUNCTIONS = [
    ("vec_dot", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)"),
    ("vec_l2_sq", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)"),
    ("vec_l2", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))"),
    ("vec_sub", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "ARRAY<DOUBLE>", "zip_with(a, b, (x, y) -> x - y)"),
    ("vec_margin", "u ARRAY<DOUBLE>, v ARRAY<DOUBLE>, w ARRAY<DOUBLE>", "DOUBLE", "vec_dot(vec_sub(w, v), u) - (vec_dot(w, w) - vec_dot(v, v)) / 2D"),
    ("vec_norm", "a ARRAY<DOUBLE>", "DOUBLE", "sqrt(vec_dot(a, a))"),
    ("vec_cosine", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "vec_dot(a, b) / (vec_norm(a) * vec_norm(b))"),
    ("vec_add", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "ARRAY<DOUBLE>", "zip_with(a, b, (x, y) -> x + y)"),
    ("vec_scale", "a ARRAY<DOUBLE>, f DOUBLE", "ARRAY<DOUBLE>", "transform(a, x -> x * f)"),
    ("vec_admits", "u ARRAY<DOUBLE>, farthest ARRAY<DOUBLE>, w ARRAY<DOUBLE>", "BOOLEAN", "vec_l2_sq(u, w) < vec_l2_sq(u, farthest)"),
    ("vec_occluded", "candidate ARRAY<DOUBLE>, inserted ARRAY<DOUBLE>, selected ARRAY<DOUBLE>", "BOOLEAN", "vec_l2_sq(candidate, selected) < vec_l2_sq(candidate, inserted)"),
    ("vec_adc", "adt ARRAY<DOUBLE>, code ARRAY<INT>, k INT", "DOUBLE", "aggregate(zip_with(code, sequence(0, size(code) - 1), (x, m) -> get(adt, m * k + x)), 0D, (s, x) -> s + x)"),
    ("vec_level", "vec_id BIGINT, degree DOUBLE", "INT", "cast(floor(-ln(((vec_id % 2147483648 * 2654435761 + 42) % 4294967296 + 1) / 4294967296D) / ln(degree)) AS INT)"),
    ("vec_segment", "vec_id BIGINT, segments INT", "INT", "cast(vec_id % 2147483648 * 2654435761 % 4294967296 % segments AS INT)"),
    ("vec_quantise", "d DOUBLE, lo DOUBLE, rng DOUBLE, bits INT", "INT", "CASE WHEN rng <= 0 THEN 0 ELSE cast(least(greatest(floor((d - lo) / rng * (pow(2, bits) - 1)), 0), pow(2, bits) - 1) AS INT) END"),
]


def register_all(spark: SparkSession) -> list[str]:
    for name, params, kind, body in SQL_FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({params}) RETURNS {kind} RETURN {body}")
    return [f[0] for f in SQL_FUNCTIONS]
