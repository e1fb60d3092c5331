"""Temporary SQL functions, inlined by the analyzer and compiled with the query."""

from __future__ import annotations

from pyspark.sql import SparkSession

FUNCTIONS = {
    "logit_hazard": "(eta DOUBLE) RETURNS DOUBLE RETURN 1 / (1 + exp(-eta))",
    "logistic_loss": "(u DOUBLE) RETURNS DOUBLE RETURN greatest(-u, 0D) + log1p(exp(-abs(u)))",
    "sanitize_loss": "(loss DOUBLE, v DOUBLE) RETURNS DOUBLE RETURN v * tanh(loss / v)",
    "spline_value": "(u DOUBLE) RETURNS ARRAY<DOUBLE> RETURN array(1D, u, pow(greatest(u, 0D), 3D) - pow(greatest(u - 1, 0D), 3D) - (pow(greatest(u - 0.5D, 0D), 3D) - pow(greatest(u - 1, 0D), 3D)) / 0.5D)",
    "vec_dot": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (acc, x) -> acc + x)",
    "vec_norm": "(a ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(aggregate(a, 0D, (acc, x) -> acc + x * x))",
    "vec_axpy": "(c DOUBLE, a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN zip_with(a, b, (x, y) -> c * x + y)",
    "vec_clip_ball": "(a ARRAY<DOUBLE>, r DOUBLE) RETURNS ARRAY<DOUBLE> RETURN transform(a, x -> x * least(1D, r / greatest(sqrt(aggregate(a, 0D, (acc, y) -> acc + y * y)), 1e-300D)))",
    "record_loss": "(t INT, y INT, z DOUBLE, alpha ARRAY<DOUBLE>, q INT) RETURNS DOUBLE RETURN aggregate(transform(sequence(1, t), s -> if(s < t, -1D, CAST(y AS DOUBLE)) * (alpha[0] + alpha[1] * s / q + alpha[2] * (pow(s / CAST(q AS DOUBLE), 3D) - 2 * pow(greatest(s / CAST(q AS DOUBLE) - 0.5D, 0D), 3D)) + z)), 0D, (acc, u) -> acc + greatest(-u, 0D) + log1p(exp(-abs(u))))",
}


def register(spark: SparkSession) -> None:
    for name, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
