"""SQL functions over array columns: registered as SQL expressions, so no Python runs."""

from __future__ import annotations

from pyspark.sql import SparkSession

DEFINITIONS = {
    "fp_dot": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> x * y), 0.0D, (s, x) -> s + x)"),
    "fp_total": ("a ARRAY<DOUBLE>", "DOUBLE", "aggregate(a, 0.0D, (s, x) -> s + x)"),
    "fp_l2": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0.0D, (s, x) -> s + x))"),
    "fp_sub": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "ARRAY<DOUBLE>", "zip_with(a, b, (x, y) -> x - y)"),
    "fp_axpy": ("k DOUBLE, a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "ARRAY<DOUBLE>", "zip_with(a, b, (x, y) -> k * x + y)"),
    "fp_block_energy": ("a ARRAY<DOUBLE>", "DOUBLE", "sqrt(aggregate(a, 0.0D, (s, x) -> s + x * x))"),
}


def register(spark: SparkSession) -> None:
    """Temporary SQL functions fp_*."""
    for name, (args, kind, body) in DEFINITIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
