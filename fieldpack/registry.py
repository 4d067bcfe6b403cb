"""All queries of the library and their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .plans import compress_queries, field_queries, function_queries, relational_queries, workloads

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
for _part in (field_queries, compress_queries, relational_queries, function_queries, workloads):
    QUERIES |= _part.QUERIES
    ORACLES |= _part.ORACLES


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The flagship: a table is gridded, encoded in three scales with empty blocks dropped, decoded and judged."""
    return QUERIES["mean_block_codec"](spark, sf_dir)
