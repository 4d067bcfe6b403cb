"""Reading the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """A table with only the columns asked for: the scan reads no others."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def register_views(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> None:
    """Temporary views of the tables, for SQL users."""
    for name in names or TABLES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)
