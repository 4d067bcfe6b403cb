"""Joins that Spark has no single operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: A dimension is broadcast up to so many rows; beyond, the join is left to the planner.
MOST_BROADCAST_ROWS = 5_000_000


def seconds_of(time: str) -> Column:
    """Whole seconds of a timestamp with or without a zone."""
    return F.unix_seconds(F.col(time).cast("timestamp"))


def micros_of(time: str) -> Column:
    return F.unix_micros(F.col(time).cast("timestamp"))


def join_dimension(facts: DataFrame, dimension: DataFrame, on: Column) -> DataFrame:
    """Facts with a dimension beside them; the dimension is counted before it is broadcast."""
    small = dimension.limit(MOST_BROADCAST_ROWS + 1).count() <= MOST_BROADCAST_ROWS
    return facts.join(F.broadcast(dimension) if small else dimension, on)


def range_join(points: DataFrame, value: str, ranges: DataFrame, lo: str, hi: str, width: float) -> DataFrame:
    """Points in [lo, hi): both sides are cut into bins of `width`, so the join is an equi-join with a test."""
    binned = ranges.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    own = points.withColumn("_bin", F.floor(F.col(value) / width))
    return own.join(binned, "_bin").where((F.col(value) >= F.col(lo)) & (F.col(value) < F.col(hi))).drop("_bin")


def asof_join(left: DataFrame, right: DataFrame, key: str, time: str, id_col: str, bucket_seconds: int = 86400) -> DataFrame:
    """`left` with `matched`: the latest row of `right` of the key at or before its time (ties: larger id).

    Keys are cut into time buckets, so that a hot key spreads; what a bucket's rows may still need from before is
    the last match of earlier buckets, carried over in one row per key and bucket."""
    bucket = F.floor(seconds_of(time) / bucket_seconds)
    both = left.select(key, time, id_col, F.lit(1).alias("_side")).unionByName(right.select(key, time, id_col, F.lit(0).alias("_side"))).withColumn("_bucket", bucket)
    seen = F.when(F.col("_side") == 0, F.col(id_col))
    last = both.where("_side = 0").groupBy(key, "_bucket").agg(F.max(F.struct(time, id_col)).alias("_m"))
    every = both.select(key, "_bucket").distinct().join(last, [key, "_bucket"], "left")
    before = Window.partitionBy(key).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    carry = every.select(key, "_bucket", F.last(F.col(f"_m.{id_col}"), ignorenulls=True).over(before).alias("_carry"))
    w = Window.partitionBy(key, "_bucket").orderBy(time, "_side", F.when(F.col("_side") == 0, F.col(id_col))).rowsBetween(Window.unboundedPreceding, 0)
    matched = both.withColumn("_here", F.last(seen, ignorenulls=True).over(w)).where("_side = 1")
    return matched.join(carry, [key, "_bucket"]).select(key, time, id_col, F.coalesce("_here", "_carry").alias("matched"))


def interval_join(left: DataFrame, right: DataFrame, key: str, time: str, seconds: int) -> DataFrame:
    """Pairs of equal key whose times lie within `seconds` of each other: bins of that width, three for each left row."""
    b = F.floor(seconds_of(time) / seconds)
    own = left.withColumn("_bin", F.explode(F.array(b - 1, b, b + 1)))
    other = right.select(key, F.col(time).alias("_time"), F.col("event_id").alias("other_id"), F.floor(seconds_of(time) / seconds).alias("_bin"))
    gap = F.abs(micros_of("_time") - micros_of(time))
    return own.join(other, [key, "_bin"]).where(gap <= seconds * 1_000_000).drop("_bin", "_time")


def salted_join(large: DataFrame, small: DataFrame, key: str, salts: int) -> DataFrame:
    """An equi-join whose hot keys spread over `salts` parts: the large side gets a hashed salt, the other side all of them."""
    own = large.withColumn("_salt", F.pmod(F.xxhash64(*large.columns, F.monotonically_increasing_id()), F.lit(salts)))
    return own.join(small.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long")))), [key, "_salt"]).drop("_salt")
