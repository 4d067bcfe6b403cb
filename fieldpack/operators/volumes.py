"""The volumes that stand for the experiments' data, made from the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import load
from ..spec import F1, F2, F3, F4, F5, F7, F8, FieldSpec
from .grid import cents, densify, prefix_cube, rasterize


def lineitem_axes() -> dict:
    return {
        "x": F.col("l_partkey") % 16, "y": F.col("l_suppkey") % 8, "z": F.floor((F.col("l_quantity") - 1) * 8 / 50),
        "t": 4 * (F.year("l_shipdate") - 1995) + F.quarter("l_shipdate") - 1,
    }


def event_axes() -> dict:
    k = F.get_json_object("props", "$.k").cast("int")
    return {"x": F.col("user_id") % 16, "y": F.hour("ts"), "z": F.floor(k * 8 / 100), "t": F.datediff("ts", F.lit("2024-01-01"))}


def lineitem_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """x, y, z, t, v (cents, long), n: sparse."""
    df = load(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_shipdate")
    return rasterize(df, lineitem_axes(), cents("l_extendedprice"), "sum", "n")


def event_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = load(spark, sf_dir, "events", "user_id", "ts", "props", "value")
    return rasterize(df, event_axes(), cents("value"), "sum", "n")


def volume(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, FieldSpec]:
    """A dense volume (x, y, z, t, v double) by its name, and its spec."""
    if name == "f1":
        cells = lineitem_cells(spark, sf_dir).select("x", "y", "z", "t", (F.col("v") / F.col("n") / 100).alias("v"))
        return densify(cells, F1, 0.0), F1
    if name == "f2":
        return densify(event_cells(spark, sf_dir).withColumn("v", F.col("v") / 100), F2, 0.0), F2
    if name in ("f3", "f4", "f5"):
        spec, m = (F4, 16) if name == "f4" else (F3 if name == "f3" else F5, 64)
        df = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_extendedprice")
        cells = rasterize(df, {"x": F.col("l_partkey") % m, "y": F.col("l_suppkey") % m, "z": F.col("l_orderkey") % m}, cents("l_extendedprice"), "sum", "n")
        return densify(cells.select("x", "y", "z", "t", (F.col("v") / F.col("n") / 100).alias("v")), spec, 0.0), spec
    if name == "f6":
        return embedding_volume(spark, sf_dir)
    if name == "f7":
        d = load(spark, sf_dir, "documents", "lang", "source", "n_chars")
        lang = F.array_position(F.array(*[F.lit(x) for x in ("de", "en", "es", "fr")]), F.col("lang")) - 1
        size = F.least(F.lit(15), F.length(F.bin("n_chars")) - 1)
        cells = rasterize(d.where(lang >= 0), {"x": lang, "y": F.substring("source", 4, 10).cast("int"), "z": size}, F.lit(1), "count")
        return densify(cells.withColumn("v", F.col("v").cast("double")), F7, 0.0), F7
    if name == "f8":
        d = load(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text")
        role = F.array_position(F.array(*[F.lit(x) for x in ("assistant", "system", "user")]), F.col("role")) - 1
        cells = rasterize(d.where((role >= 0) & (F.col("turn") < 8)), {"x": F.col("conv_id") % 8, "y": role, "z": F.least(F.lit(7), F.floor(F.length("text") / 256)), "t": F.col("turn")}, F.lit(1), "count")
        return densify(cells.withColumn("v", F.col("v").cast("double")), F8, 0.0), F8
    if name in ("f9", "f10"):
        cells, spec = (lineitem_cells(spark, sf_dir), F1) if name == "f9" else (event_cells(spark, sf_dir), F2)
        return prefix_cube(densify(cells.select("x", "y", "z", "t", "v"), spec, 0)).withColumn("v", F.col("v").cast("double")), spec
    raise ValueError(f"unknown volume {name}")


def embedding_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every embedding is one 4x4x4 block: block_id, values."""
    return load(spark, sf_dir, "embeddings", "vec_id", "embedding").select(F.col("vec_id").alias("block_id"), F.transform("embedding", lambda x: x.cast("double")).alias("values"))


def embedding_volume(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, FieldSpec]:
    """Blocks laid out in slabs of 8 x 8 (16 x 16 where there are more than 512), row-major inside."""
    blocks = embedding_blocks(spark, sf_dir)
    n = blocks.agg(F.max("block_id")).first()[0]
    side, depth = (8, 8) if n is None or n < 512 else (16, -(-(n + 1) // 256))
    spec = FieldSpec(4 * side, 4 * side, 4 * depth, 1, 4, 4, 4, 3)
    b, p = F.col("block_id"), F.col("p")
    vox = blocks.select("block_id", F.posexplode("values").alias("p", "v")).select(
        ((b % side) * 4 + F.floor(p / 16)).cast("int").alias("x"), ((F.floor(b / side) % side) * 4 + F.floor(p / 4) % 4).cast("int").alias("y"),
        (F.floor(b / (side * side)) * 4 + p % 4).cast("int").alias("z"), F.lit(0).alias("t"), "v",
    )
    return densify(vox, spec, 0.0), spec
