"""From tables to 4D fields: gridding, densifying, normalising, prefix-sum cubes, id codecs, analytic fields."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..spec import AXES, FieldSpec

AGGREGATES = {"avg": F.avg, "sum": F.sum, "count": F.count, "max": F.max, "min": F.min}


def cents(col: Column | str) -> Column:
    """A money column as whole cents, so that sums are exact in any order."""
    return F.round((F.col(col) if isinstance(col, str) else col) * 100).cast("long")


def rasterize(df: DataFrame, axes: dict[str, Column], value: Column, agg: str = "avg", count_as: str | None = None) -> DataFrame:
    """Rows to sparse voxels (x, y, z, t, v): one partial aggregate per task, one shuffle of filled cells."""
    keys = [axes.get(a, F.lit(0)).cast("int").alias(a) for a in AXES]
    out = [AGGREGATES[agg]("_value").alias("v")] + ([F.count("*").alias(count_as)] if count_as else [])
    return df.select(*keys, value.alias("_value")).groupBy(*AXES).agg(*out)


def rasterize_many(df: DataFrame, axes: dict[str, Column], values: dict[str, Column], agg: str = "avg") -> DataFrame:
    """A multivariate field: voxels with a further column `var`."""
    keys = [axes.get(a, F.lit(0)).cast("int").alias(a) for a in AXES]
    wide = df.select(*keys, *[c.alias(f"_{n}") for n, c in values.items()]).groupBy(*AXES).agg(*[AGGREGATES[agg](f"_{n}").alias(n) for n in values])
    return wide.unpivot(list(AXES), list(values), "var", "v").where("v IS NOT NULL")


def grid_index(spark: SparkSession, spec: FieldSpec) -> DataFrame:
    """All cells of a spec, made where they are used: no data is read."""
    i = F.col("id")
    cell = spark.range(spec.voxels)
    return cell.select(
        (i % spec.nx).cast("int").alias("x"), (F.floor(i / spec.nx) % spec.ny).cast("int").alias("y"),
        (F.floor(i / (spec.nx * spec.ny)) % spec.nz).cast("int").alias("z"), F.floor(i / (spec.nx * spec.ny * spec.nz)).cast("int").alias("t"),
    )


def densify(vox: DataFrame, spec: FieldSpec, fill: float | int = 0) -> DataFrame:
    """Every cell of the spec; cells without a value (or with NaN) get `fill`."""
    value = F.when(F.isnan(F.col("v").cast("double")), None).otherwise(F.col("v"))
    return grid_index(vox.sparkSession, spec).join(vox.select(*AXES, value.alias("v")), list(AXES), "left").select(*AXES, F.coalesce("v", F.lit(fill).cast(dict(vox.dtypes)["v"])).alias("v"))


def value_range(vox: DataFrame) -> DataFrame:
    """One row: lo and hi of the field."""
    return vox.agg(F.min("v").cast("double").alias("lo"), F.max("v").cast("double").alias("hi"))


def normalize(vox: DataFrame, bounds: DataFrame | None = None) -> DataFrame:
    """Values into [-1, 1]; a constant field becomes 0. The one-row range is broadcast."""
    bounds = value_range(vox) if bounds is None else bounds
    span = F.col("hi") - F.col("lo")
    return vox.crossJoin(F.broadcast(bounds)).select(*AXES, F.when(span > 0, 2 * (F.col("v").cast("double") - F.col("lo")) / span - 1).otherwise(F.lit(0.0)).alias("v"))


def denormalize(vox: DataFrame, bounds: DataFrame) -> DataFrame:
    return vox.crossJoin(F.broadcast(bounds)).select(*AXES, ((F.col("v") + 1) / 2 * (F.col("hi") - F.col("lo")) + F.col("lo")).alias("v"))


def prefix_cube(vox: DataFrame, axes: tuple[str, ...] = AXES) -> DataFrame:
    """Running sums along each axis in turn: a smooth field from any dense one. A window holds one grid line only."""
    for a in axes:
        line = Window.partitionBy(*[b for b in AXES if b != a]).orderBy(a).rowsBetween(Window.unboundedPreceding, 0)
        vox = vox.withColumn("v", F.sum("v").over(line))
    return vox


def crop_time(vox: DataFrame, first: int, last: int) -> DataFrame:
    """Timesteps first..last-1, counted from 0 again."""
    return vox.where((F.col("t") >= first) & (F.col("t") < last)).withColumn("t", (F.col("t") - first).cast("int"))


def block_id(spec: FieldSpec, t: Column, bx: Column, by: Column, bz: Column) -> Column:
    """Row-major number of a block within its scale."""
    gx, gy, gz = spec.blocks_per_axis
    return (((t.cast("long") * gz + bz) * gy + by) * gx + bx).cast("long")


def block_coords(spec: FieldSpec, block: Column) -> dict[str, Column]:
    """The inverse of `block_id`."""
    gx, gy, gz = spec.blocks_per_axis
    return {
        "bx": (block % gx).cast("int"), "by": (F.floor(block / gx) % gy).cast("int"),
        "bz": (F.floor(block / (gx * gy)) % gz).cast("int"), "t": F.floor(block / (gx * gy * gz)).cast("int"),
    }


def morton3(x: Column, y: Column, z: Column, bits: int = 10) -> Column:
    """Interleaved bits of three coordinates: neighbours in space stay close in the order."""
    out = F.lit(0).cast("long")
    for b in range(bits):
        for k, c in enumerate((x, y, z)):
            bit = F.shiftright(c.cast("long"), b).bitwiseAND(F.lit(1).cast("long"))
            out = out.bitwiseOR(F.shiftleft(bit, 3 * b + k))
    return out


def analytic_field(spark: SparkSession, spec: FieldSpec, kind: str = "blobs", cells: DataFrame | None = None) -> DataFrame:
    """Closed-form smooth fields: three moving blobs over a slow sine, or a plane wave, or a constant; at every cell
    of the spec or at the given ones (x, y, z, t and whatever else rides along)."""
    g = grid_index(spark, spec) if cells is None else cells
    unit = {a: F.col(a) / float(max(1, n - 1)) for a, n in spec.extents.items()}
    if kind == "constant":
        return g.withColumn("v", F.lit(0.5))
    if kind == "wave":
        return g.withColumn("v", F.sin(6.0 * unit["x"] + 4.0 * unit["y"] + 2.0 * unit["z"] + 3.0 * unit["t"]))
    if kind != "blobs":
        raise ValueError(f"unknown field {kind}")

    def blob(cx: float, cy: float, cz: float, dx: float, dy: float, width: float) -> Column:
        a, b, c = unit["x"] - (F.lit(cx) + dx * unit["t"]), unit["y"] - (F.lit(cy) + dy * unit["t"]), unit["z"] - cz
        return F.exp(-(a * a + b * b + c * c) / width)

    value = blob(0.25, 0.3, 0.4, 0.3, 0.1, 0.02) + 0.8 * blob(0.7, 0.6, 0.5, -0.2, 0.15, 0.03) - 0.6 * blob(0.5, 0.2, 0.7, 0.05, 0.4, 0.04)
    return g.withColumn("v", value + 0.2 * F.sin(3.0 * unit["x"] + 2.0 * unit["t"]))
