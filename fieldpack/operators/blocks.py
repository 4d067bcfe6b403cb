"""Blocks of one timestep: packing, unpacking, energies, discarding, bitmaps, seams."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..spec import AXES, FieldSpec
from .grid import block_coords, block_id

ENERGIES = ("l2", "rms", "mse")


def block_of(spec: FieldSpec) -> Column:
    b = {a: F.floor(F.col(a) / n).cast("int") for a, n in (("x", spec.bx), ("y", spec.by), ("z", spec.bz))}
    return block_id(spec, F.col("t"), b["x"], b["y"], b["z"])


def offset_in_block(spec: FieldSpec) -> Column:
    """Row-major position (x slowest) within the block."""
    return ((F.col("x") % spec.bx) * spec.by + F.col("y") % spec.by) * spec.bz + F.col("z") % spec.bz


def pack_blocks(vox: DataFrame, spec: FieldSpec) -> DataFrame:
    """Block rows: block_id, t, bx, by, bz, values (full blocks; missing cells repeat the block's first value), valid.

    A group is one block, so its size is the block's, whatever the field's."""
    cells = vox.select(block_of(spec).alias("block_id"), offset_in_block(spec).cast("int").alias("off"), "v")
    got = cells.groupBy("block_id").agg(F.array_sort(F.collect_list(F.struct("off", "v"))).alias("cells"))
    m = F.map_from_entries("cells")
    values = F.transform(F.sequence(F.lit(0), F.lit(spec.block_voxels - 1)), lambda i: F.coalesce(F.element_at(m, i), F.col("cells")[0]["v"]))
    full = F.transform("cells", lambda c: c["v"])
    packed = got.select("block_id", F.when(F.size("cells") == spec.block_voxels, full).otherwise(values).alias("values"), F.size("cells").alias("valid"))
    return packed.select("block_id", *[c.alias(k) for k, c in block_coords(spec, F.col("block_id")).items()], "values", "valid")


def unpack_blocks(blocks: DataFrame, spec: FieldSpec) -> DataFrame:
    """Voxels of block rows: a generator, no shuffle. Cells beyond the field are dropped."""
    c = block_coords(spec, F.col("block_id"))
    cells = blocks.select("block_id", F.posexplode("values").alias("p", "v"))
    out = cells.select(
        (c["bx"] * spec.bx + F.floor(F.col("p") / (spec.by * spec.bz))).cast("int").alias("x"),
        (c["by"] * spec.by + F.floor(F.col("p") / spec.bz) % spec.by).cast("int").alias("y"),
        (c["bz"] * spec.bz + F.col("p") % spec.bz).cast("int").alias("z"), c["t"].alias("t"), "v",
    )
    return out.where((F.col("x") < spec.nx) & (F.col("y") < spec.ny) & (F.col("z") < spec.nz))


def _energy(total: Column, n: Column, kind: str) -> Column:
    return {"l2": F.sqrt(total), "rms": F.sqrt(total / n), "mse": total / n}[kind]


def block_energy(vox: DataFrame, spec: FieldSpec, kind: str = "l2") -> DataFrame:
    """Voxel view to (block_id, energy): partial sums per task, so one row per block is shuffled."""
    return vox.groupBy(block_of(spec).alias("block_id")).agg(_energy(F.sum(F.col("v") * F.col("v")), F.count("*"), kind).alias("energy"))


def values_energy(values: Column, kind: str = "l2", valid: Column | None = None) -> Column:
    """Block view: energy of an array column, without Python."""
    total = F.aggregate(values, F.lit(0.0), lambda a, v: a + v * v)
    return _energy(total, F.size(values) if valid is None else valid, kind)


def effective(blocks: DataFrame, tau: float = 1e-4, kind: str = "l2", coarsest: bool = False) -> DataFrame:
    """Block rows that are kept: energy at or above tau. At the coarsest scale all are."""
    return blocks if coarsest else blocks.where(values_energy(F.col("values"), kind) >= tau)


def effective_profile(energies: DataFrame, tau: float, keep_scale: int | None = None) -> DataFrame:
    """scale, blocks, effective, discarded share; `energies` has scale and energy."""
    live = F.when(F.col("scale") == (keep_scale if keep_scale is not None else -1), True).otherwise(F.col("energy") >= tau)
    return energies.groupBy("scale").agg(F.count("*").alias("blocks"), F.sum(live.cast("long")).alias("effective")).withColumn("discarded", 1 - F.col("effective") / F.col("blocks"))


def empty_bitmap(flags: DataFrame) -> DataFrame:
    """scale, word, bits: bit i of a 64-block word is set where block 64*word+i is effective (columns scale, block_id, effective)."""
    bit = F.expr("shiftleft(1L, cast(block_id % 64 as int))")
    return flags.groupBy("scale", F.floor(F.col("block_id") / 64).alias("word")).agg(F.bit_or(F.when(F.col("effective"), bit).otherwise(F.lit(0).cast("long"))).alias("bits"))


def seam_ratio(vox: DataFrame, spec: FieldSpec) -> DataFrame:
    """axis, seam, inner, ratio: mean absolute step across block faces over that inside blocks."""
    out = None
    for a, size in (("x", spec.bx), ("y", spec.by), ("z", spec.bz)):
        line = Window.partitionBy(*[b for b in AXES if b != a]).orderBy(a)
        step = vox.withColumn("_d", F.abs(F.lead("v").over(line) - F.col("v"))).where("_d IS NOT NULL")
        face = F.col(a) % size == size - 1
        row = step.agg(F.avg(F.when(face, F.col("_d"))).alias("seam"), F.avg(F.when(~face, F.col("_d"))).alias("inner")).select(F.lit(a).alias("axis"), "seam", "inner", (F.col("seam") / F.col("inner")).alias("ratio"))
        out = row if out is None else out.unionByName(row)
    return out


def box_hierarchy(flags: DataFrame, spec: FieldSpec, factor: int = 2) -> DataFrame:
    """Bounding boxes of effective blocks inside cells of factor^3 blocks: a stratum for sampling."""
    c = block_coords(spec, F.col("block_id"))
    live = flags.where("effective").select(c["t"].alias("t"), *[c[k].alias(k) for k in ("bx", "by", "bz")])
    parent = [F.floor(F.col(k) / factor).cast("int").alias(f"p{k[1]}") for k in ("bx", "by", "bz")]
    return live.groupBy("t", *parent).agg(F.count("*").alias("n"), *[f(k).alias(f"{n}_{k}") for k in ("bx", "by", "bz") for n, f in (("lo", F.min), ("hi", F.max))])
