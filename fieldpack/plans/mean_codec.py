"""The multiscale codec with one mean per block in place of networks: the whole loop in SQL terms.

Coarsest scale: every block's mean is the decoded field. Every finer scale: the residual against the
up-sampled decoded coarser field; blocks whose residual energy is below tau are dropped, the others
keep their mean. With `keep="exact"` a kept block keeps all its values (lossless where tau is 0).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.blocks import block_of
from ..operators.pyramid import compose, downsample, residual, upsample
from ..spec import AXES, FieldSpec


@dataclass
class Level:
    scale: int
    spec: FieldSpec
    target: DataFrame  # what the scale encodes: the field itself or a residual
    blocks: DataFrame  # block_id, energy, mean, effective
    decoded: DataFrame  # the field up to this scale


def encode_levels(vox: DataFrame, spec: FieldSpec, tau: float = 1e-2, loop: str = "closed", keep: str = "mean", stage=lambda df, name: df) -> list[Level]:
    """Levels from the coarsest scale to the finest. `stage` may write and reread a table between scales."""
    specs = [spec]
    fields = [vox]
    for _ in range(spec.scales - 1):
        fields.append(downsample(fields[-1], specs[-1]))
        specs.append(specs[-1].coarser())
    out: list[Level] = []
    for scale in range(spec.scales, 0, -1):
        s, field = specs[scale - 1], fields[scale - 1]
        coarsest = scale == spec.scales
        if coarsest:
            target, up = field, None
        else:
            base = out[-1].decoded if loop == "closed" else fields[scale]
            target = residual(field, upsample(base, s))
            up = upsample(out[-1].decoded, s)
        cells = target.withColumn("block_id", block_of(s))
        blocks = cells.groupBy("block_id").agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("energy"), F.avg("v").alias("mean"), F.count("*").alias("valid"))
        blocks = stage(blocks.withColumn("effective", F.lit(True) if coarsest else F.col("energy") >= tau), f"blocks-{scale}")
        kept = cells.join(blocks.where("effective").select("block_id", "mean"), "block_id").select(*AXES, (F.col("mean") if keep == "mean" else F.col("v")).alias("v"))
        decoded = stage(kept if up is None else compose(up, kept), f"decoded-{scale}")
        out.append(Level(scale, s, target, blocks, decoded))
    return out


def archive_bytes(levels: list[Level], header: int = 64) -> DataFrame:
    """scale, blocks, effective, bytes: 4 for each stored mean, 8 for each 64-block word of the bitmap; the header counts at the coarsest."""
    out = None
    for lv in levels:
        row = lv.blocks.agg(F.count("*").alias("blocks"), F.coalesce(F.sum(F.col("effective").cast("long")), F.lit(0)).alias("effective"))
        row = row.select(F.lit(lv.scale).alias("scale"), "blocks", "effective", (F.col("effective") * 4 + 8 * F.ceil(F.col("blocks") / 64) + (header if lv is levels[0] else 0)).cast("long").alias("bytes"))
        out = row if out is None else out.unionByName(row)
    return out
