"""Error-bounded interpolating coder: odd samples are predicted from reconstructed even ones, level by level.

The coarsest grid is stored on a step of twice the error bound. On the way up, along one axis at a
time, odd samples are predicted by linear or cubic interpolation of reconstructed even neighbours;
what the prediction misses is stored as a whole number of steps, so no value is off by more than
the bound. Each axis is one window pass; a grid line is never gathered across partitions.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..operators import entropy as E
from ..plans.stages import keep
from ..spec import AXES, FieldSpec


@dataclass
class SplineArchive:
    spec: FieldSpec
    eps: float
    levels: int
    kind: str
    codes: DataFrame  # x, y, z, t of the finest grid, step (long)
    bytes: float = 0.0


def quantized(miss: Column, eps: float) -> Column:
    return F.round(miss / (2 * eps)).cast("long")


def strides(spec: FieldSpec, levels: int) -> list[tuple[str, int]]:
    """(axis, stride) of the passes from coarse to fine."""
    return [(a, 1 << level) for level in range(levels - 1, -1, -1) for a in AXES if spec.extents[a] > (1 << level)]


def _prediction(axis: str, stride: int, kind: str, known: str = "rec") -> Column:
    """From the neighbours one (and for cubic three) strides away on the line, all of them already known."""
    line = Window.partitionBy(*[a for a in AXES if a != axis]).orderBy(axis)
    at = lambda k: (F.lag(known, -k) if k < 0 else F.lag(known, k)).over(line) if k >= 0 else F.lead(known, -k).over(line)
    l1, r1 = at(1), at(-1)
    linear = F.when(r1.isNull(), l1).otherwise((l1 + r1) / 2)
    if kind == "linear":
        return linear
    l3, r3 = at(3), at(-3)
    cubic = (-l3 + 9 * l1 + 9 * r1 - r3) / 16
    return F.when(l3.isNull() | r3.isNull() | r1.isNull(), linear).otherwise(cubic)


def _on_grid(spec: FieldSpec, done: dict[str, int]) -> Column:
    keep_if = F.lit(True)
    for a, s in done.items():
        keep_if = keep_if & (F.col(a) % s == 0)
    return keep_if


def _passes(vox: DataFrame, spec: FieldSpec, levels: int, eps: float, kind: str, code: str | None) -> DataFrame:
    """Runs the passes over x, y, z, t, v (or `code`): adds rec and step to all voxels reached."""
    top = 1 << levels
    done = {a: (top if n > 1 else 1) for a, n in spec.extents.items()}
    first = _on_grid(spec, done)
    step = F.col(code) if code else quantized(F.col("v"), eps)
    now = vox.where(first).withColumn("step", step).withColumn("rec", F.col("step") * (2 * eps))
    for a, stride in strides(spec, levels):
        done[a] = stride
        here = vox.where(_on_grid(spec, done)).join(now.select(*AXES, F.col("rec").alias("_rec"), F.col("step").alias("_step")), list(AXES), "left")
        guess = here.withColumn("_guess", _prediction(a, stride, kind, "_rec"))
        odd = F.col(a) % (2 * stride) == stride
        miss = F.col(code) if code else quantized(F.col("v") - F.col("_guess"), eps)
        now = guess.withColumn("step", F.when(odd, miss).otherwise(F.col("_step"))).withColumn("rec", F.when(odd, F.col("_guess") + F.col("step") * (2 * eps)).otherwise(F.col("_rec"))).select(*vox.columns, "step", "rec")
        now = keep(now, "spline")
    return now


def spline_encode(vox: DataFrame, spec: FieldSpec, eps: float, levels: int = 3, kind: str = "cubic") -> SplineArchive:
    done = keep(_passes(vox, spec, levels, eps, kind, None).select(*AXES, "step"), "spline-codes")
    freq = E.symbol_freq(done.select(F.greatest(F.lit(-2**31), F.least(F.lit(2**31 - 1), F.col("step"))).alias("code")))
    bits = E.entropy(freq).first()
    size = bits["total"] * bits["entropy"] / 8 + 5.0 * bits["symbols"] + 64 if bits else 64.0
    return SplineArchive(spec, eps, levels, kind, done, float(size))


def spline_decode(archive: SplineArchive) -> DataFrame:
    got = _passes(archive.codes.withColumnRenamed("step", "c"), archive.spec, archive.levels, archive.eps, archive.kind, "c")
    return got.select(*AXES, F.col("rec").alias("v"))
