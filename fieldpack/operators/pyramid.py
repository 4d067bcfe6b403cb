"""The multiscale pyramid: down, up, residual, compose.

Down keeps the even indices of every halved axis. Up is separable: along an axis an even fine index
reads its coarse value and an odd one the mean of both neighbours (the last odd one without a right
neighbour repeats the left), space first and then time. So down(up(c)) = c.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..spec import AXES, FieldSpec


def downsample(vox: DataFrame, spec: FieldSpec, mode: str = "subsample") -> DataFrame:
    """The next coarser field. `subsample` is a filter without a shuffle; `mean` averages each cell's fine voxels."""
    halved = spec.halved_axes()
    half = {a: F.floor(F.col(a) / 2).cast("int").alias(a) if a in halved else F.col(a) for a in AXES}
    if mode == "mean":
        return vox.groupBy(*half.values()).agg(F.avg("v").alias("v"))
    keep = F.lit(True)
    for a in halved:
        keep = keep & (F.col(a) % 2 == 0)
    return vox.where(keep).select(*half.values(), "v")


def pyramid(vox: DataFrame, spec: FieldSpec) -> DataFrame:
    """All scales at once, with a column `scale`: one scan, each voxel goes to the scales whose stride divides its indices."""
    levels = []
    for scale in range(1, spec.scales + 1):
        stride = {a: 1 << (scale - 1) if a in spec.halved_axes() else 1 for a in AXES}
        for a in stride:  # an axis that has shrunk to extent 1 is not divided further
            while stride[a] > 1 and spec.extents[a] <= stride[a] // 2:
                stride[a] //= 2
        on = F.lit(True)
        for a, s in stride.items():
            on = on & (F.col(a) % s == 0)
        levels.append(F.when(on, F.struct(F.lit(scale).alias("scale"), *[(F.floor(F.col(a) / stride[a])).cast("int").alias(a) for a in AXES], F.col("v").alias("v"))))
    hits = F.filter(F.array(*levels), lambda s: s.isNotNull())
    return vox.select(F.inline(hits))


def _up_axis(vox: DataFrame, axis: str, fine: int) -> DataFrame:
    line = Window.partitionBy(*[a for a in AXES if a != axis]).orderBy(axis)
    nxt = F.coalesce(F.lead("v").over(line), F.col("v"))
    pair = F.array(F.struct((2 * F.col(axis)).cast("int").alias("_at"), F.col("v").alias("_v")), F.struct((2 * F.col(axis) + 1).cast("int").alias("_at"), ((F.col("v") + F.col("_next")) / 2).alias("_v")))
    others = [a for a in AXES if a != axis]
    return vox.withColumn("_next", nxt).select(*others, F.inline(pair)).where(F.col("_at") < fine).select(*others, F.col("_at").alias(axis), F.col("_v").alias("v")).select(*AXES, "v")


def upsample_sparse(vox: DataFrame, fine: FieldSpec, order: tuple[str, ...] = AXES) -> DataFrame:
    """A coarse field with holes on the grid of `fine`: one window pass per halved axis, in `order`. Next to a hole the
    neighbour is the next cell present, so only values that no hole adjoins are those of the dense field."""
    for a in order:
        if a in fine.halved_axes():
            vox = _up_axis(vox, a, fine.extents[a])
    return vox


#: Coarse cells of a tile along each axis: with its halo a tile has at most 9 * 9 * 9 * 5 cells and makes 32,768.
TILE = {"x": 8, "y": 8, "z": 8, "t": 4}


def upsample(vox: DataFrame, fine: FieldSpec, order: tuple[str, ...] = AXES) -> DataFrame:
    """A dense coarse field on the grid of `fine`, axis after axis in `order`.

    One shuffle for all axes: a cell goes to the tiles that read it (its own and, on a tile's first cells, the ones
    before), and a tile is interpolated as one array. A coarse field with a missing or a repeated cell
    is an error: its cells have no place in the array."""
    halved = [a for a in order if a in fine.halved_axes()]
    if not halved:
        return vox.select(*AXES, "v")
    coarse = fine.coarser().extents
    cells = vox.select(*AXES, F.col("v").cast("double").alias("v"))
    for a in AXES:
        own = F.floor(F.col(a) / TILE[a]).cast("int")
        to = F.array(own)
        if a in halved:
            to = F.when((F.col(a) % TILE[a] == 0) & (own > 0), F.array(own - 1, own)).otherwise(to)
        cells = cells.withColumn(f"_t{a}", F.explode(to) if a in halved else own)
    tile = [f"_t{a}" for a in AXES]
    off, grid = F.lit(0), tuple(TILE[a] + 1 for a in AXES)
    for a, m in zip(AXES, grid):
        off = off * m + F.col(a) - F.col(f"_t{a}") * TILE[a]
    # both lists are filled by the same rows in the same order
    got = cells.select(*tile, off.cast("int").alias("at"), F.coalesce("v", F.lit(float("nan"))).alias("v")).groupBy(*tile).agg(F.collect_list("at").alias("at"), F.collect_list("v").alias("v"))
    ends, ups = fine.extents, tuple(AXES.index(a) for a in halved)

    def run(batches):
        for pdf in batches:
            for key, at, v in zip(pdf[tile].to_numpy(), pdf["at"], pdf["v"]):
                first = [int(k) * TILE[a] for k, a in zip(key, AXES)]
                n = [min(coarse[a] - o, TILE[a] + (a in halved)) for o, a in zip(first, AXES)]
                flat = np.ravel_multi_index(np.unravel_index(at, grid), n)
                if len(np.unique(flat)) != len(flat) or len(flat) != np.prod(n):
                    raise ValueError("upsample: the coarse field is not dense")
                box = np.empty(np.prod(n))
                box[flat] = v
                begin = [2 * o if a in halved else o for o, a in zip(first, AXES)]
                shape = tuple(min(ends[a] - o, 2 * TILE[a]) if a in halved else m for o, m, a in zip(begin, n, AXES))
                out = up_array(box.reshape(n), shape, ups)
                where = np.indices(shape).reshape(4, -1)
                yield pd.DataFrame({**{a: (w + o).astype("int32") for a, w, o in zip(AXES, where, begin)}, "v": out.ravel()})

    return got.mapInPandas(run, "x int, y int, z int, t int, v double")


def residual(fine: DataFrame, up: DataFrame) -> DataFrame:
    """fine - up, voxel by voxel."""
    return fine.join(up.withColumnRenamed("v", "_up"), list(AXES)).select(*AXES, (F.col("v") - F.col("_up")).alias("v"))


def compose(up: DataFrame, res: DataFrame) -> DataFrame:
    """up + res; where `res` has no voxel (empty block) it counts as 0."""
    return up.join(res.withColumnRenamed("v", "_res"), list(AXES), "left").select(*AXES, (F.col("v") + F.coalesce("_res", F.lit(0.0))).alias("v"))


def subtract_arrays(a: Column, b: Column) -> Column:
    """Block view: a - b element by element."""
    return F.zip_with(a, b, lambda x, y: x - y)


def add_arrays(a: Column, b: Column) -> Column:
    """Block view: a + b; a missing residual counts as 0."""
    return F.when(b.isNull(), a).otherwise(F.zip_with(a, b, lambda x, y: x + y))


def with_halo(vox: DataFrame, spec: FieldSpec, width: int, axes: tuple[str, ...] = ("x", "y", "z")) -> DataFrame:
    """Voxels for every block that needs them: own voxels and, along `axes`, those up to `width` beyond its faces.

    Columns: block coordinates _bx, _by, _bz, t, and x, y, z, v. A voxel goes to a few blocks; nothing is joined."""
    size = {"x": spec.bx, "y": spec.by, "z": spec.bz}
    count = dict(zip(("x", "y", "z"), spec.blocks_per_axis))
    for a in ("x", "y", "z"):
        reach = width if a in axes else 0
        lo = F.greatest(F.lit(0), F.floor((F.col(a) - reach) / size[a])).cast("int")
        hi = F.least(F.lit(count[a] - 1), F.floor((F.col(a) + reach) / size[a])).cast("int")
        vox = vox.withColumn(f"_b{a}", F.explode(F.sequence(lo, hi)))
    return vox


def closed_loop_gap(original: DataFrame, decoded: DataFrame, res: DataFrame, decoded_res: DataFrame) -> DataFrame:
    """One row: squared error of the field and of the finest residual; in a closed loop both are equal."""
    err = lambda a, b, name: a.join(b.withColumnRenamed("v", "_b"), list(AXES), "left").agg(F.sum((F.col("v") - F.coalesce("_b", F.lit(0.0))) ** 2).alias(name))
    return err(original, decoded, "field_error").crossJoin(err(res, decoded_res, "residual_error"))


# numpy twins on whole arrays, axes in the order x, y, z, t: used inside workers and by tests


def down_array(a: np.ndarray, axes: tuple[int, ...]) -> np.ndarray:
    cut = tuple(slice(None, None, 2) if i in axes else slice(None) for i in range(a.ndim))
    return a[cut]


def up_array(a: np.ndarray, shape: tuple[int, ...], axes: tuple[int, ...]) -> np.ndarray:
    for i in axes:
        nxt = np.concatenate([np.take(a, range(1, a.shape[i]), axis=i), np.take(a, [a.shape[i] - 1], axis=i)], axis=i)
        out = np.stack([a, (a + nxt) / 2], axis=i + 1)
        a = np.take(out.reshape(*a.shape[:i], 2 * a.shape[i], *a.shape[i + 1 :]), range(shape[i]), axis=i)
    return a
