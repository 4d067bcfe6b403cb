"""Truncated higher-order decomposition: a core and one orthonormal factor per axis.

Mode Gram matrices are summed from the tasks' lines (n x n for an axis of n cells, which is small),
their leading eigenvectors are the factors; the core comes from mode products as joins with the
small factor tables. The tolerance is relative to the field's norm.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.stages import keep
from ..spec import AXES, FieldSpec

#: Gram matrices go to the driver: axes may have at most so many cells.
MOST_EXTENT = 4096


@dataclass
class TuckerArchive:
    spec: FieldSpec
    core: DataFrame  # x, y, z, t of the core, v
    factors: dict[str, np.ndarray]
    bytes: float


def gram(vox: DataFrame, axis: str, n: int) -> np.ndarray:
    """Sum over all grid lines along the axis of the line's outer product with itself."""
    if n > MOST_EXTENT:
        raise ValueError(f"axis {axis} has {n} cells")
    lines = vox.groupBy(*[a for a in AXES if a != axis]).agg(F.collect_list(F.struct(F.col(axis).alias("i"), "v")).alias("cells"))

    def run(batches):
        total = np.zeros((n, n))
        for pdf in batches:
            rows = np.zeros((len(pdf), n))
            for k, cells in enumerate(pdf["cells"]):
                for c in cells:
                    rows[k, c["i"]] = c["v"]
            total += rows.T @ rows
        yield pd.DataFrame({"i": np.arange(n), "row": list(total)})

    parts = lines.select("cells").mapInPandas(run, "i int, row array<double>").groupBy("i").agg(*[F.sum(F.get("row", F.lit(j))).alias(f"c{j}") for j in range(n)]).collect()
    out = np.zeros((n, n))
    for r in parts:
        out[r["i"]] = [r[f"c{j}"] for j in range(n)]
    return out


def mode_product(vox: DataFrame, axis: str, matrix: np.ndarray) -> DataFrame:
    """Replaces the axis by matrix @ axis: (rows of the matrix) new cells."""
    rows = [(int(j), [float(x) for x in matrix[:, j]]) for j in range(matrix.shape[1])]
    table = vox.sparkSession.createDataFrame(rows, f"{axis} int, _col array<double>")
    others = [a for a in AXES if a != axis]
    out = vox.join(F.broadcast(table), axis).select(*others, "v", F.posexplode("_col").alias("_new", "_w"))
    return out.groupBy(*others, F.col("_new").cast("int").alias(axis)).agg(F.sum(F.col("v") * F.col("_w")).alias("v")).select(*AXES, "v")


def tucker_encode(vox: DataFrame, spec: FieldSpec, tol: float) -> TuckerArchive:
    """Each axis may lose a quarter of the squared tolerance."""
    now = keep(vox.select(*AXES, F.col("v").cast("double").alias("v")), "tucker")
    norm2 = now.agg(F.sum(F.col("v") * F.col("v"))).first()[0] or 0.0
    factors: dict[str, np.ndarray] = {}
    for a in AXES:
        n = spec.extents[a]
        if n == 1:
            factors[a] = np.ones((1, 1))
            continue
        values, vectors = np.linalg.eigh(gram(now, a, n))
        order = np.argsort(values)[::-1]
        values, vectors = np.maximum(values[order], 0), vectors[:, order]
        tail = np.concatenate([np.cumsum(values[::-1])[::-1], [0.0]])
        rank = max(1, int(np.argmax(tail <= tol * tol * norm2 / 4)))
        factors[a] = vectors[:, :rank]
        now = keep(mode_product(now, a, factors[a].T), "tucker")
    size = 4.0 * (np.prod([f.shape[1] for f in factors.values()]) + sum(f.size for f in factors.values())) + 64
    return TuckerArchive(spec, now, factors, float(size))


def tucker_decode(archive: TuckerArchive) -> DataFrame:
    now = archive.core
    for a in AXES:
        if archive.spec.extents[a] > 1:
            now = mode_product(now, a, archive.factors[a])
    return now
