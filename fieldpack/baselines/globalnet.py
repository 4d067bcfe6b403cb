"""One coordinate network for a whole 4D field, and a trainable coarse grid.

Both train data-parallel: the driver holds the parameters (small), every step sums gradients of a
deterministic sample of voxels over the tasks. Evaluation is not part of the training time.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.metrics import avg_psnr
from ..operators.sinenet import Adam, NetSpec, backward, forward, init_params, width_for_bytes
from ..plans.stages import keep
from ..spec import AXES, FieldSpec


@dataclass
class GlobalArchive:
    spec: FieldSpec
    net: NetSpec
    theta: np.ndarray
    seconds: float = 0.0
    history: list[tuple[int, float]] = field(default_factory=list)

    @property
    def bytes(self) -> float:
        return 4.0 * len(self.theta) + 64


def match_width(spec: FieldSpec, target_cr: float, depth: int = 8) -> int:
    """The width whose parameters give the compression rate."""
    return width_for_bytes(spec.raw_bytes / target_cr, depth)


def _inputs(pdf: pd.DataFrame, spec: FieldSpec) -> np.ndarray:
    return np.stack([2 * pdf[a].to_numpy() / max(1, n - 1) - 1 for a, n in spec.extents.items()], axis=1)


def global_encode(vox: DataFrame, spec: FieldSpec, hidden: int, depth: int = 3, iterations: int = 100, sample: float = 0.1, rate: float = 1e-4, target_psnr: float | None = None, check_every: int = 50, seed: int = 0) -> GlobalArchive:
    """Random voxels each step (a hash of place and step decides, so reruns agree); stops at a target PSNR where one is given."""
    net = NetSpec(hidden=hidden, depth=depth, latent_dim=0, coords=4)
    theta, data = init_params(net, 0, 0, seed), keep(vox.select(*AXES, "v"), "global")
    adam, out = Adam(len(theta), decay=0.0), GlobalArchive(spec, net, theta)
    for step in range(iterations):
        began = time.perf_counter()
        chosen = data.where(F.pmod(F.xxhash64(*AXES, F.lit(step + seed * 7919)), F.lit(1_000_000)) < int(sample * 1_000_000))
        now = theta

        def run(batches, now=now):
            g, n = np.zeros(len(now)), 0
            for pdf in batches:
                if not len(pdf):
                    continue
                kept: list = []
                e = forward(net, now, _inputs(pdf, spec), kept) - pdf["v"].to_numpy()
                g += backward(net, now, kept, 2 * e)[0]
                n += len(pdf)
            yield pd.DataFrame({"g": [g], "n": [n]})

        rows = chosen.mapInPandas(run, "g array<double>, n long").collect()
        n = sum(r["n"] for r in rows)
        if n:
            theta = adam.step(theta, np.sum([r["g"] for r in rows], axis=0) / n, rate)
        out.theta, out.seconds = theta, out.seconds + time.perf_counter() - began
        if (step + 1) % check_every == 0 or step + 1 == iterations:
            value = avg_psnr(data, global_decode(out, data)).first()[0]
            out.history.append((step + 1, value))
            if target_psnr is not None and value >= target_psnr:
                break
    return out


def global_decode(archive: GlobalArchive, grid: DataFrame) -> DataFrame:
    """The decoded field on the cells of `grid`."""
    net, theta, spec = archive.net, archive.theta, archive.spec

    def run(batches):
        for pdf in batches:
            yield pd.DataFrame({**{a: pdf[a].astype("int32") for a in AXES}, "v": forward(net, theta, _inputs(pdf, spec)) if len(pdf) else np.empty(0)})

    return grid.select(*AXES).mapInPandas(run, "x int, y int, z int, t int, v double")


def grid_encode(vox: DataFrame, spec: FieldSpec, levels: int = 1) -> tuple[DataFrame, float]:
    """A stand-in for feature grids: the field's means on a grid halved `levels` times, read back by interpolation.
    Returns the decoded field and its bytes."""
    from ..operators.pyramid import downsample, upsample

    specs, now = [spec], vox
    for _ in range(levels):
        now = downsample(now, specs[-1], "mean")
        specs.append(specs[-1].coarser())
    size = 4.0 * specs[-1].voxels + 64
    for s in reversed(specs[:-1]):
        now = upsample(now, s)
    return now, size
