"""A light convolution network that smooths block seams of the decoded finest scale."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..spec import AXES, FieldSpec
from .pyramid import with_halo
from .quant import lloyd_1d
from .sinenet import Adam


@dataclass
class SeamNet:
    """`layers` 3x3x3 convolutions of `channels` channels, without skips; one value in, one out."""

    layers: int = 5
    channels: int = 32
    epochs: int = 100
    rate: float = 1e-5
    bits: int = 9
    seed: int = 1
    tiles: int = 256  # bound of the training tiles (blocks), by hash of the block
    theta: np.ndarray | None = field(default=None, repr=False)

    @property
    def shapes(self) -> list[tuple[int, int]]:
        c = [1] + [self.channels] * (self.layers - 1) + [1]
        return list(zip(c, c[1:]))

    @property
    def parameters(self) -> int:
        return sum(27 * a * b + b for a, b in self.shapes)

    @property
    def bytes(self) -> int:
        return -(-self.parameters * self.bits // 8) + 4 * (1 << self.bits)

    def split(self, theta: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
        out, at = [], 0
        for a, b in self.shapes:
            n = 27 * a * b
            out.append((theta[at : at + n].reshape(27, a, b), theta[at + n : at + n + b]))
            at += n + b
        return out

    def start(self) -> np.ndarray:
        """Close to passing its input on: the first channel carries it, the others start small."""
        rng = np.random.default_rng(self.seed)
        parts = []
        for a, b in self.shapes:
            w = rng.normal(0, 0.02 * np.sqrt(2 / (27 * a)), (27, a, b))
            w[13, 0, 0] = 1.0
            if b > 1:
                w[13, 0, 1] = -1.0
            if a > 1:
                w[13, 1, 0] = -1.0 if b == 1 else 0.0
                if b > 1:
                    w[13, 1, 1], w[13, 0, 1], w[13, 1, 0] = 1.0, 0.0, 0.0
            parts += [w.ravel(), np.zeros(b)]
        return np.concatenate(parts)

    def state(self) -> dict:
        return {**{k: getattr(self, k) for k in ("layers", "channels", "epochs", "rate", "bits", "seed", "tiles")}, "theta": None if self.theta is None else self.theta.tolist()}

    @staticmethod
    def from_state(state: dict) -> SeamNet:
        theta = state.pop("theta")
        return SeamNet(**state, theta=None if theta is None else np.array(theta))


def _shifts() -> list[tuple[int, int, int]]:
    return [(i, j, k) for i in range(3) for j in range(3) for k in range(3)]


def convolve(net: SeamNet, theta: np.ndarray, tile: np.ndarray, inside: np.ndarray, keep: list | None = None) -> np.ndarray:
    """Output of the size of `tile` (zero padding). `inside` marks cells of the field: others are 0 after every layer,
    so a tile with a wide enough halo gives what the whole volume gives."""
    h = (tile * inside)[..., None]
    parts = net.split(theta)
    for layer, (w, b) in enumerate(parts):
        p = np.pad(h, ((1, 1), (1, 1), (1, 1), (0, 0)))
        nx, ny, nz = h.shape[:3]
        a = np.zeros((nx, ny, nz, w.shape[2]))
        for s, (i, j, k) in enumerate(_shifts()):
            a += p[i : i + nx, j : j + ny, k : k + nz] @ w[s]
        a = (a + b) * inside[..., None]
        if keep is not None:
            keep.append((p, a))
        h = np.maximum(a, 0) if layer + 1 < len(parts) else a
    return h[..., 0]


def convolve_gradient(net: SeamNet, theta: np.ndarray, kept: list, inside: np.ndarray, d: np.ndarray) -> np.ndarray:
    parts, out = net.split(theta), []
    d = d[..., None]
    for layer in range(len(parts) - 1, -1, -1):
        w, _ = parts[layer]
        p, a = kept[layer]
        if layer + 1 < len(parts):
            d = d * (a > 0)
        d = d * inside[..., None]
        nx, ny, nz = a.shape[:3]
        gw = np.stack([np.einsum("xyza,xyzb->ab", p[i : i + nx, j : j + ny, k : k + nz], d) for i, j, k in _shifts()])
        out.append(np.concatenate([gw.ravel(), d.sum(axis=(0, 1, 2))]))
        dp = np.zeros_like(p)
        for s, (i, j, k) in enumerate(_shifts()):
            dp[i : i + nx, j : j + ny, k : k + nz] += d @ w[s].T
        d = dp[1:-1, 1:-1, 1:-1]
    return np.concatenate(out[::-1])


def _tile(pdf: pd.DataFrame, spec: FieldSpec, width: int, cols: list[str]) -> tuple[list[np.ndarray], np.ndarray, tuple[slice, ...], tuple[int, ...]]:
    """Arrays of a block with its halo, the cells inside the field, and where the block lies in them."""
    lo = [int(pdf[f"_b{a}"].iloc[0]) * n - width for a, n in (("x", spec.bx), ("y", spec.by), ("z", spec.bz))]
    shape = tuple(n + 2 * width for n in (spec.bx, spec.by, spec.bz))
    at = tuple(pdf[a].to_numpy() - o for a, o in zip("xyz", lo))
    out = []
    for c in cols:
        arr = np.zeros(shape)
        arr[at] = pdf[c].to_numpy()
        out.append(arr)
    inside = np.zeros(shape)
    inside[at] = 1
    core = tuple(slice(width, width + n) for n in (spec.bx, spec.by, spec.bz))
    return out, inside, core, tuple(lo)


KEYS = ["t", "_bx", "_by", "_bz"]


def apply_seam(vox: DataFrame, spec: FieldSpec, net: SeamNet) -> DataFrame:
    """The smoothed field: every block with a halo of one cell per layer; a group is one block's tile."""
    theta, width = net.theta, net.layers

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        (tile,), inside, core, lo = _tile(pdf, spec, width, ["v"])
        got = convolve(net, theta, tile, inside)
        x, y, z = (i + width for i in np.nonzero(inside[core]))
        return pd.DataFrame({"x": (x + lo[0]).astype("int32"), "y": (y + lo[1]).astype("int32"), "z": (z + lo[2]).astype("int32"), "t": np.full(len(x), pdf["t"].iloc[0], dtype="int32"), "v": got[x, y, z]})

    return with_halo(vox, spec, width).groupBy(*KEYS).applyInPandas(run, "x int, y int, z int, t int, v double")


def train_seam(decoded: DataFrame, truth: DataFrame, spec: FieldSpec, net: SeamNet) -> SeamNet:
    """Data-parallel gradient steps over a bounded set of tiles: tiles' gradients are summed per task, then on the driver."""
    from ..plans.stages import keep

    width = net.layers
    both = decoded.select(*AXES, "v").join(truth.select(*AXES, F.col("v").alias("truth")), list(AXES))
    tiles = with_halo(both, spec, width).groupBy(*KEYS).agg(F.collect_list(F.struct("x", "y", "z", "v", "truth")).alias("cells"))
    tiles = keep(tiles.orderBy(F.xxhash64(*KEYS), *KEYS).limit(net.tiles), "seam-tiles")
    theta = net.start() if net.theta is None else net.theta
    adam = Adam(len(theta), decay=0.0)
    for _ in range(net.epochs):
        now = theta

        def run(batches, now=now):
            g, n = np.zeros(len(now)), 0
            for pdf in batches:
                for row in pdf.itertuples(index=False):
                    cells = pd.DataFrame(list(row.cells))
                    cells["_bx"], cells["_by"], cells["_bz"] = row[1], row[2], row[3]
                    (tile, goal), inside, core, _ = _tile(cells, spec, width, ["v", "truth"])
                    kept: list = []
                    e = convolve(net, now, tile, inside, kept) - goal
                    mask = np.zeros_like(inside)
                    mask[core] = inside[core]
                    g += convolve_gradient(net, now, kept, inside, 2 * e * mask)
                    n += int(mask.sum())
            yield pd.DataFrame({"g": [g], "n": [n]})

        sums = tiles.select(*KEYS, "cells").mapInPandas(run, "g array<double>, n long").collect()
        n = sum(r["n"] for r in sums)
        if not n:
            break
        theta = adam.step(theta, np.sum([r["g"] for r in sums], axis=0) / n, net.rate)
    return SeamNet(net.layers, net.channels, net.epochs, net.rate, net.bits, net.seed, net.tiles, quantize_array(theta, net.bits))


def quantize_array(w: np.ndarray, bits: int) -> np.ndarray:
    """Every value replaced by the nearest of 2^bits k-means centers."""
    centers, _ = lloyd_1d(w, np.ones(len(w)), 1 << bits)
    return centers[np.abs(w[:, None] - centers[None, :]).argmin(axis=1)] if len(w) * len(centers) < 5e7 else centers[np.searchsorted((centers[1:] + centers[:-1]) / 2, w)]
