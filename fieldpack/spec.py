"""Field geometry: extents, block extents, scales, and the catalogue of known fields."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame

AXES = ("x", "y", "z", "t")
VOXEL_COLUMNS = {"x": "int", "y": "int", "z": "int", "t": "int", "v": "double"}


@dataclass(frozen=True)
class FieldSpec:
    """A 4D grid of nx*ny*nz*nt voxels, cut into blocks of bx*by*bz voxels of one timestep, in `scales` scales.

    Scale 1 is the full resolution. With `halve_time` the time axis is halved as the others are; an
    axis of extent 1 stays 1."""

    nx: int
    ny: int
    nz: int
    nt: int
    bx: int
    by: int
    bz: int
    scales: int = 3
    halve_time: bool = True

    def __post_init__(self):
        if min(self.nx, self.ny, self.nz, self.nt, self.bx, self.by, self.bz, self.scales) < 1:
            raise ValueError(f"extents start at 1: {self}")

    @property
    def extents(self) -> dict[str, int]:
        return {"x": self.nx, "y": self.ny, "z": self.nz, "t": self.nt}

    @property
    def voxels(self) -> int:
        return self.nx * self.ny * self.nz * self.nt

    @property
    def raw_bytes(self) -> int:
        """Size of the field as 32-bit floats."""
        return 4 * self.voxels

    @property
    def block_voxels(self) -> int:
        return self.bx * self.by * self.bz

    def halved_axes(self) -> list[str]:
        return [a for a in AXES if self.extents[a] > 1 and (a != "t" or self.halve_time)]

    def coarser(self) -> FieldSpec:
        """The spec of the next coarser scale's field."""
        half = {f"n{a}": (self.extents[a] + 1) // 2 for a in self.halved_axes()}
        return replace(self, **half, scales=max(1, self.scales - 1))

    def at_scale(self, scale: int) -> FieldSpec:
        spec = self
        for _ in range(scale - 1):
            spec = spec.coarser()
        return spec

    @property
    def blocks_per_axis(self) -> tuple[int, int, int]:
        return math.ceil(self.nx / self.bx), math.ceil(self.ny / self.by), math.ceil(self.nz / self.bz)

    @property
    def blocks(self) -> int:
        a, b, c = self.blocks_per_axis
        return a * b * c * self.nt

    def check(self, df: DataFrame) -> DataFrame:
        """Fails early where a voxel view lacks a column or has another type."""
        have = dict(df.dtypes)
        wrong = {c: have.get(c) for c, t in VOXEL_COLUMNS.items() if have.get(c) != t}
        if wrong:
            raise TypeError(f"a voxel view has {VOXEL_COLUMNS}, not {wrong}")
        return df


#: The geometry of eight known data sets, with blocks per net from the finest scale to the coarsest.
KNOWN_FIELDS: dict[str, tuple[FieldSpec, tuple[int, ...]]] = {
    "combustion": (FieldSpec(480, 720, 120, 70, 40, 45, 15, 3), (32, 16, 8)),
    "half_cylinder": (FieldSpec(640, 240, 80, 100, 40, 30, 20, 3), (32, 16, 8)),
    "solar_plume": (FieldSpec(256, 256, 1024, 28, 32, 32, 32, 3), (32, 16, 8)),
    "tangaroa": (FieldSpec(300, 180, 120, 150, 25, 15, 10, 3), (32, 16, 8)),
    "asteroids": (FieldSpec(500, 500, 500, 1, 25, 25, 25, 3), (4, 2, 1)),
    "supernova_1": (FieldSpec(432, 432, 432, 1, 18, 18, 18, 3), (4, 2, 1)),
    "supernova_2": (FieldSpec(1200, 1200, 1200, 1, 50, 50, 50, 4), (8, 4, 2, 1)),
    "supernova_3": (FieldSpec(1728, 1728, 1728, 1, 72, 72, 72, 3), (4, 2, 1)),
}

#: The volumes made from the given tables.
F0 = FieldSpec(32, 32, 32, 16, 8, 8, 8, 3)
F1 = FieldSpec(16, 8, 8, 28, 4, 2, 2, 3)
F2 = FieldSpec(16, 24, 8, 30, 4, 6, 2, 3)
F3 = FieldSpec(64, 64, 64, 1, 8, 8, 8, 4)
F4 = FieldSpec(16, 16, 16, 1, 4, 4, 4, 3)
F5 = FieldSpec(64, 64, 64, 1, 16, 16, 16, 3)
F7 = FieldSpec(4, 20, 16, 1, 1, 5, 4, 2)
F8 = FieldSpec(8, 4, 8, 8, 2, 1, 2, 2)
