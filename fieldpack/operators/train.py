"""Training and inference of all networks of a scale, in parallel over nets."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..spec import FieldSpec
from .sinenet import NetSpec, fit_net, forward, init_latent, init_params, local_coordinates, net_inputs

NETS = "net_id long, theta array<double>, alive array<boolean>, loss double"
CODES = "block_id long, net_id long, latent array<double>"


@dataclass(frozen=True)
class Schedule:
    """Epochs by scale from the coarsest, the rate, and pruning rounds (epoch, sparsity); the rate falls after each round."""

    epochs: tuple[int, ...] = (500,)
    rate: float = 1e-3
    decay: float = 0.75
    rounds: tuple[tuple[int, float], ...] = ((150, 0.30), (225, 0.40), (300, 0.45), (375, 0.50))
    beta: int = 8
    finetune: int = 75
    finetune_rate: float = 1e-5

    @staticmethod
    def dynamic() -> Schedule:
        return Schedule()

    @staticmethod
    def static() -> Schedule:
        return Schedule(epochs=(200, 150, 125), rounds=((75, 0.20), (115, 0.30)))

    @staticmethod
    def large() -> Schedule:
        return Schedule(epochs=(225, 175, 150, 125), rounds=((75, 0.20), (115, 0.30)), beta=9, finetune=20)

    def epochs_at(self, level: int) -> int:
        """`level` counts from the coarsest scale."""
        return self.epochs[min(level, len(self.epochs) - 1)]

    def segments(self, level: int, prune: bool = True) -> list[tuple[int, float | None, float]]:
        """(epochs, sparsity to prune to before them, rate). Rounds beyond the scale's epochs are skipped."""
        total, out, at, rate, sparsity = self.epochs_at(level), [], 0, self.rate, None
        for epoch, share in self.rounds if prune else ():
            if epoch >= total:
                break
            out.append((epoch - at, sparsity, rate))
            at, sparsity, rate = epoch, share, rate * self.decay
        return [*out, (total - at, sparsity, rate)]


def start_nets(assigned: DataFrame, net: NetSpec, scale: int, seed: int = 0) -> tuple[DataFrame, DataFrame]:
    """Seeded nets (NETS) and latent codes (CODES) for an assignment (block_id, net_id)."""

    def nets(batches):
        for pdf in batches:
            ids = pdf["net_id"].tolist()
            yield pd.DataFrame({"net_id": ids, "theta": [init_params(net, scale, int(i), seed) for i in ids], "alive": [[True] * net.parameters for _ in ids], "loss": [float("nan")] * len(ids)})

    def codes(batches):
        for pdf in batches:
            yield pd.DataFrame({"block_id": pdf["block_id"], "net_id": pdf["net_id"], "latent": [init_latent(net, scale, int(b), seed) for b in pdf["block_id"]]})

    pairs = assigned.select(F.col("block_id").cast("long").alias("block_id"), F.col("net_id").cast("long").alias("net_id"))
    return pairs.select("net_id").distinct().mapInPandas(nets, NETS), pairs.mapInPandas(codes, CODES)


def train_segment(blocks: DataFrame, nets: DataFrame, codes: DataFrame, spec: FieldSpec, net: NetSpec, epochs: int, rate: float, loss: str = "mse") -> DataFrame:
    """One row per net: net_id, theta, alive, loss, block_ids, latents. A group holds one net's blocks, whose number
    the assignment bounds; the net's parameters come beside them once."""
    coords = local_coordinates(spec.bx, spec.by, spec.bz)

    def run(pdf: pd.DataFrame, net_pdf: pd.DataFrame) -> pd.DataFrame:
        if not len(pdf) or not len(net_pdf):
            return pd.DataFrame({"net_id": [], "theta": [], "alive": [], "loss": [], "block_ids": [], "latents": []})
        pdf = pdf.sort_values("block_id")
        values = np.stack(pdf["values"].to_numpy()).astype(float)
        latents = np.stack(pdf["latent"].to_numpy()).astype(float).reshape(len(values), net.latent_dim)
        theta, alive = np.array(net_pdf["theta"].iloc[0], dtype=float), np.array(net_pdf["alive"].iloc[0], dtype=bool)
        theta, latents, last = fit_net(net, theta, latents, coords, values, epochs, rate, alive, loss)
        return pd.DataFrame({"net_id": [int(pdf["net_id"].iloc[0])], "theta": [theta], "alive": [alive], "loss": [last], "block_ids": [pdf["block_id"].to_numpy()], "latents": [latents.ravel()]})

    own = blocks.select("block_id", "values").join(codes, "block_id")
    return own.groupBy("net_id").cogroup(nets.groupBy("net_id")).applyInPandas(run, f"{NETS}, block_ids array<long>, latents array<double>")


def trained_nets(trained: DataFrame) -> DataFrame:
    return trained.select("net_id", "theta", "alive", "loss")


def trained_codes(trained: DataFrame, latent_dim: int) -> DataFrame:
    at = trained.select("net_id", "latents", F.posexplode("block_ids").alias("i", "block_id"))
    return at.select("block_id", "net_id", F.slice("latents", F.col("i") * latent_dim + 1, F.lit(latent_dim)).alias("latent"))


def infer(nets: DataFrame, codes: DataFrame, spec: FieldSpec, net: NetSpec) -> DataFrame:
    """block_id, values: every block's decoded voxels. Blocks and nets are joined by net; neither is broadcast."""
    coords = local_coordinates(spec.bx, spec.by, spec.bz)

    def run(batches):
        for pdf in batches:
            out = []
            for theta, latent in zip(pdf["theta"], pdf["latent"]):
                out.append(forward(net, np.asarray(theta, dtype=float), net_inputs(coords, np.asarray(latent, dtype=float).reshape(1, -1))))
            yield pd.DataFrame({"block_id": pdf["block_id"], "values": out})

    return codes.join(nets.select("net_id", "theta"), "net_id").select("block_id", "theta", "latent").mapInPandas(run, "block_id long, values array<double>")


def parameter_rows(nets: DataFrame, net: NetSpec, scale: int) -> DataFrame:
    """Long form of nets: scale, net_id, layer, kind, row, col, value, alive. The layout is a small table."""
    layout = nets.sparkSession.createDataFrame([(p, *where) for p, where in enumerate(net.layout())], "p int, layer int, kind string, row int, col int")
    long = nets.select("net_id", F.posexplode(F.arrays_zip("theta", "alive")).alias("p", "x"))
    return long.join(F.broadcast(layout), "p").select(F.lit(scale).alias("scale"), "net_id", "layer", "kind", "row", "col", F.col("x.theta").alias("value"), F.col("x.alive").alias("alive"))


def nets_of_rows(rows: DataFrame, net: NetSpec, losses: DataFrame) -> DataFrame:
    """The inverse of `parameter_rows`; a group has as many rows as a net has parameters."""
    layout = rows.sparkSession.createDataFrame([(p, *where) for p, where in enumerate(net.layout())], "p int, layer int, kind string, row int, col int")
    placed = rows.join(F.broadcast(layout), ["layer", "kind", "row", "col"]).groupBy("net_id").agg(F.array_sort(F.collect_list(F.struct("p", "value", "alive"))).alias("x"))
    return placed.join(losses.select("net_id", "loss"), "net_id").select("net_id", F.transform("x", lambda s: s["value"]).alias("theta"), F.transform("x", lambda s: s["alive"]).alias("alive"), "loss")
