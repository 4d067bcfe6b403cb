"""Assigning blocks to networks: k-means, equal-size clusters, and the controls."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.stages import keep

#: Centroids travel to every worker: k * block size may have at most so many values (64 MB of doubles).
MOST_CENTROID_VALUES = 8_000_000


def net_count(n: Column | int, b: int):
    """How many networks n blocks need at b blocks each."""
    return math.ceil(n / b) if isinstance(n, int) else F.ceil(n / b)


def blocks_per_net(scales: int, preset: str) -> tuple[int, ...]:
    """Blocks per net from the coarsest scale to the finest."""
    table = {"dynamic": (8, 16, 32), "static": (1, 2, 4), "large": (1, 2, 4, 8)}[preset]
    return tuple(table[min(i, len(table) - 1)] for i in range(scales))


def squared_distance(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda acc, d: acc + d)


def distances(blocks: DataFrame, centroids: DataFrame) -> DataFrame:
    """block_id, net_id, d2. The centroids (net_id, center) are a table of checked size and are broadcast."""
    return blocks.select("block_id", "values").crossJoin(F.broadcast(centroids)).select("block_id", "net_id", squared_distance(F.col("values"), F.col("center")).alias("d2"))


def gain(dist: DataFrame) -> DataFrame:
    """block_id, gain: how far apart a block's nearest and farthest clusters are."""
    return dist.groupBy("block_id").agg((F.max("d2") - F.min("d2")).alias("gain"))


def nearest(dist: DataFrame) -> DataFrame:
    """block_id, net_id, d2: the nearest cluster, ties to the smaller net."""
    best = F.min(F.struct("d2", "net_id"))
    return dist.groupBy("block_id").agg(best.alias("b")).select("block_id", F.col("b.net_id").alias("net_id"), F.col("b.d2").alias("d2"))


def seed_centroids(blocks: DataFrame, k: int, sample: int = 20) -> np.ndarray:
    """Greedy far-apart seeds on a hash-ordered sample of at most sample*k blocks: reruns agree."""
    rows = blocks.select("block_id", "values").orderBy(F.xxhash64("block_id"), "block_id").limit(sample * k).collect()
    x = np.array([r["values"] for r in rows], dtype=float)
    if not len(x):
        return x.reshape(0, 0)
    chosen = [0]
    d = ((x - x[0]) ** 2).sum(axis=1)
    while len(chosen) < min(k, len(x)):
        chosen.append(int(np.argmax(d)))
        d = np.minimum(d, ((x - x[chosen[-1]]) ** 2).sum(axis=1))
    return x[chosen]


def assign_nearest(blocks: DataFrame, centers: np.ndarray) -> DataFrame:
    """block_id, net_id, d2 by matrix products in Arrow batches."""
    if centers.size > MOST_CENTROID_VALUES:
        raise ValueError("too many centroids to send to workers: use uniformize_sharded")
    norm = (centers**2).sum(axis=1)

    def run(batches):
        for pdf in batches:
            x = np.stack(pdf["values"].to_numpy()) if len(pdf) else np.empty((0, centers.shape[1]))
            d = (x**2).sum(axis=1)[:, None] - 2 * x @ centers.T + norm
            best = d.argmin(axis=1) if len(pdf) else np.empty(0, dtype=int)
            exact = ((x - centers[best]) ** 2).sum(axis=1)
            yield pd.DataFrame({"block_id": pdf["block_id"], "net_id": best.astype("int32"), "d2": exact})

    return blocks.select("block_id", "values").mapInPandas(run, "block_id long, net_id int, d2 double")


def kmeans(blocks: DataFrame, k: int, iterations: int = 10, centers: np.ndarray | None = None) -> tuple[np.ndarray, list[float]]:
    """Standard Lloyd iterations: (centers, inertia of each iteration). Sums are combined in each task before
    the shuffle; an empty cluster keeps its center."""
    centers = seed_centroids(blocks, k) if centers is None else centers
    history: list[float] = []
    for _ in range(iterations):
        if not len(centers):
            break
        new = centers.copy()
        total = 0.0
        for r in _joined_sums(_partial_sums(blocks, centers)).collect():  # at most MOST_CENTROID_VALUES values
            new[r["net_id"]] = np.frombuffer(r["sums"]) / r["n"]
            total += r["inertia"]
        history.append(total)
        if np.array_equal(new, centers):
            break
        centers = new
    return centers, history


def _partial_sums(blocks: DataFrame, centers: np.ndarray) -> DataFrame:
    norm = (centers**2).sum(axis=1)
    k = len(centers)

    def run(batches):
        sums, n, inertia = np.zeros_like(centers), np.zeros(k, dtype=np.int64), np.zeros(k)
        for pdf in batches:
            if not len(pdf):
                continue
            x = np.stack(pdf["values"].to_numpy())
            best = ((x**2).sum(axis=1)[:, None] - 2 * x @ centers.T + norm).argmin(axis=1)
            np.add.at(sums, best, x)
            n += np.bincount(best, minlength=k)
            inertia += np.bincount(best, weights=((x - centers[best]) ** 2).sum(axis=1), minlength=k)
        at = np.flatnonzero(n)
        yield pd.DataFrame({"net_id": at.astype("int32"), "n": n[at], "inertia": inertia[at], "sums": [sums[i].tobytes() for i in at]})

    return blocks.select("values").mapInPandas(run, SUMS)


SUMS = "net_id int, n long, inertia double, sums binary"


def _joined_sums(partial: DataFrame) -> DataFrame:
    """One row per net: the tasks' partial sums of a net, as many as there are tasks, are added as whole arrays."""

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        sums = np.sum([np.frombuffer(x) for x in pdf["sums"]], axis=0)
        return pd.DataFrame({"net_id": [key[0]], "n": [int(pdf["n"].sum())], "inertia": [float(pdf["inertia"].sum())], "sums": [sums.tobytes()]})

    return partial.groupBy("net_id").applyInPandas(run, SUMS)


def uniform_fill(d2: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Equal-size clusters, one point at a time: points in falling order of gain (ties: smaller id) go to their
    nearest cluster with room; room is floor(n/k) until all clusters have that many, then ceil(n/k)."""
    n, k = d2.shape
    low, high = n // k, -(-n // k)
    order = np.lexsort((ids, -(d2.max(axis=1) - d2.min(axis=1))))
    choice = np.argsort(d2, axis=1, kind="stable")
    size, out, full = np.zeros(k, dtype=int), np.full(n, -1), 0
    for p in order:
        room = low if full < k and low > 0 else high
        for c in choice[p]:
            if size[c] < room:
                size[c] += 1
                full += size[c] == low
                out[p] = c
                break
    return out


def uniformize(dist: DataFrame) -> DataFrame:
    """block_id, net_id, gain: the exact sequential fill in one task; for n*k up to some 5e7 distances (a shard)."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("block_id")
        d2, ids = np.stack([np.frombuffer(x) for x in pdf["d2"]]), pdf["block_id"].to_numpy()
        got = uniform_fill(d2, ids)
        return pd.DataFrame({"block_id": ids, "net_id": nets[got], "gain": d2.max(axis=1) - d2.min(axis=1)})

    nets = np.array(sorted(r[0] for r in dist.select("net_id").distinct().collect()), dtype="int32")
    packed = dist.groupBy("block_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("net_id", "d2"))), lambda s: s["d2"]).alias("row"))
    as_bytes = packed.mapInPandas(lambda parts: (pd.DataFrame({"block_id": p["block_id"], "d2": [np.asarray(x, dtype=float).tobytes() for x in p["row"]]}) for p in parts), "block_id long, d2 binary")
    return as_bytes.groupBy(F.lit(0).alias("shard")).applyInPandas(run, "block_id long, net_id int, gain double")


def uniform_blocks(blocks: DataFrame, centers: np.ndarray) -> DataFrame:
    """block_id, net_id: the exact fill over given centers. Distances are made in the tasks, one packed row of k doubles
    per block, and never as rows of pairs; the fill reads them in the order of gain from a stream of sorted packed
    rows, so its memory is that of the sizes of k nets and one batch, whatever the number of blocks."""
    norm = (centers**2).sum(axis=1)
    k = len(centers)

    def rows(batches):
        for pdf in batches:
            if not len(pdf):
                continue
            x = np.stack(pdf["values"].to_numpy()).astype(float)
            d2 = np.maximum((x**2).sum(axis=1)[:, None] - 2 * x @ centers.T + norm, 0)
            choice = np.argsort(d2, axis=1, kind="stable").astype("int32")
            yield pd.DataFrame({"block_id": pdf["block_id"], "gain": d2.max(axis=1) - d2.min(axis=1), "choice": [c.tobytes() for c in choice]})

    told = keep(blocks.select("block_id", "values").mapInPandas(rows, "block_id long, gain double, choice binary"), "uniform-choices")
    n = told.count()
    low, high = n // k, -(-n // k)

    def fill(batches):
        size, full = np.zeros(k, dtype=np.int64), 0
        for pdf in batches:
            out = np.empty(len(pdf), dtype="int32")
            for i, raw in enumerate(pdf["choice"]):
                room = low if full < k and low > 0 else high
                order = np.frombuffer(raw, dtype="int32")
                c = order[np.argmax(size[order] < room)]
                size[c] += 1
                full += size[c] == low
                out[i] = c
            yield pd.DataFrame({"block_id": pdf["block_id"], "net_id": out})

    # the fill is sequential by the method: one task, whose sort spills to disk and whose pass holds one batch
    ordered = told.repartition(1).sortWithinPartitions(F.desc("gain"), "block_id")
    return ordered.mapInPandas(fill, "block_id long, net_id int")


def uniformize_rounds(dist: DataFrame, stage=keep, most_rounds: int = 1000) -> DataFrame:
    """The same assignment, distributed: all clusters prefer points by the same gain, so the fill is the stable
    matching of proposals and rejections. Each round every free point proposes to its next choice and a cluster
    keeps its first `room` points. First the leading k*floor(n/k) points with room floor(n/k), then the rest with 1."""
    k = dist.select("net_id").distinct().count()
    ranked = dist.withColumn("choice", F.row_number().over(Window.partitionBy("block_id").orderBy("d2", "net_id")))
    g = gain(dist)
    n = g.count()
    low = n // k if k else 0
    # places in the order of gain: range-partitioned sort, then offsets, so no single task orders all points
    placed = _global_rank(g, [F.desc("gain"), F.col("block_id")]).select("block_id", "gain", "place")
    out = None
    for first, last, room in ((0, k * low, low), (k * low, n, 1)):
        if last <= first:
            continue
        points = stage(placed.where((F.col("place") >= first) & (F.col("place") < last)).withColumn("at", F.lit(1)), "uniform-points")
        for _ in range(most_rounds):
            asked = points.join(ranked.select("block_id", "net_id", F.col("choice").alias("at")), ["block_id", "at"])
            held = asked.withColumn("seat", F.row_number().over(Window.partitionBy("net_id").orderBy("place")))
            held = stage(held, "uniform-round")
            if held.where(F.col("seat") > room).isEmpty():
                break
            points = held.select("block_id", "gain", "place", (F.col("at") + (F.col("seat") > room).cast("int")).alias("at"))
        else:
            raise RuntimeError("assignment has not settled")
        part = held.select("block_id", "net_id", "gain")
        out = part if out is None else out.unionByName(part)
    return out


def _global_rank(df: DataFrame, order: list) -> DataFrame:
    """Adds `place`, the 0-based rank in a total order, without a single-task window."""
    parts = max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    dealt = df.repartitionByRange(parts, *order).withColumn("_part", F.spark_partition_id())
    dealt = keep(dealt, "ranked")
    counts = dealt.groupBy("_part").agg(F.count("*").alias("_n"))
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)  # one row per partition
    offsets = counts.select("_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    within = Window.partitionBy("_part").orderBy(*order)
    return dealt.join(F.broadcast(offsets), "_part").withColumn("place", F.row_number().over(within) - 1 + F.col("_before")).drop("_part", "_before")


def sketch(blocks: DataFrame, size: int, dims: int = 16, seed: int = 7) -> DataFrame:
    """block_id, sketch: random projections, the same for a seed everywhere."""
    proj = np.random.default_rng(seed).normal(0, 1 / np.sqrt(dims), (size, dims))

    def run(batches):
        for pdf in batches:
            x = np.stack(pdf["values"].to_numpy()) if len(pdf) else np.empty((0, size))
            yield pd.DataFrame({"block_id": pdf["block_id"], "sketch": list(x @ proj)})

    return blocks.select("block_id", "values").mapInPandas(run, "block_id long, sketch array<double>")


def uniformize_sharded(blocks: DataFrame, size: int, b: int, shard_blocks: int = 4096, seed: int = 7, iterations: int = 5) -> DataFrame:
    """block_id, shard, net_id (numbered over all shards by shard*stride): for any number of blocks.

    Blocks are ordered along a random projection and cut into shards of whole nets; inside a shard k-means and the
    exact fill run in one worker, whose memory is the shard's."""
    shard_blocks = max(b, shard_blocks // b * b)
    one = sketch(blocks, size, 1, seed).select("block_id", F.get("sketch", F.lit(0)).alias("s"))
    placed = _global_rank(one, [F.col("s"), F.col("block_id")]).select("block_id", F.floor(F.col("place") / shard_blocks).cast("long").alias("shard"))
    stride = shard_blocks // b

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("block_id")
        x, ids = np.stack(pdf["values"].to_numpy()), pdf["block_id"].to_numpy()
        k = -(-len(x) // b)
        rng = np.random.default_rng(int(pdf["shard"].iloc[0]) + seed)
        c = x[np.sort(rng.permutation(len(x))[:k])]
        for _ in range(iterations):
            near = ((x**2).sum(axis=1)[:, None] - 2 * x @ c.T + (c**2).sum(axis=1)).argmin(axis=1)
            for j in np.unique(near):
                c[j] = x[near == j].mean(axis=0)
        d2 = np.maximum((x**2).sum(axis=1)[:, None] - 2 * x @ c.T + (c**2).sum(axis=1), 0)
        return pd.DataFrame({"block_id": ids, "shard": pdf["shard"], "net_id": pdf["shard"].to_numpy() * stride + uniform_fill(d2, ids)})

    return blocks.select("block_id", "values").join(placed, "block_id").groupBy("shard").applyInPandas(run, "block_id long, shard long, net_id long")


def assign_single(blocks: DataFrame) -> DataFrame:
    """One network for each block: ids are dense in the order of block ids."""
    return _global_rank(blocks.select("block_id"), [F.col("block_id")]).select("block_id", F.col("place").cast("long").alias("net_id"))


def assign_order(blocks: DataFrame, b: int) -> DataFrame:
    """Control: runs of b blocks in spatial order."""
    return _global_rank(blocks.select("block_id"), [F.col("block_id")]).select("block_id", F.floor(F.col("place") / b).cast("long").alias("net_id"))


def balance(assignment: DataFrame) -> DataFrame:
    """nets, smallest, largest, deviation, largest over mean."""
    sizes = assignment.groupBy("net_id").agg(F.count("*").alias("n"))
    return sizes.agg(F.count("*").alias("nets"), F.min("n").alias("smallest"), F.max("n").alias("largest"), F.stddev_pop("n").alias("deviation"), (F.max("n") / F.avg("n")).alias("imbalance"))


def cluster_quality(assignment: DataFrame, dist: DataFrame) -> DataFrame:
    """inner, outer: mean distance of blocks to their own and to the other clusters."""
    both = dist.join(assignment.select("block_id", F.col("net_id").alias("own")), "block_id")
    own = F.col("net_id") == F.col("own")
    return both.agg(F.avg(F.when(own, F.sqrt("d2"))).alias("inner"), F.avg(F.when(~own, F.sqrt("d2"))).alias("outer"))
