"""Global k-means quantization of parameters: 2^beta shared centers per group."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Values of a group are first counted in so many bins between their ends: iterations never see more rows.
BINS = 1 << 16


def group_columns(scope: str = "scale", kinds: str = "separate", group: str = "layer") -> list[str]:
    """What shares a codebook: (scale, layer, kind) by default; scope "net" adds the net, kinds "joint" drops the kind."""
    return ["scale"] + (["net_id"] if scope == "net" else []) + (["layer"] if group == "layer" else []) + (["kind"] if kinds == "separate" else [])


def lloyd_1d(values: np.ndarray, counts: np.ndarray, k: int, iterations: int = 30) -> tuple[np.ndarray, list[float]]:
    """Sorted centers of weighted values and the squared error of each iteration (never rising)."""
    order = np.argsort(values, kind="stable")
    v, c = values[order].astype(float), counts[order].astype(float)
    if len(v) <= k:
        return v.copy(), [0.0]
    at = np.searchsorted(np.cumsum(c), (np.arange(k) + 0.5) / k * c.sum())
    centers = np.unique(v[np.minimum(at, len(v) - 1)])
    history: list[float] = []
    cw, cs, cq = (np.concatenate([[0.0], np.cumsum(x)]) for x in (c, c * v, c * v * v))
    for _ in range(iterations):
        cut = np.concatenate([[0], np.searchsorted(v, (centers[1:] + centers[:-1]) / 2, side="right"), [len(v)]])
        w, s, q = (np.diff(x[cut]) for x in (cw, cs, cq))
        history.append(float(np.sum(q - 2 * centers * s + centers**2 * w)))
        new = np.where(w > 0, s / np.maximum(w, 1e-300), centers)
        if np.allclose(new, centers, rtol=0, atol=0):
            break
        centers = new
    return np.sort(centers), history


def codebooks(params: DataFrame, beta: int, by: list[str], iterations: int = 30, bins: int = BINS) -> DataFrame:
    """by..., code, center over the alive parameters. A group's values are counted in bins in the JVM (bin means
    are exact where a bin holds one value); then each group's few bins are clustered in a worker."""
    alive = params.where("alive").select(*by, F.col("value").cast("double").alias("value"))
    ends = alive.groupBy(*by).agg(F.min("value").alias("_lo"), F.max("value").alias("_hi"))
    place = F.when(F.col("_hi") > F.col("_lo"), F.least(F.floor((F.col("value") - F.col("_lo")) / (F.col("_hi") - F.col("_lo")) * bins), F.lit(bins - 1))).otherwise(F.lit(0))
    counted = alive.join(F.broadcast(ends) if "net_id" not in by else ends, by).withColumn("_bin", place).groupBy(*by, "_bin").agg(F.avg("value").alias("value"), F.count("*").alias("n"))
    schema = ", ".join(f"{c} {dict(params.dtypes)[c]}" for c in by)

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        centers, _ = lloyd_1d(pdf["value"].to_numpy(), pdf["n"].to_numpy(), 1 << beta, iterations)
        return pd.DataFrame({**dict(zip(by, key)), "code": np.arange(len(centers), dtype="int32"), "center": centers})

    return counted.groupBy(*by).applyInPandas(run, f"{schema}, code int, center double")


def nearest_code(value: Column, centers: Column) -> Column:
    """The position of the nearest of a sorted array of centers (ties to the lower), by counting passed midpoints: no Python."""
    mids = F.zip_with(F.slice(centers, F.lit(1), F.greatest(F.size(centers) - 1, F.lit(1))), F.slice(centers, F.lit(2), F.greatest(F.size(centers) - 1, F.lit(1))), lambda a, b: (a + b) / 2)
    return F.size(F.filter(mids, lambda m: m.isNotNull() & (m < value)))


def quantize(params: DataFrame, books: DataFrame, by: list[str]) -> DataFrame:
    """`params` with `code` (null where pruned): each alive value's nearest center of its group."""
    lists = books.groupBy(*by).agg(F.array_sort(F.collect_list("center")).alias("_centers"))  # at most 2^beta of a group
    return params.join(F.broadcast(lists) if "net_id" not in by else lists, by, "left").withColumn("code", F.when(F.col("alive"), nearest_code(F.col("value"), F.col("_centers"))).cast("int")).drop("_centers")


def dequantize(coded: DataFrame, books: DataFrame, by: list[str]) -> DataFrame:
    """`coded` with `value` read from the codebook; pruned parameters are 0."""
    small = F.broadcast(books) if "net_id" not in by else books
    return coded.drop("value").join(small, [*by, "code"], "left").withColumn("value", F.coalesce("center", F.lit(0.0))).drop("center")


def quant_error(params: DataFrame, coded: DataFrame, by: list[str]) -> DataFrame:
    """by..., n, mse, max_error of alive parameters against their codes' centers (`coded` from `dequantize`)."""
    keys = ["net_id", "layer", "kind", "row", "col"]
    both = params.where("alive").join(coded.select(*keys, F.col("value").alias("_q")), keys)
    d = F.col("value") - F.col("_q")
    return both.groupBy(*by).agg(F.count("*").alias("n"), F.avg(d * d).alias("mse"), F.max(F.abs(d)).alias("max_error"))
