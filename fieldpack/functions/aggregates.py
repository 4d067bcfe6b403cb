"""Aggregate expressions that can be used in any `agg`."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def psnr_agg(a: Column, b: Column, peak: float) -> Column:
    """PSNR of two columns against a known peak; equal columns give infinity."""
    mse = F.avg((a - b) * (a - b))
    return 20 * F.log10(F.lit(float(peak))) - 10 * F.log10(mse)


def entropy_agg(freq: Column) -> Column:
    """Bits per symbol from a column of counts."""
    n = F.sum(freq).cast("double")
    return F.log2(n) - F.sum(freq * F.log2(freq.cast("double"))) / n


def block_mean_vec(values: Column, size: int) -> Column:
    """Element-wise mean of array columns of one size."""
    return F.array(*[F.avg(F.get(values, F.lit(i))) for i in range(size)])
