"""Table functions for SQL users."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="scale int, extent int")
class PyramidLevels:
    """scale and extent of an axis, from the finest scale to the coarsest."""

    def eval(self, extent: int, scales: int):
        for scale in range(1, scales + 1):
            yield scale, extent
            extent = (extent + 1) // 2


@udtf(returnType="p int, v double")
class UnpackBlock:
    """position and value of a block's voxels."""

    def eval(self, values: list):
        for p, v in enumerate(values or []):
            yield p, float(v)


def register(spark: SparkSession) -> None:
    spark.udtf.register("fp_pyramid_levels", PyramidLevels)
    spark.udtf.register("fp_unpack_block", UnpackBlock)
