"""Staged tables: where an iteration ends, its result is written to the shared folder and read again."""

from __future__ import annotations

import tempfile
import uuid
from functools import cache

from pyspark.sql import DataFrame


@cache
def _own_folder() -> str:
    """Only where no shared folder is named, as in tests on one machine."""
    return tempfile.mkdtemp(prefix="fieldpack-keep-")


def keep(df: DataFrame, name: str) -> DataFrame:
    """Writes `df` under `spark.checkpoint.dir` (a temporary folder where it is unset, as in tests) and reads it
    back; elsewhere than on one machine the setting must be there. The plan's lineage ends there, and lost executors lose nothing that was written."""
    spark = df.sparkSession
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        master = spark.conf.get("spark.master", "")
        if not (master == "local" or master.startswith("local[")):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        where = _own_folder()
    path = f"{where}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
