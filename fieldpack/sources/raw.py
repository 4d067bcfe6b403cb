"""Fields on disk as 32-bit floats, one file per timestep, and streams of events."""

from __future__ import annotations

import re

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..spec import AXES, FieldSpec


def write_raw(vox: DataFrame, path: str) -> None:
    """One row per timestep: t and its bytes (x fastest), as a table; a timestep's volume must fit a worker."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["z", "y", "x"])
        return pd.DataFrame({"t": [int(pdf["t"].iloc[0])], "data": [pdf["v"].to_numpy().astype("<f4").tobytes()]})

    vox.select(*AXES, "v").groupBy("t").applyInPandas(run, "t int, data binary").write.mode("overwrite").parquet(path)


def _voxels(t: int, data: bytes, spec: FieldSpec) -> pd.DataFrame:
    v = np.frombuffer(data, dtype="<f4")
    if len(v) != spec.nx * spec.ny * spec.nz:
        raise ValueError(f"timestep {t} has {len(v)} values, not {spec.nx * spec.ny * spec.nz}")
    i = np.arange(len(v))
    return pd.DataFrame({"x": (i % spec.nx).astype("int32"), "y": (i // spec.nx % spec.ny).astype("int32"), "z": (i // (spec.nx * spec.ny)).astype("int32"), "t": np.full(len(v), t, dtype="int32"), "v": v.astype(float)})


def read_raw(spark: SparkSession, path: str, spec: FieldSpec) -> DataFrame:
    """Voxels of a table that `write_raw` wrote."""

    def run(batches):
        for pdf in batches:
            for t, data in zip(pdf["t"], pdf["data"]):
                yield _voxels(t, data, spec)

    return spark.read.parquet(path).select("t", "data").mapInPandas(run, "x int, y int, z int, t int, v double")


def read_raw_files(spark: SparkSession, pattern: str, spec: FieldSpec) -> DataFrame:
    """Voxels of binary files, one per timestep; the last number in a file's name is its timestep."""

    def run(batches):
        for pdf in batches:
            for name, data in zip(pdf["path"], pdf["content"]):
                yield _voxels(int(re.findall(r"\d+", name.rsplit("/", 1)[-1])[-1]), data, spec)

    return spark.read.format("binaryFile").load(pattern).select("path", "content").mapInPandas(run, "x int, y int, z int, t int, v double")


RUN_SCHEMA = "workload string, method string, metric string, value double, config map<string,string>"


def run_records(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, RUN_SCHEMA)


def write_runs(runs: DataFrame, path: str, kind: str = "json") -> None:
    """Run records as JSON lines or CSV (the configuration as JSON text)."""
    flat = runs.withColumn("config", F.to_json("config"))
    (flat.write.mode("overwrite").option("header", True)).format(kind).save(path)


EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def stream_events(spark: SparkSession, path: str, files_per_trigger: int = 4) -> DataFrame:
    """Events as they arrive in files of a folder."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))
