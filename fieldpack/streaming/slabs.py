"""Streams of events into slabs of a field: windows, late rows, repeated events, stateful sums, slab encoding."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.grid import cents


def cell_columns() -> list:
    k = F.get_json_object("props", "$.k").cast("int")
    return [(F.col("user_id") % 16).cast("int").alias("x"), F.hour("ts").alias("y"), F.floor(k * 8 / 100).cast("int").alias("z")]


def deduplicated(events: DataFrame, delay: str = "1 day") -> DataFrame:
    """Each event_id once, within the watermark."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def slabs(events: DataFrame, width: str = "1 day", slide: str | None = None) -> DataFrame:
    """Cells of each window: start, x, y, z, cents, n. One window is one timestep; events later than the watermark are dropped."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.select(w.alias("w"), *cell_columns(), cents("value").alias("c")).groupBy("w", "x", "y", "z").agg(F.sum("c").alias("cents"), F.count("*").alias("n")).select(F.col("w.start").alias("start"), "x", "y", "z", "cents", "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """user_id, start, finish, n of activity sessions."""
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("finish"), "n")


def with_dimension(events: DataFrame, dimension: DataFrame, key: str) -> DataFrame:
    """Stream-static join: the dimension is a small table and is broadcast by the planner's size check."""
    return events.join(dimension, key, "left")


def errors_near_purchases(events: DataFrame, seconds: int = 3600) -> DataFrame:
    """Stream-stream join: errors with purchases of the same user within the interval; both sides' state is bounded."""
    e = events.where("event_type = 'error'").select(F.col("user_id").alias("u1"), F.col("ts").alias("t1"), F.col("event_id").alias("error_id")).withWatermark("t1", "1 hour")
    p = events.where("event_type = 'purchase'").select(F.col("user_id").alias("u2"), F.col("ts").alias("t2"), F.col("event_id").alias("purchase_id")).withWatermark("t2", "1 hour")
    near = F.expr(f"u1 = u2 AND t2 >= t1 - INTERVAL {seconds} SECONDS AND t2 <= t1 + INTERVAL {seconds} SECONDS")
    return e.join(p, near).select("error_id", "purchase_id")


def running_cells(events: DataFrame) -> DataFrame:
    """x, z, cents, n so far: sums per cell column kept in state, one small state for each."""

    def add(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        total, n = state.get if state.exists else (0, 0)
        for pdf in parts:
            total, n = total + int(pdf["c"].sum()), n + len(pdf)
        state.update((total, n))
        yield pd.DataFrame({"x": [key[0]], "z": [key[1]], "cents": [total], "n": [n]})

    keyed = events.select(*cell_columns(), cents("value").alias("c"))
    return keyed.groupBy("x", "z").applyInPandasWithState(add, "x int, z int, cents long, n long", "total long, n long", "update", GroupStateTimeout.NoTimeout)


def start_slab_encoder(cells: DataFrame, group: int, encode: Callable[[DataFrame, int], None], checkpoint: str, width_days: int = 1):
    """Calls `encode(cells, first_slab)` for each run of `group` slabs (2^(scales-1), since time is halved in pairs)
    as soon as all of them are closed. `cells` comes from `slabs`; unfinished groups wait in a table beside the checkpoint."""
    waiting = f"{checkpoint}/waiting"

    def step(batch: DataFrame, epoch: int) -> None:
        spark = batch.sparkSession
        slab = F.floor(F.unix_seconds("start") / (86400 * width_days)).alias("slab")
        rows = batch.select(slab, "x", "y", "z", "cents", "n")
        if epoch and (old := _read(spark, f"{waiting}/{epoch - 1}")) is not None:
            rows = rows.unionByName(old)
        rows = rows.persist()
        last = rows.agg(F.max("slab")).first()[0]
        if last is None:
            rows.unpersist()
            return
        groups = [r[0] for r in rows.select(F.floor(F.col("slab") / group).alias("g")).distinct().orderBy("g").collect()]
        open_from = (last + 1) // group
        for g in groups:
            if g < open_from:
                encode(rows.where(F.floor(F.col("slab") / group) == g), int(g * group))
        rows.where(F.floor(F.col("slab") / group) >= open_from).write.mode("overwrite").parquet(f"{waiting}/{epoch}")
        rows.unpersist()

    return cells.writeStream.outputMode("append").foreachBatch(step).option("checkpointLocation", f"{checkpoint}/stream").trigger(availableNow=True).start()


def _read(spark, path: str) -> DataFrame | None:
    from pyspark.errors import AnalysisException

    try:
        return spark.read.parquet(path)
    except AnalysisException:
        return None


def progressive(archive, decode: Callable, emit: Callable[[int, DataFrame], None]) -> None:
    """Emits the field scale by scale, from the coarsest to the finest."""
    for part in archive.parts:
        emit(part.scale, decode(archive, part.scale))
