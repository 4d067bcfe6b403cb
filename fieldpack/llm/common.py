"""Shared helpers of the training-data operators: inputs, splits and staged tables."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from functools import cache

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Python workers get at most this many rows at a time, so that a batch of very long texts stays bounded.
ROWS_PER_BATCH = 1000


def read_table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """The named columns of a table of `sf_dir`; parquet pruning does the rest."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def bound_batches(spark: SparkSession, rows: int = ROWS_PER_BATCH) -> None:
    """Keeps Arrow batches small. A runtime setting: it is never fixed at the session's start."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(rows))


@contextmanager
def small_batches(spark: SparkSession, rows: int) -> Iterator[None]:
    """Few rows per Arrow batch while packed rows are worked on; what runs inside must be staged. The old value returns."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, str(rows))
    try:
        yield
    finally:
        spark.conf.set(key, before)


@cache
def _own_folder() -> str:
    return tempfile.mkdtemp(prefix="fieldpack-stage-")


def staging_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, `spark.checkpoint.dir`. Where it is unset, a temporary one is right
    on one machine only (tests); a cluster must name its own."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    master = spark.conf.get("spark.master", "")
    if not (master == "local" or master.startswith("local[")):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    return _own_folder()


def _remove(spark: SparkSession, path: str) -> None:
    try:
        hpath = spark._jvm.org.apache.hadoop.fs.Path(path)
        hpath.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hpath, True)
    except Exception:  # the session has ended: the folder's owner clears it
        return


def stage(df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
    """Writes `df` once to the shared folder and reads it back: lineage ends there, and a lost
    executor costs nothing that was staged. The files go when the Python process ends."""
    spark = df.sparkSession
    path = f"{staging_dir(spark)}/{name}-{uuid.uuid4().hex}"
    writer = df.write.option("compression", "zstd")
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)
    atexit.register(_remove, spark, path)
    return spark.read.schema(df.schema).parquet(path)


def drop_staged(*frames: DataFrame) -> None:
    """Deletes the files of staged tables that no later plan reads."""
    for df in frames:
        for f in {x.rsplit("/", 1)[0] for x in df.inputFiles()}:
            _remove(df.sparkSession, f)


def crc_split(id_col: Column, modulus: int, remainder: int) -> Column:
    """True on the held-out rows: crc32 of the id's text has this remainder. A null id is never held out."""
    return F.coalesce(F.crc32(F.encode(id_col.cast("string"), "UTF-8")) % modulus == remainder, F.lit(False))


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, held_out: Column, most: int, most_bytes: int | None = None) -> DataFrame:
    """At most `most` labelled rows that are not held out, as (doc_id, text, label): those of the smallest hash of
    the id, and of those as many as have `most_bytes` bytes of text together. Equal rows count once; an id with
    several texts gives several rows, which the bounds hold too. The ids are at most `most`, so they are broadcast."""
    chosen = (
        labels.filter(~held_out & F.col(label).isNotNull() & F.col("doc_id").isNotNull())
        .select("doc_id", F.col(label).cast("int").alias("label"))
        .groupBy("doc_id").agg(F.max("label").alias("label"))
        .orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    )
    named = docs.select("doc_id", F.coalesce(F.col("text"), F.lit("")).alias("text")).join(F.broadcast(chosen), "doc_id")
    rows = stage(named.withColumn("_mark", F.xxhash64("text")), "labelled")
    keys = rows.select("doc_id", "_mark", F.octet_length("text").cast("long").alias("_bytes")).distinct().orderBy(F.xxhash64("doc_id"), "doc_id", "_mark").limit(most)
    if most_bytes is not None:  # the window holds at most `most` keys
        upto = Window.orderBy(F.xxhash64("doc_id"), "doc_id", "_mark").rowsBetween(Window.unboundedPreceding, 0)
        keys = keys.withColumn("_upto", F.sum("_bytes").over(upto)).where((F.col("_upto") <= most_bytes) | (F.col("_upto") == F.col("_bytes")))
    taken = rows.join(F.broadcast(keys.select("doc_id", "_mark")), ["doc_id", "_mark"])
    return taken.dropDuplicates(["doc_id", "_mark"]).select("doc_id", "text", "label")
