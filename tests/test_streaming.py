"""Streams give what the batch gives; late and repeated rows go."""

from pyspark.sql import functions as F

from fieldpack.sources.raw import stream_events
from fieldpack.sources.tables import load
from fieldpack.streaming import slabs as S


def events_folder(spark, sf_dir, path, parts=3):
    e = load(spark, sf_dir, "events").where("event_id < 300")
    day = F.floor(F.col("event_id") / (300 // parts)).cast("int")
    for i in range(parts):
        e.where(day == i).coalesce(1).write.mode("append").parquet(path)
    e.where("event_id < 20").coalesce(1).write.mode("append").parquet(path)  # repeated
    return e


def run(df, name, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)
    return df.sparkSession.table(name)


def test_slabs_equal_batch(spark, sf_dir, tmp_path):
    path = str(tmp_path / "events")
    e = events_folder(spark, sf_dir, path)
    stream = stream_events(spark, path, 1)
    got = run(S.slabs(S.deduplicated(stream, "40 days")), "slabs", "append")
    want = S.slabs(e.withColumn("ts", F.col("ts").cast("timestamp")))
    last = want.agg(F.max("start")).first()[0]
    assert got.where(F.col("start") < last).exceptAll(want).isEmpty()


def test_stateful_sums(spark, sf_dir, tmp_path):
    path = str(tmp_path / "events")
    e = load(spark, sf_dir, "events").where("event_id < 200")
    e.coalesce(1).write.parquet(path)
    run(S.running_cells(stream_events(spark, path)), "cells", "update")
    got = spark.table("cells").groupBy("x", "z").agg(F.max("n").alias("n"))
    want = e.withColumn("ts", F.col("ts").cast("timestamp")).select(*S.cell_columns()).groupBy("x", "z").agg(F.count("*").alias("n"))
    assert got.exceptAll(want).isEmpty() and got.count() == want.count()


def test_slab_encoder_groups(spark, sf_dir, tmp_path):
    path = str(tmp_path / "events")
    load(spark, sf_dir, "events").coalesce(1).write.parquet(path)
    seen = []
    cells = S.slabs(stream_events(spark, path).withWatermark("ts", "1 hour"))
    S.start_slab_encoder(cells, 4, lambda df, first: seen.append((first, df.select("slab").distinct().count())), str(tmp_path / "ck")).awaitTermination(120)
    assert seen and all(n <= 4 for _, n in seen) and len({f for f, _ in seen}) == len(seen)
