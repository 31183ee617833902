"""Streams give what their batch form gives; state, watermark and hysteresis behave."""

from __future__ import annotations

import shutil
import tempfile

import pytest
from pyspark.sql import functions as F

from relayout.streaming import volumes

SF = "/root/testdata/sf0.001"


@pytest.fixture
def folder():
    path = tempfile.mkdtemp()
    yield path
    shutil.rmtree(path)


def played(df, mode="append"):
    q = df.writeStream.outputMode(mode).format("memory").queryName("played").start()
    q.processAllAvailable()
    q.stop()
    return df.sparkSession.sql("SELECT * FROM played")


def stream(spark, rows, folder, files=3):
    rows.repartition(files).write.parquet(f"{folder}/in")
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")


def test_windows(spark, folder):
    rows = spark.read.parquet(f"{SF}/events.parquet")
    want = sorted(map(tuple, volumes.windowed(volumes.events(rows), "1 day").collect()))
    got = played(volumes.windowed(volumes.events(stream(spark, rows, folder)), "1 day"), "complete")
    assert sorted(map(tuple, got.collect())) == want


def test_resent_events_count_once(spark, folder):
    rows = spark.read.parquet(f"{SF}/events.parquet")
    got = played(volumes.once(volumes.events(stream(spark, rows.union(rows), folder), "60 days")))
    assert got.count() == rows.select("event_id").distinct().count()


def test_tiles_are_given_out_when_complete(spark, folder):
    cells = spark.range(64).select((F.col("id") / 8).cast("long").alias("i"), (F.col("id") % 8).alias("j"), F.col("id").alias("v")).filter("id <> 63")
    got = played(volumes.assembled(stream(spark, cells, folder, 4), 4, 16))
    want = {}
    for r in cells.collect():
        want.setdefault((r.i // 4, r.j // 4), []).append(r.v)
    assert {(r.bi, r.bj): (r.total, r.cells, r.data) for r in got.collect()} == {k: (sum(v), 16, sorted(v)) for k, v in want.items() if len(v) == 16}


def test_replies_within_the_interval(spark, folder):
    asks = spark.createDataFrame([(1, "00:00"), (2, "00:10")], "user_id long, t string")
    replies = spark.createDataFrame([(1, "00:30"), (1, "05:00"), (2, "00:05"), (2, "00:40"), (3, "00:01")], "user_id long, t string")
    both = []
    for k, df in enumerate((asks, replies)):
        timed = df.select("user_id", F.to_timestamp(F.concat(F.lit("2026-01-01 00:"), "t")).alias("ts"))
        timed.write.parquet(f"{folder}/{k}")
        both.append(spark.readStream.schema(timed.schema).parquet(f"{folder}/{k}").withWatermark("ts", "10 minutes"))
    got = played(volumes.answered(*both, "1 MINUTE"))
    assert sorted((r.user, r.replied.second) for r in got.collect()) == [(1, 30), (2, 40)]


def test_relabeling_is_refreshed_by_a_stream(spark, folder):
    keep: dict = {}
    rows = spark.createDataFrame([(0, 1, 100), (1, 0, 100), (0, 0, 5)], "src int, dst int, vol long")
    q = stream(spark, rows, folder).writeStream.foreachBatch(volumes.refresh(2, keep)).start()
    q.processAllAvailable()
    q.stop()
    assert keep["sigma"] == [1, 0] and sum(keep["parcels"].values()) == 205


def test_relabeling_changes_only_for_a_real_gain(spark):
    keep: dict = {}
    step = volumes.refresh(2, keep)
    step(spark.createDataFrame([(0, 1, 100), (1, 0, 100)], "src int, dst int, vol long"), 0)
    assert keep["sigma"] == [1, 0]
    step(spark.createDataFrame([(0, 0, 101), (1, 1, 100)], "src int, dst int, vol long"), 1)
    assert keep["sigma"] == [1, 0]
    step(spark.createDataFrame([(0, 0, 900), (1, 1, 900)], "src int, dst int, vol long"), 2)
    assert keep["sigma"] == [0, 1]
