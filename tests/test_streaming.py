"""State that expires, late rows, and what a stream join keeps."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from novelspark.streaming import detector

DAY = dt.datetime(2024, 1, 1)


def hours(n):
    return DAY + dt.timedelta(hours=n)


def arrive(spark, path, rows, schema):
    """One file a list of rows; the stream reads them one after another."""
    for batch in rows:
        spark.createDataFrame(batch, schema).coalesce(1).write.mode("append").parquet(f"{path}/in")
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/in")


def finished(spark, df, path):
    df.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/offsets").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return sorted(map(tuple, spark.read.schema(df.schema).parquet(f"{path}/out").collect()))


@pytest.mark.parametrize("ttl, share", [(None, 0.0), (3600, 1.0)])
def test_keyed_state_expires(spark, tmp_path, ttl, share):
    """Key 1 returns when the watermark is a day past its first row; key 2 returns while the watermark still stands at its own first row."""
    batches = [[(1, 0, ["a", "b"], hours(0))], [(2, 0, ["c"], hours(24))], [(2, 1, ["c", "d"], hours(48))], [(1, 1, ["a"], hours(49))]]
    source = arrive(spark, f"file://{tmp_path}/s", batches, "k long, seq long, terms array<string>, ts timestamp")
    got = finished(spark, detector.keyed_novelty(source.withWatermark("ts", "1 minute"), "k", ttl=ttl), f"file://{tmp_path}/s")
    assert [(k, seq, s) for k, seq, s, _ in got] == [(1, 0, 1.0), (1, 1, share), (2, 0, 1.0), (2, 1, 0.5)]


def test_rows_behind_the_watermark_are_not_counted(spark, tmp_path):
    """A row is late by the watermark of the batch before its own, so one batch lies between hour 30 and the late row."""
    batches = [[(hours(1),), (hours(2),)], [(hours(30),)], [(hours(31),)], [(hours(3),), (hours(29),)], [(hours(60),)]]
    source = arrive(spark, f"file://{tmp_path}/s", batches, "ts timestamp")
    counted = detector.late_counts(source, "2 hours", "12 hours").select(F.unix_seconds("start"), "n")
    start = lambda h: int(hours(h).replace(tzinfo=dt.timezone.utc).timestamp())
    assert finished(spark, counted, f"file://{tmp_path}/s") == [(start(0), 2), (start(24), 3)]


def test_interval_join_of_streams(spark, tmp_path):
    rows = [(1, 7, hours(0)), (2, 7, hours(5)), (3, 7, hours(5)), (4, 8, hours(6)), (5, 7, hours(40)), (6, None, hours(40)), (7, None, hours(40))]
    schema = "event_id long, user_id long, ts timestamp"
    source = arrive(spark, f"file://{tmp_path}/s", [rows], schema)
    other = spark.readStream.schema(schema).parquet(f"file://{tmp_path}/s/in")
    assert finished(spark, detector.within_interval(source, other, "event_id", "user_id", "1 hour", "1 day"), f"file://{tmp_path}/s") == [(2, 1), (2, 3), (3, 1), (3, 2)]
