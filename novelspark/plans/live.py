"""Streaming queries: each runs a stream to its end and gives what it left. They are compared with batch runs in tests."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import tokens
from ..operators.detect import Config
from ..sources import tables
from ..sources.scratch import folder
from ..sources.tables import table
from ..streaming import detector
from ..streaming.state import StateStore
from . import streams

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return keep


def batch_files(spark, docs: DataFrame, path: str) -> str:
    """The test part of a stream as one folder with a file a batch, in order. The rows are split by batch once; each file then reads its own."""
    rows = docs.filter("batch_id > 0").select("batch_id", "doc_id", "terms")
    rows.repartition("batch_id").sortWithinPartitions("batch_id", "doc_id").write.partitionBy("batch_id").parquet(f"{path}/split")
    held = spark.read.schema(rows.schema).parquet(f"{path}/split")
    for b in range(1, held.agg(F.max("batch_id")).first()[0] + 1):
        held.filter(F.col("batch_id") == b).drop("batch_id").coalesce(1).sortWithinPartitions("doc_id").write.mode("append").parquet(f"{path}/in")
    return f"{path}/in"


def run_detector(spark, d, cfg: Config, path: str) -> DataFrame:
    docs = streams.constructed(spark, d)
    source = tables.stream(spark, "parquet", batch_files(spark, docs, path), "doc_id bigint, terms array<string>", maxFilesPerTrigger=1)
    live = detector.StreamDetector(spark, f"{path}/live", docs.filter("batch_id = 0").select("doc_id", "terms"), cfg)
    live.run(source)
    return live.scored()


@query("stream_detect")
def stream_detect(spark, d):
    return run_detector(spark, d, Config(k=4, tables=8), folder(spark, "stream"))


@query("stream_keyed")
def stream_keyed(spark, d):
    path = folder(spark, "keyed")
    table(spark, d, "conversations").select("conv_id", F.col("turn").alias("seq"), tokens(F.col("text")).alias("terms")).coalesce(1).write.parquet(f"{path}/in")
    source = tables.stream(spark, "parquet", f"{path}/in", "conv_id bigint, seq bigint, terms array<string>")
    out = detector.keyed_novelty(source, "conv_id")
    out.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/offsets").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{path}/out")


def _file_stream(spark, d, path: str, name: str = "events") -> DataFrame:
    rows = table(spark, d, name)
    rows.coalesce(1).write.parquet(f"{path}/in")
    return spark.readStream.schema(rows.schema).parquet(f"{path}/in")


def _finished(spark, df: DataFrame, path: str, mode: str = "append") -> DataFrame:
    df.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/offsets").outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{path}/out")


@query("stream_source", "SELECT event_id, event_type FROM events")
def stream_source(spark, d):
    path = folder(spark, "source")
    return _finished(spark, _file_stream(spark, d, path).select("event_id", "event_type"), path)


@query("stream_windows", "SELECT epoch_us(time_bucket(INTERVAL 6 HOUR, ts)) AS start, count(*) AS n FROM events GROUP BY 1 HAVING epoch_us(time_bucket(INTERVAL 6 HOUR, any_value(ts))) + 21600000000 <= (SELECT epoch_us(max(ts)) - 3600000000 FROM events)")
def stream_windows(spark, d):
    """Windows that the watermark has closed."""
    path = folder(spark, "windows")
    return _finished(spark, detector.late_counts(_file_stream(spark, d, path), "1 hour", "6 hours").select(F.unix_micros("start").alias("start"), "n"), path)


@query("stream_unrepeated")
def stream_unrepeated(spark, d):
    path = folder(spark, "unrepeated")
    return _finished(spark, detector.unrepeated(_file_stream(spark, d, path), "1 hour", "user_id", "event_type").select("event_id", "user_id", "event_type"), path)


@query("stream_static_join", "SELECT event_id, c_nationkey FROM events JOIN customer ON c_custkey = user_id")
def stream_static_join(spark, d):
    path = folder(spark, "joined")
    customers = table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_nationkey")
    return _finished(spark, _file_stream(spark, d, path).join(customers, "user_id").select("event_id", "c_nationkey"), path)


@query("stream_interval_join", "SELECT a.event_id AS q, b.event_id AS h FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_id <> a.event_id AND b.ts BETWEEN a.ts - INTERVAL 1 DAY AND a.ts")
def stream_interval_join(spark, d):
    """A user's events of the day before each event: two streams, each with a watermark, so that old rows leave the state."""
    path = folder(spark, "interval")
    left = _file_stream(spark, d, path)
    return _finished(spark, detector.within_interval(left, spark.readStream.schema(left.schema).parquet(f"{path}/in"), "event_id", "user_id", "1 hour", "1 day"), path)


@query("sink_stream", "SELECT event_id FROM events")
def sink_stream(spark, d):
    """``foreachBatch`` into a folder a batch: a replay overwrites its own folder."""
    path = folder(spark, "sink")

    def put(df: DataFrame, number: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/out/batch={number}")

    _file_stream(spark, d, path).select("event_id").writeStream.foreachBatch(put).option("checkpointLocation", f"{path}/offsets").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{path}/out").select("event_id")


@query("state_versions", "SELECT n_regionkey, count(*) AS n FROM nation WHERE n_regionkey <= 1 GROUP BY 1")
def state_versions(spark, d):
    store = StateStore(spark, folder(spark, "versions"))
    for v in range(3):
        store.publish(v, counts=table(spark, d, "nation").filter(F.col("n_regionkey") <= v).groupBy("n_regionkey").agg(F.count("*").alias("n")))
    return store.read(store.before(2), "counts")
