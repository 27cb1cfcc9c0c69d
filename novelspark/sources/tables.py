"""Reading tables, and arrival order and time of documents."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, fmt: str, schema: str, **options) -> DataFrame:
    """CSV, JSON lines, text or ORC with a given schema; rows that don't fit keep their text in ``_corrupt_record`` where the schema has it."""
    held = {"mode": "PERMISSIVE", "columnNameOfCorruptRecord": "_corrupt_record"} if fmt in ("csv", "json") else {}
    return spark.read.format(fmt).schema(schema).options(**held, **options).load(path)


def stream(spark: SparkSession, fmt: str, path: str | None = None, schema: str | None = None, **options) -> DataFrame:
    """A streaming source: files of any format with a given schema, ``rate``, ``socket``, or ``kafka`` where its connector is installed."""
    reader = spark.readStream.format(fmt).options(**options)
    reader = reader.schema(schema) if schema else reader
    return reader.load(path) if path else reader.load()


def write(df: DataFrame, path: str, partition_by: tuple[str, ...] = (), sort_by: tuple[str, ...] = (), mode: str = "overwrite") -> None:
    """Parquet by partition columns, rows of a partition together and sorted, so that row groups can be skipped."""
    out = df.repartition(*partition_by) if partition_by else df
    out = out.sortWithinPartitions(*partition_by, *sort_by) if sort_by else out
    out.write.mode(mode).partitionBy(*partition_by).parquet(path)


def with_arrival(docs: DataFrame, events: DataFrame) -> DataFrame:
    """``ts`` of the event whose id is the document's: the arrival time, as a timestamp with zone (watermarks need one)."""
    return docs.join(events.select(F.col("event_id").alias("doc_id"), F.col("ts").cast("timestamp").alias("ts")), "doc_id")


def batch_of(seq: Column, size: int) -> Column:
    return F.floor(seq / size).cast("bigint")
