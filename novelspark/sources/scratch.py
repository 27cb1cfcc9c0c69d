"""Intermediate tables in the folder that driver and executors share: written once, reread by every reader, also after a lost executor."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

TIDY = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder; on a local master without one (tests), a temporary folder. Elsewhere its absence is an error."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if base:
        return base
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    if not getattr(spark, "_novelspark_dir", None):
        spark._novelspark_dir = "file://" + tempfile.mkdtemp(prefix="novelspark-")
    return spark._novelspark_dir


def folder(spark: SparkSession, name: str) -> str:
    """A new folder of its own, deleted when the driver ends."""
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    held = spark._jvm.org.apache.hadoop.fs.Path(path)
    held.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(held)
    return path


class Scratch:
    """Tables of one operator call. Writing them cuts lineage and keeps plans short."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.base = spark, folder(spark, name)

    def write(self, df: DataFrame, name, rows: int = 0) -> DataFrame:
        """``rows``: most rows of a file, for rows so large that a reader cannot hold many of them at a time; 0 is any number."""
        path = f"{self.base}/{name}"
        df.write.mode("overwrite").option("maxRecordsPerFile", rows).parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def settle(self, df: DataFrame, name, rows: int = 0) -> DataFrame:
        """``write``, after which the shuffle files of the written plan go at once and not when the driver happens to collect its garbage."""
        held = self.spark.conf.get(TIDY, "false")
        self.spark.conf.set(TIDY, "true")
        try:
            return self.write(df, name, rows)
        finally:
            self.spark.conf.set(TIDY, held)

    def drop(self, *names: str) -> None:
        jvm, conf = self.spark._jvm, self.spark._jsc.hadoopConfiguration()
        for name in names:
            path = jvm.org.apache.hadoop.fs.Path(f"{self.base}/{name}")
            path.getFileSystem(conf).delete(path, True)
