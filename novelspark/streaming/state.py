"""Versioned state in shared storage: a version is written whole, then a pointer names it. A replayed batch writes the same version again."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


class StateStore:
    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def _fs(self, name: str):
        jvm = self.spark._jvm
        path = jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
        return path, path.getFileSystem(self.spark._jsc.hadoopConfiguration())

    def publish(self, version: int, **tables: DataFrame) -> None:
        for name, df in tables.items():
            df.write.mode("overwrite").parquet(f"{self.path}/v={version}/{name}")
        path, fs = self._fs(f"done/{version}")
        fs.create(path, True).close()

    def versions(self) -> list[int]:
        path, fs = self._fs("done")
        return sorted(int(x.getPath().getName()) for x in fs.listStatus(path)) if fs.exists(path) else []

    def before(self, version: int) -> int | None:
        """The newest published version below the given one: what a batch starts from, also when it is replayed."""
        return max((v for v in self.versions() if v < version), default=None)

    def read(self, version: int, name: str) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/v={version}/{name}")

    def forget(self, keep: int = 2) -> None:
        for v in self.versions()[:-keep]:
            for name in (f"done/{v}", f"v={v}"):
                path, fs = self._fs(name)
                fs.delete(path, True)
