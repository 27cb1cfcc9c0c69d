"""A data source of made-up snippets for load tests: every row follows from its number, so partitions can be read again."""

from __future__ import annotations

import hashlib

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def made(i: int) -> str:
    digest = hashlib.md5(str(i).encode()).hexdigest()
    return " ".join(f"w{int(digest[k : k + 2], 16)}" for k in range(0, 32, 2))


def of_numbers(numbers: DataFrame) -> DataFrame:
    """The source's rows for the numbers of a table, (doc_id, text); a null number is left out."""

    def rows(batches):
        for batch in batches:
            ids = batch.iloc[:, 0]
            yield pd.DataFrame({"doc_id": ids, "text": [made(int(i)) for i in ids]})

    return numbers.dropna().mapInPandas(rows, "doc_id bigint, text string")


class SnippetSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "snippets"

    def schema(self) -> str:
        return "doc_id bigint, text string"

    def reader(self, schema) -> DataSourceReader:
        return SnippetReader(int(self.options.get("rows", 100)), int(self.options.get("partitions", 2)))


class SnippetReader(DataSourceReader):
    def __init__(self, rows: int, partitions: int):
        self.rows, self.parts = rows, partitions

    def partitions(self):
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition):
        for i in range(partition.value, self.rows, self.parts):
            yield i, made(i)
