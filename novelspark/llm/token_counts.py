"""Token counts from an exact length histogram (operator 10).

Every document is encoded once and only its length is kept; documents of equal length are one row of the histogram. Suffix
sums over the histogram then answer, for every context limit, the documents and tokens that fit, that overflow, the total
after truncation and any quantile, without another look at the texts.

Defined cases: a null or empty text has length 0; repeated rows count each; an empty table gives an empty histogram.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Scratch, documents, slices

BLOCK = 1024


def lengths(docs: DataFrame, text: str = "text", path: str | None = None) -> DataFrame:
    """Histogram of each task's documents: (n_tokens, n_docs), a row for each length that occurs."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from .bpe import encoder

        found: dict[int, int] = {}
        for batch in slices(batches, 0):
            for n in encoder(path).count(batch.column(0).to_pylist()).tolist():
                found[n] = found.get(n, 0) + 1
        yield pa.RecordBatch.from_arrays([pa.array(found.keys(), pa.int64()), pa.array(found.values(), pa.int64())], names=["n_tokens", "n_docs"])

    return docs.select(F.col(text).alias("text")).mapInArrow(count, "n_tokens long, n_docs long")


def histogram(docs: DataFrame, text: str = "text", path: str | None = None) -> DataFrame:
    return lengths(docs, text, path).groupBy("n_tokens").agg(F.sum("n_docs").alias("n_docs"))


def stored(docs: DataFrame, text: str = "text", path: str | None = None) -> DataFrame:
    """The histogram as a written table: whoever reads it twice does not encode twice."""
    return Scratch(docs.sparkSession, "lengths").write(histogram(docs, text, path), "histogram")


def with_suffix_sums(hist: DataFrame) -> DataFrame:
    """For each length L: documents and tokens of length L or more, and the total when all texts are cut to L tokens.

    The sums go over blocks of lengths first, so no task gets the whole histogram row by row. The histogram is read twice: give a
    stored one.
    """
    rows = hist.withColumn("tokens", F.col("n_tokens") * F.col("n_docs")).withColumn("block", F.floor(F.col("n_tokens") / BLOCK))
    blocks = rows.groupBy("block").agg(F.sum("n_docs").alias("block_docs"), F.sum("tokens").alias("block_tokens"))
    later = W.orderBy(F.desc("block")).rowsBetween(W.unboundedPreceding, -1)
    earlier = W.orderBy("block").rowsBetween(W.unboundedPreceding, -1)
    blocks = blocks.select(
        "block",
        F.coalesce(F.sum("block_docs").over(later), F.lit(0)).alias("later_docs"),
        F.coalesce(F.sum("block_tokens").over(later), F.lit(0)).alias("later_tokens"),
        F.coalesce(F.sum("block_tokens").over(earlier), F.lit(0)).alias("earlier_tokens"),
    )
    down = W.partitionBy("block").orderBy(F.desc("n_tokens"))
    up = W.partitionBy("block").orderBy("n_tokens")
    return (
        rows.join(F.broadcast(blocks), "block")
        .withColumn("docs_from", F.sum("n_docs").over(down) + F.col("later_docs"))
        .withColumn("tokens_from", F.sum("tokens").over(down) + F.col("later_tokens"))
        .withColumn("tokens_up_to", F.sum("tokens").over(up) + F.col("earlier_tokens"))
        .withColumn("truncated_total", F.col("tokens_up_to") - F.col("tokens") + F.col("n_tokens") * F.col("docs_from"))
        .select("n_tokens", "n_docs", "tokens", "docs_from", "tokens_from", "tokens_up_to", "truncated_total")
    )


def at_limits(table: DataFrame, limits: list[int]) -> DataFrame:
    """Answers for any context limits from the suffix-sum table: one row a limit."""
    spark = table.sparkSession
    asked = spark.createDataFrame([(int(x),) for x in limits], "context_limit long")
    joined = asked.join(table, F.col("n_tokens") >= F.col("context_limit"), "left")
    over = joined.groupBy("context_limit").agg(
        F.coalesce(F.sum("n_docs"), F.lit(0)).alias("docs_from"), F.coalesce(F.sum("tokens"), F.lit(0)).alias("tokens_from")
    )
    whole = table.agg(F.coalesce(F.sum("tokens"), F.lit(0)).alias("total"), F.coalesce(F.sum("n_docs"), F.lit(0)).alias("docs"))
    return over.join(F.broadcast(whole)).select(
        "context_limit",
        (F.col("docs") - F.col("docs_from")).alias("docs_below"),
        "docs_from",
        (F.col("total") - F.col("tokens_from") + F.col("context_limit") * F.col("docs_from")).alias("truncated_total"),
        F.col("total").alias("total"),
    )


def quantile(table: DataFrame, share: float) -> DataFrame:
    """The smallest length with at least ``share`` of all documents at or below it."""
    total = table.agg(F.sum("n_docs").alias("docs"))
    below = F.col("docs") - F.col("docs_from") + F.col("n_docs")
    return table.join(F.broadcast(total)).filter(below >= F.lit(share) * F.col("docs")).agg(F.min("n_tokens").alias("length"))


def op10_length_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return with_suffix_sums(stored(documents(spark, sf_dir)))
