"""Streaming detection: each micro-batch joins the statistics, then is scored against the history under the updated model.

State is carried from batch to batch as published versions of the term counts. The version a batch starts from depends on its number alone, so
a batch that runs twice leaves state and output as one run does. Late documents are scored by the model of the batch in which they are processed.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import detect, model
from ..operators.detect import Config
from ..sources.scratch import Scratch
from .state import StateStore


class StreamDetector:
    """``train`` and the stream's rows are (doc_id, terms). The history is the training, weighed anew at every batch.

    Static and merged schemes give the rows of ``detect.scores``; settings that the stream can't carry are refused.
    """

    def __init__(self, spark: SparkSession, path: str, train: DataFrame, cfg: Config = Config()):
        if cfg.scheme not in ("static", "merged"):
            raise ValueError(f"a stream has no state for scheme {cfg.scheme!r}")
        if cfg.history != "reference":
            raise ValueError(f"a stream has no history {cfg.history!r}: it searches the training only")
        if cfg.scheme == "static" and cfg.oov == "norm":
            raise ValueError("a stream has no norm of unknown words")
        self.spark, self.path, self.cfg = spark, path, cfg
        self.state = StateStore(spark, f"{path}/state")
        self.train = model.term_counts(train)
        if not self.state.versions():
            self.state.publish(-1, frequency=model.document_frequency(self.train), size=model.corpus_size(train))

    def batch(self, rows: DataFrame, number: int) -> None:
        rows = rows.select("doc_id", "terms").dropDuplicates(["doc_id"])
        before = self.state.before(number)
        held = model.IncrementalModel(self.state.read(before, "frequency"), self.state.read(before, "size"))
        tf = model.term_counts(rows)
        if self.cfg.scheme == "static":
            now = held
            self.state.publish(number, frequency=held.frequency, size=held.size)
        else:
            new = held.update(tf, rows)
            self.state.publish(number, frequency=new.frequency, size=new.size)
            now = model.IncrementalModel(self.state.read(number, "frequency"), self.state.read(number, "size"))
        # the history is the training: batch 0; the model of this batch weighs both sides
        both = tf.withColumn("batch_id", F.lit(1).cast("bigint")).unionByName(self.train.withColumn("batch_id", F.lit(0).cast("bigint")))
        held = now.idf(self.cfg.base).select("term", F.lit(0).cast("bigint").alias("since"), F.lit(None).cast("bigint").alias("next"), "df", "cf", "idf")
        docs = rows.select("doc_id", F.lit(1).cast("bigint").alias("batch_id"))
        sizes = self.spark.range(2).select(F.col("id").alias("batch_id"), F.lit(None).cast("bigint").alias("n"))
        scratch = Scratch(self.spark, "stream")
        # within one batch no model changes, whatever the scheme
        cfg = self.cfg.but(scheme="static", oov="drop")
        scored = detect.search(docs, scratch.write(both.select("doc_id", "batch_id", "term", "tf"), "tf"), scratch.write(held, "models"), sizes, cfg, scratch)
        scored.write.mode("overwrite").parquet(f"{self.path}/scored/batch={number}")
        scratch.drop("tf", "models", "history")

    def run(self, source: DataFrame) -> None:
        """Takes what the source holds now, a micro-batch after the other; may be called again after a stop."""
        writer = source.writeStream.foreachBatch(self.batch).option("checkpointLocation", f"{self.path}/offsets")
        writer.trigger(availableNow=True).start().awaitTermination()

    def scored(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/scored").drop("batch")


def late_counts(stream: DataFrame, delay: str, every: str) -> DataFrame:
    """Documents a window of arrival time, with a watermark: rows later than ``delay`` are not counted."""
    timed = stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)
    return timed.groupBy(F.window("ts", every).alias("w")).agg(F.count("*").alias("n")).select("w.start", "n")


def unrepeated(stream: DataFrame, delay: str, *keys: str) -> DataFrame:
    """The stream without rows that repeat the keys within the watermark's delay."""
    return stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay).dropDuplicatesWithinWatermark(list(keys))


def within_interval(left: DataFrame, right: DataFrame, row: str, key: str, delay: str, span: str) -> DataFrame:
    """(q, h): each left row with the right rows of its key that came at most ``span`` before it, or with it. Both are streams with ``ts``."""
    side = lambda df, name, at: df.select(F.col(row).alias(name), F.col(key).alias(f"key_{name}"), F.col("ts").cast("timestamp").alias(at)).withWatermark(at, delay)
    met = (F.col("key_q") == F.col("key_h")) & (F.col("q") != F.col("h")) & (F.col("u") <= F.col("t")) & (F.col("u") >= F.col("t") - F.expr(f"INTERVAL {span}"))
    return side(left, "q", "t").join(side(right, "h", "u"), met).select("q", "h")


def keyed_novelty(rows: DataFrame, key: str, threshold: float = 0.5, ttl: int | None = None) -> DataFrame:
    """(key, seq, new_share, is_novel): a light detector within one key, on a stream of (key, seq, terms).

    The state of a key is the set of terms seen so far; a row is novel if the share of terms unseen in its key reaches the threshold.
    With ``ttl`` (seconds) the rows also hold ``ts``, with a watermark, and a key's state is dropped once the watermark is ``ttl`` past its last row.
    """
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(name: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        seen, last = (set(filter(None, state.get[0].split("\x1f"))), state.get[1]) if state.exists else (set(), 0)
        for batch in batches:
            out = []
            for row in batch.sort_values("seq").itertuples():
                terms = set(row.terms)
                share = len(terms - seen) / len(terms) if terms else 1.0
                out.append((name[0], row.seq, share, share >= threshold))
                seen |= terms
                last = max(last, row.ms)
            yield pd.DataFrame(out, columns=["key", "seq", "new_share", "is_novel"])
        state.update(("\x1f".join(sorted(seen)), last))
        if ttl:
            state.setTimeoutTimestamp(max(last + ttl * 1000, state.getCurrentWatermarkMs() + 1))

    at = [F.unix_millis("ts").alias("ms"), "ts"] if ttl else [F.lit(0).cast("bigint").alias("ms")]
    grouped = rows.select(F.col(key).cast("bigint").alias("key"), F.col("seq").cast("bigint").alias("seq"), "terms", *at).groupBy("key")
    timeout = GroupStateTimeout.EventTimeTimeout if ttl else GroupStateTimeout.NoTimeout
    return grouped.applyInPandasWithState(step, "key bigint, seq bigint, new_share double, is_novel boolean", "terms string, last bigint", "append", timeout)
