"""Term statistics and weights.

Statistics are long tables: (doc_id, term, tf), (term, df, cf) and one row (n). The vocabulary is open: terms are values, never positions.
``merged`` statistics are sums, so any split into batches and any order give the same; idf is derived when read.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def log(value: Column, base: float) -> Column:
    return F.log10(value) if base == 10 else F.ln(value) / F.lit(math.log(base))


def term_counts(docs: DataFrame, terms: str = "terms", keys: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """(keys, term, tf). Counting starts before the shuffle, so a document sends each of its terms once."""
    return docs.select(*keys, F.explode(terms).alias("term")).groupBy(*keys, "term").agg(F.count("*").alias("tf"))


def bags(docs: DataFrame, size: int, extra: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, block, terms, tfs, extra): a row a document with its distinct terms and their counts, counted within the row and without a shuffle.

    A block is rows of one task with about ``size`` terms, so that what blocks hold can be summed where they are read. To be written before use.
    """

    def count(batches):
        block, seen = TaskContext.get().partitionId() << 32, 0
        for batch in batches:
            held = batch.column(1).fill_null([])
            codes = held.flatten().dictionary_encode()
            lengths = held.value_lengths().to_numpy(zero_copy_only=False)
            width = max(len(codes.dictionary), 1)
            both, n = np.unique(np.repeat(np.arange(len(held)), lengths) * width + codes.indices.to_numpy(), return_counts=True)
            starts = np.searchsorted(both, np.arange(len(held) + 1) * width)
            lists = [pa.ListArray.from_arrays(pa.array(starts.astype("int32")), v) for v in (codes.dictionary.take(pa.array(both % width)), pa.array(n.astype("int64")))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(block + (seen + starts[:-1]) // size), *lists, *batch.columns[2:]], ["doc_id", "block", "terms", "tfs", *extra])
            seen += len(both)

    held = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "terms", *extra)
    kinds = "".join(f", {c} {kind}" for c, kind in held.dtypes[2:])
    return held.mapInArrow(count, f"doc_id bigint, block bigint, terms array<string>, tfs array<bigint>{kinds}")


def bag_counts(bagged: DataFrame) -> DataFrame:
    """(doc_id, block, term, tf) of bags."""
    return bagged.select("doc_id", "block", F.inline(F.arrays_zip(F.col("terms").alias("term"), F.col("tfs").alias("tf"))))


def bag_idf(bagged: DataFrame, base: float = 10) -> DataFrame:
    """(term, idf, blocks): blocks count their documents first, so a term is sent once a block and not once a document."""
    own = bagged.select("block", F.explode("terms").alias("term")).groupBy("block", "term").agg(F.count("*").alias("c"))
    both = own.groupBy("term").agg(F.sum("c").alias("df"), F.collect_list("block").alias("blocks")).join(F.broadcast(corpus_size(bagged)))
    return both.select("term", log(F.col("n") / F.col("df"), base).alias("idf"), "blocks")


def from_rows(df: DataFrame, doc: str, term: str, qty: str) -> DataFrame:
    """Bags from relational rows: what a document is, what a term is, and what is summed."""
    return df.groupBy(F.col(doc).alias("doc_id"), F.col(term).alias("term")).agg(F.sum(qty).alias("tf"))


def from_dense(df: DataFrame, doc: str, vector: str) -> DataFrame:
    return df.select(F.col(doc).alias("doc_id"), F.posexplode(vector).alias("term", "w")).withColumn("w", F.col("w").cast("double"))


def document_frequency(tf: DataFrame) -> DataFrame:
    """(term, df, cf): rows are distinct by document and term, so no distinct aggregate is needed."""
    return tf.groupBy("term").agg(F.count("*").alias("df"), F.sum("tf").alias("cf"))


def corpus_size(docs: DataFrame) -> DataFrame:
    return docs.agg(F.count("*").alias("n"))


def idf(frequency: DataFrame, size: DataFrame, base: float = 10, smooth: str = "none") -> DataFrame:
    """(term, df, cf, idf); the one row of the collection's size is broadcast, never collected."""
    both = frequency.join(F.broadcast(size))
    ratio = F.col("n") / F.col("df") if smooth == "none" else (F.col("n") + 1) / (F.col("df") + 1)
    return both.select("term", "df", "cf", log(ratio, base).alias("idf"))


def damped(tf: Column, mode: str = "log", base: float = 10, cf: Column | None = None) -> Column:
    if mode == "log":
        return log(tf, base) + 1.0
    return {"raw": tf, "binary": F.lit(1.0), "collection": cf}[mode].cast("double")


def raw_weights(tf: DataFrame, idfs: DataFrame, mode: str = "log", base: float = 10, keep_unknown: bool = False) -> DataFrame:
    """(doc_id, term, x): damped count times idf. Terms the model doesn't know are dropped, or kept with a null weight."""
    joined = tf.join(idfs, "term", "left" if keep_unknown else "inner")
    return joined.select(*tf.columns[:-2], "term", (damped(F.col("tf"), mode, base, F.col("cf")) * F.col("idf")).alias("x"))


def unit(raw: DataFrame, keys: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """(keys, term, w) of length one. Zero weights add nothing to any product and go; a document of zeros has no rows left."""
    whole = raw.filter("x <> 0").withColumn("s", F.sum(F.col("x") * F.col("x")).over(W.partitionBy(*keys)))
    return whole.select(*keys, "term", F.try_divide("x", F.sqrt("s")).alias("w"))


def weights(tf: DataFrame, n: DataFrame, base: float = 10, mode: str = "log") -> DataFrame:
    return unit(raw_weights(tf, idf(document_frequency(tf), n, base), mode, base))


def degenerate(docs: DataFrame, weighted: DataFrame) -> DataFrame:
    """Documents without any weight: nothing can be near them."""
    return docs.join(weighted.select("doc_id").distinct(), "doc_id", "left_anti")


def as_map(weighted: DataFrame) -> DataFrame:
    return weighted.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("term", "w"))).alias("vector"))


@dataclass(frozen=True)
class StaticModel:
    """Statistics of the training documents, never changed afterwards."""

    frequency: DataFrame
    size: DataFrame

    @classmethod
    def fit(cls, tf: DataFrame, docs: DataFrame) -> StaticModel:
        return cls(document_frequency(tf), corpus_size(docs))

    def idf(self, base: float = 10) -> DataFrame:
        return idf(self.frequency, self.size, base)

    def transform(self, tf: DataFrame, oov: str = "drop", base: float = 10, mode: str = "log") -> DataFrame:
        """Unit weights. ``oov='norm'``: unknown terms lengthen the norm as a term of one document would, but match nothing."""
        if oov == "drop":
            return unit(raw_weights(tf, self.idf(base), mode, base))
        known = tf.join(self.idf(base), "term", "left").join(F.broadcast(self.size))
        x = damped(F.col("tf"), mode, base, F.coalesce("cf", "tf")) * F.coalesce(F.col("idf"), log(F.col("n").cast("double"), base))
        whole = known.withColumn("x", x).withColumn("s", F.sum(F.col("x") * F.col("x")).over(W.partitionBy("doc_id")))
        return whole.filter("idf IS NOT NULL AND x <> 0").select("doc_id", "term", F.try_divide("x", F.sqrt("s")).alias("w"))


@dataclass(frozen=True)
class IncrementalModel:
    """Statistics that every batch is added to. ``merged`` adds counts; ``additive`` adds the batches' idf, as the formula is printed."""

    frequency: DataFrame
    size: DataFrame
    scheme: str = "merged"

    @classmethod
    def fit(cls, tf: DataFrame, docs: DataFrame, scheme: str = "merged", base: float = 10) -> IncrementalModel:
        frequency, size = document_frequency(tf), corpus_size(docs)
        return cls(frequency if scheme == "merged" else idf(frequency, size, base), size, scheme)

    def update(self, tf: DataFrame, docs: DataFrame, base: float = 10) -> IncrementalModel:
        other = IncrementalModel.fit(tf, docs, self.scheme, base)
        size = self.size.unionAll(other.size).agg(F.sum("n").alias("n"))
        sums = [F.sum(c).alias(c) for c in other.frequency.columns[1:]]
        return IncrementalModel(self.frequency.unionByName(other.frequency).groupBy("term").agg(*sums), size, self.scheme)

    def idf(self, base: float = 10) -> DataFrame:
        return idf(self.frequency, self.size, base) if self.scheme == "merged" else self.frequency

    def transform(self, tf: DataFrame, base: float = 10, mode: str = "log") -> DataFrame:
        return unit(raw_weights(tf, self.idf(base), mode, base))


def sizes(docs: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, batch_id, nb, n, top): documents of each batch, and of all up to it; the last batch."""
    counts = docs.groupBy(*by, "batch_id").agg(F.count("*").alias("nb"))
    return counts.withColumn("n", F.sum("nb").over(W.partitionBy(*by).orderBy("batch_id"))).withColumn("top", F.max("batch_id").over(W.partitionBy(*by)))


def changes(tf: DataFrame, size: DataFrame, base: float = 10, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, term, since, next, df, cf, idf, top): a term's running sums as they stand from one of its batches until the next."""
    own = tf.groupBy(*by, "batch_id", "term").agg(F.count("*").alias("dfb"), F.sum("tf").alias("cfb"))
    own = own.join(F.broadcast(size), [*by, "batch_id"]).withColumn("idfb", log(F.col("nb") / F.col("dfb"), base))
    so_far = W.partitionBy(*by, "term").orderBy("batch_id")
    return own.select(*by, "term", F.col("batch_id").alias("since"), F.lead("batch_id").over(so_far).alias("next"), *[F.sum(c).over(so_far).alias(c[:-1]) for c in ("dfb", "cfb", "idfb")], "top")


def history(tf: DataFrame, docs: DataFrame, scheme: str = "merged", base: float = 10, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, batch_id, term, idf, cf): the model as of every batch, in one plan. Batches are numbered without holes; 0 is the training.

    A term has rows from its first batch on, made by one generator from its sorted changes; running sums stay within a term's array, or
    run over one row a batch. ``by`` names columns of streams that are apart from each other.
    """
    size = sizes(docs, by)
    filled = changes(tf, size, base, by).select(*by, "term", "df", "cf", "idf", F.explode(F.sequence("since", F.coalesce(F.col("next") - 1, "top"))).alias("batch_id"))
    if scheme == "additive":
        return filled.select(*by, "batch_id", "term", "idf", "cf")
    return filled.join(F.broadcast(size.select(*by, "batch_id", "n")), [*by, "batch_id"]).select(*by, "batch_id", "term", log(F.col("n") / F.col("df"), base).alias("idf"), "cf")


def new_terms(tf: DataFrame) -> DataFrame:
    """(term, batch_id): the batch in which each term is first seen."""
    return tf.groupBy("term").agg(F.min("batch_id").alias("batch_id"))


def drift(before: DataFrame, after: DataFrame) -> DataFrame:
    """(term, before, after, change) of idf between two models; a term one of them doesn't know counts as 0 there."""
    joined = before.select("term", F.col("idf").alias("before")).join(after.select("term", F.col("idf").alias("after")), "term", "full_outer")
    return joined.na.fill(0.0, ["before", "after"]).withColumn("change", F.abs(F.col("after") - F.col("before")))
