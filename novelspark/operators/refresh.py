"""Keeping the history's hash projections and norms up to date without weighing it anew.

With a = damped count and r = a plane's component, the projection of a document is sum(a * idf * r) = lg(N) * A - B, where A = sum(a * r) never changes
and B = sum(a * lg(df) * r) changes only for terms whose df moved; likewise norm**2 = lg(N)**2 * S0 - 2 * lg(N) * S1 + S2. Growth of N alone costs
nothing; a batch touches the postings of its own terms. Rounding adds up in B, S1 and S2, so a full refresh is due now and then.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .lsh import WORD, _word


def _sums(rows: DataFrame, planes: int, seed: int, amount: dict[str, F.Column] | dict) -> DataFrame:
    """Per document: for each named amount an array of signed sums, a plane each, and the plain sums of the rest."""
    words = [_word(F.col("term"), seed, w).alias(f"w{w}") for w in range(-(-planes // WORD))]
    rows = rows.select("doc_id", *words, *[c.alias(n) for n, c in amount.items()])
    bit = lambda p: F.col(f"w{p // WORD}").bitwiseAND(F.lit(1 << (p % WORD))) != 0
    signed = lambda n: F.array(*[F.sum(F.when(bit(p), F.col(n)).otherwise(-F.col(n))) for p in range(planes)]).alias(n)
    return rows.groupBy("doc_id").agg(*[signed(n) if n in ("a", "b") else F.sum(n).alias(n) for n in amount])


def full(tf: DataFrame, frequency: DataFrame, planes: int, seed: int = 1) -> DataFrame:
    """(doc_id, a, b, s0, s1, s2) from all postings."""
    a, lg = F.log10("tf") + 1.0, F.log10("df")
    return _sums(tf.join(frequency.select("term", "df"), "term"), planes, seed, {"a": a, "b": a * lg, "s0": a * a, "s1": a * a * lg, "s2": a * a * lg * lg})


def changed(before: DataFrame, after: DataFrame) -> DataFrame:
    """(term, old, new) of terms whose document frequency moved."""
    both = before.select("term", F.col("df").alias("old")).join(after.select("term", F.col("df").alias("new")), "term")
    return both.filter("old <> new")


def delta(state: DataFrame, tf: DataFrame, moved: DataFrame, planes: int, seed: int = 1) -> DataFrame:
    """The state after a batch: only postings of moved terms are read."""
    a, up, sq = F.log10("tf") + 1.0, F.log10("new") - F.log10("old"), F.pow(F.log10("new"), 2) - F.pow(F.log10("old"), 2)
    step = _sums(tf.join(moved, "term"), planes, seed, {"b": a * up, "s1": a * a * up, "s2": a * a * sq})
    step = step.select("doc_id", *[F.col(c).alias(f"d{c}") for c in ("b", "s1", "s2")])
    more = lambda c: F.when(F.col(f"d{c}").isNull(), F.col(c)).otherwise(F.zip_with(c, f"d{c}", lambda x, y: x + y) if c == "b" else F.col(c) + F.col(f"d{c}"))
    return state.join(step, "doc_id", "left").select("doc_id", "a", more("b").alias("b"), "s0", more("s1").alias("s1"), more("s2").alias("s2"))


def bands(state: DataFrame, size: DataFrame, k: int) -> DataFrame:
    """(doc_id, bands, norm) under a collection of the given size."""
    at = state.join(F.broadcast(size)).withColumn("lg", F.log10("n"))
    projected = at.withColumn("p", F.zip_with("a", "b", lambda a, b: F.col("lg") * a - b))
    norm = F.sqrt(F.greatest(F.lit(0.0), F.col("lg") * F.col("lg") * F.col("s0") - 2 * F.col("lg") * F.col("s1") + F.col("s2")))
    bit = lambda t, b: F.when(F.element_at("p", t * k + b + 1) >= 0, F.call_function("shiftleft", F.lit(1).cast("bigint"), b)).otherwise(F.lit(0).cast("bigint"))
    one = lambda t: F.aggregate(F.sequence(F.lit(0), F.lit(k - 1)), F.lit(0).cast("bigint"), lambda s, b: s + bit(t, b))
    tables = F.sequence(F.lit(0), (F.size("p") / k).cast("int") - 1)
    return projected.select("doc_id", F.transform(tables, one).alias("bands"), norm.alias("norm"))
