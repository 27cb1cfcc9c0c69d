"""Random-hyperplane hashing over an open vocabulary.

A plane's component for a term is a function of the term, the plane and a seed, so no plane is ever stored or sent. Projections are sums of
integers (weights in millionths), so bits do not depend on the order of a sum. Unnormalised weights serve: a sign knows no scale.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import similarity

#: Planes that one md5 digest gives, as four words of 32 bits.
PER_DIGEST, WORD = 128, 32
QUANT = 1_000_000


def _word(term: Column, seed: int, word: int) -> Column:
    block, part = divmod(word, PER_DIGEST // WORD)
    digest = F.md5(F.concat(term, F.lit(f"|{seed}|{block}")))
    return F.conv(F.substring(digest, 8 * part + 1, 8), 16, 10).cast("bigint")


def plane_bits(terms: DataFrame, planes: int, seed: int = 1) -> DataFrame:
    """(term, plane, sign): the components of ``planes`` planes, +1 or -1."""
    words = F.array(*[_word(F.col("term"), seed, w) for w in range(-(-planes // WORD))])
    out = terms.select("term", F.explode(F.sequence(F.lit(0), F.lit(planes - 1))).alias("plane"), words.alias("words"))
    word = F.get("words", F.floor(F.col("plane") / WORD).cast("int"))
    bit = F.call_function("shiftright", word, F.col("plane") % WORD).bitwiseAND(F.lit(1).cast("bigint")) != 0
    return out.select("term", "plane", F.when(bit, 1).otherwise(-1).alias("sign"))


def plane_gauss(terms: DataFrame, planes: int, seed: int = 1) -> DataFrame:
    """(term, plane, component): normal deviates by the Box-Muller rule from two slices of a digest."""
    out = terms.select("term", F.explode(F.sequence(F.lit(0), F.lit(planes - 1))).alias("plane"))
    digest = F.md5(F.concat(F.col("term"), F.lit(f"|{seed}|g"), F.col("plane").cast("string")))
    uniform = lambda at: (F.conv(F.substring(digest, at, 8), 16, 10).cast("double") + 0.5) / float(1 << 32)
    return out.select("term", "plane", (F.sqrt(-2 * F.ln(uniform(1))) * F.cos(2 * math.pi * uniform(9))).alias("component"))


def signatures(raw: DataFrame, k: int, tables: int, seed: int = 1, keys: tuple[str, ...] = ("doc_id",), plane: str = "sign") -> DataFrame:
    """(keys, bands): an array of one bucket number a table, from (keys, term, x). Documents without weight have no row.

    The signs are read from the digest within the row; one aggregate sums all projections, map side first.
    """
    planes = k * tables
    q = F.round(F.col("x") * QUANT).cast("bigint")
    rows = raw.filter("x <> 0").select(*keys, q.alias("q"), "term")
    if plane == "gauss":
        parts = rows.join(plane_gauss(raw.select("term").distinct(), planes, seed), "term")
        sums = parts.groupBy(*keys, "plane").agg(F.sum(F.round(F.col("q") * F.col("component")).cast("bigint")).alias("s"))
        bits = sums.select(*keys, F.floor(F.col("plane") / k).cast("int").alias("t"), F.when(F.col("s") >= 0, F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("plane") % k)).otherwise(0).alias("b"))
        packed = bits.groupBy(*keys, "t").agg(F.sum("b").alias("bucket"))
        return packed.groupBy(*keys).agg(F.transform(F.sort_array(F.collect_list(F.struct("t", "bucket"))), lambda s: s["bucket"]).alias("bands"))
    words = [_word(F.col("term"), seed, w).alias(f"w{w}") for w in range(-(-planes // WORD))]
    rows = rows.select(*keys, "q", *words)
    ones = [F.sum(F.when(F.col(f"w{p // WORD}").bitwiseAND(F.lit(1 << (p % WORD))) != 0, F.col("q")).otherwise(0)).alias(f"p{p}") for p in range(planes)]
    sums = rows.groupBy(*keys).agg(F.sum("q").alias("all"), *ones)
    band = lambda t: sum((F.when(F.col(f"p{t * k + b}") * 2 >= F.col("all"), F.lit(1 << b).cast("bigint")).otherwise(F.lit(0).cast("bigint")) for b in range(k)), F.lit(0).cast("bigint"))
    return sums.select(*keys, F.array(*[band(t) for t in range(tables)]).alias("bands"))


def signatures_dense(vectors: DataFrame, k: int, tables: int, seed: int = 1) -> DataFrame:
    """Signatures of (doc_id, v): dimensions are the terms; the planes of a fixed number of dimensions are literals."""
    rows = vectors.select("doc_id", F.posexplode("v").alias("dim", "x")).select("doc_id", F.concat(F.lit("d"), F.col("dim").cast("string")).alias("term"), F.col("x").cast("double").alias("x"))
    return signatures(rows, k, tables, seed)


def hamming(a: Column, b: Column) -> Column:
    """Differing bits of two band arrays."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y)).cast("bigint")), F.lit(0).cast("bigint"), lambda s, x: s + x)


def buckets(signed: DataFrame, extra: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, extra, table_no, bucket): a row a table."""
    return signed.select("doc_id", *extra, F.posexplode("bands").alias("table_no", "bucket"))


def cap_buckets(rows: DataFrame, cap: int) -> DataFrame:
    """Only the newest ``cap`` documents of each bucket: the constant-time idea."""
    newest = W.partitionBy("table_no", "bucket").orderBy(F.desc("doc_id"))
    return rows.withColumn("age", F.row_number().over(newest)).filter(F.col("age") <= cap).drop("age")


def candidates(queries: DataFrame, history: DataFrame, extra: tuple[str, ...] = ()) -> DataFrame:
    """(q, h, extra): the union over all tables of pairs in one bucket, by one equi-join; each pair once."""
    q = queries.select(F.col("doc_id").alias("q"), "table_no", "bucket", *extra)
    h = history.select(F.col("doc_id").alias("h"), "table_no", "bucket", *extra)
    return q.join(h, ["table_no", "bucket", *extra]).filter("q <> h").select("q", "h", *extra).distinct()


def grouped_nearest(queries: DataFrame, history: DataFrame, cap: int, size: int = similarity.BLOCK) -> DataFrame:
    """(q, distance, h): the nearest of the newest ``cap`` documents of each bucket a query falls in, scored bucket by bucket.

    Both sides are (doc_id, v, table_no, bucket). A bucket's queries are dealt to parts of about ``size`` rows, each with the bucket's
    newest documents, so that a bucket of any size fits its tasks.
    """
    keys = ("table_no", "bucket", "part")

    def step(q: pd.DataFrame, h: pd.DataFrame) -> pd.DataFrame:
        found = {"q": [], "h": [], "similarity": []}
        if len(q) and len(h):
            h = h.sort_values("doc_id", ignore_index=True)
            ids, similar = h["doc_id"].to_numpy(), similarity.cosines(q, h)
            far = np.round(1 - np.clip(similar, -1, 1), similarity.DIGITS)
            far[q["doc_id"].to_numpy()[:, None] == ids[None, :]] = np.inf
            best = far.argmin(axis=1)
            met = np.isfinite(far[np.arange(len(q)), best])
            found = {"q": q["doc_id"].to_numpy()[met], "h": ids[best[met]], "similarity": similar[np.arange(len(q)), best][met]}
        return pd.DataFrame(found)

    parts = queries.groupBy("table_no", "bucket").agg(F.ceil(F.count("*") / size).alias("parts"))
    q = queries.join(parts, ["table_no", "bucket"]).withColumn("part", F.pmod(F.xxhash64("doc_id"), F.col("parts"))).select("doc_id", "v", *keys)
    h = cap_buckets(history, cap).join(parts, ["table_no", "bucket"]).withColumn("part", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("parts") - 1))).select("doc_id", "v", *keys)
    pairs = q.toDF(*q.columns).groupBy(*keys).cogroup(h.groupBy(*keys)).applyInPandas(step, "q bigint, h bigint, similarity double")
    return similarity.nearest(pairs)


def collision_law(queries: DataFrame, rows: DataFrame, planes: int, cells: int = 20) -> DataFrame:
    """(cell, n, observed, predicted) by cells of the angle: the share of differing bits and the angle itself, over pairs with h < q.

    Both sides are (doc_id, v, bands). Blocks of pairs are counted where they meet, so what leaves a task is a row a cell.
    """

    def step(q: pd.DataFrame, h: pd.DataFrame) -> pd.DataFrame:
        if not len(q) or not len(h):
            return pd.DataFrame({"cell": [], "n": [], "bits": [], "angles": []})
        angle = np.arccos(np.clip(similarity.cosines(q, h), -1, 1)) / np.pi
        a, b = (np.stack(side["bands"].to_numpy()).astype("int64") for side in (q, h))
        bits = sum(np.bitwise_count(a[:, t, None] ^ b[None, :, t]).astype("int64") for t in range(a.shape[1]))
        earlier = h["doc_id"].to_numpy()[None, :] < q["doc_id"].to_numpy()[:, None]
        pairs = pd.DataFrame({"cell": np.floor(angle[earlier] * cells).astype("int64"), "bits": bits[earlier], "angles": angle[earlier]})
        return pairs.groupby("cell").agg(n=("bits", "size"), bits=("bits", "sum"), angles=("angles", "sum")).reset_index()

    counted = similarity.blockwise(queries, rows, step, "cell bigint, n bigint, bits bigint, angles double")
    total = counted.groupBy("cell").agg(F.sum("n").alias("n"), F.sum("bits").alias("bits"), F.sum("angles").alias("angles"))
    return total.select("cell", "n", F.round(F.col("bits") / F.col("n") / planes, 4).alias("observed"), F.round(F.col("angles") / F.col("n"), 4).alias("predicted"))


def bucket_stats(rows: DataFrame) -> DataFrame:
    sizes = rows.groupBy("table_no", "bucket").agg(F.count("*").alias("size"))
    return sizes.groupBy("table_no").agg(F.count("*").alias("n_buckets"), F.max("size").alias("largest"), F.sum(F.col("size") * F.col("size")).alias("pairs"), F.expr("percentile(size, 0.5)").alias("median_size"))


def tables_needed(k: int, cos: float, miss: float) -> int:
    """Tables so that a neighbour at this cosine is missed by all with chance ``miss`` at most."""
    share = (1 - math.acos(cos) / math.pi) ** k
    return math.ceil(math.log(miss) / math.log(1 - share))


def tables_printed(k: int, cos: float, miss: float) -> float | None:
    """The table count as the formula is printed; None where its logarithm has no value. For audit only."""
    inner = miss - (math.acos(cos) / math.pi) ** k
    return math.log(inner) if inner > 0 else None


def table_counts(spark: SparkSession, cases: list[tuple[int, float, float]]) -> DataFrame:
    """Both counts for given (k, cosine, miss), as column arithmetic."""
    return counted(spark.createDataFrame(cases, "k int, cosine double, miss double"))


def counted(df: DataFrame) -> DataFrame:
    """Both counts of rows (k, cosine, miss)."""
    angle = F.acos("cosine") / F.pi()
    inner = F.col("miss") - F.pow(angle, F.col("k"))
    return df.select(
        "k", "cosine", "miss", F.ceil(F.ln("miss") / F.ln(1 - F.pow(1 - angle, F.col("k")))).cast("bigint").alias("needed"), F.round(F.when(inner > 0, F.ln(inner)), 6).alias("printed")
    )
