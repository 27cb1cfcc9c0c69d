"""Cosine similarity and exhaustive neighbour search. Vectors are long tables of (doc_id, term, w)."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Distances are rounded before they are compared, so that ties do not hang on the order of a sum.
DIGITS = 6
#: Rows of a block in exhaustive search over dense vectors.
BLOCK = 4096
#: Terms of a block of queries and of rows in exhaustive search over bags; numbers in the columns of a block's commonest terms, and of a chunk of products.
QUERY_TERMS, ROW_TERMS, DENSE, CHUNK = 1 << 22, 1 << 22, 1 << 22, 1 << 21


def cosine(pairs: DataFrame, queries: DataFrame, docs: DataFrame) -> DataFrame:
    """(q, h, similarity) of given pairs with the whole denominator; 0 where one side has no weight."""
    dots = (
        pairs.join(queries.select(F.col("doc_id").alias("q"), "term", F.col("w").alias("wq")), "q")
        .join(docs.select(F.col("doc_id").alias("h"), "term", F.col("w").alias("wh")), ["h", "term"])
        .groupBy("q", "h")
        .agg(F.sum(F.col("wq") * F.col("wh")).alias("dot"))
    )
    length = lambda v, name: v.groupBy(F.col("doc_id").alias(name)).agg(F.sum(F.col("w") * F.col("w")).alias(f"{name}2"))
    out = pairs.join(dots, ["q", "h"], "left").join(length(queries, "q"), "q", "left").join(length(docs, "h"), "h", "left")
    return out.select("q", "h", F.coalesce(F.try_divide("dot", F.sqrt(F.col("q2") * F.col("h2"))), F.lit(0.0)).alias("similarity"))


def distance(similarity: Column, kind: str = "cosine") -> Column:
    """1 - cosine, or the angle as a share of pi; the cosine is kept within its range first."""
    kept = F.greatest(F.lit(-1.0), F.least(F.lit(1.0), similarity))
    return 1 - kept if kind == "cosine" else F.acos(kept) / F.pi()


def products(queries: DataFrame, history: DataFrame, on: tuple[str, ...] = ("term",), prior: bool = False) -> DataFrame:
    """(q, h, similarity) of all pairs with a common term, by an equi-join on the term; ``prior``: only earlier documents.

    A term that only one side holds, or that weighs nothing, never meets anything, so the join's work is the sum over terms of
    query postings times history postings.
    """
    extra = [c for c in on if c != "term"]
    q = queries.select(F.col("doc_id").alias("q"), *on, F.col("w").alias("wq"), *(["seq"] if prior else []))
    h = history.select(F.col("doc_id").alias("h"), *on, F.col("w").alias("wh"), *([F.col("seq").alias("hseq")] if prior else []))
    met = q.join(h, list(on))
    met = met.filter("hseq < seq") if prior else met
    return met.groupBy("q", "h", *extra).agg(F.sum(F.col("wq") * F.col("wh")).alias("similarity"))


def ranked(pairs: DataFrame, k: int = 1) -> DataFrame:
    """The k nearest of each query: (q, h, distance, rank), ties to the smaller id."""
    far = pairs.withColumn("distance", F.round(distance(F.col("similarity")), DIGITS))
    order = W.partitionBy("q").orderBy("distance", "h")
    return far.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("q", "h", "distance", "rank")


def nearest(pairs: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, q, distance, h): the minimum as one aggregate that starts before the shuffle."""
    far = pairs.select(*by, "q", F.struct(F.round(distance(F.col("similarity")), DIGITS).alias("distance"), "h").alias("s"))
    return far.groupBy(*by, "q").agg(F.min("s").alias("s")).select(*by, "q", "s.distance", "s.h")


def within(pairs: DataFrame, threshold: float) -> DataFrame:
    return pairs.withColumn("distance", F.round(distance(F.col("similarity")), DIGITS)).filter(F.col("distance") < threshold)


def blockwise(queries: DataFrame, rows: DataFrame, step: Callable[[pd.DataFrame, pd.DataFrame], pd.DataFrame], schema: str, size: int = BLOCK) -> DataFrame:
    """``step`` on every pair of a block of queries and a block of rows, both with ``doc_id``, which is unique in each.

    Blocks hold about ``size`` rows whatever the input, so a task holds two of them at a time; only two counts are broadcast.
    """
    counts = [df.agg(F.greatest(F.ceil(F.count("*") / size), F.lit(1).cast("bigint")).alias(f"n_{name}")) for df, name in ((queries, "q"), (rows, "h"))]

    def dealt(df: DataFrame, own: str, other: str) -> DataFrame:
        placed = df.join(F.broadcast(counts[0])).join(F.broadcast(counts[1])).withColumn(f"block_{own}", F.pmod(F.xxhash64("doc_id"), F.col(f"n_{own}")))
        return placed.withColumn(f"block_{other}", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col(f"n_{other}") - 1))).drop("n_q", "n_h")

    both = ("block_q", "block_h")
    return dealt(queries.toDF(*queries.columns), "q", "h").toDF(*queries.columns, *both).groupBy(*both).cogroup(dealt(rows, "h", "q").select(*rows.columns, *both).groupBy(*both)).applyInPandas(step, schema)


def flat(column: pa.ChunkedArray, kind: pa.DataType) -> tuple[pa.Array, np.ndarray]:
    """The values of an array column, and where each row's begin, with the end."""
    parts = [c.fill_null([]) if c.null_count else c for c in column.chunks] or [pa.array([], pa.list_(kind))]
    lengths = np.concatenate([pc.list_value_length(c).to_numpy(zero_copy_only=False) for c in parts]).astype("int64")
    values = pa.chunked_array([c.flatten().cast(kind) for c in parts], kind).combine_chunks()
    return values, np.concatenate([[0], np.cumsum(lengths)])


class _Rows:
    """One block of rows: their weights of length one, in the order of terms, those of the commonest terms as columns."""

    def __init__(self, ids: np.ndarray, codes: np.ndarray, starts: np.ndarray, x: np.ndarray, width: int):
        self.ids, n = ids, len(ids)
        rows = np.repeat(np.arange(n), np.diff(starts))
        order = np.argsort(codes, kind="stable")
        self.rows, self.w = rows[order], unit_rows(x, rows, n)[order]
        counts = np.bincount(codes, minlength=width)
        self.at = np.concatenate([[0], np.cumsum(counts)])
        common = np.argsort(-counts, kind="stable")[: max(DENSE // max(n, 1), 1)]
        common = common[counts[common] * 8 >= max(n, 8)]
        self.column, self.dense = np.full(width, -1), np.zeros((len(common), n))
        self.column[common] = np.arange(len(common))
        for i, c in enumerate(common):
            self.dense[i, self.rows[self.at[c] : self.at[c + 1]]] = self.w[self.at[c] : self.at[c + 1]]
        self.met = np.where(self.column < 0, counts, 0)

    def cosines(self, codes: np.ndarray, w: np.ndarray, own: np.ndarray, queries: int) -> np.ndarray:
        """(queries, rows) from the queries' terms, weights and places."""
        n, column = len(self.ids), self.column[codes]
        few = np.zeros((queries, len(self.dense)))
        few[own[column >= 0], column[column >= 0]] = w[column >= 0]
        # every term of a query with every row that holds it
        count = self.met[codes]
        ends = np.cumsum(count)
        place = np.repeat(self.at[codes] - (ends - count), count) + np.arange(ends[-1] if len(ends) else 0)
        rare = np.bincount(np.repeat(own * n, count) + self.rows[place], np.repeat(w, count) * self.w[place], queries * n)
        return rare.reshape(queries, n) + few @ self.dense


def unit_rows(x: np.ndarray, rows: np.ndarray, n: int) -> np.ndarray:
    length = np.sqrt(np.bincount(rows, x * x, n))[rows]
    return np.divide(x, length, out=np.zeros_like(x), where=length > 0)


def distances(block: _Rows, ids: np.ndarray, codes: np.ndarray, own: np.ndarray, w: np.ndarray) -> Iterator[tuple[int, int, np.ndarray]]:
    """(first, end, far) of queries chunk by chunk: whole millionths of distance to each row of the block, -1 being no pair."""
    starts = np.searchsorted(own, np.arange(len(ids) + 1))
    work = np.concatenate([[0], np.cumsum(block.met[codes])])[starts]
    a = 0
    while a < len(ids):
        b = min(max(int(np.searchsorted(work, work[a] + CHUNK, "right")) - 1, a + 1), a + max(CHUNK // len(block.ids), 1), len(ids))
        s = slice(starts[a], starts[b])
        similar = block.cosines(codes[s], w[s], own[s] - a, b - a)
        far = np.floor((1 - np.minimum(similar, 1.0)) * 10.0**DIGITS + 0.5).astype("int64")
        far[(similar <= 0) | (block.ids == ids[a:b, None])] = -1
        yield a, b, far
        a = b


def bag_search(bags: DataFrame, idfs: DataFrame, every: int, keep: Callable[[np.ndarray], tuple[np.ndarray, np.ndarray]]) -> DataFrame:
    """(q, h, distance) by exhaustive search: rows whose id is divisible by ``every`` against all other rows that share a weighted term.

    Bags are (doc_id, block, terms, tfs), idfs (term, idf, blocks), both written tables. Each block of queries meets each block of rows in one
    task with the idf of that block's terms, so weights are made there and no row a term is shuffled. ``keep`` says which of (queries, rows)
    whole millionths of distance leave the task, -1 being no pair; rows come in the order of their ids.
    """
    none = lambda kind: F.lit(None).cast(kind)
    keys = ("qb", "block")
    asks = bags.filter(F.col("doc_id") % every == 0).select("doc_id", "terms", "tfs")
    x = (F.log10("tf") + 1.0) * F.col("idf")
    each = asks.select("doc_id", F.inline(F.arrays_zip(F.col("terms").alias("term"), F.col("tfs").alias("tf"))))
    lengths = each.join(idfs.select("term", "idf"), "term").groupBy("doc_id").agg(F.sqrt(F.sum(x * x)).alias("length"))
    count = asks.agg(F.greatest(F.ceil(F.coalesce(F.sum(F.size("terms")), F.lit(0)) / QUERY_TERMS), F.lit(1).cast("bigint")).alias("nq"))
    blocks = bags.select("block").distinct()
    over = F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("nq") - 1)).alias("qb")
    q = asks.join(lengths, "doc_id").filter("length > 0").join(F.broadcast(count)).withColumn("qb", F.pmod(F.xxhash64("doc_id"), F.col("nq"))).join(F.broadcast(blocks))
    q = q.select(*keys, "doc_id", "length", "terms", "tfs", none("array<double>").alias("idfs"))
    shards = idfs.select(F.explode("blocks").alias("block"), "term", "idf").groupBy("block", F.pmod(F.xxhash64("term"), F.lit(16)).alias("shard")).agg(F.sort_array(F.collect_list(F.struct("term", "idf"))).alias("e"))
    m = shards.join(F.broadcast(count)).select(over, "block", none("bigint").alias("doc_id"), none("double").alias("length"), F.col("e.term").alias("terms"), none("array<bigint>").alias("tfs"), F.col("e.idf").alias("idfs"))
    left, right = q.unionByName(m), bags.filter("doc_id IS NOT NULL").join(F.broadcast(count)).select(over, "block", "doc_id", "terms", "tfs")

    def step(left: pa.Table, right: pa.Table) -> pa.Table:
        found = {"q": [], "h": [], "distance": []}
        is_model = left["doc_id"].is_null().to_numpy()
        if len(right) and not is_model.all():
            search(left.filter(pa.array(is_model)), left.filter(pa.array(~is_model)).sort_by("doc_id"), right.sort_by("doc_id"), found)
        kinds = {"q": pa.int64(), "h": pa.int64(), "distance": pa.float64()}
        return pa.table({c: pa.array(np.concatenate(v) if v else [], kinds[c]) for c, v in found.items()})

    def search(model: pa.Table, queries: pa.Table, rows: pa.Table, found: dict) -> None:
        terms, idf = flat(model["terms"], pa.string())[0], flat(model["idfs"], pa.float64())[0].to_numpy()

        def weighed(side: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
            held, starts = flat(side["terms"], pa.string())
            codes = pc.fill_null(pc.index_in(held, terms), -1).to_numpy(zero_copy_only=False).astype("int64")
            x = (np.log10(flat(side["tfs"], pa.float64())[0].to_numpy()) + 1.0) * np.where(codes < 0, 0.0, idf[codes])
            return side["doc_id"].to_numpy().astype("int64"), codes, starts, x

        block = _Rows(*weighed(rows), len(terms))
        ids, codes, starts, x = weighed(queries)
        own = np.repeat(np.arange(len(ids)), np.diff(starts))
        w = x / queries["length"].to_numpy()[own]
        # a query's other terms, which no row of the block holds, are in its length only
        for a, b, far in distances(block, ids, codes[w > 0], own[w > 0], w[w > 0]):
            i, j = keep(far)
            found["q"].append(ids[a:b][i])
            found["h"].append(block.ids[j])
            found["distance"].append(far[i, j] / 10.0**DIGITS)

    return left.toDF(*left.columns).groupBy(*keys).cogroup(right.toDF(*right.columns).groupBy(*keys)).applyInArrow(step, "q bigint, h bigint, distance double")


def keep_nearest(k: int) -> Callable[[np.ndarray], tuple[np.ndarray, np.ndarray]]:
    def keep(far: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n = far.shape[1]
        # one number a pair in the order of distance and id
        order = np.where(far < 0, np.iinfo("int64").max, far * n + np.arange(n))
        best = np.partition(order, k - 1, axis=1)[:, :k] if k < n else order
        i, c = np.nonzero(best < np.iinfo("int64").max)
        return i, best[i, c] % n

    return keep


def keep_within(threshold: float) -> Callable[[np.ndarray], tuple[np.ndarray, np.ndarray]]:
    return lambda far: np.nonzero((far >= 0) & (far / 10.0**DIGITS < threshold))


def matrix(vectors: pd.Series, dims: int) -> np.ndarray:
    """Vectors as rows, of length one; a vector that is null or holds a null or no finite number is zero, a short one ends in zeros."""
    out = np.zeros((len(vectors), dims))
    for i, v in enumerate(vectors):
        if v is not None and np.isfinite(v := np.asarray(v, dtype="float64")).all():
            out[i, : len(v)] = v
    lengths = np.sqrt((out * out).sum(axis=1, keepdims=True))
    return np.divide(out, lengths, out=np.zeros_like(out), where=lengths > 0)


def cosines(queries: pd.DataFrame, rows: pd.DataFrame) -> np.ndarray:
    dims = max((len(v) for side in (queries, rows) for v in side["v"] if v is not None), default=0)
    return matrix(queries["v"], dims) @ matrix(rows["v"], dims).T


def nearest_dense(queries: DataFrame, rows: DataFrame, k: int = 1) -> DataFrame:
    """Exhaustive search over dense vectors (doc_id, v): every pair of blocks keeps each query's k nearest, then the blocks' lists meet."""

    def step(q: pd.DataFrame, h: pd.DataFrame) -> pd.DataFrame:
        found = []
        if len(q) and len(h):
            h = h.sort_values("doc_id", ignore_index=True)
            ids, similar = h["doc_id"].to_numpy(), cosines(q, h)
            far = np.round(1 - np.clip(similar, -1, 1), DIGITS)
            for i, own in enumerate(q["doc_id"]):
                far[i, ids == own] = np.inf
                near = np.argsort(far[i], kind="stable")[:k]
                near = near[np.isfinite(far[i, near])]
                found.append(pd.DataFrame({"q": own, "h": ids[near], "similarity": similar[i, near]}))
        return pd.concat(found) if found else pd.DataFrame({"q": [], "h": [], "similarity": []})

    return ranked(blockwise(queries, rows, step, "q bigint, h bigint, similarity double"), k)


def centroids(weighted: DataFrame, clusters: DataFrame) -> DataFrame:
    """(doc_id = cluster, term, w): the mean of a cluster's vectors, of length one."""
    sums = weighted.join(clusters, "doc_id").groupBy("cluster", "term").agg(F.sum("w").alias("x"))
    size = F.sqrt(F.sum(F.col("x") * F.col("x")).over(W.partitionBy("cluster")))
    return sums.select(F.col("cluster").alias("doc_id"), "term", F.try_divide("x", size).alias("w"))


def centroids_grouped(vectors: DataFrame, by: str, size: int = BLOCK) -> DataFrame:
    """(by, dim, mean) of dense vectors (doc_id, by, v), through a grouped-aggregate Arrow function.

    A group is dealt to parts of about ``size`` rows; the parts' sums are added afterwards, so no task holds a whole group. Vectors that
    are null take no part. ``centroids`` is the form without Python for weighted terms.
    """

    @F.pandas_udf("array<double>")
    def total(v: pd.Series) -> list[float]:
        out = np.zeros(max(map(len, v)))
        for x in v:
            out[: len(x)] += x
        return out.tolist()

    held = vectors.filter("v IS NOT NULL AND NOT exists(v, x -> x IS NULL)")
    counts = held.agg(F.greatest(F.ceil(F.count("*") / size), F.lit(1).cast("bigint")).alias("parts"))
    dealt = held.join(F.broadcast(counts)).withColumn("part", F.pmod(F.xxhash64("doc_id"), F.col("parts")))
    sums = dealt.groupBy(by, "part").agg(total("v").alias("v"))
    sizes = held.groupBy(by).agg(F.count("*").alias("n"))
    added = sums.select(by, F.posexplode("v").alias("dim", "x")).groupBy(by, "dim").agg(F.sum("x").alias("x"))
    return added.join(sizes.withColumnRenamed(by, "of"), F.col(by).eqNullSafe(F.col("of"))).select(by, "dim", (F.col("x") / F.col("n")).alias("mean"))
