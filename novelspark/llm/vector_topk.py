"""Exact top-k by vector-approximation files (operator 3).

Vectors are integers (``floor(scale * x)``). A packed approximation keeps for each component the number of a cell, one byte, on
the row's own scale. Scanning cells gives a lower and an upper bound of each inner product: with the cell edges, the upper bound
takes the upper edge where the query is positive and the lower edge where it is negative. A scan keeps for each query the k best lower
bounds of all blocks it has seen, and lets go of rows whose upper bound falls below the k-th. Then exact vectors are read in the order
of their bounds: first the best few of each query; the k-th exact score so found decides which of the others could still win, and only
these are read. Every read is a join on the row's id.

Queries and rows meet in blocks of bounded size in rows and in components. Of rows with the same vector only the k + 1 smallest ids
can be among the first k of any query (ties go to the smaller id, and one of them may be the query itself), so a vector that a
third of all rows share is k + 1 rows in the scan.

Defined cases: vectors that are null or hold null or non-finite components take no part; shorter vectors count as filled up
with zeros; repeated ids keep one row (the smallest vector); rows with the query's own id are never its candidates; a null id takes
no part; ties go to the smaller id; an empty table gives no rows. Scaled components beyond 2**62 in size count as 2**62, and scores
beyond a 64-bit integer are given (and ranked) as the nearest one.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Scratch

SCALE, TOP = 1024, 10
CELLS = 256
#: Blocks hold at most so many rows, and so many components together.
QUERY_BLOCK, ROW_BLOCK, BLOCK_COMPONENTS = 512, 4096, 1 << 22
#: Candidates that a scan holds for a block of queries before it looks through them again.
HELD = 200_000
#: Exact vectors read at first for each query, as a multiple of k.
FIRST_READ = 2
LIMIT = 1 << 62


def whole_vectors(df: DataFrame, key: str = "vec_id", vector: str = "embedding", scale: int = SCALE) -> DataFrame:
    """(id, v): one row an id, integer components; rows that take no part are gone."""
    x, limit = F.col(vector), F.lit(float(LIMIT))
    finite = F.forall(x, lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < F.lit(float("inf"))))
    ints = F.transform(x, lambda e: F.floor(F.greatest(-limit, F.least(limit, e.cast("double") * F.lit(float(scale))))).cast("long"))
    return df.filter(F.col(key).isNotNull() & x.isNotNull() & finite).select(F.col(key).alias("id"), ints.alias("v")).groupBy("id").agg(F.min("v").alias("v"))


def contenders(vectors: DataFrame, k: int) -> DataFrame:
    """The rows without those of a vector's copies that are never among the first k. Only copied vectors are shuffled."""
    held = vectors.withColumn("h", F.xxhash64("v"))
    copied = held.groupBy("h").agg(F.count("*").alias("c")).filter(F.col("c") > k + 1).select("h", F.lit(True).alias("often"))
    marked = held.join(copied, "h", "left")
    few = marked.filter("often IS NULL").select("id", "v")
    order = W.partitionBy("h", "v").orderBy("id")
    return few.unionByName(marked.filter("often").withColumn("n", F.row_number().over(order)).filter(F.col("n") <= k + 1).select("id", "v"))


def _blocks(vectors: list[np.ndarray], most: int) -> Iterator[np.ndarray]:
    """Places of the vectors in blocks of similar length, so that filling up to a block's longest stays within its components."""
    sizes = np.array([len(v) for v in vectors], dtype=np.int64)
    order, at = np.argsort(sizes, kind="stable"), 0
    while at < len(order):
        end = at + 1
        while end < len(order) and end - at < most and (end - at + 1) * sizes[order[end]] <= BLOCK_COMPONENTS:
            end += 1
        yield order[at:end]
        at = end


def _matrix(vectors: list[np.ndarray]) -> np.ndarray:
    out = np.zeros((len(vectors), max(1, max(map(len, vectors)))), dtype=np.int64)
    for i, v in enumerate(vectors):
        out[i, : len(v)] = v
    return out


def packed_rows(rows: DataFrame) -> DataFrame:
    """(ids, dims, low, width, cells): packed approximations; a component of cell c lies between low + c * width and the next edge less one."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            ids, vectors = batch["id"].to_numpy(dtype="<i8"), [np.asarray(v, dtype=np.int64) for v in batch["v"]]
            for at in _blocks(vectors, ROW_BLOCK):
                m = _matrix([vectors[i] for i in at]).astype(np.float64)
                low, top = m.min(axis=1), m.max(axis=1)
                width = np.floor((top - low) / CELLS) + 1
                cells = np.clip(np.floor((m - low[:, None]) / width[:, None]), 0, CELLS - 1).astype(np.uint8)
                yield pd.DataFrame({"ids": [ids[at].tobytes()], "dims": [m.shape[1]], "low": [low.tobytes()], "width": [width.tobytes()], "cells": [cells.tobytes()]})

    return rows.mapInPandas(run, "ids binary, dims int, low binary, width binary, cells binary")


def packed_queries(queries: DataFrame) -> DataFrame:
    """(names, size, vectors): blocks of queries."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            ids, vectors = batch["id"].to_numpy(dtype="<i8"), [np.asarray(v, dtype=np.int64) for v in batch["v"]]
            for at in _blocks(vectors, QUERY_BLOCK):
                m = _matrix([vectors[i] for i in at])
                yield pd.DataFrame({"names": [ids[at].tobytes()], "size": [m.shape[1]], "vectors": [m.tobytes()]})

    return queries.mapInPandas(run, "names binary, size int, vectors binary")


class Scan:
    """What a task knows of one block of queries: the k best lower bounds and the rows that may still win."""

    def __init__(self, names: np.ndarray, q: np.ndarray, k: int):
        self.names, self.q, self.k = names, q.astype(np.float64), k
        self.best = np.full((k, len(names)), -np.inf)
        self.held: list[tuple[np.ndarray, ...]] = []
        self.size = 0

    def meet(self, rows: np.ndarray, low: np.ndarray, width: np.ndarray, cells: np.ndarray) -> None:
        dims = min(cells.shape[1], self.q.shape[1])
        q, below = self.q[:, :dims], cells[:, :dims].astype(np.float64) * width[:, None] + low[:, None]
        above = below + (width - 1)[:, None]
        up, down = np.maximum(q, 0).T, np.minimum(q, 0).T
        high, least = above @ up + below @ down, below @ up + above @ down
        largest = float(np.abs(q).max(initial=0)) * max(float(np.abs(below).max(initial=0)), float(np.abs(above).max(initial=0))) * dims
        if largest >= 2.0**52:  # sums may be rounded
            slack = np.maximum(np.abs(below), np.abs(above)) @ np.abs(q).T * 2.0**-40
            # scores saturate at 64 bits, and so do their bounds
            high, least = np.clip(high + slack, -(2.0**63), 2.0**63), np.clip(least - slack, -(2.0**63), 2.0**63)
        own = rows[:, None] == self.names[None, :]
        high[own] = least[own] = -np.inf
        both = np.concatenate([self.best, least])
        self.best = np.partition(both, len(both) - self.k, axis=0)[len(both) - self.k :]
        r, c = np.nonzero((high >= self.best.min(axis=0)[None, :]) & ~own)
        self.held.append((c, rows[r], least[r, c], high[r, c]))
        self.size += len(r)
        if self.size > HELD:
            self.prune()

    def prune(self) -> tuple[np.ndarray, ...]:
        c, rows, least, high = (np.concatenate(x) for x in zip(*self.held, strict=True))
        keep = high >= self.best.min(axis=0)[c]
        self.held, self.size = [(c[keep], rows[keep], least[keep], high[keep])], int(keep.sum())
        return self.held[0]


def bounded_candidates(queries: DataFrame, rows: DataFrame, k: int) -> DataFrame:
    """(query_id, id, low, high) of rows that can be among the first k of all rows that their task has seen."""

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        scans: dict[tuple, Scan] = {}
        for batch in batches:
            for ids, dims, low, width, cells, names, size, vectors in batch.itertuples(index=False):
                if (names, vectors) not in scans:
                    asked = np.frombuffer(names, dtype="<i8")
                    scans[names, vectors] = Scan(asked, np.frombuffer(vectors, dtype=np.int64).reshape(len(asked), size), k)
                at = np.frombuffer(ids, dtype="<i8")
                scans[names, vectors].meet(at, np.frombuffer(low), np.frombuffer(width), np.frombuffer(cells, dtype=np.uint8).reshape(len(at), dims))
        for one in scans.values():
            c, found, least, high = one.prune()
            for at in range(0, len(c), HELD):
                part = slice(at, at + HELD)
                yield pd.DataFrame({"query_id": one.names[c[part]], "id": found[part], "low": least[part], "high": high[part]})

    # each block of cells is sent to each block of queries; both are bounded in size
    return packed_rows(rows).join(packed_queries(queries)).mapInPandas(scan, "query_id long, id long, low double, high double")


def inner_product(a: np.ndarray, b: np.ndarray) -> int:
    """Exact, whatever the size of the components; the nearest 64-bit integer if it is beyond these."""
    n = min(len(a), len(b))
    a, b = a[:n], b[:n]
    if float(np.abs(a, dtype=np.float64).max(initial=0)) * float(np.abs(b, dtype=np.float64).max(initial=0)) * n < 2.0**62:
        return int(a @ b)
    return max(-(1 << 63), min((1 << 63) - 1, sum(x * y for x, y in zip(a.tolist(), b.tolist(), strict=True))))


def exact(pairs: DataFrame, vectors: DataFrame, queries: DataFrame) -> DataFrame:
    """(query_id, id, score) of pairs, by the exact vectors."""
    q = queries.select(F.col("id").alias("query_id"), F.col("v").alias("qv"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns = [batch.column(i) for i in (2, 3)]
            scores = [inner_product(a.values.to_numpy(), b.values.to_numpy()) for a, b in zip(*columns, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(scores, pa.int64())], names=["query_id", "id", "score"])

    return pairs.join(vectors, "id").join(q, "query_id").select("query_id", "id", "v", "qv").mapInArrow(run, "query_id long, id long, score long")


def top_k(rows: DataFrame, is_query, key: str = "vec_id", vector: str = "embedding", k: int = TOP, scale: int = SCALE) -> DataFrame:
    """(query_id, rank, id, score): the k highest inner products of each query, over all rows but its own."""
    scratch = Scratch(rows.sparkSession, "vectors")
    vectors = scratch.write(whole_vectors(rows, key, vector, scale), "vectors")
    queries = vectors.filter(is_query(F.col("id")))
    # as many partitions as there are whole blocks, so that neither side meets in slivers
    sizes = vectors.agg(F.count("*").alias("rows"), F.count_if(is_query(F.col("id"))).alias("queries")).first()
    some = contenders(vectors, k).coalesce(max(1, -(-sizes.rows // ROW_BLOCK)))
    found = scratch.write(bounded_candidates(queries.repartition(max(1, -(-sizes.queries // QUERY_BLOCK))), some, k), "bounds")
    by_low = W.partitionBy("query_id").orderBy(F.desc("low"), "id")
    floor = found.withColumn("n", F.row_number().over(by_low)).filter(F.col("n") == k).select("query_id", F.col("low").alias("floor"))
    alive = found.join(floor, "query_id", "left").filter(F.col("floor").isNull() | (F.col("high") >= F.col("floor"))).drop("floor")
    by_high = W.partitionBy("query_id").orderBy(F.desc("high"), "id")
    alive = scratch.write(alive.withColumn("place", F.row_number().over(by_high)), "alive")
    first = scratch.write(exact(alive.filter(F.col("place") <= FIRST_READ * k), vectors, queries), "first")
    by_score = W.partitionBy("query_id").orderBy(F.desc("score"), "id")
    kth = first.withColumn("n", F.row_number().over(by_score)).filter(F.col("n") == k).select("query_id", F.col("score").alias("kth"))
    late = alive.filter(F.col("place") > FIRST_READ * k).join(kth, "query_id").filter(F.col("high") >= F.col("kth"))
    both = first.unionByName(exact(late.select("query_id", "id"), vectors, queries))
    return both.withColumn("rank", F.row_number().over(by_score)).filter(F.col("rank") <= k).select("query_id", "rank", "id", "score")


def op3_vector_approximation(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding")
    return top_k(rows, lambda c: c % 100 == 0).withColumnRenamed("id", "vec_id")


OP3_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(CAST(x AS DOUBLE) * 1024) AS BIGINT)) AS e FROM embeddings WHERE embedding IS NOT NULL),
q AS (SELECT vec_id AS query_id, unnest(e) AS a, generate_subscripts(e, 1) AS k FROM v WHERE vec_id % 100 = 0),
c AS (SELECT vec_id, unnest(e) AS b, generate_subscripts(e, 1) AS k FROM v),
s AS (SELECT query_id, vec_id, CAST(sum(a * b) AS BIGINT) AS score FROM q JOIN c USING (k) WHERE query_id <> vec_id GROUP BY 1, 2)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= 10
"""
