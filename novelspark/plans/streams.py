"""Experiment inputs: streams with known truth, in DataFrames and in SQL for the oracle.

``constructed`` follows the paper's set-up on the given documents: a training set of mutually different events, then test snippets
that are either first reports or retell a known event in part, with new words. All choices hang on md5 values, so SQL rebuilds them.
"""

from __future__ import annotations

import functools

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.text import ngrams, tokens
from ..operators.model import term_counts
from ..sources.scratch import Scratch
from ..sources.tables import table

SIZE, LONG, GRAM = 40, 200, 5
USED = 100 + SIZE


def tokenised(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select("doc_id", "lang", "source", tokens(F.col("text")).alias("terms"))


def numbered(rows: DataFrame, bucket: Column, order: list, name: str) -> DataFrame:
    """Adds ``name``: each row's place from 0, by bucket, then order. Buckets are numbered each in its own task; only one row a bucket
    meets in one window. Rows are read twice: give a written table."""
    held = rows.withColumn("_b", bucket)
    sizes = held.groupBy("_b").agg(F.count("*").alias("_c"))
    firsts = sizes.select("_b", F.coalesce(F.sum("_c").over(W.orderBy("_b").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_f"))
    placed = held.withColumn("_r", F.row_number().over(W.partitionBy("_b").orderBy(*order)) - 1)
    return placed.join(firsts, "_b").withColumn(name, F.col("_r") + F.col("_f")).drop("_b", "_r", "_f")


def hashed_bucket(digest: Column) -> Column:
    """4,096 buckets in the order of hexadecimal digests."""
    return F.substring(digest, 1, 3)


def parents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, terms, p, e): long documents whose openings share no 5-gram with an earlier long document's, numbered by md5; ``e`` is the
    number of events, a third of them.

    Only the terms that snippets are cut from are kept. They are shuffled once, to meet their rows' numbers; grams are, too.
    """
    scratch = Scratch(spark, "parents")
    long = tokenised(spark, sf_dir).filter(F.size("terms") >= LONG).select(F.monotonically_increasing_id().alias("row"), "doc_id", F.slice("terms", 1, USED).alias("terms"))
    long = scratch.write(long, "long")
    grams = long.select("doc_id", F.explode(ngrams(F.slice("terms", 1, SIZE), GRAM)).alias("g"))
    shared = grams.withColumn("first", F.min("doc_id").over(W.partitionBy("g"))).filter("first < doc_id").select("doc_id").distinct()
    kept = scratch.write(long.select("row", "doc_id").join(shared, "doc_id", "left_anti").withColumn("m", F.md5(F.concat(F.lit("p"), F.col("doc_id").cast("string")))), "kept")
    count = kept.agg(F.floor(F.count("*") / 3).cast("int").alias("e"))
    placed = numbered(kept, hashed_bucket(F.col("m")), ["m", "doc_id"], "p").join(F.broadcast(count))
    return scratch.write(long.join(placed.select("row", F.col("p").cast("int").alias("p"), "e"), "row").select("doc_id", "terms", "p", "e"), "parents")


def constructed(spark: SparkSession, sf_dir: str, keep: float = 0.3, burst: int = 1, batch: int = 42, held: DataFrame | None = None) -> DataFrame:
    """(doc_id, batch_id, truth_id, source_id, terms). A third of the parents are events; redundant snippets open like an event and go on
    with words of another parent; novel snippets open parents used nowhere else. ``source_id`` is the document a snippet was cut from
    (a redundant one: that its tail is from)."""
    held = parents(spark, sf_dir) if held is None else held
    head, none = int(round(keep * SIZE)), F.lit(None).cast("bigint")
    events = held.filter("p < e").select(F.col("p").cast("bigint").alias("doc_id"), none.alias("truth_id"), F.col("doc_id").alias("source_id"), F.slice("terms", 1, SIZE).alias("terms"), "e")
    filler = held.filter("p >= e AND p < 2 * e").select((F.col("p") - F.col("e")).alias("i"), F.col("doc_id").alias("source_id"), F.slice("terms", 101, SIZE - head).alias("tail"), "e")
    known = events.select(F.col("doc_id").alias("truth"), F.slice("terms", 1, head).alias("start"))
    old = filler.withColumn("truth", F.floor(F.col("i") / burst).cast("bigint")).join(known, "truth")
    old = old.select(F.concat(F.lit("r"), F.col("i").cast("string")).alias("name"), F.col("truth").alias("truth_id"), "source_id", F.concat("start", "tail").alias("terms"), "e")
    new = held.filter("p >= 2 * e AND p < 3 * e").select(F.concat(F.lit("n"), F.col("p").cast("string")).alias("name"), none.alias("truth_id"), F.col("doc_id").alias("source_id"), F.slice("terms", 1, SIZE).alias("terms"), "e")
    rows = old.unionByName(new).withColumn("m", F.md5("name"))
    test = numbered(rows, hashed_bucket(F.col("m")), ["m", "name"], "k")
    test = test.select((F.col("e") + F.col("k")).cast("bigint").alias("doc_id"), (F.floor(F.col("k") / batch) + 1).cast("bigint").alias("batch_id"), "truth_id", "source_id", "terms")
    return Scratch(spark, "constructed").write(events.select("doc_id", F.lit(0).cast("bigint").alias("batch_id"), "truth_id", "source_id", "terms").unionByName(test), "docs")


def together(parts: dict[str, DataFrame]) -> DataFrame:
    """Several streams as one input, told apart by ``stream``."""
    return functools.reduce(DataFrame.unionByName, [df.withColumn("stream", F.lit(name)) for name, df in parts.items()])


def constructed_sql(keep: float = 0.3, burst: int = 1, batch: int = 42) -> str:
    """CTEs up to ``docs(doc_id, batch_id, truth_id, terms)`` for DuckDB."""
    head = int(round(keep * SIZE))
    return rf"""
toks AS (SELECT doc_id, regexp_extract_all(lower(coalesce(text, '')), '\p{{L}}+') AS terms FROM documents),
longs AS (SELECT * FROM toks WHERE len(terms) >= {LONG}),
grams AS (SELECT doc_id, unnest([array_to_string(terms[i:i+{GRAM - 1}], ' ') FOR i IN range(1, {SIZE - GRAM + 2})]) AS g FROM longs),
firsts AS (SELECT g, min(doc_id) AS first FROM grams GROUP BY g),
shared AS (SELECT DISTINCT doc_id FROM grams JOIN firsts USING (g) WHERE first < doc_id),
held AS (SELECT doc_id AS src, terms, row_number() OVER (ORDER BY md5('p' || doc_id), doc_id) - 1 AS p, count(*) OVER () // 3 AS e FROM longs WHERE doc_id NOT IN (SELECT doc_id FROM shared)),
evs AS (SELECT p AS doc_id, src, terms[1:{SIZE}] AS terms, e FROM held WHERE p < e),
olds AS (SELECT 'r' || (h.p - h.e) AS name, v.doc_id AS truth_id, h.src, list_concat(v.terms[1:{head}], h.terms[101:{100 + SIZE - head}]) AS terms, h.e AS e
  FROM held h JOIN evs v ON v.doc_id = (h.p - h.e) // {burst} WHERE h.p >= h.e AND h.p < 2 * h.e),
news AS (SELECT 'n' || p AS name, CAST(NULL AS BIGINT) AS truth_id, src, terms[1:{SIZE}] AS terms, e FROM held WHERE p >= 2 * e AND p < 3 * e),
tests AS (SELECT *, row_number() OVER (ORDER BY md5(name), name) - 1 AS k FROM (SELECT * FROM olds UNION ALL SELECT * FROM news)),
docs AS (SELECT doc_id, CAST(0 AS BIGINT) AS batch_id, CAST(NULL AS BIGINT) AS truth_id, src AS source_id, terms FROM evs
  UNION ALL SELECT e + k, k // {batch} + 1, truth_id, src, terms FROM tests)"""


def truth(rows: DataFrame, least: float = 0.5) -> DataFrame:
    """(doc_id, truth_id, jaccard): the earlier document with the most similar set of word 5-grams, if similar enough.

    Made from grams alone, apart from any weight or hash of the detectors. Rows are (doc_id, terms).
    """
    grams = rows.select("doc_id", F.explode(F.array_distinct(ngrams(F.col("terms"), GRAM))).alias("g"))
    size = grams.groupBy("doc_id").agg(F.count("*").alias("size"))
    met = grams.select(F.col("doc_id").alias("q"), "g").join(grams.select(F.col("doc_id").alias("h"), "g"), "g").filter("h < q").groupBy("q", "h").agg(F.count("*").alias("c"))
    both = met.join(size.select(F.col("doc_id").alias("q"), F.col("size").alias("nq")), "q").join(size.select(F.col("doc_id").alias("h"), F.col("size").alias("nh")), "h")
    j = both.withColumn("j", F.round(F.col("c") / (F.col("nq") + F.col("nh") - F.col("c")), 6)).filter(F.col("j") >= least)
    best = j.groupBy("q").agg(F.min(F.struct((-F.col("j")).alias("m"), "h")).alias("s"))
    return best.select(F.col("q").alias("doc_id"), F.col("s.h").alias("truth_id"), (-F.col("s.m")).alias("jaccard"))


TRUTH_SQL = rf"""
tgrams AS (SELECT DISTINCT doc_id, unnest([array_to_string(terms[i:i+{GRAM - 1}], ' ') FOR i IN range(1, greatest(len(terms) - {GRAM - 2}, 1))]) AS g FROM docs),
tsize AS (SELECT doc_id, count(*) AS size FROM tgrams GROUP BY 1),
tmet AS (SELECT a.doc_id AS q, b.doc_id AS h, count(*) AS c FROM tgrams a JOIN tgrams b ON a.g = b.g AND b.doc_id < a.doc_id GROUP BY 1, 2),
tj AS (SELECT q, h, round(c / CAST(n.size + m.size - c AS DOUBLE), 6) AS j FROM tmet JOIN tsize n ON n.doc_id = q JOIN tsize m ON m.doc_id = h),
truths AS (SELECT q AS doc_id, h AS truth_id, j AS jaccard FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY j DESC, h) AS r FROM tj WHERE j >= 0.5) WHERE r = 1)"""


def natural(spark: SparkSession, sf_dir: str, batch: int = 200, train: int | None = None, test: int | None = None, rows: DataFrame | None = None, share: float = 1 / 3) -> DataFrame:
    """(doc_id, batch_id, truth_id, terms) of the documents in order: the first third trains, without those the truth calls repeats.

    With ``train`` and ``test``, exactly so many of each, as in the paper's group. ``rows`` (doc_id, terms) replaces the plain tokens; the
    truth is always that of the plain tokens.
    """
    scratch = Scratch(spark, "natural")
    plain = scratch.write(tokenised(spark, sf_dir).select("doc_id", "terms"), "tokens")
    found = scratch.write(truth(plain), "truth")
    first = plain.agg(F.floor(F.count("*") * share).alias("third"))
    rows = plain if rows is None else rows
    marked = rows.join(found, "doc_id", "left").join(F.broadcast(first)).select("doc_id", "terms", "truth_id", (F.col("doc_id") < F.col("third")).alias("early"))
    marked = scratch.write(marked.filter("truth_id IS NULL OR NOT early"), "marked")
    by_id = F.floor(F.col("doc_id") / 4096)
    first, late = (numbered(marked.filter(F.col("early") == early), by_id, ["doc_id"], "k") for early in (True, False))
    first = first.filter(F.col("k") < train) if train else first
    late = late.filter(F.col("k") < test) if test else late
    # only training documents can be matched: a truth elsewhere counts as none
    ids = first.select(F.col("doc_id").alias("truth_id"), F.lit(True).alias("there"))
    late = late.join(ids, "truth_id", "left").select("doc_id", (F.floor(F.col("k") / batch) + 1).cast("bigint").alias("batch_id"), F.when(F.col("there"), F.col("truth_id")).alias("truth_id"), "terms")
    return scratch.write(first.select("doc_id", F.lit(0).cast("bigint").alias("batch_id"), F.lit(None).cast("bigint").alias("truth_id"), "terms").unionByName(late), "docs")


def natural_sql(batch: int = 200) -> str:
    return rf"""
docs AS (SELECT doc_id, regexp_extract_all(lower(coalesce(text, '')), '\p{{L}}+') AS terms FROM documents),{TRUTH_SQL},
marked AS (SELECT doc_id, terms, truth_id, doc_id < (SELECT count(*) // 3 FROM docs) AS early FROM docs LEFT JOIN truths USING (doc_id)),
trains AS (SELECT doc_id, terms FROM marked WHERE early AND truth_id IS NULL),
lates AS (SELECT *, row_number() OVER (ORDER BY doc_id) - 1 AS k FROM marked WHERE NOT early),
ndocs AS (SELECT doc_id, CAST(0 AS BIGINT) AS batch_id, CAST(NULL AS BIGINT) AS truth_id, terms FROM trains
  UNION ALL SELECT doc_id, k // {batch} + 1, CASE WHEN truth_id IN (SELECT doc_id FROM trains) THEN truth_id END, terms FROM lates)"""


def baskets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders as documents, parts as terms, quantities as counts; the month of the order is the batch."""
    lines = table(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("doc_id"), F.col("l_partkey").alias("term")).agg(F.sum("l_quantity").cast("bigint").alias("tf"))
    when = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("doc_id"), F.date_trunc("month", "o_orderdate").alias("month"))
    return lines.join(when, "doc_id")


__all__ = ["baskets", "constructed", "constructed_sql", "natural", "natural_sql", "numbered", "parents", "term_counts", "together", "tokenised", "truth"]
