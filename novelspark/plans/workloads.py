"""Detectors on the given tables as they are: whole documents, sentences, pages, benchmark passages, baskets, user-days, and streams told
apart by language or source. Ablations of preprocessing, training share and folds. They have no SQL; tests compare them with small runs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import text
from ..operators import detect, metrics
from ..operators.detect import Config
from ..sources.scratch import Scratch
from ..sources.tables import table
from . import streams
from .detectors import EXACT, THRESHOLD, best_of, union_all, with_truth

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str):
    def keep(f):
        QUERIES[name] = f
        return f

    return keep


def prepared(spark, d, stop: bool = True, stems: bool = True) -> DataFrame:
    """(doc_id, lang, source, terms) of whole documents, stop words removed and endings taken off."""
    docs = table(spark, d, "documents").filter("doc_id IS NOT NULL")
    terms = text.tokens(F.col("text"))
    terms = text.drop_stopwords(terms, F.col("lang")) if stop else terms
    terms = F.transform(terms, text.stem) if stems else terms
    return docs.select("doc_id", "lang", "source", terms.alias("terms"))


def arriving(rows: DataFrame, by: str | None = None, share: float = 1 / 3, batches: int = 5) -> DataFrame:
    """Documents (doc_id, [stream,] terms) in the order of their ids: the first share of each stream is batch 0, the rest come in equal batches."""
    keys = [by] if by else []
    ends = rows.groupBy(*keys).agg(F.min("doc_id").alias("low"), F.max("doc_id").alias("high"))
    placed = (rows.join(F.broadcast(ends), keys) if by else rows.join(F.broadcast(ends))).withColumn("at", (F.col("doc_id") - F.col("low")) / (F.col("high") - F.col("low") + 1))
    batch = F.when(F.col("at") < share, 0).otherwise(F.floor((F.col("at") - share) / (1 - share) * batches) + 1).cast("bigint")
    return placed.select("doc_id", *[F.col(k).alias("stream") for k in keys], batch.alias("batch_id"), "terms", *[c for c in ("cluster",) if c in rows.columns])


def run(docs: DataFrame, cfg: Config, threshold: float = THRESHOLD) -> DataFrame:
    return detect.decide(detect.scores(docs, cfg), threshold)


for _scheme in ("static", "merged", "additive"):

    def _whole(spark, d, scheme=_scheme):
        return run(arriving(prepared(spark, d)), Config(scheme=scheme, search="exact"))

    QUERIES[f"detect_documents_{_scheme}"] = _whole


@query("detect_by_language")
def detect_by_language(spark, d):
    return run(arriving(prepared(spark, d), "lang"), EXACT)


@query("detect_by_source")
def detect_by_source(spark, d):
    return run(arriving(prepared(spark, d), "source"), EXACT)


@query("detect_centroid")
def detect_centroid(spark, d):
    """Nearest centroid on the constructed stream: each event's cluster holds its opening and a later stretch of the same text."""
    held = streams.parents(spark, d)
    docs = streams.constructed(spark, d, held=held)
    top = docs.agg((F.max("doc_id") + 1).alias("top"))
    more = held.filter("p < e").join(F.broadcast(top)).select((F.col("top") + F.col("p")).cast("bigint").alias("doc_id"), F.lit(0).cast("bigint").alias("batch_id"), F.slice("terms", 41, streams.SIZE).alias("terms"), F.col("p").cast("bigint").alias("cluster"))
    first = docs.select("doc_id", "batch_id", "terms", F.when(F.col("batch_id") == 0, F.col("doc_id")).alias("cluster"))
    return run(first.unionByName(more), Config(target="centroid"))


@query("detect_sentences")
def detect_sentences(spark, d):
    """Sentences of five tokens or more against those of the first third of the documents; (doc_id, n, n_novel, any_novel)."""
    parts = text.sentences(table(spark, d, "documents").select("doc_id", "lang", "text"), min_tokens=5)
    terms = text.drop_stopwords(text.tokens(F.col("text")), F.col("lang"))
    rows = parts.select(F.col("doc_id").alias("of"), (F.col("doc_id") * 1_000_000 + F.col("pos")).alias("doc_id"), terms.alias("terms"))
    docs = Scratch(spark, "sentences").write(arriving(rows.drop("of"), batches=1), "docs")
    scored = run(docs, Config(scheme="static", k=16, tables=4), 0.5)
    back = scored.select(F.floor(F.col("doc_id") / 1_000_000).alias("doc_id"), "is_novel")
    return back.groupBy("doc_id").agg(F.count("*").alias("n"), F.count_if("is_novel").alias("n_novel"), F.bool_or("is_novel").alias("any_novel"))


@query("detect_pages")
def detect_pages(spark, d):
    pages = table(spark, d, "pages").select(F.col("page_id").alias("doc_id"), text.tokens(text.html_text(F.col("html"))).alias("terms"))
    return run(arriving(pages), EXACT)


@query("detect_benchmark")
def detect_benchmark(spark, d):
    """Benchmark passages are the known events; documents arrive. A document's nearest passage and its distance; ids of passages begin at 0."""
    known = table(spark, d, "benchmark").select(F.col("item_id").alias("doc_id"), F.lit(0).cast("bigint").alias("batch_id"), text.tokens(F.col("text")).alias("terms"))
    first = known.agg((F.max("doc_id") + 1).alias("first"))
    docs = table(spark, d, "documents").join(F.broadcast(first)).select((F.col("doc_id") + F.col("first")).alias("doc_id"), F.lit(1).cast("bigint").alias("batch_id"), text.tokens(F.col("text")).alias("terms"))
    scored = run(known.unionByName(docs), Config(scheme="static", search="exact"))
    return scored.join(F.broadcast(first)).withColumn("doc_id", F.col("doc_id") - F.col("first")).drop("first")


def bags(rows: DataFrame) -> DataFrame:
    """(doc_id, batch_id, terms) from (doc_id, batch_id, term, tf): each term as often as it counts."""
    return rows.groupBy("doc_id", "batch_id").agg(F.flatten(F.collect_list(F.array_repeat(F.col("term").cast("string"), F.col("tf").cast("int")))).alias("terms"))


@query("detect_baskets")
def detect_baskets(spark, d):
    """Orders as bags of parts; the first year trains, each later year is a batch."""
    rows = streams.baskets(spark, d)
    first = rows.agg(F.min(F.year("month")).alias("first"))
    held = rows.join(F.broadcast(first)).select("doc_id", (F.year("month") - F.col("first")).cast("bigint").alias("batch_id"), "term", "tf")
    return run(bags(held), EXACT)


@query("detect_user_days")
def detect_user_days(spark, d):
    """A user's day as a bag of event types and property values; days in order, the first third trains."""
    days = table(spark, d, "events").select("user_id", F.datediff(F.to_date("ts"), F.lit("2024-01-01")).alias("day"), F.explode(F.array("event_type", F.concat(F.lit("k"), F.get_json_object("props", "$.k")))).alias("term"))
    counted = days.filter("term IS NOT NULL").groupBy("user_id", "day", "term").agg(F.count("*").alias("tf"))
    rows = counted.select((F.col("day") * 1_000_000 + F.col("user_id")).cast("bigint").alias("doc_id"), F.lit(0).cast("bigint").alias("batch_id"), "term", "tf")
    return run(arriving(bags(rows).drop("batch_id")), EXACT)


@query("exp_preprocessing")
def exp_preprocessing(spark, d):
    """Best points on the documents in order, with and without stop words and endings; the truth stays that of plain tokens."""
    parts = []
    for stop in (False, True):
        for stems in (False, True):
            docs = streams.natural(spark, d, rows=prepared(spark, d, stop, stems).select("doc_id", "terms"))
            parts.append(best_of(with_truth(docs, EXACT)).select(F.lit(stop).alias("stop_words_removed"), F.lit(stems).alias("stems"), "*"))
    return union_all(parts)


@query("exp_training_share")
def exp_training_share(spark, d):
    parts = []
    for share in (0.1, 0.33, 0.5):
        docs = streams.natural(spark, d, share=share)
        for scheme in ("static", "merged"):
            parts.append(best_of(with_truth(docs, Config(scheme=scheme, search="exact"))).select(F.lit(share).alias("share"), F.lit(scheme).alias("scheme"), "*"))
    return union_all(parts)


@query("exp_cross_validation")
def exp_cross_validation(spark, d, folds: int = 5):
    """The threshold of the best point of all folds but one, and the rates it gives on that one, for both schemes."""
    docs = streams.constructed(spark, d)
    fold = F.pmod(F.xxhash64("doc_id"), F.lit(folds)).cast("int").alias("fold")
    parts = []
    for scheme in ("static", "merged"):
        rows = with_truth(docs, Config(scheme=scheme, search="exact")).select("*", fold)
        others = rows.withColumnRenamed("fold", "own").withColumn("fold", F.explode(F.sequence(F.lit(0), F.lit(folds - 1)))).filter("own <> fold")
        best = metrics.best_point(metrics.det_curve(others, ("fold",)), ("fold",)).select("fold", "threshold")
        novel, called = F.col("truth_id").isNull(), F.col("distance") >= F.col("threshold")
        counts = rows.join(F.broadcast(best), "fold").groupBy("fold", "threshold").agg(
            F.count_if(novel & called).alias("tp"), F.count_if(novel & ~called).alias("fn"), F.count_if(~novel & called).alias("fp"), F.count_if(~novel & ~called).alias("tn")
        )
        parts.append(metrics.rates(counts).select(F.lit(scheme).alias("scheme"), "fold", "threshold", "p_miss", "p_fa", "cost"))
    return union_all(parts)


__all__ = ["QUERIES", "SQL", "arriving", "bags", "prepared"]
