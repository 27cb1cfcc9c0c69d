"""Detectors: from documents to a scored row each, and from scores to decisions.

The threshold comes last, so one scored run serves every threshold. Documents are (doc_id, batch_id, terms): batch 0 is the training, later batches
arrive one after another.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..sources.scratch import Scratch
from . import blocks, lsh, model, similarity


@dataclass(frozen=True)
class Config:
    scheme: str = "merged"  # static, merged, additive
    search: str = "lsh"  # lsh, exact
    k: int = 8
    tables: int = 14
    seed: int = 1
    base: float = 10
    tf_mode: str = "log"  # log, raw, collection
    oov: str = "drop"  # drop, norm (static only)
    history: str = "reference"  # reference, all_seen
    target: str = "document"  # document, centroid
    distance: str = "cosine"  # cosine, hamming
    combine: str = "union"  # union, mean
    bucket_cap: int | None = None

    def but(self, **changes) -> Config:
        return replace(self, **changes)


STATIC, INCREMENTAL = Config(scheme="static"), Config()


def streams_of(docs: DataFrame) -> tuple[str, ...]:
    """Documents may carry a column ``stream``: streams are then detected apart from each other, all in one plan."""
    return ("stream",) if "stream" in docs.columns else ()


def models(docs: DataFrame, tf: DataFrame, cfg: Config) -> DataFrame:
    """(stream, batch_id, term, idf, cf): the model that each batch is scored with."""
    by = streams_of(docs)
    if cfg.scheme != "static":
        return model.history(tf, docs, cfg.scheme, cfg.base, by)
    ends = docs.groupBy(*by).agg(F.max("batch_id").alias("top"))
    known = static_model(docs, tf, cfg)
    known = known.join(F.broadcast(ends), list(by)) if by else known.join(F.broadcast(ends))
    return known.select(*by, F.explode(F.sequence(F.lit(0).cast("bigint"), "top")).alias("batch_id"), "term", "idf", "cf")


def static_model(docs: DataFrame, tf: DataFrame, cfg: Config) -> DataFrame:
    """(stream, term, df, cf, idf) of the training."""
    by = streams_of(docs)
    size = docs.filter("batch_id = 0").groupBy(*by).agg(F.count("*").alias("n"))
    known = tf.filter("batch_id = 0").groupBy(*by, "term").agg(F.count("*").alias("df"), F.sum("tf").alias("cf"))
    known = known.join(F.broadcast(size), list(by)) if by else known.join(F.broadcast(size))
    return known.select(*by, "term", "df", "cf", model.log(F.col("n") / F.col("df"), cfg.base).alias("idf"))


def changing(docs: DataFrame, cfg: Config, scratch: Scratch) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Counts (stream, batch_id, doc_id, term, tf), the model's changes (stream, term, since, next, df, cf, idf) and the batches' sizes, as written
    tables. A model has a row a change, not a row a batch: what stays as it is, in the static model everything, is held once."""
    by = streams_of(docs)
    tf = scratch.write(model.term_counts(docs, keys=(*by, "doc_id", "batch_id")), "tf")
    size = scratch.write(model.sizes(docs, by), "sizes")
    if cfg.scheme == "static":
        found = static_model(docs, tf, cfg).select(*by, "term", F.lit(0).cast("bigint").alias("since"), F.lit(None).cast("bigint").alias("next"), "df", "cf", "idf")
    else:
        found = model.changes(tf, size, cfg.base, by).drop("top")
    return tf, scratch.write(found, "changes"), size


def statistics(docs: DataFrame, cfg: Config, scratch: Scratch) -> tuple[DataFrame, DataFrame]:
    """Counts (stream, batch_id, doc_id, term, tf) and models of every batch, as written tables: all later steps read these."""
    by = streams_of(docs)
    tf = scratch.write(model.term_counts(docs, keys=(*by, "doc_id", "batch_id")), "tf")
    return tf, scratch.write(models(docs, tf, cfg), "models")


def vectors(tf: DataFrame, held: DataFrame, cfg: Config) -> tuple[DataFrame, DataFrame]:
    """Raw weights (stream, batch_id, doc_id, term, x) of queries, and of the history *as each batch's model weighs it*.

    A pair is scored with both vectors under the query's model. The weighed history is never stored: lengths, signatures and centroids
    are aggregates that start where it is made, and products read the plain counts.
    """
    by = streams_of(tf)
    x = (model.damped(F.col("tf"), cfg.tf_mode, cfg.base, F.col("cf")) * F.col("idf")).alias("x")
    queries = tf.filter("batch_id > 0").join(held, [*by, "batch_id", "term"]).select(*by, "batch_id", "doc_id", "term", x, "idf", "cf")
    past = known(tf, cfg).join(held.filter("batch_id > 0"), [*by, "term"]).filter("own <= batch_id").select(*by, "batch_id", "doc_id", "term", x)
    return queries, past


def known(tf: DataFrame, cfg: Config) -> DataFrame:
    """Counts of the history, ``own`` being the batch in which a document came."""
    return (tf if cfg.history == "all_seen" else tf.filter("batch_id = 0")).withColumnRenamed("batch_id", "own")


def _unknown_norm(docs: DataFrame, tf: DataFrame, cfg: Config) -> DataFrame:
    """(stream, batch_id, doc_id, more): what unknown words add to the squared length, each weighed as a word of one document."""
    by = streams_of(docs)
    train, size = tf.filter("batch_id = 0"), docs.filter("batch_id = 0").groupBy(*by).agg(F.count("*").alias("n"))
    unknown = tf.filter("batch_id > 0").join(train.select(*by, "term").distinct(), [*by, "term"], "left_anti")
    unknown = unknown.join(F.broadcast(size), list(by)) if by else unknown.join(F.broadcast(size))
    x = model.damped(F.col("tf"), cfg.tf_mode, cfg.base, F.col("tf")) * model.log(F.col("n").cast("double"), cfg.base)
    return unknown.groupBy(*by, "batch_id", "doc_id").agg(F.sum(x * x).alias("more"))


def scores(docs: DataFrame, cfg: Config) -> DataFrame:
    """(stream, doc_id, distance, match_id) of every document after the training; distance 1 and no match where nothing was compared.

    With ``target='centroid'`` history documents carry a ``cluster``, and ``match_id`` is the nearest cluster.
    """
    scratch, by = Scratch(docs.sparkSession, "detect"), streams_of(docs)
    extra = ("cluster",) if cfg.target == "centroid" else ()
    docs = scratch.write(docs.select(*by, "doc_id", "batch_id", "terms", *extra), "docs")
    if cfg.target == "centroid":
        return _by_centroid(docs, *changing(docs, cfg, scratch), cfg, scratch)
    return search(docs, *changing(docs, cfg, scratch), cfg, scratch)


def hashed(tf: DataFrame, held: DataFrame, cfg: Config) -> tuple[DataFrame, DataFrame]:
    """Signatures (stream, batch_id, doc_id, bands) of queries and of the history under each batch's model."""
    by = streams_of(tf)
    return tuple(lsh.signatures(v, cfg.k, cfg.tables, cfg.seed, (*by, "batch_id", "doc_id")) for v in vectors(tf, held, cfg))


def met_in_tables(q: DataFrame, h: DataFrame, cfg: Config) -> DataFrame:
    """(stream, batch_id, q, h, table_no) of pairs in one bucket, the history document being the earlier one."""
    extra = (*streams_of(q), "batch_id")
    q, h = (lsh.buckets(v, extra) for v in (q, h))
    if cfg.bucket_cap:
        newest = W.partitionBy(*extra, "table_no", "bucket").orderBy(F.desc("doc_id"))
        h = h.withColumn("age", F.row_number().over(newest)).filter(F.col("age") <= cfg.bucket_cap).drop("age")
    return q.withColumnRenamed("doc_id", "q").join(h.withColumnRenamed("doc_id", "h"), [*extra, "table_no", "bucket"]).filter("h < q").select(*extra, "q", "h", "table_no")


def search(docs: DataFrame, tf: DataFrame, found: DataFrame, size: DataFrame, cfg: Config, scratch: Scratch) -> DataFrame:
    """The search alone, from written counts, changes and sizes: nearest history document of each query."""
    by = streams_of(docs)
    more = _unknown_norm(docs, tf, cfg) if cfg.oov == "norm" and cfg.scheme == "static" else None
    tabled = cfg.search == "lsh" and (cfg.combine == "mean" or cfg.bucket_cap) and cfg.distance != "hamming"
    if cfg.search == "lsh" and cfg.distance == "hamming" and cfg.bucket_cap:
        raise ValueError("bits are compared in whole buckets")
    near = blocks.search(tf, found, size, known(tf, cfg), cfg, by, scratch.write, more, "tables" if tabled else "nearest")
    if cfg.search == "lsh" and cfg.distance == "hamming":
        share = F.round(F.col("value") / (cfg.k * cfg.tables), similarity.DIGITS)
        return finished(docs, near.groupBy(*by, "q").agg(F.min(F.struct(share.alias("d"), "h")).alias("s")).select(*by, "q", F.col("s.d").alias("distance"), "s.h"))
    near = near.withColumnRenamed("value", "similarity")
    if tabled and cfg.bucket_cap:
        newest = W.partitionBy(*by, "q", "table_no").orderBy(F.desc("h"))
        near = near.withColumn("age", F.row_number().over(newest)).filter((F.col("age") <= cfg.bucket_cap) & (F.col("h") < F.col("q"))).drop("age")
    return _by_mean(docs, near, cfg) if cfg.combine == "mean" and tabled else finished(docs, similarity.nearest(near, by))


def work(docs: DataFrame, cfg: Config, scratch: Scratch) -> DataFrame:
    """(hashed, joined): pairs that meet in a bucket, and pairs with a common weighed term."""
    tf, found, size = changing(docs, cfg, scratch)
    counted = blocks.search(tf, found, size, known(tf, cfg), cfg, streams_of(docs), scratch.write, what="work")
    return counted.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("hashed", "joined")])


def _similarities(docs: DataFrame, tf: DataFrame, held: DataFrame, cfg: Config) -> DataFrame:
    """(stream, q, h, similarity) of all pairs with a common term."""
    by = streams_of(docs)
    at = [*by, "batch_id"]
    queries, past = vectors(tf, held, cfg)
    length = lambda v: v.groupBy(*at, "doc_id").agg(F.sum(F.col("x") * F.col("x")).alias("s"))
    ql, hl = length(queries), length(past)
    # the query's row carries its batch's idf, so history postings enter the product as plain counts, once and not once a batch
    qv = queries.filter("x <> 0").select(*at, F.col("doc_id").alias("q"), "term", "x", "idf", "cf")
    hv = known(tf, cfg).select(*by, "own", F.col("doc_id").alias("h"), "term", "tf")
    met = qv.join(hv, [*by, "term"]).filter("h < q")
    xh = model.damped(F.col("tf"), cfg.tf_mode, cfg.base, F.col("cf")) * F.col("idf")
    dots = met.filter("own <= batch_id").groupBy(*at, "q", "h").agg(F.sum(F.col("x") * xh).alias("dot"))
    whole = dots.join(ql.select(*at, F.col("doc_id").alias("q"), F.col("s").alias("sq")), [*at, "q"]).join(hl.select(*at, F.col("doc_id").alias("h"), F.col("s").alias("sh")), [*at, "h"])
    return whole.select(*by, "q", "h", F.coalesce(F.try_divide("dot", F.sqrt(F.col("sq") * F.col("sh"))), F.lit(0.0)).alias("similarity"))


def all_distances(docs: DataFrame, tf: DataFrame, held: DataFrame, cfg: Config) -> DataFrame:
    """(stream, q, h, distance) of all pairs with a common weighed term, under the query's model."""
    near = _similarities(docs, tf, held, cfg)
    return near.select(*streams_of(docs), "q", "h", F.round(similarity.distance(F.col("similarity")), similarity.DIGITS).alias("distance"))


def _by_mean(docs: DataFrame, near: DataFrame, cfg: Config) -> DataFrame:
    """Mean over tables of each table's smallest distance; a table without a candidate counts as 1."""
    by = streams_of(docs)
    far = near.withColumn("d", F.round(1 - F.col("similarity"), similarity.DIGITS))
    best = far.groupBy(*by, "q", "table_no").agg(F.min(F.struct("d", "h")).alias("s"))
    mean = best.groupBy(*by, "q").agg(F.round((F.sum("s.d") + F.lit(cfg.tables) - F.count("*")) / cfg.tables, similarity.DIGITS + 3).alias("distance"), F.min("s").alias("m"))
    return finished(docs, mean.select(*by, "q", "distance", F.col("m.h").alias("h")))


def _by_centroid(docs: DataFrame, tf: DataFrame, found: DataFrame, size: DataFrame, cfg: Config, scratch: Scratch) -> DataFrame:
    """Distance to the nearest centroid: the mean of a cluster's unit vectors under the query's model."""
    by = streams_of(docs)
    of = docs.filter("cluster IS NOT NULL").select(*by, "doc_id", "cluster")
    near = blocks.search(tf, found, size, known(tf, cfg), cfg.but(search="exact", distance="cosine"), by, scratch.write, clusters=of)
    return finished(docs, similarity.nearest(near.withColumnRenamed("value", "similarity"), by))


def finished(docs: DataFrame, near: DataFrame) -> DataFrame:
    """Every document after the training has a row; a nearest one at distance 1 is no match."""
    by = streams_of(docs)
    near = near.filter("distance < 1").select(*by, F.col("q").alias("doc_id"), "distance", F.col("h").alias("match_id"))
    return docs.filter("batch_id > 0").select(*by, "doc_id").join(near, [*by, "doc_id"], "left").select(*by, "doc_id", F.coalesce("distance", F.lit(1.0)).alias("distance"), "match_id")


def decide(scored: DataFrame, threshold: float) -> DataFrame:
    """Strictly nearer than the threshold is redundant. ``predicted`` is 0 for novel, else the matched id plus one (ids begin at 0)."""
    near = F.col("distance") < F.lit(threshold)
    out = scored.withColumn("match_id", F.when(near, F.col("match_id"))).withColumn("is_novel", F.col("match_id").isNull())
    return out.withColumn("predicted", F.coalesce(F.col("match_id") + 1, F.lit(0)))


def random(docs: DataFrame, share: float = 0.5, seed: int = 1) -> DataFrame:
    """Scores of a detector that knows nothing: uniform values from a hash of the id."""
    u = F.conv(F.substring(F.md5(F.concat_ws("|", F.col("doc_id").cast("string"), F.lit(str(seed)))), 1, 8), 16, 10).cast("double") / float(1 << 32)
    return docs.filter("batch_id > 0").select("doc_id", F.round(u, similarity.DIGITS).alias("distance"), F.lit(None).cast("bigint").alias("match_id"))


def constant(docs: DataFrame, novel: bool) -> DataFrame:
    return docs.filter("batch_id > 0").select("doc_id", F.lit(1.0 if novel else 0.0).alias("distance"), F.lit(None).cast("bigint").alias("match_id"))


def settle(pairs: DataFrame, docs: DataFrame, write) -> DataFrame:
    """``novel_only``: a document is redundant if a *novel* earlier document is near. (doc_id, is_novel), as taking them in order would give.

    Pairs are (q, h) with h earlier and near. Each round settles documents whose earlier neighbours are all settled or of
    which one is novel; rounds are at most the longest chain of neighbours. ``write`` puts a round into shared storage.
    """
    state = write(docs.select("doc_id", F.lit(None).cast("boolean").alias("novel")), 0)
    r = 0
    while True:
        r += 1
        seen = pairs.join(state.select(F.col("doc_id").alias("h"), F.col("novel").alias("hn")), "h").groupBy("q").agg(F.max(F.coalesce(F.col("hn"), F.lit(False))).alias("hit"), F.max(F.col("hn").isNull()).alias("open"))
        after = state.join(seen.withColumnRenamed("q", "doc_id"), "doc_id", "left").select(
            "doc_id",
            F.coalesce("novel", F.when(F.coalesce("hit", F.lit(False)), False).when(~F.coalesce("open", F.lit(False)), True)).alias("novel"),
        )
        state = write(after, r)
        if state.filter("novel IS NULL").isEmpty():
            return state.select("doc_id", F.col("novel").alias("is_novel"))


def chains(decided: DataFrame, write) -> DataFrame:
    """(doc_id, story): matches followed to their first story; pointers double their reach each round."""
    now = write(decided.select("doc_id", F.coalesce("match_id", "doc_id").alias("story")), 0)
    r = 0
    while True:
        r += 1
        up = now.select(F.col("doc_id").alias("story"), F.col("story").alias("next"))
        after = write(now.join(up, "story", "left").select("doc_id", F.coalesce("next", "story").alias("story"), (F.coalesce("next", "story") != F.col("story")).alias("moved")), r)
        if after.filter("moved").isEmpty():
            return after.select("doc_id", "story")
        now = after.select("doc_id", "story")
