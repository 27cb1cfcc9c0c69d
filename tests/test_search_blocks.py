"""The detectors' search by blocks: results do not hang on the size of blocks, and plans send neither a row a batch and term nor a row a pair."""

import pytest
from novelspark.operators import blocks, detect
from novelspark.operators.detect import Config
from novelspark.plans import detectors
from novelspark.sources.scratch import Scratch
from pyspark.sql import functions as F

LSH = Config(k=2, tables=3)


@pytest.fixture(scope="module")
def docs(spark):
    """60 documents of 8 of 40 words, in batches 0 to 6 of two streams; stream b has no batch 3."""
    rows = [(s, i, max(0, i // 8 - 1), [f"w{(i * i + 7 * j * (1 + i % 3)) % 40}" for j in range(8)]) for s in "ab" for i in range(60)]
    rows = [r for r in rows if r[:1] + r[2:3] != ("b", 3)]
    return Scratch(spark, "blocks").write(spark.createDataFrame(rows, "stream string, doc_id long, batch_id long, terms array<string>"), "docs")


def rows(df):
    return sorted((r.stream, r.doc_id, round(r.distance, 6), r.match_id) for r in df.collect())


@pytest.mark.parametrize("cfg", [Config(search="exact", scheme=s, history=h) for s in ("static", "merged", "additive") for h in ("reference", "all_seen")] + [LSH, LSH.but(combine="mean"), LSH.but(bucket_cap=2), LSH.but(distance="hamming"), LSH.but(history="all_seen")], ids=str)
def test_blocks_of_any_size_give_the_same(docs, cfg, monkeypatch):
    whole = rows(detect.scores(docs, cfg))
    for name, size in (("QUERY_TERMS", 60), ("HISTORY_TERMS", 50), ("HASHED_TERMS", 50)):
        monkeypatch.setattr(blocks, name, size)
    assert rows(detect.scores(docs, cfg)) == whole


@pytest.mark.parametrize("cfg", [Config(search="exact", scheme=s) for s in ("static", "merged", "additive")] + [Config(search="exact", history="all_seen"), Config(search="exact", tf_mode="collection")], ids=str)
def test_blocks_give_the_nearest_of_the_plain_join(docs, cfg):
    scratch = Scratch(docs.sparkSession, "plain")
    tf, held = detect.statistics(docs, cfg, scratch)
    best = detect.all_distances(docs, tf, held, cfg).groupBy("stream", "q").agg(F.min(F.struct("distance", "h")).alias("s"))
    want = rows(detect.finished(docs, best.select("stream", "q", "s.distance", "s.h")))
    assert rows(detect.scores(docs, cfg)) == want


@pytest.mark.parametrize("scheme", ["static", "merged", "additive"])
def test_model_has_a_row_a_change_not_a_row_a_batch(docs, scheme):
    """A static model written for each batch made its small file a table that no driver could broadcast."""
    cfg, scratch = Config(search="exact", scheme=scheme), Scratch(docs.sparkSession, "changes")
    tf, found, _ = detect.changing(docs, cfg, scratch)
    own = tf.filter("batch_id = 0") if scheme == "static" else tf
    assert found.count() == own.select("stream", "term", *([] if scheme == "static" else ["batch_id"])).distinct().count()


def test_blocks_are_sent_the_changes_of_their_own_terms(docs, monkeypatch):
    """Changes sent to every block of the history, with counts that no product reads, were most of what the search put on disk."""
    monkeypatch.setattr(blocks, "HISTORY_TERMS", 50)
    cfg, scratch = Config(search="exact"), Scratch(docs.sparkSession, "sent")
    tf, found, size = detect.changing(docs, cfg, scratch)
    past = scratch.write(detect.known(tf, cfg).groupBy("stream", "doc_id", "own").agg(F.count("*").alias("size"), F.sort_array(F.collect_list(F.struct("term", "tf"))).alias("e")), "history")
    queries = blocks.weighed(tf, found, size, cfg, ("stream",)).groupBy("stream", "batch_id", "doc_id").agg(F.sum("x").alias("sq"), F.sort_array(F.collect_list(F.struct("term", "x"))).alias("e")).withColumn("bands", F.lit(None).cast("array<bigint>"))
    left, right, _ = blocks._dealt(tf, queries, found, size, past, cfg, ("stream",), 50)
    own = {}
    for r in right.collect():
        own.setdefault((r.stream, r.hb), set()).update(r.terms)
    sent = {}
    for r in left.filter("id IS NULL").collect():
        assert r.ys is None
        sent.setdefault((r.stream, r.hb), set()).update(r.terms)
    assert sent == own and len(own) > 2


#: Queries whose runs ended by the driver's memory or by disk, with the findings' numbers.
FOUND = {"decide": 1, "detect_static_exact": 3}


@pytest.mark.parametrize("name", FOUND)
def test_search_shuffles_no_row_a_pair(spark, sf, name):
    plan = detectors.QUERIES[name](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "FlatMapCoGroupsInArrow" in plan and "(own#" not in plan
