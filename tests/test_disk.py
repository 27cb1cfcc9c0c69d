"""What the detectors put on disk: terms of the stream's parents are shuffled once, the history is not copied to blocks of queries that came before it."""

import pytest
from novelspark.operators import blocks, detect
from novelspark.operators.detect import Config
from novelspark.plans import streams
from novelspark.sources.scratch import Scratch
from pyspark.sql import functions as F


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, max(0, i // 8 - 1), [f"w{(i * i + 7 * j * (1 + i % 3)) % 40}" for j in range(8)]) for i in range(80)]
    return Scratch(spark, "disk").write(spark.createDataFrame(rows, "doc_id long, batch_id long, terms array<string>"), "docs")


def dealt(docs, cfg, history_terms):
    scratch = Scratch(docs.sparkSession, "dealt")
    tf, found, size = detect.changing(docs, cfg, scratch)
    past = scratch.write(detect.known(tf, cfg).groupBy("doc_id", "own").agg(F.count("*").alias("size"), F.sort_array(F.collect_list(F.struct("term", "tf"))).alias("e")), "history")
    queries = blocks.weighed(tf, found, size, cfg, ()).groupBy("batch_id", "doc_id").agg(F.sum("x").alias("sq"), F.sort_array(F.collect_list(F.struct("term", "x"))).alias("e")).withColumn("bands", F.lit(None).cast("array<bigint>"))
    return blocks._dealt(tf, queries, found, size, past, cfg, (), history_terms)


def test_queries_are_not_sent_to_a_later_history(docs, monkeypatch):
    monkeypatch.setattr(blocks, "QUERY_TERMS", 60)
    left, right, _ = dealt(docs, Config(search="exact", history="all_seen"), 60)
    last = {r.g: r.b for r in left.filter("id IS NOT NULL").groupBy("g").agg(F.max("batch_id").alias("b")).collect()}
    first = {r.hb: r.b for r in right.groupBy("hb").agg(F.min("own").alias("b")).collect()}
    sent = {(r.g, r.hb) for r in left.select("g", "hb").distinct().collect()}
    assert sent == {(r.g, r.hb) for r in right.select("g", "hb").distinct().collect()}
    assert sent == {(g, hb) for g, b in last.items() for hb, own in first.items() if own <= b} and len(sent) < len(last) * len(first)


def test_blocks_of_queries_grow_before_the_history_is_copied_more(docs, monkeypatch):
    for name, size in (("QUERY_TERMS", 20), ("QUERY_BLOCKS", 3), ("MOST_TERMS", 1000)):
        monkeypatch.setattr(blocks, name, size, raising=False)
    _, right, _ = dealt(docs, Config(search="exact"), 1000)
    assert right.select("g").distinct().count() <= 4


def test_parents_send_their_terms_once(spark, sf, monkeypatch):
    """Written tables before the last hold no terms but the long documents'."""
    written, write = {}, Scratch.write

    def kept(self, df, name):
        written[name] = (set(df.columns), df._jdf.queryExecution().optimizedPlan().toString())
        return write(self, df, name)

    monkeypatch.setattr(Scratch, "write", kept)
    streams.parents(spark, sf)
    assert [n for n, (columns, _) in written.items() if "terms" in columns] == ["long", "parents"]
    assert written["kept"][1].count("Generate explode") == 1
