"""Every registered query against its SQL at the smallest scale; streams against batch runs."""

import pytest

from novelspark import registry
from novelspark.operators import detect
from novelspark.operators.detect import Config
from novelspark.plans import live, streams

QUERIES, SQL = registry.queries(), registry.oracle_sql()


@pytest.mark.parametrize("name", list(SQL))
def test_query_equals_sql(spark, sf, duck, same, name):
    same(QUERIES[name](spark, sf), duck.sql(SQL[name]))


@pytest.mark.parametrize("name", [n for n in QUERIES if n not in SQL and n != "stream_detect"])
def test_query_without_sql_runs(spark, sf, name):
    assert QUERIES[name](spark, sf).count() > 0


def test_stream_equals_batch_run_and_replay(spark, sf, tmp_path):
    """Micro-batches give what the one-shot plan gives, also after a batch is run twice."""
    cfg = Config(search="exact")
    path = f"file://{tmp_path}/s"
    docs = streams.constructed(spark, sf, batch=10).cache()
    source = live.tables.stream(spark, "parquet", live.batch_files(spark, docs, path), "doc_id bigint, terms array<string>", maxFilesPerTrigger=1)
    held = live.detector.StreamDetector(spark, f"{path}/live", docs.filter("batch_id = 0").select("doc_id", "terms"), cfg)
    held.run(source)
    want = sorted(map(tuple, detect.scores(docs, cfg).collect()))
    assert sorted(map(tuple, held.scored().select("doc_id", "distance", "match_id").collect())) == want
    last = docs.agg({"batch_id": "max"}).first()[0]
    held.batch(docs.filter(docs.batch_id == last), last - 1)
    assert sorted(map(tuple, held.scored().select("doc_id", "distance", "match_id").collect())) == want


def test_no_cross_join_in_hashed_search(spark, sf):
    plan = QUERIES["lsh_multi"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "Python" not in plan


@pytest.mark.parametrize("cfg", [Config(scheme="additive"), Config(history="all_seen"), Config(scheme="static", oov="norm")])
def test_stream_refuses_what_it_cannot_carry(spark, tmp_path, cfg):
    train = spark.createDataFrame([(0, ["a", "b"])], "doc_id long, terms array<string>")
    with pytest.raises(ValueError):
        live.detector.StreamDetector(spark, f"file://{tmp_path}/s", train, cfg)


@pytest.mark.parametrize("cfg", [Config(scheme="static", search="exact"), Config(k=4, tables=8), Config(search="exact", tf_mode="raw"), Config(search="exact", tf_mode="collection")])
def test_stream_settings_equal_batch_run(spark, tmp_path, cfg):
    rows = [(0, 0, "a b c".split()), (1, 0, "b d d e".split()), (2, 1, "a b c f".split()), (3, 1, "d d e".split()), (4, 2, "f c a".split()), (5, 2, "x".split())]
    docs = spark.createDataFrame(rows, "doc_id long, batch_id long, terms array<string>")
    held = live.detector.StreamDetector(spark, f"file://{tmp_path}/s", docs.filter("batch_id = 0").select("doc_id", "terms"), cfg)
    for b in (1, 2):
        held.batch(docs.filter(f"batch_id = {b}"), b - 1)
    key = lambda df: sorted(map(tuple, df.select("doc_id", "distance", "match_id").collect()), key=str)
    assert key(held.scored()) == key(detect.scores(docs, cfg))
