"""Each document's nearest source: no row a term and source is shuffled, and results do not hang on the size of blocks."""

import pytest
from novelspark import registry
from novelspark.operators import model, whole
from novelspark.sources.scratch import Scratch


def test_no_row_a_term_and_source_is_sent(spark, sf):
    plan = registry.queries()["nn_centroid"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "FlatMapCoGroupsInArrow" in plan and "term#" not in plan


@pytest.mark.parametrize("terms", [3000, 1 << 21])
def test_centroids_of_any_size_of_blocks_equal_sql(spark, sf, duck, same, monkeypatch, terms):
    for limit, size in (("TERMS", terms), ("CHUNK", 5000 if terms == 3000 else 1 << 21)):
        monkeypatch.setattr(whole, limit, size)
    same(registry.queries()["nn_centroid"](spark, sf), duck.sql(registry.oracle_sql()["nn_centroid"]))


def test_rows_without_cluster_terms_or_weight(spark):
    rows = [(1, ["a", "b"], "x"), (2, ["b", "c", "a"], "x"), (3, [], "y"), (4, None, "x"), (5, ["d", "c"], None), (6, ["c", "e"], "y"), (7, ["e", "e"], "y")]
    scratch = Scratch(spark, "odd")
    bags = scratch.write(model.bags(spark.createDataFrame(rows, "doc_id long, terms array<string>, cluster string"), 100, ("cluster",)), "bags")
    got = {r.q: r.h for r in whole.nearest_centroid(bags, scratch).collect()}
    assert got == {1: "x", 2: "x", 5: None, 6: "y", 7: "y"}
