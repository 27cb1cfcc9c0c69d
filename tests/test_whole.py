"""Searches of all rows by packed blocks: every row is a query, and results do not hang on the size of blocks."""

import pytest
from novelspark import registry
from novelspark.operators import similarity, whole


def test_every_row_is_a_query(spark, sf):
    rows = registry.queries()["nn_exact"](spark, sf).collect()
    weighed = registry.queries()["vsm_weights"](spark, sf).select("doc_id").distinct().count()
    assert len(rows) > 0.9 * weighed and any(r.q % 50 for r in rows)


@pytest.mark.parametrize("group", [2, 4])
def test_packed_blocks_of_any_size_equal_sql(spark, sf, duck, same, monkeypatch, group):
    """Small blocks, so that there are several rounds, and one round."""
    for at, limit, size in ((whole, "TERMS", 9000), (whole, "BLOCKS", 3 if group == 2 else 50), (whole, "GROUP", group), (similarity, "DENSE", 400), (similarity, "CHUNK", 900)):
        monkeypatch.setattr(at, limit, size)
    same(registry.queries()["nn_exact"](spark, sf), duck.sql(registry.oracle_sql()["nn_exact"]))


def test_rows_without_id_or_terms(spark):
    from novelspark.operators import model
    from novelspark.sources.scratch import Scratch

    rows = [(1, ["a", "b"]), (2, ["b", "c", "a"]), (None, ["a", "b"]), (3, []), (4, None), (5, ["d"]), (6, ["c", "e"])]
    scratch = Scratch(spark, "odd")
    bags = scratch.write(model.bags(spark.createDataFrame(rows, "doc_id long, terms array<string>"), 100), "bags")
    got = {r.q: r.h for r in whole.nearest(bags, scratch).collect()}
    assert got == {1: 2, 2: 1, 6: 2}
