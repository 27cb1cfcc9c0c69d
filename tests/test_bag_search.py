"""Exhaustive search over bags: no row a term or a pair is shuffled, and results do not hang on the size of blocks."""

import pytest
from novelspark import registry
from novelspark.operators import similarity

#: Queries whose runs ended by disk, with the findings' numbers.
FOUND = {"nn_exact": 14, "nn_topk": 15, "nn_within": 16}


@pytest.mark.parametrize("name", FOUND)
def test_search_shuffles_no_row_a_pair(spark, sf, name):
    plan = registry.queries()[name](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "FlatMapCoGroupsInArrow" in plan and "w#" not in plan


@pytest.mark.parametrize("name", FOUND)
def test_blocks_of_any_size_equal_sql(spark, sf, duck, same, monkeypatch, name):
    for limit, size in (("QUERY_TERMS", 400), ("ROW_TERMS", 9000), ("DENSE", 200), ("CHUNK", 500)):
        monkeypatch.setattr(similarity, limit, size)
    same(registry.queries()[name](spark, sf), duck.sql(registry.oracle_sql()[name]))
