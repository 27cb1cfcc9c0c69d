"""Block-wise search over dense vectors against brute force, with small blocks and odd vectors."""

import math

import pytest

from novelspark.operators import lsh, similarity

ROWS = [(i, [math.sin(i), math.cos(3 * i), math.sin(7 * i) + 0.1]) for i in range(40)] + [(40, None), (41, [1.0, None, 0.0]), (42, [0.5]), (43, [0.0, 0.0, 0.0]), (44, [math.sin(3), math.cos(9), math.sin(21) + 0.1])]


def cosine(a, b):
    if a is None or b is None or None in a or None in b:
        return 0.0
    n = math.sqrt(sum(x * x for x in a)) * math.sqrt(sum(x * x for x in b))
    return sum(x * y for x, y in zip(a, b)) / n if n else 0.0


def brute(ids, k, allowed=lambda q, h: True):
    held, out = dict(ROWS), []
    for q in ids:
        near = sorted((round(1 - max(-1, min(1, cosine(held[q], v))), 6), h) for h, v in ROWS if h != q and allowed(q, h))
        out += [(q, h, r + 1) for r, (_, h) in enumerate(near[:k])]
    return sorted(out)


@pytest.fixture(scope="module")
def rows(spark):
    return spark.createDataFrame(ROWS, "doc_id long, v array<double>")


@pytest.mark.parametrize("size", [7, 4096])
def test_blocks_give_the_nearest_of_all_rows(rows, size, monkeypatch):
    monkeypatch.setattr(similarity.blockwise, "__defaults__", (size,))
    queries = rows.filter("doc_id % 5 = 0")
    got = similarity.nearest_dense(queries, rows, 3).select("q", "h", "rank").collect()
    assert sorted(map(tuple, got)) == brute(range(0, 45, 5), 3)


def test_no_rows_no_neighbours(rows):
    none = rows.filter("doc_id < 0")
    assert similarity.nearest_dense(none, rows).count() == similarity.nearest_dense(rows, none).count() == 0


def test_plan_sends_no_side_whole(rows):
    plan = similarity.nearest_dense(rows.filter("doc_id % 5 = 0"), rows, 3)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "FlatMapCoGroupsInPandas" in plan


@pytest.mark.parametrize("cap, size", [(3, 4), (100, 4), (100, 4096)])
def test_grouped_scores_read_the_newest_of_each_bucket(rows, cap, size):
    placed = rows.selectExpr("doc_id", "v", "0 AS table_no", "CAST(doc_id < 35 AS long) AS bucket")
    got = lsh.grouped_nearest(placed, placed, cap, size).select("q", "h").collect()
    newest = {1: list(range(35))[-cap:], 0: list(range(35, 45))[-cap:]}
    assert sorted(map(tuple, got)) == [(q, h) for q, h, _ in brute(range(45), 1, lambda q, h: h in newest[int(q < 35)])]


def test_centroid_parts_add_up(spark):
    data = [(i, "a" if i % 3 else None, [float(i), 1.0]) for i in range(30)] + [(30, "a", None), (31, "a", [None, 1.0])]
    got = similarity.centroids_grouped(spark.createDataFrame(data, "doc_id long, g string, v array<double>"), "g", size=4).collect()
    mean = lambda g: sum(v[0] for i, x, v in data[:30] if x == g) / sum(x == g for _, x, _ in data[:30])
    assert sorted(map(tuple, got), key=str) == sorted([("a", 0, mean("a")), ("a", 1, 1.0), (None, 0, mean(None)), (None, 1, 1.0)], key=str)
