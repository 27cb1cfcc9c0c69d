"""A query's bands, made where its terms lie in one row, are those of the aggregate over a row a term; no row a plane is sent."""

import pytest
from novelspark.operators import blocks, lsh
from novelspark.plans import detectors
from pyspark.sql import functions as F

#: Hashed detectors whose runs ended by disk or the driver's memory, with the findings' numbers.
FOUND = {"detect_static_lsh": 4, "combine_mean": 17, "combine_union": 18, "detect_additive_lsh": 20, "detect_capped": 23}


def test_bands_of_rows_are_those_of_the_aggregate(spark):
    import pyarrow as pa

    rows = [(i, f"w{j * (i + 3) % 50}é", 0.0 if i % 5 == 4 else (i * 7 + j * 13) % 29 / 17) for i in range(40) for j in range(i % 7)]
    raw = spark.createDataFrame(rows, "doc_id long, term string, x double").dropDuplicates(["doc_id", "term"])
    want = {r.doc_id: r.bands for r in lsh.signatures(raw, 4, 22, 1).collect()}
    held = raw.groupBy("doc_id").agg(F.sort_array(F.collect_list(F.struct("term", "x"))).alias("e")).collect()
    ids = [*[r.doc_id for r in held], -1]
    terms, xs = (pa.array([*[[e[c] for e in r.e] for r in held], []], pa.list_(kind)) for c, kind in (("term", pa.string()), ("x", pa.float64())))
    got = dict(zip(ids, blocks.query_bands(terms, xs, 4, 22, 1).to_pylist()))
    assert {i: b for i, b in got.items() if b is not None} == want and got[-1] is None and len(want) < len(held)
    assert blocks.query_bands(terms.slice(len(terms)), xs.slice(len(xs)), 4, 22, 1).to_pylist() == []


@pytest.mark.parametrize("name", FOUND)
def test_queries_send_no_row_a_plane(spark, sf, name):
    plan = detectors.QUERIES[name](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "FlatMapCoGroupsInArrow" in plan and "w0#" not in plan and "p87#" not in plan
