"""Streams told apart in one plan against each alone; detectors against brute force on small bags."""

import math
import random

import pytest
from pyspark.sql import functions as F

from novelspark.operators import detect
from novelspark.operators.detect import Config
from novelspark.plans import streams, workloads


def bags(seed, n=24, vocabulary=14):
    r = random.Random(seed)
    return [(i, 0 if i < 8 else (i - 8) // 6 + 1, [f"t{r.randrange(vocabulary)}" for _ in range(r.randrange(1, 9))]) for i in range(n)]


@pytest.mark.parametrize("cfg", [Config(search="exact"), Config(scheme="static", search="exact", oov="norm"), Config(scheme="additive", search="exact", history="all_seen"), Config(k=3, tables=6), Config(k=3, tables=6, combine="mean")])
def test_streams_in_one_plan_equal_each_alone(spark, cfg):
    schema = "doc_id long, batch_id long, terms array<string>"
    parts = {name: spark.createDataFrame(bags(seed), schema) for name, seed in (("a", 1), ("b", 2))}
    got = {(r.stream, r.doc_id): (r.distance, r.match_id) for r in detect.scores(streams.together(parts), cfg).collect()}
    want = {(name, r.doc_id): (r.distance, r.match_id) for name, df in parts.items() for r in detect.scores(df, cfg).collect()}
    assert got == want and len(got) == 32


def weights(rows, upto):
    seen = [t for _, b, t in rows if b <= upto]
    df = {}
    for t in seen:
        for w in set(t):
            df[w] = df.get(w, 0) + 1
    return lambda terms: {w: (math.log10(terms.count(w)) + 1) * math.log10(len(seen) / df[w]) for w in set(terms)}


def cosine(a, b):
    length = math.sqrt(sum(x * x for x in a.values())) * math.sqrt(sum(x * x for x in b.values()))
    return sum(x * b.get(w, 0.0) for w, x in a.items()) / length if length else 0.0


@pytest.mark.parametrize("history", ["reference", "all_seen"])
def test_incremental_detector_equals_brute_force(spark, history):
    rows = bags(7)
    got = {r.doc_id: r.distance for r in detect.scores(spark.createDataFrame(rows, "doc_id long, batch_id long, terms array<string>"), Config(search="exact", history=history)).collect()}
    for i, b, terms in rows:
        if b:
            weigh = weights(rows, b)
            past = [t for j, c, t in rows if j < i and (c == 0 or history == "all_seen")]
            assert abs(got[i] - min([1.0, *(1 - cosine(weigh(terms), weigh(t)) for t in past)])) < 2e-6


def test_centroid_detector_equals_brute_force(spark):
    rows = bags(9)
    df = spark.createDataFrame([(i, b, t, i % 3 if b == 0 else None) for i, b, t in rows], "doc_id long, batch_id long, terms array<string>, cluster long")
    got = {r.doc_id: (r.distance, r.match_id) for r in detect.scores(df, Config(target="centroid")).collect()}
    for i, b, terms in rows:
        if not b:
            continue
        weigh, best = weights(rows, b), (1.0, None)
        for c in range(3):
            mean = {}
            for j, batch, t in rows:
                v = weigh(t)
                length = math.sqrt(sum(x * x for x in v.values()))
                if batch == 0 and j % 3 == c and length:
                    for w, x in v.items():
                        mean[w] = mean.get(w, 0.0) + x / length
            best = min(best, (round(1 - cosine(weigh(terms), mean), 6), c), key=lambda x: x[0])
        assert abs(got[i][0] - best[0]) < 2e-6


def test_one_document_a_batch_makes_additive_static(spark):
    rows = [(i, 0 if i < 8 else i - 7, t) for i, _, t in bags(3)]
    df = spark.createDataFrame(rows, "doc_id long, batch_id long, terms array<string>")
    scored = [{r.doc_id: r.distance for r in detect.scores(df, Config(scheme=s, search="exact")).collect()} for s in ("additive", "static")]
    known = {w for _, b, t in rows if b == 0 for w in t}
    assert all(scored[0][i] == scored[1][i] for i, b, t in rows if b and set(t) <= known)


def test_numbering_is_gapless_and_in_order(spark):
    df = spark.range(1000).selectExpr("id * 7 % 5000 AS x").distinct()
    rows = streams.numbered(df, F.floor(F.col("x") / 64), ["x"], "k").collect()
    order = sorted(rows, key=lambda r: r.k)
    assert [r.k for r in order] == list(range(len(rows))) and [r.x for r in order] == sorted(r.x for r in rows)


def test_benchmark_passages_are_found(spark, sf):
    rows = {r.doc_id: r for r in workloads.QUERIES["detect_benchmark"](spark, sf).collect()}
    assert len(rows) == spark.read.parquet(f"{sf}/documents.parquet").count()


def test_sketches_keep_their_error_bounds(spark, sf, duck):
    """Distinct counts within three times their relative error, medians within two hundredths of the rank."""
    from novelspark import registry

    got = registry.queries()["agg_approx"](spark, sf).first()
    tok = r"(SELECT doc_id, unnest(regexp_extract_all(lower(coalesce(text, '')), '\p{L}+')) AS term FROM documents)"
    distinct, n = duck.sql(f"SELECT count(DISTINCT term), count(*) FROM {tok}").fetchall()[0]
    assert abs(got["distinct"] / distinct - 1) < 0.06 and abs(got["hll"] / distinct - 1) < 0.06
    for name in ("median", "kll_median"):
        below, upto = duck.sql(f"SELECT count(*) FILTER (doc_id < {got[name]}), count(*) FILTER (doc_id <= {got[name]}) FROM {tok}").fetchall()[0]
        assert below / n - 0.02 <= 0.5 <= upto / n + 0.02
