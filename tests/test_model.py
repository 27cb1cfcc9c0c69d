"""Worked examples and invariants of the weights, the search and the measures."""

import math

import pytest
from pyspark.sql import functions as F

from novelspark.functions import text
from novelspark.operators import detect, lsh, metrics, model, similarity
from novelspark.operators.detect import Config

SMALL = [(1, 0, ["a", "a", "b"]), (2, 0, ["b", "c"]), (3, 1, ["a", "d"])]


@pytest.fixture(scope="module")
def small(spark):
    return spark.createDataFrame(SMALL, "doc_id long, batch_id long, terms array<string>")


@pytest.mark.parametrize("cfg, idf, distance, novel", [
    (Config(scheme="static", search="exact"), {"a": 0.30103, "b": 0, "c": 0.30103}, 0.0, False),
    (Config(search="exact"), {"a": 0.176091, "b": 0.176091, "c": 0.477121, "d": 0.477121}, 1 - 0.274520, True),
    (Config(scheme="additive", search="exact"), {"a": 0.30103, "b": 0, "c": 0.30103, "d": 0}, 0.0, False),
])
def test_unseen_word(small, cfg, idf, distance, novel):
    """A word that the training lacks: static weights drop it and see a repeat, merged weights see a first report."""
    tf = model.term_counts(small, keys=("doc_id", "batch_id"))
    got = {r.term: r.idf for r in detect.models(small, tf, cfg).filter("batch_id = 1").collect()}
    assert {k: round(v, 6) for k, v in got.items()} == idf
    row = detect.decide(detect.scores(small, cfg), 0.5).first()
    assert row.distance == pytest.approx(distance, abs=1e-6) and row.is_novel is novel
    assert row.predicted == (0 if novel else 2)


def test_idf_base_cancels(small):
    tf, n = model.term_counts(small), model.corpus_size(small)
    counts = model.document_frequency(tf)
    ten, two = (model.unit(model.raw_weights(tf, model.idf(counts, n, base), "raw")) for base in (10, 2))
    both = ten.join(two.withColumnRenamed("w", "v"), ["doc_id", "term"]).collect()
    assert all(abs(r.w - r.v) < 1e-12 for r in both) and both


def test_merged_is_a_sum_in_any_split(small):
    tf, whole = model.term_counts(small), model.IncrementalModel.fit(model.term_counts(small), small).idf().collect()
    parts = [small.filter(F.col("doc_id") == i) for i in (3, 1, 2)]
    held = model.IncrementalModel.fit(model.term_counts(parts[0]), parts[0])
    for p in parts[1:]:
        held = held.update(model.term_counts(p), p)
    assert sorted(map(tuple, held.idf().collect())) == sorted(map(tuple, whole)) and tf.count() == 6


def test_additive_batches_of_one_change_nothing(spark):
    rows = [(i, 0, ["a", "b", "c"][: i % 3 + 1]) for i in range(6)] + [(6 + i, 1 + i, ["a", "x", "c"]) for i in range(3)]
    df = spark.createDataFrame(rows, "doc_id long, batch_id long, terms array<string>")
    one, other = (detect.scores(df, Config(scheme=s, search="exact")).orderBy("doc_id").collect() for s in ("static", "additive"))
    assert [r.distance for r in one] == [r.distance for r in other]


def test_degenerate_documents(spark):
    rows = [(0, 0, ["a", "b"]), (1, 0, ["a", "c"]), (2, 1, []), (3, 1, ["zz"]), (4, 1, ["a"])]
    df = spark.createDataFrame(rows, "doc_id long, batch_id long, terms array<string>")
    got = detect.decide(detect.scores(df, Config(scheme="static")), 0.9).collect()
    assert {(r.distance, r.is_novel, r.predicted) for r in got} == {(1.0, True, 0)} and len(got) == 3


def test_ties_equality_and_id_zero(spark):
    rows = [(0, 0, ["a", "b"]), (1, 0, ["a", "b"]), (2, 0, ["c"]), (3, 1, ["a", "b"])]
    df = spark.createDataFrame(rows, "doc_id long, batch_id long, terms array<string>")
    row = detect.decide(detect.scores(df, Config(scheme="static", search="exact")), 0.5).first()
    assert row.match_id == 0 and row.predicted == 1
    same = spark.createDataFrame([(9, 0.5, 1)], "doc_id long, distance double, match_id long")
    assert detect.decide(same, 0.5).first().is_novel


def test_settled_in_order(spark, tmp_path):
    pairs = spark.createDataFrame([(2, 1), (3, 2), (5, 4), (6, 5), (6, 4)], "q long, h long")
    docs = spark.createDataFrame([(i,) for i in range(1, 8)], "doc_id long")
    put = lambda df, r: (df.write.parquet(f"{tmp_path}/{r}"), spark.read.parquet(f"{tmp_path}/{r}"))[1]
    got = {r.doc_id: r.is_novel for r in detect.settle(pairs, docs, put).collect()}
    assert got == {1: True, 2: False, 3: True, 4: True, 5: False, 6: False, 7: True}


def test_chains(spark, tmp_path):
    df = spark.createDataFrame([(1, None), (2, 1), (3, 2), (4, 3), (5, None), (6, 0)], "doc_id long, match_id long")
    put = lambda d, r: (d.write.parquet(f"{tmp_path}/{r}"), spark.read.parquet(f"{tmp_path}/{r}"))[1]
    assert {r.doc_id: r.story for r in detect.chains(df, put).collect()} == {1: 1, 2: 1, 3: 1, 4: 1, 5: 5, 6: 0}


def test_table_counts(spark):
    want = {(4, 0.5, 0.1): 11, (8, 0.5, 0.1): 58, (4, 0.8, 0.1): 5, (8, 0.8, 0.1): 14, (13, 0.8, 0.1): 45, (16, 0.8, 0.1): 89, (26, 0.9, 0.1): 129, (8, 0.8, 0.025): 22}
    assert {c: lsh.tables_needed(*c) for c in want} == want
    assert {(r.k, r.cosine, r.miss): r.needed for r in lsh.table_counts(spark, list(want)).collect()} == want
    assert lsh.tables_printed(8, 0.8, 0.1) == pytest.approx(-2.303, abs=1e-3) and lsh.tables_printed(1, 0.0, 0.1) is None


@pytest.mark.parametrize("plane", ["sign", "gauss"])
def test_signatures(spark, plane):
    rows = [(1, "a", 1.0), (1, "b", 2.0), (2, "a", 10.0), (2, "b", 20.0), (3, "c", 1.0), (4, "c", -1.0)]
    df = spark.createDataFrame(rows, "doc_id long, term string, x double")
    got = {r.doc_id: r.bands for r in lsh.signatures(df, 8, 4, plane=plane).collect()}
    assert got[1] == got[2] and all(a ^ b == 255 for a, b in zip(got[3], got[4], strict=True))
    again = {r.doc_id: r.bands for r in lsh.signatures(df.repartition(5), 8, 4, plane=plane).collect()}
    assert got == again


def test_collision_chance_falls_with_the_angle(spark, sf):
    from novelspark.plans.novelty import QUERIES

    rows = [r for r in QUERIES["lsh_collision"](spark, sf).orderBy("cell").collect() if r.n >= 30]
    assert all(abs(r.observed - r.predicted) < 0.06 for r in rows)
    assert [r.observed for r in rows] == sorted(r.observed for r in rows)


def test_candidates_grow_with_tables(spark, sf):
    from novelspark.plans.novelty import candidate_rows

    one, five = ({(r.q, r.h) for r in candidate_rows(spark, sf, t).collect()} for t in (1, 5))
    assert one <= five and all(h < q for q, h in five)


def test_cost_and_curve(spark):
    cost = lambda m, f: spark.range(1).select(metrics.cost(F.lit(m), F.lit(f)).alias("c")).first().c
    assert round(cost(0.271, 0.0801), 5) == 0.66349 and round(cost(0.116, 0.072), 5) == 0.46880
    assert cost(0.0, 0.0) == 0 and min(cost(1.0, 0.0), cost(0.0, 1.0)) == pytest.approx(1) and cost(0.0, 1.0) == pytest.approx(4.9)
    rows = [(1, 0.1, 9), (2, 0.2, 9), (3, 0.4, None), (4, 0.6, 9), (5, 0.9, None)]
    scored = spark.createDataFrame([(a, b, c, c) for a, b, c in rows], "doc_id long, distance double, match_id long, truth_id long")
    rate = metrics.rates(metrics.confusion(detect.decide(scored.withColumn("match_id", F.lit(9)), 0.5))).first()
    assert (rate.p_miss, rate.p_fa, rate.p_fa_flagged) == (0.5, pytest.approx(1 / 3), 0.5)
    curve = metrics.det_curve(scored).orderBy("threshold").collect()
    assert (curve[0].p_miss, curve[0].p_fa) == (0, 1) and (curve[-1].p_miss, curve[-1].p_fa) == (1, 0)
    assert all(a.p_miss <= b.p_miss and a.p_fa >= b.p_fa for a, b in zip(curve, curve[1:], strict=False))


def test_probit_is_near_the_normal_quantile(spark):
    from statistics import NormalDist

    for r in spark.range(1, 100).select((F.col("id") / 100).alias("p")).select("p", metrics.probit(F.col("p")).alias("z")).collect():
        assert abs(r.z - NormalDist().inv_cdf(r.p)) < 5e-4


def test_porter_words():
    want = {"caresses": "caress", "ponies": "poni", "cats": "cat", "agreed": "agre", "plastered": "plaster", "motoring": "motor", "hopping": "hop", "falling": "fall", "happy": "happi", "relational": "relat", "vietnamization": "vietnam", "electrical": "electr", "adoption": "adopt", "controlling": "control", "sky": "sky"}
    assert {w: text.porter(w) for w in want} == want


def test_distance_kinds(spark):
    row = spark.range(1).select(similarity.distance(F.lit(1.0 + 1e-12), "angular").alias("a"), similarity.distance(F.lit(0.0), "angular").alias("b")).first()
    assert row.a == 0 and row.b == pytest.approx(0.5) and not math.isnan(row.a)


def test_static_cross_check_with_spark_ml(small):
    """Spark ML's smoothed natural-log idf is a shift of ours with ``plus1`` smoothing and base e."""
    from pyspark.ml.feature import IDF, CountVectorizer

    cv = CountVectorizer(inputCol="terms", outputCol="c").fit(small)
    ml = dict(zip(cv.vocabulary, IDF(inputCol="c", outputCol="i").fit(cv.transform(small)).idf.toArray(), strict=True))
    ours = model.idf(model.document_frequency(model.term_counts(small)), model.corpus_size(small), math.e, "plus1").collect()
    assert all(abs(ml[r.term] - r.idf) < 1e-9 for r in ours)


def test_delta_refresh_equals_full(spark, sf):
    from novelspark.operators import refresh
    from novelspark.plans.novelty import halves

    train, test = (x.cache() for x in halves(spark, sf))
    tf = model.term_counts(train).cache()
    first = model.IncrementalModel.fit(tf, train)
    after = first.update(model.term_counts(test), test)
    state = refresh.full(tf, first.frequency, 16)
    moved = refresh.changed(first.frequency, after.frequency)
    stepped = refresh.bands(refresh.delta(state, tf, moved, 16), after.size, 4)
    whole = refresh.bands(refresh.full(tf, after.frequency, 16), after.size, 4)
    both = stepped.join(whole.select("doc_id", F.col("bands").alias("b"), F.col("norm").alias("n")), "doc_id").collect()
    assert len(both) == train.count() and all(abs(r.norm - r.n) < 1e-9 for r in both)
    assert sum(r.bands != r.b for r in both) == 0
    raw = model.raw_weights(tf, after.idf())
    direct = {r.doc_id: r.bands for r in lsh.signatures(raw, 4, 4).collect()}
    assert sum(direct[r.doc_id] != r.b for r in both) <= 1
