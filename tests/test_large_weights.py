"""Hashed detectors whose weights' sums leave 32 bits, as added idf do after some thousand batches."""

import pytest
from novelspark.operators import detect
from novelspark.operators.detect import Config
from novelspark.sources.scratch import Scratch
from pyspark.sql import functions as F


def plain(docs, cfg):
    """Hashed detection by joins: signatures as aggregates, pairs of a bucket, their distances."""
    tf, held = detect.statistics(docs, cfg, Scratch(docs.sparkSession, "large"))
    met = detect.met_in_tables(*detect.hashed(tf, held, cfg), cfg).select("q", "h").distinct()
    best = met.join(detect.all_distances(docs, tf, held, cfg), ["q", "h"]).groupBy("q").agg(F.min(F.struct("distance", "h")).alias("s"))
    return rows(detect.finished(docs, best.select("q", "s.distance", "s.h")))


def rows(df):
    return sorted((r.doc_id, round(r.distance, 6), r.match_id) for r in df.collect())


@pytest.mark.parametrize("scheme", ["additive", "merged", "static"])
def test_sums_beyond_32_bits(spark, scheme):
    """Raw counts of some thousand stand for the many batches."""
    # fixed rows: a word that repeats 4,000 times and more in half of the documents
    data = [(i, max(0, i // 8 - 1), [f"w{(i * i + 7 * j * (1 + i % 3)) % 40}" for j in range(8)] + [f"w{i % 5}"] * (4000 + 900 * (i % 7)) * (i % 2)) for i in range(40)]
    docs = Scratch(spark, "docs").write(spark.createDataFrame(data, "doc_id long, batch_id long, terms array<string>"), "docs")
    cfg = Config(scheme=scheme, k=3, tables=5, tf_mode="raw")
    got = rows(detect.scores(docs, cfg))
    assert got == plain(docs, cfg) and sum(m is not None for _, _, m in got) > 10
