"""The centroid detector's search by blocks: no row a batch and term of the history is sent, and results are those of centroids made one by one."""

import math

import pytest
from novelspark.operators import blocks, detect
from novelspark.operators.detect import Config
from novelspark.plans import workloads
from novelspark.sources.scratch import Scratch

#: Fixed rows: 60 documents of 8 of 40 words in batches 0 to 6; three in four have a cluster, later ones too.
ROWS = [(i, max(0, i // 8 - 1), [f"w{(i * i + 7 * j * (1 + i % 3)) % 40}" for j in range(8)], None if i % 4 == 3 else 100 + i % 9) for i in range(60)]


def brute(cfg):
    """(distance, cluster) of every document after batch 0."""
    out = {}
    for i, b, terms, _ in ROWS:
        if not b:
            continue
        held = [t for _, c, t, _ in ROWS if c <= (0 if cfg.scheme == "static" else b)]
        idf = lambda w: math.log10(len(held) / n) if (n := sum(w in t for t in held)) else 0.0
        weigh = lambda t: {w: (math.log10(t.count(w)) + 1) * idf(w) for w in set(t)}
        length = lambda v: math.sqrt(sum(x * x for x in v.values()))
        q, means = weigh(terms), {}
        for _, c, t, cluster in ROWS:
            if cluster is not None and c <= (b if cfg.history == "all_seen" else 0):
                v = weigh(t)
                for w, x in v.items():
                    m = means.setdefault(cluster, {})
                    m[w] = m.get(w, 0.0) + x / length(v)
        near = [(round(1 - sum(x * m.get(w, 0.0) for w, x in q.items()) / length(q) / length(m), 6), c) for c, m in means.items() if length(m)]
        best = min([n for n in near if n[0] < 1], default=(1.0, None))
        out[i] = best
    return out


@pytest.mark.parametrize("small", [False, True])
@pytest.mark.parametrize("cfg", [Config(scheme=s, history=h, target="centroid") for s, h in (("merged", "reference"), ("merged", "all_seen"), ("static", "all_seen"), ("static", "reference"))], ids=str)
def test_centroids_by_blocks_equal_brute_force(spark, cfg, small, monkeypatch):
    for name, size in (("QUERY_TERMS", 60), ("HISTORY_TERMS", 60), ("DENSE", 30), ("CHUNK", 40)) if small else ():
        monkeypatch.setattr(blocks, name, size)
    docs = Scratch(spark, "docs").write(spark.createDataFrame(ROWS, "doc_id long, batch_id long, terms array<string>, cluster long"), "docs")
    got, want = {r.doc_id: (round(r.distance, 6), r.match_id) for r in detect.scores(docs, cfg).collect()}, brute(cfg)
    assert got.keys() == want.keys()
    assert all(abs(got[i][0] - want[i][0]) < 2e-6 and (got[i][1] == want[i][1] or abs(got[i][0] - want[i][0]) > 0) for i in want)


def test_no_row_a_batch_and_term_is_sent(spark, sf):
    """The history weighed anew for every batch by joins filled the disk."""
    plan = workloads.QUERIES["detect_centroid"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "FlatMapCoGroupsInArrow" in plan and "idf#" not in plan[: plan.index("FlatMapCoGroupsInArrow")]
