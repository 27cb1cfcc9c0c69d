"""What each operator keeps of its method, and inputs at the edges: very long, very large, repeated, null, clashing names."""

import base64
import random

import numpy as np

from novelspark.llm import chunk_bpe, common, jaccard, packing, pii, secrets, sharding, token_counts, vector_topk


class Kept(common.Scratch):
    """Remembers its tables' folders."""

    made: list = []

    def __init__(self, *args):
        super().__init__(*args)
        Kept.made.append(self.base)


def passage(seed, words):
    r = random.Random(seed)
    return " ".join("".join(r.choice("abcdefgh") for _ in range(6)) for _ in range(words))


def test_repeated_chunks_are_encoded_once_over_all_tasks(spark, monkeypatch):
    monkeypatch.setattr(chunk_bpe, "Scratch", Kept)
    shared = passage(1, 3000)
    texts = [f"{passage(10 + i, 200)} {shared} {passage(30 + i, 300)}" for i in range(6)] + [passage(50, 2000), None, "", "short"]
    df = spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)], "doc_id long, text string, digest string").repartition(4)
    got = {r.doc_id: r.ids for r in chunk_bpe.encode(df).collect()}
    for i, ids in enumerate(chunk_bpe.chunk_encoder().units.whole([t or "" for t in texts])):
        assert bytes(got[i]) == ids.astype("<u4").tobytes()
    steps, known = (spark.read.parquet(f"{Kept.made[-1]}/{name}") for name in ("steps", "known"))
    counts = {}
    for t in texts:
        for c in chunk_bpe.chunks(t or ""):
            counts[c] = counts.get(c, 0) + 1
    often = {c for c, n in counts.items() if n > 1}
    assert len(often) > 5 and known.count() == len(often)  # one encoding each
    assert steps.filter("step = 2").count() == sum(counts[c] for c in often)
    assert steps.filter("step = 0").count() == 4


def test_map_versions_are_stored_and_edited(spark, tmp_path):
    df = spark.createDataFrame([(i, "x" * (i % 97)) for i in range(3000)], "doc_id long, text string")
    path = f"file://{tmp_path}/map"
    sharding.SlotMap.even(256, 8).save(spark, path)
    _, second = sharding.shard(df, 8, n_slots=256, path=path)
    _, third = sharding.shard(df.union(df.selectExpr("doc_id + 5000", "repeat('y', 300)").limit(500)), 8, n_slots=256, path=path)
    assert (second.version, third.version) == (2, 3)
    assert sharding.SlotMap.load(spark, path, 1).shard_of == sharding.SlotMap.even(256, 8).shard_of
    assert sharding.SlotMap.load(spark, path, 2).shard_of == second.shard_of != third.shard_of
    sizes, _ = sharding.slot_histogram(sharding.with_slots(df, n_slots=256), 256)
    loads, before = second.loads(sizes), sharding.SlotMap.even(256, 8).loads(sizes)
    assert max(loads) - min(loads) < max(before) - min(before) and max(loads) <= 1.02 * sum(loads) / 8
    assert sum(a != b for a, b in zip(second.shard_of, sharding.SlotMap.even(256, 8).shard_of, strict=True)) < 128


def test_packing_keeps_most_placements():
    r, p = random.Random(4), packing.Packer(1024)
    rows = []
    for i in range(3000):
        rows += p.add(i, np.arange(r.choice([r.randrange(1, 300), r.randrange(200, 1500)]), dtype=np.uint32))
    rows += p.settle(last=True)
    assert p.recut < 0.1 * p.placed
    fill = {}
    for row in rows:
        fill[row[5]] = fill.get(row[5], 0) + row[2]
    assert sum(1024 - f for f in fill.values()) < 1024


def test_packing_memory_is_bounded():
    p, rows = packing.Packer(1024, max_open=50), []
    for i in range(2000):  # no two of these rests fit into one window
        rows += p.add(i, np.full(600, i, dtype=np.uint32))
        assert len(p.waiting) <= 50
    rows += p.settle(last=True)
    assert sum(x[2] for x in rows) == 2000 * 600
    assert len({x[5] for x in rows}) == -(-2000 * 600 // 1024)


def test_histogram_encodes_once(spark, sf):
    plan = token_counts.op10_length_histogram(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "MapInPandas" not in plan  # the answer reads the stored histogram


def test_token_header_nested_too_deep():
    deep = base64.urlsafe_b64encode(b'{"a":' * 100_000).decode().rstrip("=")
    assert secrets.scan(f"{deep}.eyJhIjoxfQ.abc") == []
    assert secrets.scan("eyJ" * 300_000) == []


def test_topk_with_huge_long_and_copied_vectors(spark):
    r = random.Random(2)
    rows = [(i, [float(r.randrange(-3, 4)) for _ in range(3)]) for i in range(40)]
    rows += [(40, [1e18, -1.0, 0.0]), (41, [3e38, 3e38, 3e38]), (42, [-3e38]), (43, [0.25] * 50_000)] + [(i, [1.0, 2.0, 3.0]) for i in range(100, 400)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(3)
    got = {}
    for x in vector_topk.top_k(df, lambda c: c % 20 == 0, k=5).orderBy("query_id", "rank").collect():
        got.setdefault(x.query_id, []).append((x.id, x.score))
    clip = lambda x: max(-(1 << 62), min(1 << 62, x))
    ints = {i: [clip(int(np.floor(x * 1024))) for x in v] for i, v in rows}
    score = lambda a, b: max(-(1 << 63), min((1 << 63) - 1, sum(x * y for x, y in zip(a, b, strict=False))))
    for q in (0, 20, 40, 100, 380):
        want = sorted(((score(ints[q], v), i) for i, v in ints.items() if i != q), key=lambda s: (-s[0], s[1]))[:5]
        assert got[q] == [(i, s) for s, i in want]


def test_long_lists_are_compared_in_blocks(spark, monkeypatch):
    """Near copies around the threshold, lists dealt into blocks of 16."""
    from test_search import links_brute

    monkeypatch.setattr(jaccard, "LIST_BLOCK", 16)
    r = random.Random(9)
    words = [f"w{i}" for i in range(400)]
    base, rows = [r.choice(words) for _ in range(90)], []
    for i in range(120):
        b = list(base)
        for _ in range(r.randrange(1, 6)):
            b[r.randrange(90)] = r.choice(words)
        rows.append((i, " ".join(b)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {x.doc_id: (x.n_shingles, x.component_id) for x in jaccard.join(df).collect()}
    assert got == links_brute(rows) and len({c for _, c in got.values()}) > 1


def test_block_comparison_loses_no_pair():
    r = np.random.RandomState(5)
    for _ in range(30):
        pool = np.unique(r.randint(0, 1 << 62, 700).astype(np.uint64))
        base = r.choice(pool, int(r.randint(20, 500)), replace=False)
        sets = [np.unique(np.concatenate([base[r.rand(len(base)) < 0.95], r.choice(pool, int(r.randint(1, 20)))])) for _ in range(12)]
        comp = r.randint(0, 4, 12)
        bits, n = [jaccard.parity_bits(s) for s in sets], np.array([len(s) for s in sets])
        want = set()
        for i in range(12):
            for j in range(i):
                common_part = len(np.intersect1d(sets[i], sets[j]))
                if comp[i] != comp[j] and 100 * common_part >= 80 * (n[i] + n[j] - common_part):
                    want.add((j, i))
        got = {tuple(sorted(x)) for x in zip(*(y.tolist() for y in jaccard.near_members(n, comp, bits, 80)), strict=True)}
        assert want <= got
        split = {tuple(sorted(x)) for x in zip(*(y.tolist() for y in jaccard.near_members(n, comp, bits, 80, 5)), strict=True)}
        assert split == {p for p in got if p[0] < 5 <= p[1]}


def test_sanitiser_on_a_long_text_of_identifiers(spark):
    text = " ".join(f"Zoë wrote to a{i}@b.example.com" for i in range(2000))
    df = spark.createDataFrame([(1, text, "x"), (2, None, "y"), (None, "calm words only", "z")], "doc_id long, text string, row string")
    out = {r.row: r.text for r in pii.sanitise(df).collect()}
    assert "@" not in out["x"] and out["x"].count("[EMAIL]") == 2000 and out["y"] is None and out["z"] == "calm words only"


def test_pipeline_edges(spark, tmp_path):
    """Nulls, repeated rows and an extra column with a clashing name through all stages, and an empty table."""
    import corpus_pipeline

    good = "The quick brown fox jumps over the lazy dog today, and then it sleeps for a long while near the old river bank. It dreams."
    rows = [(1, good, "en", "s", 5, "k"), (1, good, "en", "s", 5, "k"), (None, good + " More words are here now.", None, None, None, None), (3, None, "en", "s", 0, "k"), (4, "", "en", None, 0, "k"), (5, good.replace("fox", "cat"), "en", "s", 9, "k")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, row string")
    for name, table in (("full", df), ("none", df.limit(0))):
        table.write.parquet(f"file://{tmp_path}/{name}/documents.parquet")
    out = corpus_pipeline.run(spark, f"file://{tmp_path}/full").collect()
    assert {r.doc_id for r in out} == {1, None, 5} or {r.doc_id for r in out} == {1, None}
    assert corpus_pipeline.run(spark, f"file://{tmp_path}/none").count() == 0
