"""Exact top-k, secret scans, Jaccard join, the pipeline."""

import collections
import random
import re
import zlib

import numpy as np
import pytest

from novelspark.llm import jaccard, secrets, vector_topk


def test_topk_sql(spark, sf, duck, same):
    same(vector_topk.op3_vector_approximation(spark, sf), duck.sql(vector_topk.OP3_SQL))


def test_topk_edges(spark):
    r = random.Random(1)
    rows = [(i, [r.choice([-1.0, 0.0, 0.5, 1.0]) for _ in range(4)]) for i in range(60)]
    rows += [(100, None), (101, [1.0, None, 0.0, 0.0]), (102, [float("nan"), 0.0, 0.0, 0.0]), (103, [float("inf"), 0.0, 0.0, 0.0]), (104, [1.0]), (5, rows[5][1]), (None, [1.0, 1.0, 1.0, 1.0])]
    df = spark.createDataFrame([(a, b, a) for a, b in rows], "vec_id long, embedding array<float>, query_id long")
    got = collections.defaultdict(list)
    for x in vector_topk.top_k(df, lambda c: c % 20 == 0, k=3).orderBy("query_id", "rank").collect():
        got[x.query_id].append((x.id, x.score))
    good = {i: np.pad(np.floor(np.array(v) * 1024).astype(int), (0, 4 - len(v))) for i, v in rows if i is not None and i not in (100, 101, 102, 103)}
    for q in (0, 20, 40):
        want = sorted(((int(good[q] @ v), i) for i, v in good.items() if i != q), key=lambda s: (-s[0], s[1]))[:3]
        assert got[q] == [(i, s) for s, i in want]
    assert set(got) == {0, 20, 40}
    few = vector_topk.top_k(df.filter("vec_id in (0, 1)"), lambda c: c % 20 == 0, k=3).collect()
    assert [(x.query_id, x.id) for x in few] == [(0, 1)]
    assert vector_topk.top_k(df.limit(0), lambda c: c % 20 == 0).count() == 0


BASE = {
    "assign": (r"""([pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", lambda m: len(m[2]) >= 6),
    "access": (r"AKIA[A-Z0-9]+", lambda m: len(m[0]) >= 20),
    "hex": (r"[0-9a-f]+", lambda m: len(m[0]) >= 24),
}


def secret_brute(text):
    found = [(m.start(), k, (m.start(), m.end(), kind)) for k, (kind, (p, ok)) in enumerate(BASE.items()) for m in re.finditer(p, text or "") if ok(m)]
    return [x[2] for x in sorted(found)]


def test_secrets_equal_plain_expressions():
    r = random.Random(3)
    parts = ["password", "PASSWD", "secret", "token", "api_key", "ApiKey", "AKIA", "=", ":", " ", '"', "'", "abc123", "x", "0123456789abcdef" * 2, "ABCDEFGH12345678", "é", "İ", "K", "\n", "_", "ſecret"]
    for _ in range(3000):
        text = "".join(r.choice(parts) for _ in range(r.randrange(14)))
        assert [s for s in secrets.scan(text) if s[2] in secrets.BASE] == secret_brute(text), text
    assert secrets.scan(None) == secrets.scan("") == []


def test_checksums_decide():
    body = "A1b2C3d4E5f6G7h8I9j0K1l2M3n4O5"
    good = "ghp_" + body + secrets.base62(zlib.crc32(body.encode()))
    assert [s[2] for s in secrets.scan(f"x {good} y")] == ["forge"]
    assert secrets.scan(f"x {good[:-1]}! y") == [] and secrets.scan("x ghp_" + body + "000000") == []
    assert [s[2] for s in secrets.scan("eyJhbGciOiJIUzI1NiJ9.eyJhIjoxfQ.abc")] == ["webtoken"]
    assert secrets.scan("eyJhbGciOiJIUzI1NiJ.eyJhIjoxfQ.abc") == []
    assert secrets.redact(f"x {good} y") == "x [SECRET] y"


def test_secret_query(spark, sf):
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    for r in secrets.op8_secret_scan(spark, sf).collect():
        assert r.spans == secrets.digest(secrets.scan(texts[r.doc_id]))
    df = spark.createDataFrame([(1, None, "k"), (None, "token = abcdef", "k")], "doc_id long, text string, key string")
    assert sorted(len(r.spans) for r in secrets.spans(df).collect()) == [0, 1]
    assert secrets.spans(df.limit(0)).count() == 0


def links_brute(rows):
    sets = {}
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]+", lambda m: m[0].lower(), t or ""))
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    up = {i: i for i in sets}

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    shared, where = collections.Counter(), collections.defaultdict(list)
    for i, s in sets.items():
        for g in s:
            where[g].append(i)
    for held in where.values():
        for k, a in enumerate(held):
            for b in held[:k]:
                shared[a, b] += 1
    for (a, b), c in shared.items():
        if 100 * c >= 80 * (len(sets[a]) + len(sets[b]) - c):
            x, y = sorted((top(a), top(b)))
            up[y] = x
    return {i: (len(sets[i]), top(i)) for i in sets}


def edited(seed, groups=18, copies=9, vocabulary=300):
    r = random.Random(seed)
    words, rows = [f"w{i}" for i in range(vocabulary)], []
    for _ in range(groups):
        base = [r.choice(words) for _ in range(r.choice([3, 5, 8, 12, 20, 40, 100, 260, 520]))]
        for _ in range(copies):
            b = list(base)
            for _ in range(r.randrange(max(1, len(b) // 35) + 2)):
                k, o = r.randrange(len(b)), r.random()
                if o < 0.4:
                    b[k] = r.choice(words)
                elif o < 0.7:
                    b.insert(k, r.choice(words))
                elif len(b) > 1:
                    del b[k]
            rows.append((3 * len(rows) + 1, " ".join(b)))
    rows += [(5000, None), (5001, ""), (5002, "A b C d e f"), (5003, "a B c\td e F"), (5004, " \n ")]
    r.shuffle(rows)
    return rows


@pytest.mark.parametrize("frequent", [None, 2])
def test_join_equals_brute_force(spark, monkeypatch, frequent):
    """With the given classes, and with nearly every token in a frequent class, so that combinations carry the join."""
    if frequent:
        monkeypatch.setattr(jaccard, "classes", lambda c: np.where(c <= frequent, 0, 1).astype(np.uint8))
    rows = edited(5 if frequent else 6)
    df = spark.createDataFrame([(a, b, "k") for a, b in rows], "doc_id long, text string, id string")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.join(df).collect()}
    assert got == links_brute(rows)


def test_combinations_meet_for_every_linked_pair():
    """Any two sets at the threshold share an index key, whatever tokens count as frequent."""
    r = np.random.RandomState(0)
    for trial in range(300):
        n = int(r.randint(1, 400))
        pool = r.randint(0, 1 << 62, 2 * n + 8).astype(np.uint64)
        pool = np.unique(pool)
        a = np.sort(pool[:n])
        out = int(r.randint(0, n // 5 + 1))
        b = np.sort(np.unique(np.concatenate([a[out:], pool[n : n + int(r.randint(0, n // 9 + 1))]])))
        common = len(np.intersect1d(a, b))
        if not len(b) or 100 * common < 80 * (len(a) + len(b) - common):
            continue
        share = r.rand()
        klass = {int(t): int(r.rand() < share) for t in pool}
        keys = [set(jaccard.signatures(s, np.array([klass[int(t)] for t in s]))[0].tolist()) for s in (a, b)]
        assert keys[0] & keys[1], trial


def test_join_edges(spark):
    df = spark.createDataFrame([(1, "a b c d e f"), (1, "a b c d e f"), (None, "a b c d e f"), (2, "a b c d e f"), (3, None)], "doc_id long, text string")
    got = sorted((r.doc_id, r.n_shingles, r.component_id) for r in jaccard.join(df).collect())
    assert got == [(1, 2, 1), (2, 2, 1), (3, 0, 3)]
    assert jaccard.join(df.limit(0)).count() == 0
    assert sorted((r.doc_id or 0) for r in jaccard.one_of_each(df).collect()) == [0, 1, 1, 3]


def test_pipeline(spark, sf):
    import corpus_pipeline as p

    from novelspark.llm import pii, quality

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    cleaned = [tuple(r) for r in p.STAGES[0][1](spark, docs, sf).select("doc_id", "text").collect()]
    kept = {r.doc_id for r in quality.op7_line_first(spark, sf).collect() if r.kept}
    assert {a for a, _ in cleaned} == kept
    links = links_brute(cleaned)
    left = {a for a, (_, top) in links.items() if a == top}
    rows = p.run(spark, sf).collect()
    assert {r.doc_id for r in rows} == left and "pii" in pii.__name__
    for _, stage in p.STAGES[:-1]:
        assert stage(spark, docs, sf).columns == columns


def test_bitmaps_bound_differences():
    r = np.random.RandomState(3)
    for _ in range(200):
        pool = np.unique(r.randint(0, 1 << 62, 900).astype(np.uint64))
        a, b = (np.sort(r.choice(pool, int(r.randint(1, 800)), replace=False)) for _ in range(2))
        assert jaccard.fewest_differences(jaccard.parity_bits(a), jaccard.parity_bits(b)) <= len(np.setxor1d(a, b))
