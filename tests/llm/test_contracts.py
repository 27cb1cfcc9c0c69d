"""The registered queries on all documents of the smallest scale, every contract column, against brute force."""

import collections
import hashlib
import re
import zlib

import numpy as np
import pytest

from novelspark.llm import bpe, chunk_bpe, jaccard, packing, pii, secrets, sharding, token_counts

from test_search import BASE, links_brute


@pytest.fixture(scope="module")
def texts(spark, sf):
    return {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}


@pytest.fixture(scope="module")
def ids(texts):
    return dict(zip(texts, bpe.encoder().whole([t or "" for t in texts.values()]), strict=True))


def sha(text):
    return hashlib.sha256(text.encode()).hexdigest()


def digest(spans):
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


def luhn(text):
    d = [int(c) for c in re.sub("[^0-9]", "", text)]
    return 14 <= len(d) <= 19 and sum(x if i % 2 == 0 else sum(divmod(2 * x, 10)) for i, x in enumerate(reversed(d))) % 10 == 0


PRIVATE = {
    "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda t: True),
    "ip": (r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda t: all(int(x) <= 255 for x in t.split("."))),
    "card": (r"[0-9]([\x20-]?[0-9])+", luhn),
    "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", lambda t: 10 <= len(re.sub("[^0-9]", "", t)) <= 15),
}


def private_brute(text):
    found = [(m.start(), k, m.end(), kind) for k, (kind, (p, ok)) in enumerate(PRIVATE.items()) for m in re.finditer(p, text or "") if ok(m[0])]
    return [(a, b, kind) for a, _, b, kind in sorted(found)]


def test_op1(spark, sf, texts):
    rows = pii.op1_disclosure_sanitiser(spark, sf).collect()
    assert sorted(r.doc_id for r in rows) == sorted(texts)
    some = 0
    for r in rows:
        want = private_brute(texts[r.doc_id])
        assert r.base_sha256 == sha(digest(want))
        assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == [sum(k == kind for _, _, k in want) for kind in PRIVATE]
        all_spans = r.spans.split(",") if r.spans else []
        assert [s for s in all_spans if not s.startswith("term:")] == [f"{k}:{a}:{b}" for a, b, k in want]
        starts = [int(s.split(":")[1]) for s in all_spans]
        assert starts == sorted(starts)
        some += len(all_spans) > len(want)
    assert some


def test_op4(spark, sf, texts, ids):
    rows = chunk_bpe.op4_chunk_reuse(spark, sf).collect()
    assert sorted(r.doc_id for r in rows) == sorted(texts)
    for r in rows:
        assert r.n_tokens == len(ids[r.doc_id]) and r.ids_sha256 == hashlib.sha256(ids[r.doc_id].astype("<u4").tobytes()).hexdigest()
        assert r.decoded_sha256 == sha(texts[r.doc_id] or "")


def test_op5(spark, sf, texts):
    rows = sharding.op5_virtual_slots(spark, sf).collect()
    assert sorted(r.doc_id for r in rows) == sorted(texts)
    places, sizes = collections.defaultdict(list), collections.Counter()
    for r in rows:
        data = (texts[r.doc_id] or "").encode()
        assert (r.size, r.text_crc32, r.law, r.grown_shard) == (len(data) + 1, zlib.crc32(data), "bytes", None)
        places[r.shard].append(r.slot)
        sizes[r.shard] += r.size
    assert all(sorted(p) == list(range(len(p))) for p in places.values()) and set(places) <= set(range(16))
    assert {r.map_version for r in rows} == {2}
    assert max(sizes.values()) - min(sizes.values()) <= 2 * max(len((t or "").encode()) + 1 for t in texts.values())


def test_op6(spark, sf, texts, ids):
    rows = packing.op6_sum_of_squares(spark, sf).collect()
    pieces, windows = collections.defaultdict(list), collections.defaultdict(list)
    for r in rows:
        pieces[r.doc_id].append(r)
        windows[r.sequence_id].append((r.offset, r.length))
    assert sorted(pieces) == sorted(texts)
    for name, held in pieces.items():
        whole, at = np.append(ids[name], np.uint32(0)).astype("<u4"), 0
        for r in sorted(held, key=lambda r: r.start):
            assert r.start == at and r.length > 0 and r.doc_tokens == len(whole)
            assert r.ids_crc32 == zlib.crc32(whole[at : at + r.length].tobytes())
            at += r.length
        assert at == len(whole)
    for held in windows.values():
        at = 0
        for offset, length in sorted(held):
            assert offset == at
            at += length
        assert at <= 1024


def test_op8(spark, sf, texts):
    for r in secrets.op8_secret_scan(spark, sf).collect():
        text = texts[r.doc_id] or ""
        found = [(m.start(), k, m.end(), kind) for k, (kind, (p, ok)) in enumerate(BASE.items()) for m in re.finditer(p, text) if ok(m)]
        want = [(a, b, kind) for a, _, b, kind in sorted(found)]
        assert r.base_sha256 == sha(digest(want))
        assert [r.n_assign, r.n_access, r.n_hex] == [sum(k == kind for _, _, k in want) for kind in BASE]


def test_op9(spark, sf, texts):
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.op9_token_combinations(spark, sf).collect()}
    assert got == links_brute(list(texts.items()))


def test_op10(spark, sf, ids):
    lengths = [len(x) for x in ids.values()]
    rows = token_counts.op10_length_histogram(spark, sf).collect()
    assert sorted(r.n_tokens for r in rows) == sorted(set(lengths))
    for r in rows:
        assert (r.n_docs, r.tokens) == (lengths.count(r.n_tokens), r.n_tokens * lengths.count(r.n_tokens))
        assert (r.docs_from, r.tokens_from) == (sum(x >= r.n_tokens for x in lengths), sum(x for x in lengths if x >= r.n_tokens))
        assert (r.tokens_up_to, r.truncated_total) == (sum(x for x in lengths if x <= r.n_tokens), sum(min(x, r.n_tokens) for x in lengths))
