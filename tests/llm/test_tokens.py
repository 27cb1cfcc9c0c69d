"""Encoders against the library, packing, length histogram."""

import random
import zlib

import numpy as np
import pytest

from novelspark.llm import bpe, chunk_bpe, packing, token_counts

PARTS = ["a", "the", " ", "  ", "\n", " \n", "'ll", "'s", "'", "<|endoftext|>", "<|endof", "é", "日本", "12", "!!", "\t", "don't", " we'll", " ", "x" * 50, " " * 40]


def library(texts):
    return bpe.encoder().whole([t or "" for t in texts])


def odd_texts(n, seed=1):
    r = random.Random(seed)
    return ["".join(r.choice(PARTS) for _ in range(r.randrange(150))) for _ in range(n)] + ["", None, " ", "\n", "word " * 30_000]


def test_units_equal_library():
    texts = odd_texts(150)
    for got, want in zip(bpe.encoder().encode(texts), library(texts), strict=True):
        assert got.tolist() == want.tolist()


def test_units_with_small_table():
    texts = odd_texts(40, 3)
    for got, want in zip(bpe.UnitEncoder(max_units=50).encode(texts), library(texts), strict=True):
        assert got.tolist() == want.tolist()


@pytest.mark.parametrize("bits", [3, 6, 11])
def test_chunks_equal_library_and_decode(bits):
    texts = odd_texts(120, bits)
    held = chunk_bpe.ChunkEncoder(bits=bits)
    for text, got, want in zip(texts, held.encode(texts), library(texts), strict=True):
        assert got.tolist() == want.tolist()
        assert held.decode(got) == (text or "") == held.units.tokenizer.decode(want.tolist(), skip_special_tokens=False)


def test_shared_passages_are_encoded_once():
    r = random.Random(2)
    passage = " ".join("".join(r.choice("abcdefgh") for _ in range(6)) for _ in range(4000))
    held = chunk_bpe.ChunkEncoder()
    held.encode([f"first {passage} end", f"other start {passage} tail"])
    assert held.reused > 5


def test_chunk_ends_move_with_content():
    data = bytes(random.Random(4).randrange(97, 123) for _ in range(40_000))
    a, b = chunk_bpe.chunk_ends(data), chunk_bpe.chunk_ends(b"xyz" + data)
    assert len({x + 3 for x in a} & set(b)) >= len(a) - 2
    assert chunk_bpe.chunk_ends(b"") == []


DOCS = [(0, "one two three"), (1, None), (2, ""), (3, "word " * 3000), (4, "one two three"), (4, "one two three"), (None, "no id"), (6, "a b c " * 120)]


def test_round_trip_query(spark):
    df = spark.createDataFrame([(a, b, "x") for a, b in DOCS], "doc_id long, text string, key string")
    got = chunk_bpe.round_trip(df).collect()
    assert sorted((r.doc_id is None, r.doc_id or 0, r.n_tokens) for r in got) == sorted((a is None, a or 0, len(library([b])[0])) for a, b in DOCS)
    back = chunk_bpe.decode(chunk_bpe.encode(df)).collect()
    assert sorted(r.text for r in back) == sorted(b or "" for _, b in DOCS)
    assert chunk_bpe.round_trip(df.limit(0)).count() == 0


def test_packing_keeps_every_id_once(spark):
    df = spark.createDataFrame([(a, b, 1) for a, b in DOCS * 4], "doc_id long, text string, length int")
    rows = packing.pack(df.repartition(3)).collect()
    by_window = {}
    for r in rows:
        by_window.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for pieces in by_window.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at and length > 0
            at += length
        assert at <= 1024
    want = sum(len(x) + 1 for x in library([b for _, b in DOCS * 4]))
    assert sum(r.length for r in rows) == want
    assert len(by_window) <= want // 1024 + 1 + 3  # one window with padding a task at most
    big = [r for r in rows if r.doc_id == 3]
    ids = np.append(library(["word " * 3000])[0], np.uint32(0))
    for r in big:
        assert r.ids_crc32 == zlib.crc32(ids[r.start : r.start + r.length].astype("<u4").tobytes()) and r.doc_tokens == len(ids)
    assert packing.pack(df.limit(0)).count() == 0


def test_sum_of_squares_choice():
    p = packing.SumOfSquares(10)
    assert p.place(4) == (0, 0)
    # a second window at level 4 would give 2**2; joining leaves one window at level 8
    assert p.place(4) == (0, 4)
    assert p.counts[8] == 1 and p.counts.sum() == 1
    assert p.place(2) == (0, 8) and p.counts.sum() == 0


def test_placement_minimises_sum_of_squares():
    r, p = random.Random(5), packing.SumOfSquares(32)
    for _ in range(400):
        length, before = r.randrange(1, 32), p.counts.copy()
        options = []
        for level in [0, *np.flatnonzero(before)]:
            if level + length <= 32:
                after = before.copy()
                if level:
                    after[level] -= 1
                if level + length < 32:
                    after[level + length] += 1
                options.append(int((after**2).sum()))
        p.place(length)
        assert int((p.counts**2).sum()) == min(options)


def test_histogram_answers_every_limit(spark):
    df = spark.createDataFrame(DOCS * 3, "doc_id long, text string")
    lengths = [len(x) for x in library([b for _, b in DOCS * 3])]
    table = token_counts.with_suffix_sums(token_counts.histogram(df)).cache()
    for r in table.collect():
        assert r.n_docs == lengths.count(r.n_tokens)
        assert r.docs_from == sum(x >= r.n_tokens for x in lengths)
        assert r.tokens_from == sum(x for x in lengths if x >= r.n_tokens)
        assert r.truncated_total == sum(min(x, r.n_tokens) for x in lengths)
    for r in token_counts.at_limits(table, [0, 1, 5, 500, 10**6]).collect():
        assert r.truncated_total == sum(min(x, r.context_limit) for x in lengths) and r.total == sum(lengths)
    assert token_counts.quantile(table, 0.5).first().length == sorted(lengths)[len(lengths) // 2 - 1]
    assert token_counts.with_suffix_sums(token_counts.histogram(df.limit(0))).count() == 0
