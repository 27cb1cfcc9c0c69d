"""Sharding, quality rules, chat formatting, personal data."""

import hashlib
import re

from pyspark.sql import functions as F

from novelspark.llm import chat, pii, quality, sharding


def test_shards_are_even_and_gapless(spark, sf):
    rows = sharding.op5_virtual_slots(spark, sf).collect()
    assert len(rows) == 200
    for s in range(16):
        mine = sorted(r.slot for r in rows if r.shard == s)
        assert mine == list(range(len(mine)))
    loads = [sum(r.size for r in rows if r.shard == s) for s in range(16)]
    assert sum(loads) / 16 + max(r.size for r in rows) >= max(loads)


def test_shard_edges(spark):
    import zlib

    rows = [(1, "é"), (None, None), (1, "é"), (2, "")]
    df = spark.createDataFrame([(a, b, 7, "s") for a, b in rows], "doc_id long, text string, size int, slot string")
    got = sharding.shard(df, 4)[0].collect()
    assert sorted((r.size, r.text_crc32) for r in got) == sorted((len((b or "").encode()) + 1, zlib.crc32((b or "").encode())) for _, b in rows)
    assert sharding.shard(df.limit(0), 4)[0].count() == 0


def test_slot_map_grows_only_into_new_shards(spark, tmp_path):
    loads = [(i * 7919) % 101 for i in range(400)]
    m = sharding.SlotMap.balanced(loads, 16)
    g = m.grown(loads)
    assert g.version == 2 and all(b == 16 for a, b in zip(m.shard_of, g.shard_of, strict=True) if a != b)
    assert max(m.loads(loads)) - min(m.loads(loads)) <= max(loads)
    assert min(g.loads(loads)) > 0.9 * sum(loads) / 17
    m.save(spark, str(tmp_path))
    g.save(spark, str(tmp_path))
    assert sharding.SlotMap.load(spark, str(tmp_path), 1).shard_of == m.shard_of
    assert sharding.SlotMap.load(spark, str(tmp_path), 2).shard_of == g.shard_of


def quality_brute(text):
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    windows = [tuple(words[i : i + 8]) for i in range(len(words) - 7)]
    twice = {k for k, w in enumerate(windows) if windows.count(w) > 1}
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len({p for k in twice for p in range(k, k + 8)})


def test_quality_counts(spark):
    prose = "This is a plain sentence with enough words to stay in any corpus, I should think. It goes on."
    texts = [None, "", "a " * 30, "one two three four five six seven eight nine " * 4, f"{prose}\n{prose}\nHome | About | Contact | Jobs\n{prose}", prose + " x\x0b y\x0cz", prose, prose]
    df = spark.createDataFrame([(i, t, "z", True) for i, t in enumerate(texts)], "doc_id long, text string, n_words string, kept boolean")
    got = quality.verdicts(df.select("doc_id", "text")).collect()
    for r in got:
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == quality_brute(texts[r.doc_id])
    kept = quality.clean(df).collect()
    assert {r.doc_id for r in kept if not r.text} == set() and df.columns == list(kept[0].asDict())
    whole = spark.createDataFrame([(1, prose + " More words follow here, of another kind.\nHome | About | Contact | Jobs", 1)], "doc_id long, text string, n_chars long")
    row = quality.clean(whole).first()
    assert "Home" not in row.text and row.n_chars == len(row.text)
    assert quality.clean(df.limit(0)).count() == 0


def test_quality_sql(spark, sf, duck, same):
    same(quality.op7_line_first(spark, sf), duck.sql(quality.OP7_SQL))


def test_chat_sql(spark, sf, duck, same):
    same(chat.op2_reply_trees(spark, sf), duck.sql(chat.OP2_SQL))


def test_escaping_is_reversible(spark):
    texts = ["plain", "<|turn|>x<|end|>", "a\\<|b", "\\", "</s>[INST] ok [/INST]", "<<SYS>>\\\\n<|", "\\n<\\|", ""]
    df = spark.createDataFrame([(t,) for t in texts], "t string").select("t", chat.escape(F.col("t")).alias("e"))
    for r in df.select("t", "e", chat.unescape(F.col("e")).alias("u")).collect():
        assert r.u == r.t and "<|" not in r.e and "</s>" not in r.e and "[INST]" not in r.e


def test_reply_trees(spark):
    # tree 1: 1 -> 2 -> 4, 1 -> 3; tree 2: a cycle 1 <-> 2 and a root 3; tree 3: one message with a missing parent
    rows = [(1, 1, None, "user", "q", 1.0), (1, 2, 1, "assistant", "a<|end|>", 1.0), (1, 3, 1, "assistant", "b", 5.0), (1, 4, 2, "user", None, 1.0),
            (2, 1, 2, "user", "x", 1.0), (2, 2, 1, "user", "y", 1.0), (2, 3, None, "user", "z", 1.0), (3, 9, 8, "user", "w", 0.0)]
    df = spark.createDataFrame(rows, "tree long, msg long, parent long, role string, text string, score double")
    best = {r.tree: r.turns for r in chat.conversations(df).select("tree", chat.read_back(F.col("formatted")).alias("turns")).collect()}
    assert [tuple(t) for t in best[1]] == [("user", "q"), ("assistant", "b")]
    assert [tuple(t) for t in best[2]] == [("user", "z")] and [tuple(t) for t in best[3]] == [("user", "w")]
    both = chat.best_paths(df.filter("tree = 1"), 2).orderBy("rank", "place").collect()
    assert [(r.rank, r.msg) for r in both] == [(1, 1), (1, 3), (2, 1), (2, 2), (2, 4)]
    assert chat.conversations(df.limit(0)).count() == 0


def test_long_chain(spark):
    df = spark.range(1, 301).select(F.lit(1).cast("long").alias("tree"), F.col("id").alias("msg"), (F.col("id") - 1).alias("parent"), F.lit("user").alias("role"), F.col("id").cast("string").alias("text"), F.lit(1.0).alias("score"))
    turns = chat.conversations(df).select(chat.read_back(F.col("formatted")).alias("t")).first().t
    assert [t.text for t in turns] == [str(i) for i in range(1, 301)]


BASE = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def passes(kind, value):
    d = re.sub("[^0-9]", "", value)
    if kind == "ip":
        return all(int(x) <= 255 for x in value.split("."))
    if kind == "card":
        worth = [int(c) if i % 2 == 0 else int(c) * 2 - 9 * (int(c) > 4) for i, c in enumerate(reversed(d))]
        return 14 <= len(d) <= 19 and sum(worth) % 10 == 0
    return kind != "phone" or 10 <= len(d) <= 15


def pii_brute(text):
    found = [(m.start(), k, f"{kind}:{m.start()}:{m.end()}") for k, (kind, p) in enumerate(BASE.items()) for m in re.finditer(p, text or "") if passes(kind, m[0])]
    return ",".join(x[2] for x in sorted(found))


TEXTS = [
    "a@b.c@d.e x@y.z_q@r.s.t", "1.2.3.4.5.6.7.8 300.1.1.1 001.002.003.255 0.0.0.0", "+1 (523) 555-1055+1 (523) 555-1055", "é 4111 1111 1111 1111-2 4111111111111111 😀 4111111111111111",
    "+" + "1" * 3000 + " " + "a" * 5000 + "@", "1" * 20000 + "." + "a@b-c." * 3000, None, "", "x@y.com 10.0.0.1 " * 300, "@@a@b.c@@", "a.@-.-",
]
STORY = ["Zorb Quix zq@mail.com likes tea", "then zorb wrote zq@mail.com again", "zorb and zq@mail.com too", "likes tea then again too and wrote", "likes the tea and then it wrote again too"]


def test_personal_data_spans(spark):
    texts = TEXTS + STORY
    df = spark.createDataFrame([(i, t, 1) for i, t in enumerate(texts)] + [(99, TEXTS[0], 1)], "doc_id long, text string, row int")
    thin, terms = pii.sanitise_spans(df)
    rows = pii.with_spans(df.select("doc_id", pii.row_key().alias("row")), thin, terms).collect()
    assert len(rows) == len(texts) + 1
    for r in rows:
        text = texts[r.doc_id] if r.doc_id < 99 else TEXTS[0]
        assert ",".join(f"{s.kind}:{s.start}:{s.end}" for s in r.base) == pii_brute(text)
        words = {text[s.start : s.end].lower() for s in r.spans if s.kind == "term"}
        assert words == ({"zorb"} if "zq@" in (text or "") else set())


def test_sanitised_texts(spark):
    df = spark.createDataFrame([(i, t, len(t), "s") for i, t in enumerate(STORY)] + [(7, None, 0, "s")], "doc_id long, text string, n_chars long, spans string")
    got = {r.doc_id: r for r in pii.sanitise(df).collect()}
    assert got[0].text == "[TERM] Quix [EMAIL] likes tea" and got[0].n_chars == len(got[0].text)
    assert got[3].text == STORY[3] and got[7].text is None and got[7].spans == "s"
    assert pii.sanitise(df.limit(0)).count() == 0


def test_personal_data_query(spark, sf):
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    for r in pii.op1_disclosure_sanitiser(spark, sf).collect():
        assert r.base_sha256 == hashlib.sha256(pii_brute(texts[r.doc_id]).encode()).hexdigest()


def test_word_beside_an_identifier_seen_once(spark):
    """A rare word that stands only beside an identifier of one text discloses it; a common word does not."""
    texts = ["Vexley writes from vx@mail.org today"] + [f"somebody writes from home today and stays {'in' if i % 2 else 'out'} {'a' * (3 + i)}" for i in range(40)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r.text for r in pii.sanitise(df).collect()}
    assert got.pop(0) == "[TERM] writes from [EMAIL] today"
    assert all(got[i] == texts[i] for i in got)


def test_disclosing_word_is_replaced_in_the_whole_text(spark):
    """Also far from the identifier and beyond a number that fails its check; a word inside an identifier is no word of the text."""
    far = " ".join(["somebody writes from home today"] * 60)
    texts = [f"Vexley born 1970, card 4111 1111 1111 1111 {far} vexley. vexley@mail.org"] + [f"somebody writes from home today born card {'a' * (3 + i)}" for i in range(60)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r.text for r in pii.sanitise(df).collect()}
    assert got[0] == f"[TERM] born 1970, card [CARD] {far} [TERM]. [EMAIL]"
    assert all(got[i] == texts[i] for i in range(1, 61))


def test_identifiers_of_the_same_texts_are_scored_once(spark):
    listed = " ".join(f"user{i}@mail.org" for i in range(200))
    base = pii.base_spans(pii.distinct_texts(spark.createDataFrame([(f"Vexley {listed}",), ("user0@mail.org other",)], "text string")))
    assert base.count() == 2 and pii.identifier_groups(base).count() == 3


def test_words_that_touch_an_identifier_are_counted(spark):
    texts = ["zq@mail.comÉtoile glows"] + [f"somebody glows from home today {'a' * (3 + i)}" for i in range(40)]
    got = {r.doc_id: r.text for r in pii.sanitise(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert got[0] == "[EMAIL][TERM] glows"
