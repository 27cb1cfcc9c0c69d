"""Information-theoretic sanitisation of personal data (operator 1, native).

Four kinds of identifiers are found by their patterns and checks. The method then asks which *other* words give such an
identifier away: over all texts it counts in how many a word stands together with an identifier and in how many it occurs at all. A word
whose pointwise mutual information with an identifier reaches a share ``threshold`` of the identifier's own information content
discloses it, and all its occurrences in texts that hold the identifier become spans too (kind ``term``). Sanitised texts put the
kind's general name in place of each span.

Every pair is scored, also one seen once: most identifiers stand in one text only. Chance is held off by the word's frequency in
the corpus: the pair's evidence (the number of texts times the mutual information of "holds the word" and "holds the
identifier", in nats) must reach the logarithm of the number of words scored with that identifier. Equal texts count once, so
copies of one document prove nothing. Identifiers that stand in the same texts have the same counts and are scored as one, so a
long list of them makes no pairs of its own. A word inside an identifier is part of it: it is neither counted nor replaced.

Defined cases: null texts are empty; repeated rows get the same result each; a null ``doc_id`` is a value like others; an empty
table gives no rows. Offsets are in code points, ends exclusive.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, cut, documents, let, prefix, prefix_sums, text_blocks, text_of

KINDS = ("email", "ip", "card", "phone")
#: Expressions of the base with possessive repeats where these change no match, so that long runs cost no stack; and for
#: the first character, what may not stand before a match that did not begin there.
LOCAL = r"A-Za-z0-9._%+-"
PATTERNS = {
    "email": rf"(?:\G|(?<![{LOCAL}]))[{LOCAL}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"[0-9]++(?:\.[0-9]++)(?:\.[0-9]++)(?:\.[0-9]++)",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: What a text must hold before the pattern is tried at all.
HINTS = {"email": "@", "phone": "+"}
THRESHOLD = 0.5
#: Tables of spans are broadcast up to this size (64 bytes a row and a span), larger ones joined by shuffle.
BROADCAST_BYTES, ROW_BYTES = 64_000_000, 64
TERM = r"\p{L}{3,}"
GENERAL = {"email": "[EMAIL]", "ip": "[IP]", "card": "[CARD]", "phone": "[PHONE]", "term": "[TERM]"}


def _digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def _luhn(value: Column) -> Column:
    """14 to 19 digits whose check sum, every second digit from the right doubled, is a multiple of ten."""

    def holds(d: Column) -> Column:
        n = F.length(d)
        places = F.sequence(F.lit(0), n - 1)
        digit = lambda i: F.substr(d, n - i, F.lit(1)).cast("int")
        worth = lambda i: F.when(i % 2 == 0, digit(i)).otherwise(F.when(digit(i) > 4, digit(i) * 2 - 9).otherwise(digit(i) * 2))
        return n.between(14, 19) & (F.aggregate(F.when(n.between(14, 19), places).otherwise(F.array().cast("array<int>")), F.lit(0), lambda s, i: s + worth(i)) % 10 == 0)

    return let(_digits(value), holds)


def _ip(value: Column) -> Column:
    return F.forall(F.split(value, r"\."), lambda p: let(F.ltrim(p, F.lit("0")), lambda q: (F.length(q) <= 3) & (F.coalesce(q.try_cast("int"), F.lit(0)) <= 255)))


def _phone(value: Column) -> Column:
    return F.length(_digits(value)).between(10, 15)


CHECKS = {"email": lambda v: F.lit(True), "ip": _ip, "card": _luhn, "phone": _phone}


def _found(text: Column, kind: str) -> Column:
    """Array of (start, end, kind, value) of one kind's matches that pass its check."""
    pattern = PATTERNS[kind]
    empty = F.array().cast("array<struct<start:bigint,end:bigint,kind:string,value:string>>")
    hint = text.contains(HINTS[kind]) if kind in HINTS else text.rlike("[0-9]")

    def spans(both: Column) -> Column:
        gaps, hits = both["gaps"], both["hits"]
        sizes = F.transform(hits, lambda h, i: (F.length(h) + F.length(F.get(gaps, i))).cast("long"))

        def place(before: Column) -> Column:
            return F.transform(
                hits,
                lambda h, i: let(
                    F.get(before, i) + F.length(F.get(gaps, i)),
                    lambda a: F.struct(a.cast("long").alias("start"), (a + F.length(h)).cast("long").alias("end"), F.lit(kind).alias("kind"), h.alias("value")),
                ),
            )

        return F.filter(let(prefix_sums(sizes), place), lambda s: CHECKS[kind](s["value"]))

    hits = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    found = let(hits, lambda h: F.when(F.size(h) > 0, let(F.struct(F.split(text, pattern, -1).alias("gaps"), h.alias("hits")), spans)).otherwise(empty))
    return F.when(hint, found).otherwise(empty)


def base_spans(docs: DataFrame, text: str = "text") -> DataFrame:
    """The input with array column ``spans``, by start, then kind in the order of KINDS."""
    body = F.coalesce(F.col(text), F.lit(""))
    order = F.array(*[F.lit(k) for k in KINDS])

    def sooner(a: Column, b: Column) -> Column:
        rank = lambda s: s["start"] * 8 + F.array_position(order, s["kind"])
        return F.when(rank(a) < rank(b), -1).when(rank(a) > rank(b), 1).otherwise(0)

    return docs.withColumn("spans", F.array_sort(F.flatten(F.array(*[_found(body, k) for k in KINDS])), sooner))


def distinct_texts(docs: DataFrame, text: str = "text") -> DataFrame:
    """(row, text): each text once. Only texts that have a copy are shuffled."""
    rows = docs.select(row_key(text).alias("row"), text_of(text).alias("text"))
    copied = Scratch(docs.sparkSession, "copied").write(rows.groupBy("row").agg(F.count("*").alias("c")).filter("c > 1").select("row"), "rows")
    few = F.broadcast(copied) if copied.count() * ROW_BYTES <= BROADCAST_BYTES else copied
    return rows.join(few, "row", "left_anti").unionByName(rows.join(few, "row", "left_semi").distinct())


def _words(text: Column) -> Column:
    """The different words of a text, lower-cased."""
    return F.array_distinct(F.transform(F.regexp_extract_all(text, F.lit(TERM), F.lit(0)), F.lower))


def _between(text: Column, spans: Column, put) -> Column:
    """The text with ``put(span, end of all earlier spans)`` in place of each span; spans come by start and may overlap."""

    def inner(both: Column) -> Column:
        blocks, ends = both["blocks"], both["ends"]

        def part(s: Column, i: Column) -> Column:
            return let(F.get(ends, i), lambda at: F.concat(cut(blocks, at, s["start"] - at), put(s, at)))

        last = F.coalesce(F.array_max(F.transform(spans, lambda s: s["end"])), F.lit(0).cast("bigint"))
        return F.concat(F.array_join(F.transform(spans, part), ""), cut(blocks, last, F.length(text).cast("bigint") - last))

    ends = prefix(F.transform(spans, lambda s: s["end"].cast("bigint")), F.lit(0).cast("bigint"), lambda a, x: F.greatest(a, x))
    return let(F.struct(text_blocks(text).alias("blocks"), ends.alias("ends")), inner)


def _blanked(text: Column, spans: Column) -> Column:
    """The text with blanks in place of the spans, of the same length."""
    return _between(text, spans, lambda s, at: F.repeat(F.lit(" "), F.greatest(s["end"] - F.greatest(at, s["start"]), F.lit(0)).cast("int")))


def _placed_words(text: Column) -> Column:
    """All words of a text, lower-cased, as (term, start, end)."""
    # letters and other runs alternate, so their lengths add up to offsets
    runs = F.regexp_extract_all(text, F.lit(r"\p{L}++|[^\p{L}]++"), F.lit(0))

    def placed(pieces: Column) -> Column:
        ends = lambda at: F.transform(pieces, lambda p, i: F.struct(F.lower(p).alias("term"), F.get(at, i).alias("start"), (F.get(at, i) + F.length(p)).alias("end")))
        return let(prefix_sums(F.transform(pieces, lambda p: F.length(p).cast("long"))), ends)

    return F.filter(let(runs, placed), lambda p: (p["end"] - p["start"] >= 3) & p["term"].rlike(r"^\p{L}"))


def identifier_groups(base: DataFrame) -> DataFrame:
    """(row, who, seen): the identifiers of each text, those with the same set of ``seen`` texts as one ``who``."""
    values = base.select("row", F.explode(F.array_distinct(F.transform("spans", lambda s: s["value"]))).alias("value"))
    sets = values.groupBy("value").agg(F.count("*").alias("seen"), F.bit_xor(F.xxhash64("row")).alias("a"), F.bit_xor(F.xxhash64("row", F.lit(1))).alias("b"))
    return values.join(sets, "value").select("row", F.struct("seen", "a", "b").alias("who"), "seen").distinct()


def word_counts(texts: DataFrame, held: DataFrame) -> DataFrame:
    """(term, documents): texts that hold a word outside identifiers. ``held`` has for texts with identifiers the words that
    only these make up (``inside``) and those that appear once they are cut off (``beside``)."""
    words = texts.select(F.explode(_words(F.col("text"))).alias("term"), F.lit(1).alias("one"))
    for column, one in (("inside", -1), ("beside", 1)):
        words = words.unionByName(held.select(F.explode(column).alias("term"), F.lit(one).alias("one")))
    return words.groupBy("term").agg(F.sum("one").alias("documents"))


def disclosing_terms(pairs: DataFrame, counts: DataFrame, total: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(who, term, disclosure) of words that give identifiers away, from all (who, seen, term, together).

    disclosure = PMI(term; who) / IC(who), from corpus counts: 1 if the word is never seen apart from the identifier.
    """
    tried = pairs.groupBy("who").agg(F.count("*").alias("tried"))
    scored = pairs.join(counts, "term").join(tried, "who").join(F.broadcast(total)).withColumn("disclosure", _disclosure())
    return scored.filter((F.col("disclosure") >= threshold) & (_evidence() >= F.log("tried"))).select("who", "term", "disclosure")


def _disclosure() -> Column:
    """PMI over information content from columns n, together, seen and documents; it falls as ``documents`` grows."""
    information = F.log(F.col("n") / F.col("seen"))
    pmi = F.log(F.col("n") * F.col("together") / (F.col("documents") * F.col("seen")))
    return F.try_divide(pmi, information)


def _evidence() -> Column:
    """n times the mutual information of the word's and the identifier's presence, in nats."""
    xlogx = lambda c: F.when(c > 0, c * F.log(c)).otherwise(0.0)
    n, seen, often, both = (F.col(c) for c in ("n", "seen", "documents", "together"))
    cells = xlogx(both) + xlogx(seen - both) + xlogx(often - both) + xlogx(n - seen - often + both)
    return cells - xlogx(seen) - xlogx(n - seen) - xlogx(often) - xlogx(n - often) + xlogx(n)


def sanitise_spans(docs: DataFrame, text: str = "text", threshold: float = THRESHOLD) -> tuple[DataFrame, DataFrame]:
    """Tables (row, base) and (row, terms): spans of each text that has any, under the row key of ``row_key``."""
    scratch = Scratch(docs.sparkSession, "spans")
    texts = distinct_texts(docs, text)
    found = base_spans(texts).filter(F.size("spans") > 0)
    found = found.select("row", "text", "spans", _placed_words(_blanked(F.col("text"), F.col("spans"))).alias("words"))
    whole, own = _words(F.col("text")), F.transform("words", lambda w: w["term"])
    base = scratch.write(found.select("row", "spans", "words", F.array_except(whole, own).alias("inside"), F.array_except(own, whole).alias("beside")), "base")
    held = scratch.write(identifier_groups(base), "held")
    words = base.select("row", F.explode(F.array_distinct(F.transform("words", lambda w: w["term"]))).alias("term"))
    pairs = held.join(words, "row").groupBy("who", "seen", "term").agg(F.count("*").alias("together"))
    flagged = scratch.write(disclosing_terms(pairs, word_counts(texts, base), texts.agg(F.count("*").alias("n")), threshold), "flagged")
    asked = held.join(flagged, "who").select("row", "term").distinct()
    hits = base.select("row", F.explode("words").alias("w")).select("row", "w.term", "w.start", "w.end").join(asked, ["row", "term"])
    terms = hits.groupBy("row").agg(F.sort_array(F.collect_list(F.struct("start", "end"))).alias("terms"))
    thin = base.select("row", F.transform("spans", lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))).alias("base"))
    return thin, terms


def row_key(text: str = "text") -> Column:
    """Texts that are equal share their spans."""
    body = F.coalesce(F.col(text), F.lit(""))
    return F.struct(F.xxhash64(body).alias("a"), F.crc32(F.encode(body, "UTF-8")).alias("b"), F.length(body).alias("c"))


def found_spans(thin: DataFrame, terms: DataFrame) -> DataFrame:
    """(row, base, spans): arrays of (start, end, kind) of each text that has any."""
    kind = "array<struct<start:bigint,end:bigint,kind:string>>"
    found = thin.join(terms, "row", "left")
    extra = F.coalesce(F.transform("terms", lambda t: F.struct(t["start"].alias("start"), t["end"].alias("end"), F.lit("term").alias("kind"))), F.array().cast(kind))
    order = F.array(*[F.lit(k) for k in (*KINDS, "term")])
    rank = lambda s: s["start"] * 8 + F.array_position(order, s["kind"])
    sooner = lambda a, b: F.when(rank(a) < rank(b), -1).when(rank(a) > rank(b), 1).otherwise(0)
    return found.select("row", "base", F.array_sort(F.concat("base", extra), sooner).alias("spans"))


def with_spans(rows: DataFrame, thin: DataFrame, terms: DataFrame) -> DataFrame:
    """``rows`` (with column ``row``) with arrays ``base`` and ``spans``."""
    none = F.array().cast("array<struct<start:bigint,end:bigint,kind:string>>")
    found = _sized(found_spans(thin, terms), (F.size("base") + F.size("spans")) * ROW_BYTES)
    return rows.join(found, "row", "left").withColumn("base", F.coalesce("base", none)).withColumn("spans", F.coalesce("spans", none))


def _sized(found: DataFrame, size: Column) -> DataFrame:
    """The table, written, with a broadcast hint if its rows and cells together, ``size`` bytes each, are small enough. If broadcast, a
    group of equal texts stays where its rows are."""
    found = Scratch(found.sparkSession, "found").write(found, "found")
    total = found.agg(F.coalesce(F.sum(size + ROW_BYTES), F.lit(0)).alias("n")).first().n
    return F.broadcast(found) if total <= BROADCAST_BYTES else found


def replaced(text: Column, spans: Column) -> Column:
    """The text with each span's general name in its place; a span that begins inside an earlier one only lengthens it."""
    name = lambda s: F.element_at(F.create_map(*[F.lit(x) for kv in GENERAL.items() for x in kv]), s["kind"])
    return F.when(F.size(spans) == 0, text).otherwise(_between(text, spans, lambda s, at: F.when(s["start"] >= at, name(s)).otherwise(F.lit(""))))


def sanitise(docs: DataFrame, text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """The documents with sanitised texts, in the columns they came with; ``n_chars`` is the new text's length."""
    own = docs.columns
    thin, terms = sanitise_spans(docs, text, threshold)
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in own]).alias("doc"), row_key(text).alias("row"))
    # most texts have no span: the few rows of spans go to the texts, not the texts to the spans
    found = _sized(found_spans(thin, terms).select("row", "spans"), F.size("spans") * ROW_BYTES)
    both = rows.join(found, "row", "left")
    spans = F.coalesce("spans", F.array().cast("array<struct<start:bigint,end:bigint,kind:string>>"))
    new = both.withColumn("new", F.when(F.size(spans) == 0, F.col("doc")[text]).otherwise(replaced(F.col("doc")[text], spans)))
    change = {text: F.col("new"), "n_chars": F.coalesce(F.length("new"), F.lit(0)).cast("long")}
    return new.select(*[change[c].alias(c) if c in change else F.col("doc")[c].alias(c) for c in own])


def op1_disclosure_sanitiser(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text")
    thin, terms = sanitise_spans(docs)
    joined = lambda c: F.array_join(F.transform(c, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    of_kind = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    # the digest columns of each different text go to its rows
    found = found_spans(thin, terms).select("row", *[of_kind(k) for k in KINDS], F.sha2(joined("base"), 256).alias("base_sha256"), joined("spans").alias("spans"))
    rows = docs.select("doc_id", row_key().alias("row")).join(_sized(found, F.length("spans") + 2 * ROW_BYTES), "row", "left")
    counts = [F.coalesce(f"n_{k}", F.lit(0)).cast("long").alias(f"n_{k}") for k in KINDS]
    return rows.select("doc_id", *counts, F.coalesce("base_sha256", F.sha2(F.lit(""), 256)).alias("base_sha256"), F.coalesce("spans", F.lit("")).alias("spans"))
