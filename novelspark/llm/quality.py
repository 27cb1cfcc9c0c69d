"""Line-first cleaning (operator 7, native).

Each line is judged by itself: a line without any sentence mark, a navigation line, a line of symbols and a boilerplate line
fail and are removed. A document is rejected if the removed lines held too large a share of its words. The word and repetition counts
of the base are made in the same pass; everything stays within the row, so nothing is shuffled.

Defined cases: a null or empty text has no words and is not kept; repeated rows are judged each; an empty table gives no rows;
other columns are passed through by ``clean`` and ignored by the query. Windows of 8 words are compared by a 64-bit hash
within their document.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, let

WINDOW = 8
MIN_WORDS, MAX_REPEAT_PERCENT = 20, 30
#: A document is rejected if removed lines held more than this percentage of its words.
MAX_LOST_PERCENT = 40
BLANKS = r"[\x20\x09-\x0D]+"
A_WORD = r"[^\x20\x09-\x0D]"
SYMBOLS = r"[#*$%&|<>]"
SENTENCE_MARK = r"[.!?…;:。！？؟]"
SEPARATORS = "[|»›·]"
BOILERPLATE = (
    r"(?i)\b(all rights reserved|copyright (\(c\)|©|[0-9]{4})|cookie (policy|settings)|accept cookies|privacy policy|terms of (use|service)|"
    r"licensed under|released under the|subscribe to our|sign up for|enable javascript|click here|lorem ipsum)\b"
)


#: Every boilerplate phrase holds one of these in lower case; texts without any skip the expression.
HINTS = ("rights reserved", "copyright", "cookie", "privacy", "terms of", "licensed", "released", "subscribe", "sign up", "javascript", "click here", "lorem")


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(text, BLANKS), "")


def _pairs(hashes: Column, step: int) -> Column:
    """Hash of each window of 2 * step words from the hashes of its halves."""

    def both(h: Column) -> Column:
        n = F.greatest(F.size(h) - step, F.lit(0))
        return F.zip_with(F.slice(h, F.lit(1), n), F.slice(h, F.lit(step + 1), n), lambda a, b: F.xxhash64(a, b))

    return let(hashes, both)


def repeated_words(windows: Column) -> Column:
    """Words in windows that occur twice or more: the size of the union of their places."""
    zero = F.lit(0).cast("long")
    placed = F.array_sort(F.transform(windows, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

    def twins(p: Column) -> Column:
        same = lambda a, k: (k >= 0) & (k < F.size(p)) & F.coalesce(F.get(p, k)["h"] == a["h"], F.lit(False))
        return F.transform(F.filter(p, lambda a, k: same(a, k + 1) | same(a, k - 1)), lambda a: a["i"])

    twice = F.array_sort(let(placed, twins))
    start = F.struct(zero.alias("words"), F.lit(-WINDOW).cast("long").alias("last"))
    total = F.aggregate(
        twice, start, lambda a, i: F.struct((a["words"] + F.least(i.cast("long") - a["last"], F.lit(WINDOW).cast("long"))).alias("words"), i.cast("long").alias("last"))
    )
    return total["words"]


def line_fails(line: Column, hinted: Column) -> Column:
    """A line with words that has no sentence mark, is navigation, is mostly symbols, or holds a boilerplate phrase."""
    separators, symbols = F.regexp_count(line, F.lit(SEPARATORS)), F.regexp_count(line, F.lit(SYMBOLS))
    crowded = let(
        F.struct(separators.alias("a"), symbols.alias("b")),
        lambda c: ((c["a"] >= 3) | (c["b"] >= 3))
        & let(F.size(words_of(line)), lambda n: ((c["a"] >= 3) & (c["a"] * 5 >= n)) | ((c["b"] >= 3) & (c["b"] * 2 >= n))),
    )
    return line.rlike(A_WORD) & (~line.rlike(SENTENCE_MARK) | crowded | (hinted & line.rlike(BOILERPLATE)))


def measured(docs: DataFrame, text: str = "text") -> DataFrame:
    """The input with struct column ``_m``: counts, words lost with failing lines, and the kept text."""
    value = F.coalesce(F.col(text), F.lit(""))
    low = F.lower(value)
    hinted = low.contains(HINTS[0])
    for phrase in HINTS[1:]:
        hinted = hinted | low.contains(phrase)
    out = docs.withColumn("_w", words_of(value)).withColumn("_l", F.split(value, "\n", -1)).withColumn("_b", hinted)
    out = out.withColumn("_h", F.transform("_w", lambda w: F.xxhash64(w)))
    out = out.withColumn("_h", F.when(F.size("_h") > WINDOW, _pairs(_pairs(_pairs(F.col("_h"), 1), 2), 4)).otherwise(F.array().cast("array<bigint>")))
    out = out.withColumn("_f", F.transform("_l", lambda x: line_fails(x, F.col("_b"))))
    failing = F.filter("_l", lambda x, i: F.get("_f", i))
    lost = F.aggregate(failing, F.lit(0).cast("long"), lambda n, x: n + F.size(words_of(x)))
    left = F.array_join(F.filter("_l", lambda x, i: ~F.get("_f", i)), "\n")
    spoken = F.filter("_l", lambda x: x.rlike(A_WORD))
    some = F.exists("_f", lambda x: x)
    repeat = F.when(F.size(F.array_distinct("_h")) == F.size("_h"), F.lit(0).cast("long")).otherwise(repeated_words(F.col("_h")))
    out = out.withColumn(
        "_m",
        F.struct(
            F.size("_w").cast("long").alias("n_words"),
            F.coalesce(F.length(F.array_join("_w", "")), F.lit(0)).cast("long").alias("word_chars"),
            F.regexp_count(value, F.lit(SYMBOLS)).cast("long").alias("n_symbols"),
            let(spoken, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"),
            repeat.alias("n_repeat_words"),
            (F.size("_w") - F.when(some, lost).otherwise(0)).cast("long").alias("n_left"),
            F.when(some, left).otherwise(value).alias("text"),
        ),
    )
    return out.drop("_w", "_l", "_h", "_f", "_b")


def _verdict(m: Column, max_lost_percent: int) -> tuple[Column, Column]:
    """``base_failed`` and ``kept`` from the counts of ``measured``."""
    failed = (m["n_words"] < MIN_WORDS) | (m["n_repeat_words"] * 100 > m["n_words"] * MAX_REPEAT_PERCENT)
    lost = (m["n_words"] - m["n_left"]) * 100 > m["n_words"] * max_lost_percent
    return failed, ~failed & ~lost


def verdicts(docs: DataFrame, text: str = "text", max_lost_percent: int = MAX_LOST_PERCENT) -> DataFrame:
    """Adds the counts, ``base_failed``, ``kept``, ``n_left`` and ``clean_text``."""
    m = F.col("_m")
    failed, kept = _verdict(m, max_lost_percent)
    counts = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_left")
    return measured(docs, text).select("*", *[m[c].alias(c) for c in counts], m["text"].alias("clean_text"), failed.alias("base_failed"), kept.alias("kept")).drop("_m")


def clean(docs: DataFrame, text: str = "text", max_lost_percent: int = MAX_LOST_PERCENT) -> DataFrame:
    """Kept documents with the columns they came with; their text is that of the lines left, ``n_chars`` its length.

    The verdict comes out of a generator, past which no filter moves, so that the optimiser cannot evaluate all counts a second time
    within the filter, once for each of their uses.
    """
    own = docs.columns
    inner = docs.select(F.struct(*[F.col(f"`{c}`") for c in own]).alias("row"), F.col(f"`{text}`").alias("body"))
    judged = measured(inner, "body").select("row", F.explode(F.array("_m")).alias("v"))
    left = judged.filter(_verdict(F.col("v"), max_lost_percent)[1])
    new = {text: F.col("v")["text"], "n_chars": F.length(F.col("v")["text"]).cast("long")}
    return left.select(*[new[c].alias(c) if c in new else F.col("row")[c].alias(c) for c in own])


def op7_line_first(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text")
    return verdicts(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_left")


#: The same for DuckDB: one row a document, counted from exploded words and lines.
OP7_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT r, doc_id, t, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS ws, string_split(t, chr(10)) AS ls FROM d),
l AS (SELECT r, unnest(ls) AS line, generate_subscripts(ls, 1) AS k FROM w),
lw AS (SELECT r, k, line, len(regexp_extract_all(line, '[^\x20\x09-\x0D]+')) AS n,
       length(line) - length(regexp_replace(line, '[|»›·]', '', 'g')) AS seps,
       length(line) - length(regexp_replace(line, '[#*$%&|<>]', '', 'g')) AS syms FROM l),
lines AS (SELECT r, count(*) FILTER (n > 0) - count(DISTINCT line) FILTER (n > 0) AS dup,
    sum(n) FILTER (NOT (n > 0 AND (NOT regexp_matches(line, '[.!?…;:。！？؟]') OR (seps >= 3 AND seps * 5 >= n) OR (syms * 2 >= n AND syms >= 3)
      OR regexp_matches(line, '(?i)\b(all rights reserved|copyright (\(c\)|©|[0-9]{4})|cookie (policy|settings)|accept cookies|privacy policy|terms of (use|service)|licensed under|released under the|subscribe to our|sign up for|enable javascript|click here|lorem ipsum)\b')))) AS n_left
  FROM lw GROUP BY r),
win AS (SELECT r, i, array_to_string(ws[i:i+7], ' ') AS g FROM (SELECT r, ws, unnest(range(1, greatest(len(ws) - 6, 1))) AS i FROM w)),
rep AS (SELECT r, i, lag(i) OVER (PARTITION BY r ORDER BY i) AS p FROM (SELECT r, i, count(*) OVER (PARTITION BY r, g) AS c FROM win) WHERE c > 1),
reps AS (SELECT r, sum(least(8, i - coalesce(p, i - 8))) AS n FROM rep GROUP BY r),
m AS (SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(length(array_to_string(ws, '')) AS BIGINT) AS word_chars,
  CAST(length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, CAST(coalesce(dup, 0) AS BIGINT) AS n_dup_lines,
  CAST(coalesce(reps.n, 0) AS BIGINT) AS n_repeat_words, CAST(coalesce(n_left, 0) AS BIGINT) AS n_left
  FROM w LEFT JOIN lines USING (r) LEFT JOIN reps USING (r))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_words < 20 OR n_repeat_words * 100 > n_words * 30 AS base_failed,
  NOT (n_words < 20 OR n_repeat_words * 100 > n_words * 30) AND NOT ((n_words - n_left) * 100 > n_words * 40) AS kept, n_left
FROM m
"""
