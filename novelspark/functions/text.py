"""Turning text into terms: column expressions that stay in generated code."""

from __future__ import annotations

import glob
import os
import zipfile
from functools import cache

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .exprs import let

LANGUAGES = {"en": "english", "fr": "french", "de": "german", "es": "spanish"}
#: Endings that the light stemmer takes off, longest first; a stem keeps three letters or more.
SUFFIXES = ("ements", "ement", "ingly", "ation", "ment", "ungen", "ung", "heit", "keit", "ción", "ing", "ed", "es", "en", "er", "ly", "s")
STEM_PATTERN = f"^(.{{3,}}?)({'|'.join(SUFFIXES)})$"
PATTERNS = {"letters": r"(\p{L}+)", "word": r"([\p{L}\p{N}_]+)", "space": r"(\S+)"}


def tokens(text: Column, kind: str = "letters", ngram: int = 1) -> Column:
    """Case-folded terms in order: runs of letters, of word characters (digits stay) or of anything but white space; or n-grams of them."""
    plain = F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(PATTERNS[kind]), F.lit(1))
    return plain if ngram == 1 else ngrams(plain, ngram)


def ngrams(terms: Column, n: int) -> Column:
    def grams(t: Column) -> Column:
        starts = F.when(F.size(t) >= n, F.sequence(F.lit(1), F.size(t) - n + 1)).otherwise(F.array().cast("array<int>"))
        return F.transform(starts, lambda i: F.array_join(F.slice(t, i, F.lit(n)), " "))

    return let(terms, grams)


@cache
def stopwords(lang: str) -> tuple[str, ...]:
    """The stop list that Spark's own library ships for a language, in small letters, letter runs only."""
    import pyspark

    jar = next(iter(glob.glob(os.path.join(os.path.dirname(pyspark.__file__), "jars", "spark-mllib_*.jar"))), None)
    if jar is None:
        return ()
    with zipfile.ZipFile(jar) as z:
        lines = z.read(f"org/apache/spark/ml/feature/stopwords/{LANGUAGES[lang]}.txt").decode().split("\n")
    return tuple(sorted({w.strip().lower() for w in lines if w.strip().isalpha()}))


def drop_stopwords(terms: Column, lang: Column) -> Column:
    """Terms without their language's stop words; the lists are literals, so nothing is joined."""
    out = terms
    for code in LANGUAGES:
        words = F.array(*[F.lit(w) for w in stopwords(code)])
        out = F.when(lang == code, F.filter(terms, _absent(words))).otherwise(out)
    return out


def _absent(words: Column):
    return lambda t: ~F.array_contains(words, t)


def stem(term: Column) -> Column:
    """The light stemmer: one listed ending off, if three letters or more stay."""
    return F.regexp_replace(term, STEM_PATTERN, "$1")


def porter(word: str) -> str:
    """Suffix stripping after Porter (1980), for English words in small letters."""
    vowel = lambda w, i: w[i] in "aeiou" or (w[i] == "y" and i > 0 and not vowel(w, i - 1))

    def measure(w: str) -> int:
        kinds = [vowel(w, i) for i in range(len(w))]
        return sum(a and not b for a, b in zip(kinds, kinds[1:], strict=False))

    has_vowel = lambda w: any(vowel(w, i) for i in range(len(w)))
    double = lambda w: len(w) > 1 and w[-1] == w[-2] and not vowel(w, len(w) - 1)
    cvc = lambda w: len(w) > 2 and not vowel(w, len(w) - 3) and vowel(w, len(w) - 2) and not vowel(w, len(w) - 1) and w[-1] not in "wxy"
    if len(word) < 3:
        return word
    w = word
    for a, b in (("sses", "ss"), ("ies", "i"), ("ss", "ss"), ("s", "")):
        if w.endswith(a):
            w = w[: -len(a)] + b
            break
    if w.endswith("eed"):
        w = w[:-1] if measure(w[:-3]) > 0 else w
    else:
        for a in ("ed", "ing"):
            if w.endswith(a) and has_vowel(w[: -len(a)]):
                w = w[: -len(a)]
                if w.endswith(("at", "bl", "iz")):
                    w += "e"
                elif double(w) and w[-1] not in "lsz":
                    w = w[:-1]
                elif measure(w) == 1 and cvc(w):
                    w += "e"
                break
    if w.endswith("y") and has_vowel(w[:-1]):
        w = w[:-1] + "i"
    # fixed values: endings and what replaces them
    second = {"ational": "ate", "tional": "tion", "enci": "ence", "anci": "ance", "izer": "ize", "abli": "able", "alli": "al", "entli": "ent", "eli": "e", "ousli": "ous", "ization": "ize", "ation": "ate", "ator": "ate", "alism": "al", "iveness": "ive", "fulness": "ful", "ousness": "ous", "aliti": "al", "iviti": "ive", "biliti": "ble"}
    third = {"icate": "ic", "ative": "", "alize": "al", "iciti": "ic", "ical": "ic", "ful": "", "ness": ""}
    fourth = ("al", "ance", "ence", "er", "ic", "able", "ible", "ant", "ement", "ment", "ent", "ion", "ou", "ism", "ate", "iti", "ous", "ive", "ize")
    for table in (second, third):
        ending = max((e for e in table if w.endswith(e)), key=len, default=None)
        if ending and measure(w[: -len(ending)]) > 0:
            w = w[: -len(ending)] + table[ending]
    ending = max((e for e in fourth if w.endswith(e)), key=len, default=None)
    if ending:
        rest = w[: -len(ending)]
        if measure(rest) > 1 and (ending != "ion" or rest[-1:] in ("s", "t")):
            w = rest
    if w.endswith("e") and (measure(w[:-1]) > 1 or (measure(w[:-1]) == 1 and not cvc(w[:-1]))):
        w = w[:-1]
    return w[:-1] if measure(w) > 1 and double(w) and w[-1] == "l" else w


def stem_vocab(vocabulary: DataFrame, term: str = "term") -> DataFrame:
    """(term, stem) for distinct terms: the Python stemmer sees each word once, however often it occurs."""

    def stems(words: pd.Series) -> pd.Series:
        return words.map(porter)

    udf = F.pandas_udf(stems, "string")
    return vocabulary.select(term).distinct().withColumn("stem", udf(F.col(term)))


def sentences(df: DataFrame, text: str = "text", min_tokens: int = 0) -> DataFrame:
    """One row a sentence, with its place: split after end marks before blanks, and at line ends."""
    marked = F.regexp_replace(F.coalesce(F.col(text), F.lit("")), r"([.!?])\x20+", "$1\n")
    parts = F.filter(F.split(marked, "\n+"), lambda s: F.trim(s) != "")
    out = df.withColumn("_p", parts).drop(text).select("*", F.posexplode("_p").alias("pos", text)).drop("_p").withColumn(text, F.trim(text))
    return out.filter(F.size(tokens(F.col(text))) >= min_tokens) if min_tokens else out


def html_text(html: Column) -> Column:
    """Visible text of a page: scripts, styles and tags go, common entities are read."""
    out = F.regexp_replace(F.coalesce(html, F.lit("")), r"(?is)<script[^>]*>.*?</script>|<style[^>]*>.*?</style>", " ")
    out = F.regexp_replace(out, r"<[^>]*>", " ")
    for entity, char in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        out = F.replace(out, F.lit(entity), F.lit(char))
    return F.trim(F.regexp_replace(out, r"[\x20\t\r\n]+", " "))


def snippet(terms: Column, size: int = 40) -> Column:
    return F.slice(terms, 1, size)
