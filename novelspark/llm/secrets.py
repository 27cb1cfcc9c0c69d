"""Secret scans (operator 8).

One Aho-Corasick automaton finds all keywords in one pass over the text; regular expressions run only where a keyword was
hit, anchored at that place. Formats with an embedded checksum are kept only if the checksum holds. Runs of hexadecimal digits
have no keyword and are found by their own expression.

Kinds of the base: ``assign``, ``access``, ``hex``. The method adds ``forge`` (prefix, 30 characters and the CRC-32 of
these in six base-62 digits) and ``webtoken`` (three base64url parts whose first holds a JSON header with ``alg``).

Defined cases: a null text is empty; offsets are in code points, ends exclusive; repeated rows are scanned each; an empty table
gives no rows; a token header that is nested too deep to be read is none. Long runs of one alphabet are read once for each kind.
"""

from __future__ import annotations

import base64
import hashlib
import json
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, slices

ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII | re.IGNORECASE)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
FORGE = re.compile(r"gh[pousr]_([A-Za-z0-9]{30})([A-Za-z0-9]{6})(?![A-Za-z0-9])")
TOKEN_RUN = re.compile(r"[A-Za-z0-9_-]+")
WEBTOKEN = re.compile(r"(eyJ[A-Za-z0-9_-]+)\.(eyJ[A-Za-z0-9_-]+)\.[A-Za-z0-9_-]+")
KEYWORDS = {
    "password": "assign", "passwd": "assign", "secret": "assign", "token": "assign", "api_key": "assign", "apikey": "assign", "akia": "access",
    "ghp_": "forge", "gho_": "forge", "ghu_": "forge", "ghs_": "forge", "ghr_": "forge", "eyj": "webtoken",
}
#: The order of kinds at one start.
KINDS = ("assign", "access", "hex", "forge", "webtoken")
BASE = KINDS[:3]
DIGITS = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"


def base62(number: int, width: int = 6) -> str:
    out = ""
    for _ in range(width):
        number, rest = divmod(number, 62)
        out = DIGITS[rest] + out
    return out


def forge_checksum_holds(match: re.Match) -> bool:
    return base62(zlib.crc32(match[1].encode())) == match[2]


def webtoken_header_holds(match: re.Match) -> bool:
    try:
        head = json.loads(base64.urlsafe_b64decode(match[1] + "=" * (-len(match[1]) % 4)))
    except (ValueError, RecursionError):  # no JSON, or nested too deep for a header
        return False
    return isinstance(head, dict) and "alg" in head


#: For each kind: the anchored expression, and what a match must hold to count.
RULES = {
    "assign": (ASSIGN, lambda m: len(m[2]) >= 6),
    "access": (ACCESS, lambda m: len(m[0]) >= 20),
    "forge": (FORGE, forge_checksum_holds),
    "webtoken": (WEBTOKEN, webtoken_header_holds),
}
_automaton = None


def automaton():
    global _automaton
    if _automaton is None:
        import ahocorasick

        _automaton = ahocorasick.Automaton()
        for word, kind in KEYWORDS.items():
            _automaton.add_word(word, (len(word), kind))
        _automaton.make_automaton()
    return _automaton


def lowered(text: str) -> str:
    """Lower case, character for character; where a letter's lower case is longer than one, only A-Z are changed."""
    low = text.lower()
    return low if len(low) == len(text) else re.sub("[A-Z]+", lambda m: m[0].lower(), text)


def scan(text: str | None) -> list[tuple[int, int, str]]:
    """(start, end, kind) by start, then kind in the order of KINDS."""
    text = text or ""
    found, past = [], dict.fromkeys(RULES, 0)
    hits = sorted((last + 1 - size, kind) for last, (size, kind) in automaton().iter(lowered(text)))
    for start, kind in hits:
        if start < past[kind]:
            continue
        expression, holds = RULES[kind]
        if match := expression.match(text, start):
            past[kind] = match.end()
            if holds(match):
                found.append((start, match.end(), kind))
        elif kind == "webtoken":  # whether a run is a header hangs on what follows it, so no later start in it does better
            past[kind] = TOKEN_RUN.match(text, start).end()
    found += [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    return sorted(found, key=lambda x: (x[0], KINDS.index(x[2])))


def redact(text: str | None, mark: str = "[SECRET]") -> str:
    """The text with every found span replaced; overlapping spans become one mark."""
    text, out, at = text or "", [], 0
    for start, end, _ in scan(text):
        if start >= at:
            out += [text[at:start], mark]
        at = max(at, end)
    return "".join([*out, text[at:]])


def spans(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, spans): an array of (start, end, kind) for every row."""
    kind = docs.schema[key].dataType.simpleString()
    out_type = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("kind", pa.string())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            rows = [[{"start": a, "end": b, "kind": k} for a, b, k in scan(t)] for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, type=out_type)], names=["key", "spans"])

    schema = f"key {kind}, spans array<struct<start:long,end:long,kind:string>>"
    return docs.select(F.col(key).alias("key"), F.col(text).alias("text")).mapInArrow(run, schema).withColumnRenamed("key", key)


def digest(found: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in found)


def op8_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    joined = lambda c: F.array_join(F.transform(c, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    base = F.filter("spans", lambda s: s["kind"].isin(*BASE))
    counts = [F.size(F.filter(F.transform("spans", lambda s: s["kind"]), (lambda k: lambda s: s == k)(k))).cast("long").alias(f"n_{k}") for k in BASE]
    return spans(documents(spark, sf_dir)).select("doc_id", *counts, F.sha2(joined(base), 256).alias("base_sha256"), joined(F.col("spans")).alias("spans"))
