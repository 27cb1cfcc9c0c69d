"""N-gram Jaccard join by token-combination prefixes (operator 9).

A document's tokens are the 64-bit hashes of its distinct word shingles. All tokens have one global order, rare classes first.
If two sets of sizes n and m reach the threshold t, their common tokens fill all but n - ceil(t n) places of the one and m - ceil(t m)
of the other; so their *prefixes* of n - ceil(t n) + k tokens share at least k tokens. Classes decide what is indexed:

* tokens of the rare class are indexed one by one;
* tokens of frequent classes are indexed in combinations of two. They are dealt into g groups by hash, the prefix is extended so that
  g + 1 tokens are shared, and two of these then lie in one group (or one shared token is rare). g depends on the size level of
  the set; sets near the next level are indexed for it as well. A set whose plain prefix is all rare needs no extension.

The class comes from a counter sketch over all documents with a fixed number of counters. A counter holds its tokens and the noise of
others; the noise is about the median counter, so a token is frequent if its counter exceeds the median by a constant and some
deviations. Rare lists therefore grow with the square root of the noise, not with the corpus. Any class boundary gives right results.

Candidates first meet a bound: every set has a bitmap of the parities of its hashed tokens, two to four bits a token, and two sets differ in
at least as many tokens as their bitmaps differ in bits. What is left is verified on the texts. No list of an index is ever expanded
into all its pairs: equal sets are one representative from the start; each list first pairs its members with its first one; members of
one component need no more comparison, so only lists that still span several components compare the members outside the most common
component with the others. Members without any possible partner in their list, by size and place, go first; the others get their
bitmaps, lists of the same members are compared once, as arrays and block by block, and only pairs that the bitmaps leave become rows.

Defined cases: null texts and texts without a word have an empty set and no links; fewer words than a shingle make one shingle of all; a null id
takes no part; rows that repeat an id count as one document (of the smallest text); an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from math import ceil

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, documents, slices

SHINGLE, PERCENT = 5, 80
#: Counters of the frequency sketch; 4 MB of classes whatever the input.
SKETCH_BITS = 22
#: A token is frequent if its counter is above the median by more than this and by more than so many square roots of the median.
FREQUENT, DEVIATIONS = 64, 8
#: Members of a list that are compared as one block, and bytes of bitmap differences that a comparison holds at once.
LIST_BLOCK, COMPARE_BYTES = 512, 4_000_000
#: Pairs of members whose sizes and places are looked at in one step.
PAIRS_AT_ONCE = 1 << 20
#: Partners of one document that a task verifies against one copy of its text.
VERIFY_BLOCK = 128
#: Tables of ids up to this number are broadcast.
BROADCAST_ROWS = 500_000
MULTIPLIER = 0x5851F42D4C957F2D | 1
INVERSE = pow(MULTIPLIER, -1, 1 << 64)
BYTE_VALUES = np.random.RandomState(7).randint(1, 1 << 62, 256, dtype=np.int64).astype(np.uint64)
_powers: list[np.ndarray] = [np.ones(1, dtype=np.uint64), np.ones(1, dtype=np.uint64)]


def _power_tables(n: int) -> list[np.ndarray]:
    while len(_powers[0]) < n:
        for i, base in enumerate((MULTIPLIER, INVERSE)):
            old = _powers[i]
            _powers[i] = np.concatenate([old, old * np.uint64(pow(base, len(old), 1 << 64))])
    return _powers


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


#: Words whose shingles are hashed in one step: a very long text costs no more memory than its words.
WORDS_AT_ONCE = 20_000


def shingles(text: str | None, size: int = SHINGLE) -> np.ndarray:
    """Sorted 64-bit hashes of the distinct word shingles of a text."""
    words = (text or "").encode().lower().split()  # A-Z lower-cased; split at blanks 0x20 and 0x09-0x0D
    if not words:
        return np.zeros(0, dtype=np.uint64)
    # a shingle's hash does not depend on its place, so each part of the text can be hashed by itself
    parts = [_hashes(words[at : at + WORDS_AT_ONCE + size - 1], size) for at in range(0, max(1, len(words) - size + 1), WORDS_AT_ONCE)]
    return np.unique(np.concatenate(parts) if len(parts) > 1 else parts[0])


def _hashes(words: list[bytes], size: int) -> np.ndarray:
    data = np.frombuffer(b" ".join(words) + b" ", dtype=np.uint8)
    ups, downs = _power_tables(len(data) + 1)
    sums = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum(BYTE_VALUES[data] * ups[: len(data)], dtype=np.uint64)])
    ends = np.flatnonzero(data == 32) + 1
    starts = np.concatenate([[0], ends[:-1]])
    n = max(1, len(ends) - size + 1)
    first, last = starts[:n], ends[min(size, len(ends)) - 1 :][:n]
    return _mixed((sums[last] - sums[first]) * downs[first])


def plain_prefix(n: int, percent: int = PERCENT) -> int:
    return n - -(-n * percent // 100) + 1


def groups_of_level(level: int) -> int:
    """Groups that frequent tokens are dealt into for sets of 2**level to 2**(level + 1) tokens."""
    return max(1, (1 << level) // 16)


def signatures(tokens: np.ndarray, klass: np.ndarray, percent: int = PERCENT) -> tuple[np.ndarray, np.ndarray]:
    """Index keys of one set and, for single tokens, their place in the global order (combinations: 0)."""
    n = len(tokens)
    order = np.lexsort((tokens, klass))
    ranked, frequent = tokens[order], klass[order] > 0
    plain = plain_prefix(n, percent)
    if not frequent[plain - 1]:
        return ranked[:plain], np.arange(plain)
    rare = int(np.argmax(frequent))
    level = n.bit_length() - 1
    levels = [level, level + 1] if n * 100 >= (2 << level) * percent else [level]
    keys, longest = [], plain
    for lv in levels:
        g = groups_of_level(lv)
        length = min(n, plain + g)
        longest = max(longest, length)
        some = np.sort(ranked[max(rare, 0) : length])
        group = (_mixed(some ^ np.uint64(0xA5A5A5A5A5A5A5A5)) % np.uint64(g)).astype(np.int64)
        for x in range(g):
            own = some[group == x]
            if len(own) > 1:
                a, b = np.triu_indices(len(own), 1)
                keys.append(_mixed(own[a] * np.uint64(3) + _mixed(own[b] + np.uint64(lv + 1))))
    combos = np.concatenate(keys) if keys else tokens[:0]
    return np.concatenate([ranked[:rare], combos]), np.concatenate([np.arange(rare), np.zeros(len(combos), dtype=np.int64)])


def parity_bits(tokens: np.ndarray) -> bytes:
    """Parities of the tokens that fall on each of two to four times as many bits as there are tokens (a power of two, 64 at least)."""
    width = max(64, 2 << (len(tokens) - 1).bit_length()) if len(tokens) else 64
    at = (tokens & np.uint64(width - 1)).astype(np.int64)
    return np.packbits((np.bincount(at, minlength=width) & 1).astype(np.uint8)).tobytes()


def fewest_differences(a: bytes, b: bytes) -> int:
    """A lower bound of the tokens in which two sets differ; the longer bitmap is folded to the shorter one's width."""
    x, y = np.frombuffer(a, dtype=np.uint8), np.frombuffer(b, dtype=np.uint8)
    while len(x) > len(y):
        x = x[: len(x) // 2] ^ x[len(x) // 2 :]
    while len(y) > len(x):
        y = y[: len(y) // 2] ^ y[len(y) // 2 :]
    return int(np.bitwise_count(x ^ y).sum())


# ---- passes over the texts -------------------------------------------------------------------------------------------------


def _digests(docs: DataFrame, size: int, bits: int) -> DataFrame:
    """(kind, id, n, a, b, bits, part, counts): a row a document with a 128-bit digest and the bitmap of its set, and each task's counters in parts."""
    parts = 64

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(1 << bits, dtype=np.uint8)
        names = ["kind", "id", "n", "a", "b", "bits", "part", "counts"]
        for batch in slices(batches):
            ns, a, b, bitmaps, pending = [], [], [], [], []
            for text in batch.column(1).to_pylist():
                s = shingles(text, size)
                ns.append(len(s))
                a.append(int(np.bitwise_xor.reduce(s)) if len(s) else 0)
                b.append(int(np.sum(_mixed(s + np.uint64(1)), dtype=np.uint64)) if len(s) else 0)
                bitmaps.append(parity_bits(s))
                pending.append(s)
            at, more = np.unique(np.concatenate(pending) >> np.uint64(64 - bits), return_counts=True)
            counts[at] = np.minimum(counts[at] + more, 255)
            rows = len(ns)
            signed = lambda x: pa.array(np.array(x, dtype=np.uint64).view(np.int64))
            yield pa.RecordBatch.from_arrays(
                [pa.array([0] * rows, pa.int32()), batch.column(0), pa.array(ns, pa.int64()), signed(a), signed(b), pa.array(bitmaps, pa.binary()), pa.nulls(rows, pa.int32()), pa.nulls(rows, pa.binary())], names=names
            )
        if not counts.any():
            return
        pieces = []
        for piece in np.split(counts, parts):
            at = np.flatnonzero(piece)
            # few counters in use: their places and values; else all of them
            pieces.append(b"s" + at.astype("<u2").tobytes() + piece[at].tobytes() if len(at) * 3 < piece.nbytes else b"d" + piece.tobytes())
        none = pa.nulls(parts, pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array([1] * parts, pa.int32()), none, none, none, none, pa.nulls(parts, pa.binary()), pa.array(range(parts), pa.int32()), pa.array(pieces, pa.binary())], names=names)

    return docs.mapInArrow(run, "kind int, id long, n long, a long, b long, bits binary, part int, counts binary")


def _merged_sketch(pieces: DataFrame, bits: int) -> np.ndarray:
    """Counters summed over all tasks (a task tells up to 255 of each); parts are merged in a tree, so no task reads more than a bounded
    number of pieces."""
    width = (1 << bits) // 64

    def values(piece: bytes) -> np.ndarray:
        out = np.zeros(width, dtype=np.uint32)
        if piece[:1] == b"s":
            n = (len(piece) - 1) // 3
            out[np.frombuffer(piece[1 : 1 + 2 * n], dtype="<u2")] = np.frombuffer(piece[1 + 2 * n :], dtype="u1")
        else:
            out[:] = np.frombuffer(piece[1:], dtype="u1" if piece[:1] == b"d" else "<u4")
        return out

    def run(key, table):
        total = np.zeros(width, dtype=np.uint64)
        for piece in table.column("counts").to_pylist():
            total += values(piece)
        whole = np.minimum(total, np.iinfo(np.uint32).max).astype("<u4")
        return pa.table({"part": pa.array([key[0].as_py()], pa.int32()), "lot": pa.array([key[1].as_py()], pa.int64()), "counts": pa.array([b"t" + whole.tobytes()], pa.binary())})

    lots = pieces.withColumn("lot", F.spark_partition_id().cast("long"))
    tasks = lots.agg(F.max("lot")).first()[0]
    while True:
        lots = lots.select("part", F.floor(F.col("lot") / 64).cast("long").alias("lot"), "counts").groupBy("part", "lot").applyInArrow(run, "part int, lot long, counts binary")
        if (tasks or 0) < 64:
            break
        tasks //= 64
    out = np.zeros(1 << bits, dtype=np.uint32)
    for row in lots.collect():  # 64 rows
        out[row.part * width : (row.part + 1) * width] = values(bytes(row.counts))
    return out


def classes(counters: np.ndarray) -> np.ndarray:
    """One byte a counter: 0 for rare, else 1 + the power of two by which it exceeds the bound."""
    noise = float(np.median(counters))
    bound = noise + max(FREQUENT, DEVIATIONS * noise**0.5)
    return np.where(counters <= bound, 0, 1 + np.floor(np.log2(np.maximum(counters, 1) / bound))).astype(np.uint8)


def _index(docs: DataFrame, klass, size: int, percent: int, bits: int) -> DataFrame:
    """(sig, id, n, pos): the index keys of every set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = klass.value
        for batch in slices(batches):
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            sigs, owners, sizes, places = [], [], [], []
            for name, text in zip(ids.tolist(), batch.column(1).to_pylist(), strict=True):
                s = shingles(text, size)
                if not len(s):
                    continue
                keys, at = signatures(s, table[(s >> np.uint64(64 - bits)).astype(np.int64)], percent)
                sigs.append(keys)
                places.append(at)
                owners.append(np.full(len(keys), name, dtype=np.int64))
                sizes.append(np.full(len(keys), len(s), dtype=np.int32))
            if sigs:
                yield _rows(sigs, owners, sizes, places)

    def _rows(sigs, owners, sizes, places):
        return pa.RecordBatch.from_arrays(
            [pa.array(np.concatenate(sigs).view(np.int64)), pa.array(np.concatenate(owners)), pa.array(np.concatenate(sizes)), pa.array(np.concatenate(places).astype(np.int32))],
            names=["sig", "id", "n", "pos"],
        )

    return docs.mapInArrow(run, "sig long, id long, n int, pos int")


def _lists(index: DataFrame) -> DataFrame:
    """Index rows of keys with two documents or more, each with the first document of its list.

    Rows come sorted by key; a list is never held, only its first row.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["sig", "id", "n", "pos", "head", "head_n", "head_pos"]
        held = None  # the first row of the list that goes on: sig, id, n, pos, already written
        for batch in batches:
            cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(4)]
            if not len(cols[0]):
                continue
            if held is not None:
                cols = [np.concatenate([np.array([h], dtype=c.dtype), c]) for h, c in zip(held[:4], cols, strict=True)]
            sig = cols[0]
            new = np.concatenate([[True], sig[1:] != sig[:-1]])
            first = np.maximum.accumulate(np.where(new, np.arange(len(sig)), 0))
            shared = ~new | np.concatenate([~new[1:], [False]])
            if held is not None and held[4]:
                shared[0] = False  # written with an earlier batch
            last = int(first[-1])
            written = bool(shared[last]) or (held is not None and last == 0 and held[4])
            held = (*[c[last] for c in cols], written)
            at = np.flatnonzero(shared)
            if len(at):
                yield pa.RecordBatch.from_arrays([pa.array(c[at]) for c in cols] + [pa.array(c[first[at]]) for c in cols[1:]], names=names)

    return index.repartition("sig").sortWithinPartitions("sig", "id").mapInArrow(run, "sig long, id long, n int, pos int, head long, head_n int, head_pos int")


def _possible(n: str, m: str, pos: str = "", other: str = "", percent: int = PERCENT):
    """Sizes and places that leave the threshold possible: the first shared token bounds the common rest."""
    small, large = F.least(n, m), F.greatest(n, m)
    fits = small * 100 >= large * percent
    if pos:
        rest = F.least(F.col(n) - F.col(pos), F.col(m) - F.col(other))
        fits &= rest * (100 + percent) >= (F.col(n) + F.col(m)) * percent
    return fits


def bounded(pairs: DataFrame, bitmaps: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) whose bitmaps (id, n, bits) leave the threshold possible."""
    x, y = (bitmaps.select(F.col("id").alias(c), F.col("n").alias(f"n{c}"), F.col("bits").alias(f"bits{c}")) for c in "ab")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cols = [batch.column(i).to_pylist() for i in range(6)]
            keep = [fewest_differences(p, q) * (100 + percent) <= (n + m) * (100 - percent) for _, _, n, p, m, q in zip(*cols, strict=True)]
            chosen = np.flatnonzero(keep)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(chosen)), batch.column(1).take(pa.array(chosen))], names=["a", "b"])

    return pairs.join(x, "a").join(y, "b").select("a", "b", "na", "bitsa", "nb", "bitsb").mapInArrow(run, "a long, b long")


def _folded(rows: list[bytes], width: int) -> np.ndarray:
    """Bitmaps of ``width`` or twice as many bits, folded to ``width``, as rows of 64-bit words."""
    out = np.empty((len(rows), width // 64), dtype=np.uint64)
    for i, row in enumerate(rows):
        words = np.frombuffer(row, dtype=np.uint64)
        out[i] = words if len(words) == out.shape[1] else words[: out.shape[1]] ^ words[out.shape[1] :]
    return out


def near_members(n: np.ndarray, comp: np.ndarray, bits: list[bytes], percent: int, left: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Places (i, j) of members of different components whose sizes and bitmaps leave the threshold possible. With ``left``, only pairs
    of one of the first ``left`` members and one of the others.

    At the threshold the sizes differ by less than a factor of two, so bitmaps differ in width by a factor of two at most.
    """
    widths = np.fromiter((8 * len(b) for b in bits), dtype=np.int64, count=len(bits))
    out_i, out_j = [], []
    for width in np.unique(widths).tolist():
        narrow, wide = np.flatnonzero(widths == width), np.flatnonzero(widths == 2 * width)
        members = np.concatenate([narrow, wide])
        words = _folded([bits[i] for i in members.tolist()], width)
        step = max(1, COMPARE_BYTES // max(1, words.nbytes))
        for at in range(0, len(narrow), step):
            some = narrow[at : at + step]
            far = np.bitwise_count(words[at : at + len(some), None, :] ^ words[None, :, :]).sum(axis=2, dtype=np.int64)
            x, y = n[some][:, None], n[members][None, :]
            keep = (far * (100 + percent) <= (x + y) * (100 - percent)) & (np.minimum(x, y) * 100 >= np.maximum(x, y) * percent)
            keep &= comp[some][:, None] != comp[members][None, :]
            keep &= (np.arange(len(members)) >= len(narrow))[None, :] | (some[:, None] < members[None, :])  # equal widths: each pair once
            if left is not None:
                keep &= (some < left)[:, None] != (members < left)[None, :]
            r, c = np.nonzero(keep)
            out_i.append(some[r])
            out_j.append(members[c])
    none = np.zeros(0, dtype=np.int64)
    return (np.concatenate(out_i), np.concatenate(out_j)) if out_i else (none, none)


def with_partner(starts: np.ndarray, n: np.ndarray, pos: np.ndarray, comp: np.ndarray, percent: int) -> np.ndarray:
    """Marks members of lists (``starts``: where each begins, and the end) that have a member of another component in their list whose
    size and place leave the threshold possible."""
    sizes = np.diff(starts)
    out = np.zeros(len(n), dtype=bool)
    work = np.concatenate([[0], np.cumsum(sizes * sizes)])
    at = 0
    while at < len(sizes):  # lots of lists with a bounded number of pairs
        end = max(at + 1, int(np.searchsorted(work, work[at] + PAIRS_AT_ONCE, side="right")) - 1)
        first, last = starts[at], starts[end]
        own = np.repeat(sizes[at:end], sizes[at:end])  # for each member the size of its list
        i = np.repeat(np.arange(first, last), own)
        j = np.arange(len(i)) - np.repeat(np.cumsum(own) - own, own) + np.repeat(np.repeat(starts[at:end], sizes[at:end]), own)
        x, y = n[i], n[j]
        keep = (comp[i] != comp[j]) & (np.minimum(x, y) * 100 >= np.maximum(x, y) * percent)
        keep &= np.minimum(x - pos[i], y - pos[j]) * (100 + percent) >= (x + y) * percent
        out[i[keep]] = True
        at = end
    return out


def across(wide: DataFrame, bitmaps: DataFrame, percent: int, scratch: Scratch) -> DataFrame:
    """Pairs (a, b) of lists (sig, id, n, pos, comp, main, w), w the list's length, that are in different components and may link.

    Lists of at most a block are rows. First, without bitmaps, members go that have no possible partner in their list by size and place; of
    lists with the same members left one stays; then bitmaps decide. Longer lists, of which also one stays for the same members, are dealt
    into blocks with bitmaps; each block outside the main component meets the blocks of the main one and, once, every other block
    outside it.
    """
    short, long = wide.filter(F.col("w") <= LIST_BLOCK), wide.filter(F.col("w") > LIST_BLOCK)
    lists = short.groupBy("sig").agg(F.collect_list(F.struct("id", "n", "pos", "comp")).alias("m")).select("m")

    def prune(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        given = set()
        for batch in batches:
            column = batch.column(0)
            starts, cells = column.offsets.to_numpy().astype(np.int64), column.values
            ids, n, pos, comp = (cells.field(k).to_numpy().astype(np.int64) for k in range(4))
            left = with_partner(starts, n, pos, comp, percent)
            counts = np.add.reduceat(np.append(left, False), starts[:-1]) if len(starts) > 1 else []
            rows: list[tuple] = []
            for k in np.flatnonzero(counts):
                at = np.flatnonzero(left[starts[k] : starts[k + 1]]) + starts[k]
                at = at[np.argsort(ids[at])]
                name = hashlib.blake2b(ids[at].tobytes(), digest_size=16).digest()
                if name not in given:
                    given.add(name)
                    rows.append((name, ids[at], comp[at]))
            if rows:
                ends = np.cumsum([0] + [len(r[1]) for r in rows])
                members = pa.StructArray.from_arrays([pa.array(np.concatenate([r[k] for r in rows])) for k in (1, 2)], names=["id", "comp"])
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.binary()), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), members)], names=["list", "m"])

    kept = lists.mapInArrow(prune, "list binary, m array<struct<id:bigint,comp:bigint>>").groupBy("list").agg(F.first("m").alias("m"))
    kept = scratch.write(kept, "kept").select("list", F.explode("m").alias("m")).select("list", "m.id", "m.comp")
    member = F.struct("id", "n", "bits", "comp").alias("m")
    few = kept.join(bitmaps, "id").groupBy("list").agg(F.collect_list(member).alias("members"))
    few = few.select("members", F.lit(None).cast(few.schema["members"].dataType).alias("others"))

    same = long.groupBy("sig", "w", "main").agg(F.bit_xor(F.xxhash64("id")).alias("x"), F.bit_xor(F.xxhash64("id", F.lit(1))).alias("y"))
    same = same.groupBy("w", "main", "x", "y").agg(F.min("sig").alias("sig")).select("sig")
    rows = long.join(same, "sig").select("sig", "id", "comp", "main", "w").join(bitmaps, "id").withColumn("side", F.col("comp") != F.col("main"))
    block = F.pmod(F.xxhash64("id"), F.ceil(F.col("w") / LIST_BLOCK)).cast("int").alias("block")
    packed = rows.select("sig", "side", block, member).groupBy("sig", "side", "block").agg(F.collect_list("m").alias("members"))
    outer = packed.filter("side").select("sig", F.col("block").alias("x"), "members")
    met = outer.join(packed.select("sig", "side", "block", F.col("members").alias("others")), "sig").filter("NOT side OR x <= block")
    met = met.select("members", F.when(~(F.col("side") & (F.col("x") == F.col("block"))), F.col("others")).alias("others"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def parts(cell: list) -> list[list]:
            return [[m[k] for m in cell] for k in ("id", "n", "comp", "bits")]

        for batch in batches:
            for at in range(batch.num_rows):
                ids, n, comp, bits = parts(batch.column(0)[at].as_py())
                more, left = batch.column(1)[at].as_py(), None
                if more is not None:
                    left = len(ids)
                    ids, n, comp, bits = (a + b for a, b in zip((ids, n, comp, bits), parts(more), strict=True))
                i, j = near_members(np.array(n, dtype=np.int64), np.array(comp, dtype=np.int64), bits, percent, left)
                if len(i):
                    names = np.array(ids, dtype=np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(np.minimum(names[i], names[j])), pa.array(np.maximum(names[i], names[j]))], names=["a", "b"])

    return few.unionByName(met).mapInArrow(run, "a long, b long").distinct()


def verified(pairs: DataFrame, docs: DataFrame, size: int, percent: int, scratch: Scratch, name: str) -> DataFrame:
    """Pairs (a, b) that link, by their texts. Each pair moves one text; a much-paired document is copied for each block of partners."""
    pairs = scratch.write(pairs.select("a", "b"), f"{name}-pairs")
    counts = pairs.groupBy("a").agg(F.count("*").alias("c")).select("a", F.ceil(F.col("c") / VERIFY_BLOCK).cast("int").alias("blocks"))
    dealt = pairs.join(counts, "a").withColumn("block", F.pmod(F.xxhash64("b"), F.col("blocks")).cast("int"))
    ids = pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct()
    few = ids.count() <= BROADCAST_ROWS
    texts = scratch.write(docs.join(F.broadcast(ids) if few else ids, "id", "left_semi"), f"{name}-texts")
    left = counts.select("a", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block")).join(texts.withColumnRenamed("id", "a"), "a")
    right = dealt.select("a", "b", "block").join(texts.withColumnRenamed("id", "b"), "b")
    rows = left.select("a", "block", F.lit(None).cast("long").alias("b"), "text").unionByName(right.select("a", "block", "b", "text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, own = None, None
        for batch in batches:
            out_a, out_b = [], []
            for a, block, b, text in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                mine = shingles(text, size)
                if b is None:
                    now, own = (a, block), mine
                    continue
                assert now == (a, block)
                common = len(np.intersect1d(own, mine, assume_unique=True))
                if common and 100 * common >= percent * (len(own) + len(mine) - common):
                    out_a.append(a)
                    out_b.append(b)
            yield pa.RecordBatch.from_arrays([pa.array(out_a, pa.int64()), pa.array(out_b, pa.int64())], names=["a", "b"])

    links = rows.repartition("a", "block").sortWithinPartitions("a", "block", F.col("b").asc_nulls_first()).mapInArrow(run, "a long, b long")
    out = scratch.write(links, f"{name}-links")
    scratch.drop(f"{name}-texts", f"{name}-pairs")
    return out


def components(links: DataFrame, scratch: Scratch, name: str) -> DataFrame:
    """(id, comp) of all linked ids: comp is the smallest id that links reach.

    Each round takes the smallest label among neighbours, then follows labels to their labels; chains shorten by halves.
    """
    both = scratch.write(links.select("a", "b").union(links.select("b", "a")).distinct(), f"{name}-both")
    labels = scratch.write(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("comp")).withColumnRenamed("a", "id"), f"{name}-0")
    r = 0
    while True:
        r += 1
        offer = both.join(labels.select(F.col("id").alias("b"), "comp"), "b").groupBy("a").agg(F.min("comp").alias("offer"))
        lower = labels.join(offer.withColumnRenamed("a", "id"), "id", "left").select("id", F.col("comp").alias("was"), F.least("comp", F.coalesce("offer", "comp")).alias("comp"))
        lower = scratch.write(lower, f"{name}-{r}-half")
        jump = lower.select(F.col("id").alias("comp"), F.col("comp").alias("next"))
        after = scratch.write(lower.join(jump, "comp", "left").select("id", "was", F.coalesce("next", "comp").alias("comp")), f"{name}-{r}")
        if after.filter(F.col("was") != F.col("comp")).isEmpty():
            return after.select("id", "comp")
        labels = after.select("id", "comp")
        scratch.drop(f"{name}-{r}-half", f"{name}-{r - 1}")


def join(docs: DataFrame, key: str = "doc_id", text: str = "text", size: int = SHINGLE, percent: int = PERCENT, bits: int = SKETCH_BITS) -> DataFrame:
    """(key, n_shingles, component_id) of every document."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "jaccard")
    plain = docs.filter(F.col(key).isNotNull()).select(F.col(key).cast("long").alias("id"), F.col(text).alias("text"))
    rows = scratch.write(_digests(plain, size, bits), "digests")
    klass = spark.sparkContext.broadcast(classes(_merged_sketch(rows.filter("kind = 1").select("part", "counts"), bits)))
    sets = rows.filter("kind = 0").select("id", "n", "a", "b", "bits")
    # one row an id; equal sets have one representative, the smallest id
    one = sets.groupBy("id").agg(F.min(F.struct("n", "a", "b", "bits")).alias("s")).select("id", "s.n", "s.a", "s.b", "s.bits")
    heads = one.filter("n > 0").groupBy("n", "a", "b").agg(F.min("id").alias("rep"), F.count("*").alias("copies"))
    member = scratch.write(one.join(heads, ["n", "a", "b"], "left").select("id", "n", "bits", F.coalesce("rep", "id").alias("rep"), F.coalesce("copies", F.lit(1)).alias("copies")), "members")
    scratch.drop("digests")
    bitmaps = member.filter("id = rep").select("id", "n", "bits")
    # texts of repeated sets but for their representative need no index
    spare = member.filter("rep <> id").select("id")
    few = spare.count() <= BROADCAST_ROWS
    reps = plain.join(F.broadcast(spare) if few else spare, "id", "left_anti")
    lists = scratch.write(_lists(_index(reps, klass, size, percent, bits)), "lists")
    star = lists.filter((F.col("head") != F.col("id")) & _possible("n", "head_n", "pos", "head_pos", percent)).select(F.col("head").alias("a"), F.col("id").alias("b")).distinct()
    links = verified(bounded(star, bitmaps, percent), reps, size, percent, scratch, "star")
    first = components(links, scratch, "first")
    # lists that still span several components
    placed = lists.select("sig", "id", "n", "pos").join(first, "id", "left").withColumn("comp", F.coalesce("comp", "id"))
    placed = scratch.write(placed, "placed")
    scratch.drop("lists")
    per = placed.groupBy("sig", "comp").agg(F.count("*").alias("c"))
    spread = per.groupBy("sig").agg(F.count("*").alias("parts"), F.sum("c").alias("w"), F.max(F.struct("c", "comp")).alias("m")).filter("parts > 1").select("sig", "w", F.col("m.comp").alias("main"))
    rest = across(placed.join(spread, "sig"), bitmaps, percent, scratch)
    late = verified(rest, reps, size, percent, scratch, "rest")
    scratch.drop("placed", "kept")
    all_links = links.union(late)
    comp = components(all_links, scratch, "last")
    out = member.join(comp.withColumnRenamed("id", "rep"), "rep", "left").select("id", "n", F.coalesce("comp", "rep").alias("component_id"))
    # a class's smallest id is that of its smallest representative, since a representative is the smallest of its copies
    return out.select(F.col("id").alias(key), F.col("n").alias("n_shingles"), "component_id")


def one_of_each(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents but for those linked with one of a smaller id; rows without an id stay; rows that repeat an id stay or go together."""
    spare = join(docs, key, text).filter(F.col(key) != F.col("component_id")).select(key)
    few = spare.count() <= BROADCAST_ROWS
    left = docs.join(F.broadcast(spare) if few else spare, key, "left_anti")
    return left.select(*docs.columns)


def op9_token_combinations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return join(documents(spark, sf_dir))
