"""Byte-pair encoding and decoding with reuse of content-defined chunks (operator 4).

A rolling hash over the text's bytes sets chunk ends where its low bits are zero, so equal passages fall into equal chunks
wherever they stand. Chunks that occur twice or more in the whole corpus are encoded once:

* all chunk digests are counted; the repeated ones set bits in a bitmap of fixed size, which every task gets;
* a text without a marked chunk is encoded where it stands. Of the others, the task gives each marked chunk once, and a row for each place
  that needs it;
* each distinct marked chunk is encoded, and its ids go to the places by a join;
* a text is put together from these and from its own stretches between them. Joins are repaired: from the last piece boundary before
  the join that no later text can move, text is encoded again over a growing stretch until its piece boundaries meet those of the
  next part, from where that part's own ids hold. The result is the ids of the whole text, exactly.

A bit that two digests share only marks a chunk that occurs once; it is encoded once as well. Texts with a special-token string are
encoded whole, since the tokenizers library splits these off first. Decoding joins the tokens' bytes.

Defined cases: a null or empty text has no ids and decodes to the empty text; repeated rows share all their chunks; an empty table
gives no rows; other columns of the input are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, documents, slices

#: A chunk ends where the rolling hash over this many bytes has its low bits zero; 2**CHUNK_BITS bytes on average.
ROLL_BYTES, CHUNK_BITS = 32, 11
#: Bits of the bitmap of repeated chunks: 16 MB whatever the input.
MARK_BITS = 27
#: Later text can move a piece boundary at most this many characters before the end (contractions look two ahead).
UNSURE = 8
MIXER = np.uint64(0x9E3779B97F4A7C15)


def chunk_ends(data: bytes, bits: int = CHUNK_BITS) -> list[int]:
    """Byte offsets at which chunks end, always at character boundaries; the last is the length."""
    n = len(data)
    if n <= ROLL_BYTES:
        return [n] if n else []
    raw = np.frombuffer(data, dtype=np.uint8)
    h = (raw.astype(np.uint64) + np.uint64(1)) * MIXER
    h ^= h >> np.uint64(29)
    span = 1
    while span < ROLL_BYTES:  # doubling: the hash of 2s bytes from two hashes of s bytes
        step = np.uint64(pow(0x100000001B3, span, 1 << 64))
        longer = h.copy()
        longer[span:] += h[:-span] * step
        h, span = longer, 2 * span
    h ^= h >> np.uint64(32)
    cut = (h & np.uint64((1 << bits) - 1)) == 0
    cut[:ROLL_BYTES] = False
    at = np.flatnonzero(cut) + 1
    at = at[at < n]
    at = at[(raw[at] & 0xC0) != 0x80]
    return [*at.tolist(), n]


class Chunk:
    """A chunk's text, ids, and the places where pieces start: in characters and in ids."""

    __slots__ = ("text", "ids", "piece_at", "id_at")

    def __init__(self, text: str, ids: np.ndarray, piece_at: np.ndarray, id_at: np.ndarray):
        self.text, self.ids, self.piece_at, self.id_at = text, ids, piece_at, id_at


class KnownIds:
    """Ids and boundaries of a chunk that was encoded elsewhere."""

    __slots__ = ("ids", "piece_at", "id_at")

    def __init__(self, ids: np.ndarray, piece_at: np.ndarray, id_at: np.ndarray):
        self.ids, self.piece_at, self.id_at = ids, piece_at.astype(np.int64), id_at.astype(np.int64)


def chunks(text: str, bits: int = CHUNK_BITS) -> list[str]:
    data = text.encode()
    ends = chunk_ends(data, bits)
    return [data[a:b].decode() for a, b in zip([0, *ends], ends, strict=False)]


def digest(chunk: str) -> bytes:
    return hashlib.blake2b(chunk.encode(), digest_size=16).digest()


class ChunkEncoder:
    def __init__(self, path: str | None = None, bits: int = CHUNK_BITS):
        from .bpe import SPECIAL, ByteDecoder, encoder

        self.units, self.special, self.bits = encoder(path), SPECIAL, bits
        self.decoder = ByteDecoder(self.units.tokenizer)
        self.encoded = self.reused = self.repaired = 0

    def _pieces(self, text: str) -> list[tuple[int, int]]:
        return [span for _, span in self.units.tokenizer.pre_tokenizer.pre_tokenize_str(text)]

    def parts(self, texts: list[str]) -> list[Chunk]:
        """Texts that will be joined, each encoded by itself."""
        return [Chunk(t, ids, *self._edges(t, ids)) for t, ids in zip(texts, self.units.encode(texts), strict=True)]

    def encode(self, texts: list[str | None]) -> list[np.ndarray]:
        """Ids of texts, those of chunks that occur twice or more among them from one encoding."""
        cuts = [chunks(t or "", self.bits) if self.special not in (t or "") else [] for t in texts]
        seen: dict[str, int] = {}
        for cut in cuts:
            for c in cut:
                seen[c] = seen.get(c, 0) + 1
        often = [c for c, n in seen.items() if n > 1]
        known = dict(zip(often, self.parts(often), strict=True))
        self.encoded += len(seen)
        self.reused += sum(seen.values()) - len(seen)
        return self.assembled([(t or "", {i: known[c] for i, c in enumerate(cut) if c in known}) for t, cut in zip(texts, cuts, strict=True)])

    def assembled(self, given: list[tuple[str, dict[int, Chunk]]]) -> list[np.ndarray]:
        """Ids of texts of which some chunks, by their place, are known. Stretches between these are encoded as they are."""
        plans: list[list] = []
        fresh: list[str] = []
        whole: list[str] = []
        for text, known in given:
            plan: list = []
            if known:
                held = ""
                for i, c in enumerate(chunks(text, self.bits)):
                    if i not in known:
                        held += c
                        continue
                    if held:
                        plan.append(len(fresh))
                        fresh.append(held)
                        held = ""
                    plan.append(Chunk(c, known[i].ids, known[i].piece_at, known[i].id_at))
                if held:
                    plan.append(len(fresh))
                    fresh.append(held)
            else:
                whole.append(text)
            plans.append(plan)
        parts, plain = self.parts(fresh), iter(self.units.encode(whole))
        return [self._join([parts[x] if isinstance(x, int) else x for x in plan]) if plan else next(plain) for plan in plans]

    def _edges(self, text: str, ids: np.ndarray, reach: int = 192) -> tuple[np.ndarray, np.ndarray]:
        """Piece starts near both ends of the text, in characters and in ids.

        Only these can matter for joins; a join that needs more asks for all (``reach`` of the whole text).
        """
        ends = np.cumsum(self.units.token_sizes[ids])
        head, tail = text[:reach], text[-reach:]
        if len(text) <= 2 * reach:
            starts = np.array([a for a, _ in self._pieces(text)], dtype=np.int64)
        else:
            front = [a for a, _ in self._pieces(head) if a <= reach - UNSURE]
            # the tail is read from a blank that certainly starts a piece
            sure = next((k for k in range(len(tail) - 1) if tail[k] == " " and not tail[k + 1].isspace()), None)
            back = [] if sure is None else [len(text) - len(tail) + sure + a for a, _ in self._pieces(tail[sure:])]
            if sure is None:
                return self._edges(text, ids, len(text))
            starts = np.array(front + back, dtype=np.int64)
        # byte place of each start, then the id that begins there
        if text.isascii():
            at = starts
        else:
            raw = np.frombuffer(text.encode(), dtype=np.uint8)
            at = np.append(np.flatnonzero((raw & 0xC0) != 0x80), len(raw))[starts]
        return starts, np.searchsorted(ends, at, side="right")

    def _join(self, chunks: list[Chunk]) -> np.ndarray:
        """Ids of the chunks' joined text."""
        if not chunks:
            return np.zeros(0, dtype=np.uint32)
        ids, now = [], chunks[0]
        for nxt in chunks[1:]:
            kept, now = self._repair(now, nxt)
            ids.append(kept)
        return np.concatenate([*ids, now.ids]) if ids else now.ids

    def _repair(self, left: Chunk, right: Chunk) -> tuple[np.ndarray, Chunk]:
        """Ids that hold whatever follows ``right``, and the rest as a chunk that starts at a certain piece boundary."""
        self.repaired += 1
        sure = np.flatnonzero(left.piece_at <= max(0, len(left.text) - UNSURE))
        k = int(sure[-1]) if len(sure) else 0
        start, first_id = (int(left.piece_at[k]), int(left.id_at[k])) if len(left.piece_at) else (0, 0)
        tail = left.text[start:]
        meets = dict(zip((right.piece_at + len(tail)).tolist(), right.id_at.tolist(), strict=True))
        reach = 48
        while reach < len(right.text):
            window = tail + right.text[:reach]
            for at, _ in self._pieces(window):
                if at >= len(tail) and at in meets and at <= len(window) - UNSURE:
                    again = self.units.encode([window])[0]
                    again = again[: np.searchsorted(np.cumsum(self.units.token_sizes[again]), len(window[:at].encode()), side="right")]
                    cut, skipped = at - len(tail), meets[at]
                    keep = right.piece_at >= cut
                    rest = Chunk(right.text[cut:], right.ids[skipped:], right.piece_at[keep] - cut, right.id_at[keep] - skipped)
                    return np.concatenate([left.ids[:first_id], again]), rest
            reach *= 2
        text = tail + right.text  # no agreement in this chunk: both are one from here on
        ids = self.units.encode([text])[0]
        return left.ids[:first_id], Chunk(text, ids, *self._edges(text, ids))

    def decode(self, ids: np.ndarray) -> str:
        return self.decoder.decode(ids)


_held: dict[tuple, ChunkEncoder] = {}


def chunk_encoder(path: str | None = None, bits: int = CHUNK_BITS) -> ChunkEncoder:
    """One encoder per Python worker, vocabulary file and chunk size."""
    if (path, bits) not in _held:
        _held[path, bits] = ChunkEncoder(path, bits)
    return _held[path, bits]


def repeated_chunks(docs: DataFrame, text: str = "text", bits: int = CHUNK_BITS) -> np.ndarray:
    """The bitmap, as bytes, in which the digest of every chunk that occurs twice or more has its bit set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, 0):
            found: dict[bytes, int] = {}
            for t in batch.column(0).to_pylist():
                for c in chunks(t or "", bits):
                    d = digest(c)
                    found[d] = found.get(d, 0) + 1
            yield pa.RecordBatch.from_arrays([pa.array(found.keys(), pa.binary()), pa.array(found.values(), pa.int64())], names=["digest", "n"])

    counts = docs.select(F.col(text).alias("text")).mapInArrow(run, "digest binary, n long").groupBy("digest").agg(F.sum("n").alias("n"))
    slot = F.conv(F.hex(F.substring("digest", 1, 4)), 16, 10).cast("long") % (1 << MARK_BITS) + 1
    marked = counts.filter("n > 1").select(slot.alias("slot"))
    parts = marked.groupBy(F.bitmap_bucket_number("slot").alias("part")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("slot")).alias("bits"))
    out = np.zeros((1 << MARK_BITS) // 8, dtype=np.uint8)
    for row in parts.toLocalIterator():  # 4096 bytes each
        at = (row.part - 1) * 4096
        out[at : at + 4096] = np.frombuffer(bytes(row.bits), dtype=np.uint8)
    return out


def is_marked(bitmap: np.ndarray, name: bytes) -> bool:
    slot = int.from_bytes(name[:4], "big") % (1 << MARK_BITS)
    return bool(bitmap[slot >> 3] >> (slot & 7) & 1)


def _made(docs: DataFrame, key: str, text: str, path: str | None, bits: int, finish, columns: str) -> DataFrame:
    """(key, columns) of every row, ``finish`` making the columns' values from an encoder and a text's ids."""
    spark = docs.sparkSession
    kind = docs.schema[key].dataType.simpleString()
    scratch, bitmap = Scratch(spark, "chunks"), spark.sparkContext.broadcast(repeated_chunks(docs, text, bits))
    names = [c.split()[0] for c in columns.split(", ")]
    held_schema = f"step int, row long, pos int, digest binary, text string, key {kind}, {columns}"
    types = pa.schema([("step", pa.int32()), ("row", pa.int64()), ("pos", pa.int32()), ("digest", pa.binary()), ("text", pa.string())])
    out_types = {"long": pa.int64(), "string": pa.string(), "binary": pa.binary()}
    made_types = [out_types[c.split()[1]] for c in columns.split(", ")]

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Step 0: finished rows. Step 1: texts to be put together. Step 2: a place (row, pos) and its chunk. Step 3: a chunk's text."""
        from pyspark import TaskContext

        held, number, given = chunk_encoder(path, bits), TaskContext.get().partitionId() << 33, set()
        for batch in slices(batches):
            texts = batch.column(1).to_pylist()
            steps: list[tuple] = []  # step, row, pos, digest, text, place of the key
            plain: list[int] = []
            for i, t in enumerate(texts):
                named = [] if not t or held.special in t else [(p, c, digest(c)) for p, c in enumerate(chunks(t, bits))]
                marked = [x for x in named if is_marked(bitmap.value, x[2])]
                if not marked:
                    plain.append(i)
                    continue
                number += 1
                steps.append((1, number, -1, None, t, i))
                for p, c, d in marked:
                    steps.append((2, number, p, d, None, None))
                    if d not in given:
                        given.add(d)
                        steps.append((3, None, None, d, c, None))
            done = [finish(held, ids) for ids in held.units.encode([texts[i] or "" for i in plain])]
            steps += [(0, None, None, None, None, i) for i in plain]
            cells = [pa.array([s[k] for s in steps], type=types.field(k).type) for k in range(5)]
            blank = len(steps) - len(plain)
            made = [pa.array([None] * blank + [d[k] for d in done], type=made_types[k]) for k in range(len(names))]
            yield pa.RecordBatch.from_arrays([*cells, batch.column(0).take(pa.array([s[5] for s in steps], pa.int64())), *made], names=[*types.names, "key", *names])

    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = chunk_encoder(path, bits)
        for batch in slices(batches):
            known = held.parts(batch.column(1).to_pylist())
            cells = [pa.array([getattr(c, f).astype("<u4").tobytes() for c in known], pa.binary()) for f in ("ids", "piece_at", "id_at")]
            yield pa.RecordBatch.from_arrays([batch.column(0), *cells], names=["digest", "ids", "piece_at", "id_at"])

    def together(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by row and pos: a text, then its known chunks. A text is put together when the next begins."""
        held = chunk_encoder(path, bits)
        waiting: list[tuple] = []  # key, text, known
        size = 0

        def ready(rows: list[tuple]) -> pa.RecordBatch:
            done = [finish(held, ids) for ids in held.assembled([(t, known) for _, t, known in rows])]
            return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], type=key_type), *(pa.array([d[k] for d in done], type=made_types[k]) for k in range(len(names)))], names=["key", *names])

        key_type = None
        for batch in batches:
            key_type = batch.column(2).type
            cols = [batch.column(k).to_pylist() for k in range(7)]
            for _, pos, name, text, ids, piece_at, id_at in zip(*cols, strict=True):
                if pos < 0:
                    if size > 2_000_000:
                        yield ready(waiting)
                        waiting, size = [], 0
                    waiting.append((name, text, {}))
                    size += len(text)
                else:
                    waiting[-1][2][pos] = KnownIds(*(np.frombuffer(x, dtype="<u4") for x in (ids, piece_at, id_at)))
        if waiting:
            yield ready(waiting)

    steps = scratch.write(docs.select(F.col(key).alias("key"), F.col(text).alias("text")).mapInArrow(first, held_schema), "steps")
    known = scratch.write(steps.filter("step = 3").groupBy("digest").agg(F.first("text").alias("text")).mapInArrow(learn, "digest binary, ids binary, piece_at binary, id_at binary"), "known")
    needs = steps.filter("step = 2").select("row", "pos", "digest").join(known, "digest").select("row", "pos", F.lit(None).cast(kind).alias("key"), F.lit(None).cast("string").alias("text"), "ids", "piece_at", "id_at")
    none = F.lit(None).cast("binary")
    texts = steps.filter("step = 1").select("row", "pos", "key", "text", none.alias("ids"), none.alias("piece_at"), none.alias("id_at"))
    joined = texts.unionByName(needs).repartition("row").sortWithinPartitions("row", "pos").mapInArrow(together, f"key {kind}, {columns}")
    return steps.filter("step = 0").select("key", *names).unionByName(joined).withColumnRenamed("key", key)


def encode(docs: DataFrame, key: str = "doc_id", text: str = "text", path: str | None = None, bits: int = CHUNK_BITS) -> DataFrame:
    """(key, ids): ids as little-endian unsigned 32-bit integers."""
    return _made(docs, key, text, path, bits, lambda held, ids: (ids.astype("<u4").tobytes(),), "ids binary")


def decode(encoded: DataFrame, key: str = "doc_id", ids: str = "ids", path: str | None = None) -> DataFrame:
    """(key, text) from ids as ``encode`` gives them."""
    kind = encoded.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [chunk_encoder(path).decode(np.frombuffer(x or b"", dtype="<u4")) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, type=pa.string())], names=["key", "text"])

    return encoded.select(F.col(key).alias("key"), F.col(ids).alias("ids")).mapInArrow(run, f"key {kind}, text string").withColumnRenamed("key", key)


def round_trip(docs: DataFrame, key: str = "doc_id", text: str = "text", path: str | None = None, bits: int = CHUNK_BITS) -> DataFrame:
    """Digests of ids and decoded text; both are made in one task, so that neither is sent on."""

    def digests(held: ChunkEncoder, ids: np.ndarray) -> tuple:
        return len(ids), hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest(), hashlib.sha256(held.decode(ids).encode()).hexdigest()

    return _made(docs, key, text, path, bits, digests, "n_tokens long, ids_sha256 string, decoded_sha256 string")


def op4_chunk_reuse(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_trip(documents(spark, sf_dir))
