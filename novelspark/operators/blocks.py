"""The detectors' search by blocks: every block of queries meets every block of the history in one task.

A block of queries holds whole batches, one after another, with the changes of the model in between, so that the task weighs its part of
the history anew for each batch in memory. Neither the history as each batch weighs it nor a row a pair is ever shuffled: what leaves a task
is the nearest of each query, and blocks' nearest meet in one aggregate.
"""

from __future__ import annotations

import ctypes
import hashlib
import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import lsh, model, similarity

#: Terms of documents in a block of queries, and of the history (fewer where it is hashed, since signs of all its terms are held).
QUERY_TERMS, HISTORY_TERMS, HASHED_TERMS = 1 << 17, 1 << 19, 1 << 18
#: From so many blocks of queries on they get larger, up to so many terms: the history is copied once a block of queries.
QUERY_BLOCKS, MOST_TERMS = 16, 1 << 19
#: Terms of a model row; numbers in the columns of the commonest terms; numbers of a chunk of products.
SHARDS, DENSE, CHUNK = 16, 1 << 21, 1 << 19


def weighed(tf: DataFrame, changes: DataFrame, sizes: DataFrame, cfg, by: tuple[str, ...]) -> DataFrame:
    """Raw weights (by, batch_id, doc_id, term, x) of the queries. A query's term changes the growing models in the query's own batch."""
    held = changes.select(*by, "term", "idf", "cf", "df", *([] if cfg.scheme == "static" else [F.col("since").alias("batch_id")]))
    met = tf.filter("batch_id > 0").join(held, [*by, "term"] if cfg.scheme == "static" else [*by, "term", "batch_id"])
    if cfg.scheme == "merged":
        met = met.join(F.broadcast(sizes.select(*by, "batch_id", "n")), [*by, "batch_id"]).withColumn("idf", model.log(F.col("n") / F.col("df"), cfg.base))
    return met.select(*by, "batch_id", "doc_id", "term", (model.damped(F.col("tf"), cfg.tf_mode, cfg.base, F.col("cf")) * F.col("idf")).alias("x"))


def _entries(*columns: str):
    """Sorted, so that a row is the same whatever the order in which its entries came."""
    return F.sort_array(F.collect_list(F.struct("term", *columns)))


def _dealt(tf: DataFrame, queries: DataFrame, changes: DataFrame, sizes: DataFrame, history: DataFrame, cfg, by: tuple[str, ...], history_terms: int) -> tuple[DataFrame, DataFrame, list[str]]:
    """Both sides of the blocks with their keys: queries and model changes, and the history."""
    keys = [*by, "g", "part", "hb"]
    on = lambda a, b: a.join(F.broadcast(b), list(by)) if by else a.join(F.broadcast(b))
    # blocks of queries: one row a batch
    posts = tf.filter("batch_id > 0").groupBy(*by, "batch_id").agg(F.count("*").alias("c"))
    before = lambda batch: W.partitionBy(*by).orderBy(batch).rowsBetween(W.unboundedPreceding, -1)
    batches = sizes.join(posts, [*by, "batch_id"], "left").withColumn("c", F.coalesce("c", F.lit(0)))
    batches = batches.withColumn("most", F.greatest(F.lit(QUERY_TERMS), F.least(F.ceil(F.sum("c").over(W.partitionBy(*by)) / QUERY_BLOCKS), F.lit(MOST_TERMS))))
    batches = batches.select(*by, "batch_id", "n", F.floor(F.coalesce(F.sum("c").over(before("batch_id")), F.lit(0)) / F.col("most")).alias("g"), F.greatest(F.ceil(F.col("c") / F.col("most")), F.lit(1).cast("bigint")).alias("parts"))
    groups = batches.groupBy(*by, "g").agg(F.min("batch_id").alias("low"), F.max("batch_id").alias("high"), F.max("parts").alias("parts"))
    # blocks of the history in the order of arrival, so that queries are not sent to blocks that are all later
    if "cluster" in history.columns:
        # a centroid is made where all of its cluster lies, placed by its first document
        history = history.withColumn("at", F.min("own").over(W.partitionBy(*by, "cluster")))
    else:
        history = history.withColumn("at", F.col("own"))
    came = history.groupBy(*by, "at").agg(F.sum("size").alias("s"))
    came = came.select(*by, "at", "s", F.coalesce(F.sum("s").over(before("at")), F.lit(0)).alias("from"))
    within = F.pmod(F.xxhash64("cluster" if "cluster" in history.columns else "doc_id"), F.lit(1 << 20)) / float(1 << 20)
    placed = history.join(F.broadcast(came), [*by, "at"]).withColumn("hb", F.floor((F.col("from") + within * F.col("s")) / history_terms)).drop("from", "s", "at")
    pairs = on(placed.groupBy(*by, "hb").agg(F.min("own").alias("first")), groups).filter("first <= high").select(*by, "g", "hb", "parts")
    none = lambda kind: F.lit(None).cast(kind)
    q = queries.join(F.broadcast(batches), [*by, "batch_id"]).withColumn("part", F.pmod(F.xxhash64("doc_id"), F.col("parts")))
    q = q.drop("parts").join(F.broadcast(pairs.drop("parts")), [*by, "g"]).select(*by, "g", "part", "hb", F.col("doc_id").alias("id"), "batch_id", F.col("n").cast("double").alias("n"), "sq", "bands", F.col("e.term").alias("terms"), F.col("e.x").alias("xs"), none("array<double>").alias("ys"))
    # a change holds from its batch until the next of its term: in all blocks of queries that this time touches
    at = lambda name, g: batches.select(*by, F.col("batch_id").alias(name), F.col("g").alias(g))
    last = batches.groupBy(*by).agg(F.max("g").alias("g_last"))
    held = placed.select(*by, "hb", F.explode("e.term").alias("term")).groupBy(*by, "term").agg(F.collect_set("hb").alias("hbs"))
    m = changes.join(held, [*by, "term"]).join(F.broadcast(at("since", "g_since")), [*by, "since"]).join(F.broadcast(at("next", "g_next")), [*by, "next"], "left")
    m = on(m, last).withColumn("g", F.explode(F.sequence("g_since", F.coalesce("g_next", "g_last")))).join(F.broadcast(groups.drop("parts", "high")), [*by, "g"]).filter("next IS NULL OR next > low")
    value = F.col("df" if cfg.scheme == "merged" else "idf").cast("double").alias("v")
    # a block of the history is sent the changes of its own terms only, most of which no other block holds; products need no counts
    counts = ["cf"] if cfg.tf_mode == "collection" else []
    m = m.withColumn("hb", F.explode("hbs")).join(F.broadcast(pairs), [*by, "g", "hb"])
    m = m.select(*by, "g", "parts", "hb", F.greatest("since", "low").alias("since"), "term", value, *[F.col(c).cast("double").alias(c) for c in counts], F.pmod(F.xxhash64("term"), F.lit(SHARDS)).alias("shard"))
    m = m.groupBy(*by, "g", "parts", "hb", "since", "shard").agg(_entries("v", *counts).alias("e"))
    ys = F.col("e.cf") if counts else none("array<double>")
    m = m.select(*by, "g", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("parts") - 1)).alias("part"), "hb", none("bigint").alias("id"), F.col("since").alias("batch_id"), none("double").alias("n"), none("double").alias("sq"), none("array<bigint>").alias("bands"), F.col("e.term").alias("terms"), F.col("e.v").alias("xs"), ys.alias("ys"))
    h = placed.join(F.broadcast(pairs), [*by, "hb"]).withColumn("part", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("parts") - 1)))
    extra = [c for c in ("cluster",) if c in h.columns]
    return q.unionByName(m), h.select(*keys, F.col("doc_id").alias("h"), "own", F.col("e.term").alias("terms"), F.col("e.tf").alias("tfs"), *extra), keys


def _flat(column: pa.ChunkedArray, kind: pa.DataType) -> tuple[pa.Array, np.ndarray]:
    """The values of an array column, and where each row's begin, with the end."""
    parts = [c.fill_null([]) if c.null_count else c for c in column.chunks] or [pa.array([], pa.list_(kind))]
    lengths = np.concatenate([pc.list_value_length(c).to_numpy(zero_copy_only=False) for c in parts]).astype("int64")
    flat = pa.chunked_array([c.flatten().cast(kind) for c in parts], kind).combine_chunks()
    return flat, np.concatenate([[0], np.cumsum(lengths)])


def _signs(terms: pa.Array, planes: int, seed: int) -> np.ndarray:
    """(terms, lanes): signs of two planes in a number, 32 bits each, read from the same digests as in ``lsh``."""
    bits = np.zeros((len(terms), planes + planes % 2), dtype="int64")
    for i, term in enumerate(terms.to_pylist()):
        digest = b"".join(hashlib.md5(f"{term}|{seed}|{b}".encode()).digest() for b in range(-(-planes // lsh.PER_DIGEST)))
        # words are read from the left, bits of a word from the right
        words = np.frombuffer(digest, dtype=">u4").astype("<u4")
        bits[i, :planes] = np.unpackbits(words.view("u1"), bitorder="little")[:planes]
    return bits[:, 0::2] | bits[:, 1::2] << 32


def query_bands(terms: pa.ListArray, xs: pa.ListArray, k: int, tables: int, seed: int) -> pa.Array:
    """Bucket numbers of each row's terms and weights, as ``lsh.signatures`` gives them; null where nothing weighs."""
    out, planes = [None] * len(terms), k * tables
    coded = terms.flatten().dictionary_encode()
    codes, starts = coded.indices.to_numpy(), np.concatenate([[0], np.cumsum(terms.value_lengths().to_numpy(zero_copy_only=False))])
    x = xs.flatten().to_numpy()
    q, some = half_up(x * lsh.QUANT, 0).astype("int64"), np.concatenate([[0], np.cumsum(x != 0)])
    held = np.flatnonzero(some[starts[1:]] > some[starts[:-1]])
    if len(held):
        # rows without terms lie between the others and take nothing from them
        at, signs = starts[:-1][held], _signs(coded.dictionary, planes, seed)
        q[np.repeat(~np.isin(np.arange(len(terms)), held), np.diff(starts))] = 0
        total, bands = np.add.reduceat(q, at), np.zeros((len(held), tables), dtype="int64")
        for p in range(planes):
            s = np.add.reduceat(q * (signs[:, p // 2] >> 32 * (p % 2) & 1)[codes], at)
            bands[:, p // k] |= (s * 2 >= total).astype("int64") << (p % k)
        for i, row in zip(held, bands.tolist()):
            out[i] = row
    return pa.array(out, pa.list_(pa.int64()))


def give_back() -> None:
    """Returns a worker's freed memory to the system: workers live on between tasks, beside the executor's heap."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def half_up(x: np.ndarray, digits: int = similarity.DIGITS) -> np.ndarray:
    return np.floor(x * 10.0**digits + 0.5) / 10.0**digits


class _History:
    """One block of the history: terms in the order of its documents and in the order of terms, and its weights under a batch's model."""

    def __init__(self, right: pa.Table, codes: np.ndarray, starts: np.ndarray, tfs: np.ndarray, vocabulary: pa.Array, cfg):
        self.cfg = cfg
        self.ids, self.own = (right[c].to_numpy().astype("int64") for c in ("h", "own"))
        self.codes, self.starts, n = codes, starts[:-1], len(self.ids)
        damp = {"raw": tfs, "collection": np.ones(len(tfs))}.get(cfg.tf_mode)
        damp = damp if damp is not None else (np.log10(tfs) if cfg.base == 10 else np.log(tfs) / math.log(cfg.base)) + 1.0
        self.damp, rows = damp.astype("float64"), np.repeat(np.arange(n), np.diff(starts))
        order = np.argsort(codes, kind="stable")
        self.rows, self.by_term = rows[order], self.damp[order]
        counts = np.bincount(codes, minlength=len(vocabulary))
        self.at = np.concatenate([[0], np.cumsum(counts)])
        common = np.argsort(-counts, kind="stable")[: max(DENSE // max(n, 1), 1)]
        common = common[counts[common] * 8 >= max(n, 8)]
        self.column = np.full(len(vocabulary), -1)
        self.column[common] = np.arange(len(common))
        self.dense = np.zeros((len(common), n))
        for i, c in enumerate(common):
            self.dense[i, self.rows[self.at[c] : self.at[c + 1]]] = self.by_term[self.at[c] : self.at[c + 1]]
        if cfg.search == "lsh":
            self.signs = _signs(vocabulary, cfg.k * cfg.tables, cfg.seed)

    def weigh(self, w: np.ndarray, batch: int) -> None:
        """Lengths and signatures under the weights ``w`` of the terms, which are those of a batch."""
        x = self.damp * w[self.codes]
        length = np.sqrt(np.add.reduceat(x * x, self.starts))
        self.w, self.some = w, length > 0
        self.scale = np.divide(1.0, length, out=np.zeros_like(length), where=self.some)
        if self.cfg.search != "lsh":
            return
        q, k, tables = half_up(x * lsh.QUANT, 0).astype("int64"), self.cfg.k, self.cfg.tables
        total = np.add.reduceat(q, self.starts)
        # two planes share a number while a sum fits in 32 bits; idf that are added up batch by batch outgrow that
        narrow = not len(total) or total.max() < 1 << 32
        self.bands = np.zeros((tables, len(total)), dtype="int64")
        for lane in range(self.signs.shape[1]):
            signs = self.signs[:, lane]
            if narrow:
                both = np.add.reduceat(q * signs[self.codes], self.starts)
                sums = both & 0xFFFFFFFF, both >> 32 & 0xFFFFFFFF
            else:
                sums = (np.add.reduceat(q * (signs >> at & 1)[self.codes], self.starts) for at in (0, 32))
            for p, s in zip((2 * lane, 2 * lane + 1), sums):
                if p < k * tables:
                    self.bands[p // k] |= (s * 2 >= total).astype("int64") << (p % k)
        # every query is held against all of them, so they are as narrow as their bits allow
        self.bands = self.bands.astype(np.min_scalar_type((1 << k) - 1))

    def cosines(self, terms: list[np.ndarray], xs: list[np.ndarray], lengths: np.ndarray) -> np.ndarray:
        out = np.zeros((len(terms), len(self.scale)))
        few = np.zeros((len(terms), len(self.dense)))
        for i, (t, x) in enumerate(zip(terms, xs)):
            for c, y in zip(t.tolist(), (x * self.w[t]).tolist()):
                if self.column[c] >= 0:
                    few[i, self.column[c]] = y
                elif (b := self.at[c]) < (e := self.at[c + 1]):
                    out[i, self.rows[b:e]] += y * self.by_term[b:e]
        out += few @ self.dense
        out *= self.scale
        return np.divide(out, lengths[:, None], out=np.zeros_like(out), where=lengths[:, None] > 0)


class _Clusters(_History):
    """A block of whole clusters: ``ids`` are theirs, and cosines those of their centroids, the means of the unit vectors of documents so far."""

    def __init__(self, right: pa.Table, codes: np.ndarray, starts: np.ndarray, tfs: np.ndarray, vocabulary: pa.Array, cfg):
        super().__init__(right, codes, starts, tfs, vocabulary, cfg)
        cluster = right["cluster"].to_numpy().astype("int64")
        self.came, self.firsts = self.own, np.flatnonzero(np.concatenate([[True], np.diff(cluster) != 0]))
        self.ids, self.own = cluster[self.firsts], np.minimum.reduceat(self.came, self.firsts)
        self.place = np.repeat(np.arange(len(self.ids)), np.diff(np.concatenate([self.firsts, [len(cluster)]])))
        # only terms that several documents of a cluster hold make its centroid's length differ from theirs
        rows = np.repeat(np.arange(len(cluster)), np.diff(starts))
        key = self.place[rows] * len(vocabulary) + codes
        order = np.argsort(key, kind="stable")
        of, count = np.unique(key[order], return_counts=True)
        self.shared = order[np.repeat(count > 1, count)]
        self.rows_shared, self.of = rows[self.shared], of[count > 1] // max(len(vocabulary), 1)
        self.begin = np.concatenate([[0], np.cumsum(count[count > 1])])[:-1]

    def weigh(self, w: np.ndarray, batch: int) -> None:
        super().weigh(w, batch)
        self.scale = np.where(self.came <= batch, self.scale, 0.0)
        n = len(self.ids)
        square = np.bincount(self.place, self.scale > 0, n)
        if len(self.shared):
            u = self.damp[self.shared] * w[self.codes[self.shared]] * self.scale[self.rows_shared]
            both = np.add.reduceat(u, self.begin)
            square += np.bincount(self.of, both * both, n) - np.bincount(self.place[self.rows_shared], u * u, n)
        length = np.sqrt(np.maximum(square, 0.0))
        self.mean = np.divide(1.0, length, out=np.zeros(n), where=length > 0)

    def cosines(self, terms: list[np.ndarray], xs: list[np.ndarray], lengths: np.ndarray) -> np.ndarray:
        return np.add.reduceat(super().cosines(terms, xs, lengths), self.firsts, axis=1) * self.mean


def _step(cfg, streams: int, what: str):
    """The function of a pair of blocks. ``what``: nearest, tables (one row a query and table), or work (counted pairs)."""
    hashed, capped, clustered = cfg.search == "lsh", cfg.bucket_cap, cfg.target == "centroid"
    names = {"nearest": ("q", "h", "value"), "tables": ("q", "h", "value", "table_no"), "work": ("hashed", "joined")}[what]
    types = {"value": pa.float64(), "table_no": pa.int32()}

    def step(key, left: pa.Table, right: pa.Table) -> pa.Table:
        found = {c: [] for c in names}
        kind = left["id"].is_null().to_numpy() if len(left) else np.zeros(0, dtype=bool)
        if len(right) and not kind.all():
            search(left, right.sort_by([("cluster", "ascending"), ("h", "ascending")] if clustered else "h"), kind, found)
        out = {c: pa.array(np.concatenate(v) if v else [], types.get(c, pa.int64())) for c, v in found.items()}
        rows = len(out[names[0]])
        give_back()
        return pa.table({**{f"k{i}": pa.array([key[i].as_py()] * rows, pa.string()) for i in range(streams)}, **out})

    def search(left: pa.Table, right: pa.Table, is_model: np.ndarray, found: dict) -> None:
        h_terms, h_at = _flat(right["terms"], pa.string())
        l_terms, l_at = _flat(left["terms"], pa.string())
        coded = pa.chunked_array([h_terms, l_terms]).combine_chunks().dictionary_encode()
        codes, (xs, _), (ys, _) = coded.indices.to_numpy(), _flat(left["xs"], pa.float64()), _flat(left["ys"], pa.float64())
        h_codes, l_codes, xs, ys = codes[: len(h_terms)], codes[len(h_terms) :], xs.to_numpy(), ys.to_numpy()
        width = int(h_codes.max()) + 1  # codes go by first sight, the history's first
        block = (_Clusters if clustered else _History)(right, h_codes, h_at, _flat(right["tfs"], pa.float64())[0].to_numpy(), coded.dictionary[:width], cfg)
        batch = left["batch_id"].to_numpy()
        value, cf = np.zeros(width), np.zeros(width)
        # only model rows have ys: they come in the order of rows
        y_at = np.concatenate([[0], np.cumsum(np.where(is_model, np.diff(l_at), 0))])
        changes = sorted(np.flatnonzero(is_model), key=lambda r: batch[r])
        n, sq = (left[c].to_numpy() for c in ("n", "sq"))
        queries, done = np.flatnonzero(~is_model), 0
        ids, bands = left["id"].fill_null(0).to_numpy(), left["bands"].to_pylist() if hashed else None
        queries = queries[np.lexsort((ids[queries], batch[queries]))]
        ends = np.flatnonzero(np.diff(batch[queries])) + 1
        for own in np.split(queries, ends):
            b, fresh = batch[own[0]], False
            while done < len(changes) and batch[changes[done]] <= b:
                r = changes[done]
                c, y = l_codes[l_at[r] : l_at[r + 1]], slice(y_at[r], y_at[r + 1])
                inside = c < width
                value[c[inside]] = xs[l_at[r] : l_at[r + 1]][inside]
                if cfg.tf_mode == "collection":
                    cf[c[inside]] = ys[y][inside]
                done, fresh = done + 1, True
            if fresh or cfg.scheme == "merged" or not hasattr(block, "w") or (clustered and cfg.history == "all_seen"):
                w = value
                if cfg.scheme == "merged":
                    ratio = np.divide(n[own[0]], value, out=np.ones(width), where=value > 0)
                    w = np.log10(ratio) if cfg.base == 10 else np.log(ratio) / math.log(cfg.base)
                block.weigh(w * cf if cfg.tf_mode == "collection" else w.copy(), b)
            size = max(CHUNK // len(block.scale), 1)
            for part in (own[i : i + size] for i in range(0, len(own), size)):
                at = [slice(l_at[r], l_at[r + 1]) for r in part]
                kept = [l_codes[s] < width for s in at]
                similar = None
                if cfg.distance != "hamming":
                    similar = block.cosines([l_codes[s][k] for s, k in zip(at, kept)], [xs[s][k] for s, k in zip(at, kept)], np.sqrt(sq[part]))
                for i, r in enumerate(part):
                    seen = block.own <= b
                    if hashed:
                        if bands[r] is None:
                            continue
                        same = block.bands == np.asarray(bands[r], dtype=block.bands.dtype)[:, None]
                        seen = same if seen.all() and block.some.all() else same & seen & block.some
                    take(ids[r], bands[r] if hashed else None, None if similar is None else similar[i], block, seen, found)

    def take(q: int, bands: list | None, similar: np.ndarray | None, block: _History, seen: np.ndarray, found: dict) -> None:
        earlier = np.full(len(block.ids), True) if clustered else block.ids < q

        def put(h: np.ndarray, values: np.ndarray, table: int | None = None) -> None:
            found["q"].append(np.full(len(h), q))
            found["h"].append(block.ids[h])
            found["value"].append(values)
            if table is not None:
                found["table_no"].append(np.full(len(h), table))

        if what == "work":
            found["hashed"].append(np.array([np.count_nonzero(seen.any(axis=0) & earlier)]))
            found["joined"].append(np.array([np.count_nonzero((similar > 0) & earlier)]))
        elif what == "tables":
            for t in range(cfg.tables):
                met = np.flatnonzero(seen[t])
                # the newest of a bucket are those of all blocks, whether earlier or not
                met = met[-capped:] if capped else met[earlier[met]]
                if not len(met):
                    continue
                values = similar[met]
                if not capped:
                    best = np.lexsort((met, half_up(1 - values)))[:1]
                    met, values = met[best], values[best]
                put(met, values, t)
        else:
            met = np.flatnonzero((seen.any(axis=0) if hashed else seen) & earlier)
            if not len(met):
                return
            if cfg.distance == "hamming":
                differing = np.bitwise_count(block.bands[:, met] ^ np.asarray(bands, dtype=block.bands.dtype)[:, None]).sum(axis=0, dtype="int64")
                best = met[differing.argmin()]
                put(np.array([best]), np.array([float(differing.min())]))
                return
            top = similar[met].max()
            if top > 0:
                near = met[similar[met] >= min(top, 1.0) - 3e-6]
                far = half_up(1 - np.minimum(similar[near], 1.0))
                best = near[far.argmin()]
                put(np.array([best]), similar[np.array([best])])

    return step


def search(tf: DataFrame, changes: DataFrame, sizes: DataFrame, history: DataFrame, cfg, by: tuple[str, ...], write, more: DataFrame | None = None, what: str = "nearest", clusters: DataFrame | None = None) -> DataFrame:
    """(by, q, h, value) of each query's nearest in every block of the history, or what ``_step`` says.

    Counts, changes and sizes are written tables; ``history`` is (by, doc_id, own, term, tf), ``more`` what unknown words add to a query's squared length.
    With ``clusters`` (by, doc_id, cluster) only their documents are history, and ``h`` is the cluster whose centroid is nearest. A cluster lies in one block.
    """
    x = weighed(tf, changes, sizes, cfg, by)
    queries = x.groupBy(*by, "batch_id", "doc_id").agg(F.sum(F.col("x") * F.col("x")).alias("sq"), _entries("x").alias("e"))
    if more is not None:
        queries = queries.join(more, [*by, "batch_id", "doc_id"], "left").withColumn("sq", F.col("sq") + F.coalesce("more", F.lit(0.0)))
    bands = F.lit(None).cast("array<bigint>")
    if cfg.search == "lsh":
        # a query's terms lie in one row by now, so its projections are summed where it is and no row a plane is sent
        k, tables, seed = cfg.k, cfg.tables, cfg.seed

        @F.arrow_udf("array<bigint>")
        def signed(terms: pa.Array, xs: pa.Array) -> pa.Array:
            return query_bands(terms, xs, k, tables, seed)

        bands = signed("e.term", "e.x")
    queries = queries.withColumn("bands", bands)
    past = history.groupBy(*by, "doc_id", "own").agg(F.count("*").alias("size"), _entries("tf").alias("e"))
    past = write(past if clusters is None else past.join(clusters, [*by, "doc_id"]), "history")
    left, right, keys = _dealt(tf, queries, changes, sizes, past, cfg, by, HASHED_TERMS if cfg.search == "lsh" else HISTORY_TERMS)
    columns = {"nearest": "q bigint, h bigint, value double", "tables": "q bigint, h bigint, value double, table_no int", "work": "hashed bigint, joined bigint"}[what]
    schema = ", ".join([*[f"k{i} string" for i in range(len(by))], columns])
    # both sides come of the same tables: new names for their columns keep them apart
    out = left.toDF(*left.columns).groupBy(*keys).cogroup(right.toDF(*right.columns).groupBy(*keys)).applyInArrow(_step(cfg, len(by), what), schema)
    return out.withColumnsRenamed({f"k{i}": c for i, c in enumerate(by)})
