"""Searches of all rows over whole texts, by packed blocks.

A block is some thousand documents in one compressed value: the places of their terms in the block's own vocabulary, and counts. A term travels as a
word once a block, in parts by hash where the blocks' counts meet; what comes back are numbers in the order of the block's vocabulary. Ids are unique.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..sources.scratch import Scratch
from . import model
from .blocks import give_back
from .similarity import CHUNK, DIGITS, _Rows, distances, flat, unit_rows

#: Terms of a block, fewer where that would give less than so many blocks; blocks that meet another one in the same task.
TERMS, BLOCKS, GROUP = 1 << 21, 12, 4
NONE = np.iinfo("int64").max


def lists(values: pa.Array | np.ndarray, cuts: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.asarray(cuts).astype("int32")), values if isinstance(values, pa.Array) else pa.array(values))


def grouped(step):
    """``step`` on a group's rows, after which the worker's freed memory goes back to the system."""

    def run(table: pa.Table) -> pa.Table:
        out = step(table)
        give_back()
        return out

    return run


def paired(step):
    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        out = step(left, right)
        give_back()
        return out

    return run


def packed(columns: dict[str, pa.Array | np.ndarray]) -> bytes:
    """Columns of any lengths as one compressed value."""
    batch = pa.RecordBatch.from_arrays([lists(c, np.array([0, len(c)])) for c in columns.values()], list(columns))
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_batch(batch)
    return sink.getvalue().to_pybytes()


def unpacked(blob: pa.Scalar) -> dict[str, pa.Array]:
    batch = pa.ipc.open_stream(blob.as_buffer()).read_next_batch()
    return {name: column.flatten() for name, column in zip(batch.schema.names, batch.columns)}


def raw(held: dict[str, pa.Array]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places of the terms, where each row's begin, with the end, and raw weights."""
    codes, starts, tfs, idfs = (held[c].to_numpy() for c in ("codes", "starts", "tfs", "idfs"))
    return codes, starts, (np.log10(tfs) + 1.0) * idfs[codes]


def dealt(bags: DataFrame, by: str) -> tuple[DataFrame, DataFrame]:
    """Rows with their block, rows of one value of ``by`` lying together, and the values with their number in order."""
    sizes = bags.groupBy(F.col(by).alias("of")).agg(F.sum(F.size("terms")).alias("s"))
    order = W.orderBy(F.asc_nulls_last("of"))
    before = F.coalesce(F.sum("s").over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    placed = sizes.select("of", "s", before.alias("from"), F.sum("s").over(W.partitionBy()).alias("total"), (F.row_number().over(order) - 1).alias("no"))
    placed = placed.withColumn("each", F.least(F.lit(TERMS), F.greatest(F.ceil(F.col("total") / BLOCKS), F.lit(max(TERMS // 32, 1)))))
    placed = placed.withColumn("parts", F.greatest(F.ceil(F.col("total") / F.col("each")), F.lit(BLOCKS)).cast("int"))
    within = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) / float(1 << 20)
    rows = bags.join(F.broadcast(placed), F.col(by).eqNullSafe(F.col("of"))).withColumn("to", F.floor((F.col("from") + within * F.col("s")) / F.col("each")))
    return rows.select("to", "parts", "no", "doc_id", "terms", "tfs"), placed.select("of", "no")


def pack(rows: DataFrame) -> DataFrame:
    """(block, part, blob, terms, counts): the block itself, without a part, and each part of its vocabulary with the number of documents of a term."""

    def step(table: pa.Table) -> pa.Table:
        table = table.sort_by("doc_id")
        held, starts = flat(table["terms"], pa.string())
        coded, parts = held.dictionary_encode(), table["parts"][0].as_py()
        part = np.array([zlib.crc32(t.encode()) % parts for t in coded.dictionary.to_pylist()], dtype="int64")
        order = np.argsort(part, kind="stable")
        place = np.empty(len(order), dtype="int32")
        place[order] = np.arange(len(order))
        codes, cuts = place[coded.indices.to_numpy()], np.searchsorted(part[order], np.arange(parts + 1)).astype("int32")
        words = coded.dictionary.take(pa.array(order))
        tfs = flat(table["tfs"], pa.int32())[0]
        blob = packed({"ids": table["doc_id"].combine_chunks(), "nos": table["no"].combine_chunks(), "starts": starts.astype("int32"), "codes": codes, "tfs": tfs, "cuts": cuts, "terms": words})
        counts = pa.array(np.bincount(codes, minlength=len(order)).astype("int64"))
        both = [pa.concat_arrays([pa.nulls(1, pa.list_(v.type)), lists(v, cuts)]) for v in (words, counts)]
        return pa.table({"block": pa.array([table["to"][0].as_py()] * (parts + 1), pa.int64()), "part": pa.array(range(-1, parts), pa.int32()), "blob": pa.array([blob] + [None] * parts, pa.binary()), "terms": both[0], "counts": both[1]})

    return rows.groupBy("to").applyInArrow(grouped(step), "block bigint, part int, blob binary, terms array<string>, counts array<bigint>")


def frequencies(parts: DataFrame, size: DataFrame) -> DataFrame:
    """(block, part, idfs) in the order of each block's part of its vocabulary: a part's counts of all blocks meet in one task."""

    def step(table: pa.Table) -> pa.Table:
        held, starts = flat(table["terms"], pa.string())
        coded = held.dictionary_encode()
        codes = coded.indices.to_numpy()
        df = np.bincount(codes, flat(table["counts"], pa.float64())[0].to_numpy(), len(coded.dictionary))
        return pa.table({"block": table["block"], "part": table["part"], "idfs": lists(np.log10(table["n"][0].as_py() / df)[codes], starts)})

    held = parts.filter("part >= 0").select("block", "part", "terms", "counts").join(F.broadcast(size))
    return held.groupBy("part").applyInArrow(grouped(step), "block bigint, part int, idfs array<double>")


def met(parts: DataFrame, numbers: DataFrame, step, schema: str) -> DataFrame:
    """``step`` on each block and the numbers of its parts."""
    blobs = parts.filter("part < 0").select("block", "blob")
    return blobs.toDF(*blobs.columns).groupBy("block").cogroup(numbers.toDF(*numbers.columns).groupBy("block")).applyInArrow(paired(step), schema)


def counted(bags: DataFrame, by: str, scratch: Scratch) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Packed blocks and their idfs, as written tables, and the numbered values of ``by``."""
    rows, placed = dealt(bags, by)
    parts = scratch.settle(pack(rows), "parts")
    return parts, scratch.settle(frequencies(parts, model.corpus_size(bags)), "idfs"), placed


def nearest(bags: DataFrame, scratch: Scratch) -> DataFrame:
    """(q, distance, h): each row's nearest of all others that share a weighted term, by exhaustive search; ties to the smaller id.

    Two blocks meet once and serve the rows of both. A group of blocks meets every later block; where there are many, group by group, each
    group's nearest being written, so that shuffle files hold a few copies of the blocks and not one for each pair.
    """

    def whole(left: pa.Table, right: pa.Table) -> pa.Table:
        if not len(left):
            return pa.table({"block": pa.array([], pa.int64()), "blob": pa.array([], pa.binary())})
        held = unpacked(left["blob"][0])
        held["idfs"] = flat(right.sort_by("part")["idfs"], pa.float64())[0]
        # rows without an id come last: they count as documents, but are no queries and near nothing
        n = len(held["ids"]) - held["ids"].null_count
        end = held["starts"][n].as_py()
        held |= {"ids": held["ids"][:n], "starts": held["starts"][: n + 1], "codes": held["codes"][:end], "tfs": held["tfs"][:end]}
        return pa.table({"block": left["block"], "blob": pa.array([packed({c: held[c] for c in ("ids", "starts", "codes", "tfs", "idfs", "terms")})], pa.binary())})

    def step(left: pa.Table, right: pa.Table) -> pa.Table:
        found = {"q": [], "h": [], "far": []}
        if len(left) and len(right):
            search(left.sort_by("block"), right, found)
        return pa.table({c: pa.array(np.concatenate(v) if v else [], pa.int64()) for c, v in found.items()})

    def search(left: pa.Table, right: pa.Table, found: dict) -> None:
        def put(q: np.ndarray, h: np.ndarray, far: np.ndarray) -> None:
            for c, v in (("q", q), ("h", h), ("far", far)):
                found[c].append(v[far < NONE])

        held = unpacked(right["blob"][0])
        if not len(held["ids"]):
            return
        codes, starts, x = raw(held)
        block = _Rows(held["ids"].to_numpy(), codes, starts, x, len(held["terms"]))
        best, of = np.full(len(block.ids), NONE), np.zeros(len(block.ids), dtype="int64")
        for number, blob in zip(left["block"], left["blob"]):
            other, twice = unpacked(blob), number.as_py() != right["hb"][0].as_py()
            ids, (codes, starts, x) = other["ids"].to_numpy(), raw(other)
            own = np.repeat(np.arange(len(ids)), np.diff(starts))
            w = unit_rows(x, own, len(ids))
            codes = pc.fill_null(pc.index_in(other["terms"], held["terms"]), -1).to_numpy(zero_copy_only=False)[codes]
            some = (codes >= 0) & (w > 0)
            for a, b, far in distances(block, ids, codes[some], own[some], w[some]):
                far[far < 0] = NONE
                h = far.argmin(axis=1)
                put(ids[a:b], block.ids[h], far[np.arange(b - a), h])
                if twice:
                    q = far.argmin(axis=0)
                    here, q = far[q, np.arange(len(q))], ids[a:b][q]
                    nearer = (here < best) | ((here == best) & (q < of))
                    best[nearer], of[nearer] = here[nearer], q[nearer]
        put(block.ids, of, best)

    parts, idfs, _ = counted(bags, "block", scratch)
    blocks = scratch.settle(met(parts, idfs, whole, "block bigint, blob binary"), "blocks")
    scratch.drop("parts", "idfs", "bags")
    last = blocks.agg(F.max("block")).first()[0] or 0
    groups = range(last // GROUP + 1)
    rounds = [groups] if last < BLOCKS else [[g] for g in groups]
    done = []
    for r in rounds:
        left = blocks.filter(F.floor(F.col("block") / GROUP).isin(list(r))).select(F.floor(F.col("block") / GROUP).alias("g"), F.explode(F.sequence("block", F.lit(last).cast("bigint"))).alias("hb"), "block", "blob")
        right = blocks.select(F.explode(F.array(*[F.lit(g).cast("bigint") for g in r])).alias("g"), F.col("block").alias("hb"), "blob").filter(F.col("g") * GROUP <= F.col("hb"))
        near = left.toDF(*left.columns).groupBy("g", "hb").cogroup(right.toDF(*right.columns).groupBy("g", "hb")).applyInArrow(paired(step), "q bigint, h bigint, far bigint")
        near = near.groupBy("q").agg(F.min(F.struct("far", "h")).alias("s"))
        done.append(near if r is rounds[-1] else scratch.settle(near, f"near-{r[0]}"))
    out = done[0]
    for near in done[1:]:
        out = out.unionByName(near)
    out = out.groupBy("q").agg(F.min("s").alias("s"))
    return out.select("q", (F.col("s.far") / 10.0**DIGITS).alias("distance"), F.col("s.h").alias("h"))


def nearest_centroid(bags: DataFrame, scratch: Scratch) -> DataFrame:
    """(q, distance, h): each row's nearest cluster by the mean of its rows' unit vectors; ties to the smaller cluster. Bags carry ``cluster``.

    A block sums its rows' weights by cluster and term, the parts of the vocabulary add the blocks' sums, and a group of blocks gets back the centroids'
    weights of its own terms, so that no row a term and cluster is shuffled and a row's cosines are made where it lies.
    """

    def weigh(left: pa.Table, right: pa.Table) -> pa.Table:
        out = {"part": [], "blob": [], "at": [], "no": [], "x": []}
        for blob in left["blob"]:
            held = unpacked(blob)
            held["idfs"] = flat(right.sort_by("part")["idfs"], pa.float64())[0]
            codes, starts, x = raw(held)
            n, cuts, nos = len(held["ids"]), held["cuts"].to_numpy(), held["nos"].to_numpy().astype("int64")
            rows = np.repeat(np.arange(n), np.diff(starts))
            w, width = unit_rows(x, rows, n), int(nos.max(initial=0)) + 1
            # rows without an id come last: they are compared, but belong to no cluster
            some = (w > 0) & (rows < n - held["ids"].null_count)
            of, place = np.unique(codes[some].astype("int64") * width + nos[rows[some]], return_inverse=True)
            sums, codes, nos = np.bincount(place, w[some], len(of)), of // width, of % width
            ends = np.searchsorted(codes, cuts)
            here = [slice(a, b) for a, b in zip(ends[:-1], ends[1:])]
            out["part"] += [-1, *range(len(here))]
            out["blob"] += [packed({c: held[c] for c in ("ids", "starts", "codes", "tfs", "idfs")})] + [None] * len(here)
            for name, values in (("at", codes - np.repeat(cuts[:-1], np.diff(ends))), ("no", nos), ("x", sums)):
                out[name] += [None, *[values[s] for s in here]]
        block = [left["block"][0].as_py()] * len(out["part"]) if len(left) else []
        kinds = {"part": pa.int32(), "blob": pa.binary(), "at": pa.list_(pa.int32()), "no": pa.list_(pa.int32()), "x": pa.list_(pa.float64())}
        exact = {"at": "int32", "no": "int32", "x": "float64"}
        return pa.table({"block": pa.array(block, pa.int64()), **{c: pa.array([v if v is None or c not in exact else v.astype(exact[c]) for v in values], kinds[c]) for c, values in out.items()}})

    def add(left: pa.Table, right: pa.Table) -> pa.Table:
        left, right = left.sort_by("block"), right.sort_by("block")
        held, starts = flat(left["terms"], pa.string())
        coded = held.dictionary_encode()
        codes, words = coded.indices.to_numpy(), len(coded.dictionary)
        (at, ends), (no, _), (x, _) = flat(right["at"], pa.int64()), flat(right["no"], pa.int64()), flat(right["x"], pa.float64())
        at, no, x = at.to_numpy(), no.to_numpy(), x.to_numpy()
        width = int(no.max(initial=0)) + 1
        of, place = np.unique(codes[at + np.repeat(starts[:-1], np.diff(ends))].astype("int64") * width + no, return_inverse=True)
        sums, no = np.bincount(place, x, len(of)), of % width
        begin = np.searchsorted(of // width, np.arange(words + 1))
        out = {"together": [], "block": [], "at": [], "counts": [], "no": [], "x": []}

        def put(*row) -> None:
            for c, v in zip(out, row):
                out[c].append(v)

        blocks = left["block"].to_numpy()
        for members in np.split(np.arange(len(blocks)), np.flatnonzero(np.diff(blocks // GROUP)) + 1):
            g = blocks[members[0]] // GROUP
            own, place = np.unique(codes[starts[members[0]] : starts[members[-1] + 1]], return_inverse=True)
            count = begin[own + 1] - begin[own]
            got = np.repeat(begin[own] - (np.cumsum(count) - count), count) + np.arange(count.sum())
            put(g, None, None, count.astype("int32"), no[got].astype("int32"), sums[got])
            for r in members:
                put(g, blocks[r], place[starts[r] - starts[members[0]] : starts[r + 1] - starts[members[0]]].astype("int32"), None, None, None)
        # the part's share of the centroids' squared lengths, for no block
        put(-1, None, None, None, np.arange(width, dtype="int32"), np.bincount(no, sums * sums, width))
        kinds = {"together": pa.int64(), "block": pa.int64(), "at": pa.list_(pa.int32()), "counts": pa.list_(pa.int32()), "no": pa.list_(pa.int32()), "x": pa.list_(pa.float64())}
        return pa.table({"part": pa.array([left["part"][0].as_py()] * len(out["block"]), pa.int32()), **{c: pa.array(v, kinds[c]) for c, v in out.items()}}).select(["together", "block", "part", "at", "counts", "no", "x"])

    def compare(left: pa.Table, right: pa.Table) -> pa.Table:
        found = {"q": [], "no": [], "far": []}
        if not len(left) or not len(right):
            return pa.table({c: pa.array([], pa.int64()) for c in found})
        whole = right.select(["block", "part", "counts", "no", "x"]).filter(pc.is_null(right["block"])).sort_by("part")
        right = right.select(["block", "part", "at"]).filter(pc.is_valid(right["block"])).sort_by("part")
        of, lengths = left["of"][0].as_py(), left["lengths"][0].as_py()
        width = max(of, default=-1) + 1
        scale = np.zeros(width)
        scale[of] = [1 / x if x > 0 else 0.0 for x in lengths]
        (no, _), (v, _), (count, ends) = (flat(whole[c], kind) for c, kind in (("no", pa.int32()), ("x", pa.float64()), ("counts", pa.int64())))
        no, v, count = no.to_numpy(), v.to_numpy(), count.to_numpy()
        v, begin = v * scale[no], np.cumsum(count) - count
        del whole
        for number, blob in zip(left["block"], left["blob"]):
            held = unpacked(blob)
            codes, starts, x = raw(held)
            at, cuts = flat(right.filter(pc.equal(right["block"], number))["at"], pa.int64())
            codes = (at.to_numpy() + np.repeat(ends[:-1], np.diff(cuts)))[codes]
            n = len(held["ids"])
            w = unit_rows(x, np.repeat(np.arange(n), np.diff(starts)), n)
            work, a = np.concatenate([[0], np.cumsum(count[codes])])[starts], 0
            while a < n:
                b = min(max(int(np.searchsorted(work, work[a] + CHUNK // 4, "right")) - 1, a + 1), a + max(CHUNK // 4 // max(width, 1), 1), n)
                s = slice(starts[a], starts[b])
                each, rows = count[codes[s]], np.repeat(np.arange(b - a), np.diff(starts[a : b + 1]))
                got = np.repeat(begin[codes[s]] - (np.cumsum(each) - each), each) + np.arange(each.sum())
                similar = np.bincount(np.repeat(rows, each) * width + no[got], np.repeat(w[s], each) * v[got], (b - a) * width).reshape(b - a, width)
                far = np.floor((1 - np.minimum(similar, 1.0)) * 10.0**DIGITS + 0.5).astype("int64")
                far[similar <= 0] = NONE
                best = far.argmin(axis=1)
                far = far[np.arange(b - a), best]
                found["q"].append(held["ids"][a:b].filter(pa.array(far < NONE)))
                found["no"].append(pa.array(best[far < NONE].astype("int64")))
                found["far"].append(pa.array(far[far < NONE]))
                a = b
        return pa.table({c: pa.chunked_array(v, pa.int64()) for c, v in found.items()})

    parts, idfs, placed = counted(bags, "cluster", scratch)
    # each value's number is kept: numbering again might read the bags when they are gone
    placed = scratch.write(placed, "clusters")
    scratch.drop("bags")
    blocks = scratch.settle(met(parts, idfs, weigh, "block bigint, part int, blob binary, at array<int>, no array<int>, x array<double>"), "blocks")
    scratch.drop("idfs")
    words, sums = parts.filter("part >= 0").select("block", "part", "terms"), blocks.filter("part >= 0").select("block", "part", "at", "no", "x")
    added = words.toDF(*words.columns).groupBy("part").cogroup(sums.toDF(*sums.columns).groupBy("part")).applyInArrow(paired(add), "together bigint, block bigint, part int, at array<int>, counts array<int>, no array<int>, x array<double>")
    added = scratch.settle(added, "centroids", 16)
    scratch.drop("parts")
    length = added.filter("together < 0").select(F.inline(F.arrays_zip("no", "x"))).groupBy("no").agg(F.sqrt(F.sum("x")).alias("length"))
    length = length.agg(F.collect_list(F.struct("no", "length")).alias("e")).select(F.col("e.no").alias("of"), F.col("e.length").alias("lengths"))
    blobs = blocks.filter("part < 0").select(F.floor(F.col("block") / GROUP).alias("together"), "block", "blob").join(F.broadcast(length))
    own = added.filter("together >= 0")
    near = blobs.toDF(*blobs.columns).groupBy("together").cogroup(own.toDF(*own.columns).groupBy("together")).applyInArrow(paired(compare), "q bigint, no bigint, far bigint")
    return near.join(F.broadcast(placed.withColumnRenamed("of", "h")), "no").select("q", (F.col("far") / 10.0**DIGITS).alias("distance"), "h")
