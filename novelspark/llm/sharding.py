"""Sharding by fixed virtual slots (operator 5, native).

Records are hashed into some thousands of virtual slots; bytes and rows are summed for each slot. A stored, versioned map says
which shard each slot belongs to: the first version deals slots evenly, and rebalancing by the bytes found writes an edited version
beside it. Rows find their shard through the version read back. Rebalancing edits the map, never the hash, so rows only move with
their slots.

The slot histogram has ``n_slots`` rows whatever the input, which bounds both what the driver sees and what is broadcast.

Defined cases: a null text has no bytes (size 1); a null ``doc_id`` hashes like any other value; repeated rows keep one place
each; an empty table gives an empty result; other columns of the input are ignored.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Scratch, documents

N_SLOTS = 4096


@dataclass(frozen=True)
class SlotMap:
    """Which shard each virtual slot belongs to; every edit gives a new version."""

    shard_of: tuple[int, ...]
    n_shards: int
    version: int = 1
    moved: tuple[int, ...] = field(default=())

    @classmethod
    def balanced(cls, loads: list[int], n_shards: int) -> SlotMap:
        """Heaviest slot first, each to the lightest shard."""
        heap = [(0, 0, s) for s in range(n_shards)]
        shard_of = [0] * len(loads)
        for slot in sorted(range(len(loads)), key=lambda i: (-loads[i], i)):
            load, slots, shard = heapq.heappop(heap)
            shard_of[slot] = shard
            heapq.heappush(heap, (load + loads[slot], slots + 1, shard))
        return cls(tuple(shard_of), n_shards)

    @classmethod
    def even(cls, n_slots: int, n_shards: int) -> SlotMap:
        """The map before anything is known of the bytes."""
        return cls(tuple(slot % n_shards for slot in range(n_slots)), n_shards)

    def rebalanced(self, loads: list[int]) -> SlotMap:
        """An edited map with near equal bytes; slots that need not move stay.

        Shards above the mean give their largest slots that fit into the excess; the slots given go, heaviest first, to the lightest
        shard; single moves from the fullest to the lightest shard then even out what is left.
        """
        new, now, target = list(self.shard_of), self.loads(loads), sum(loads) / self.n_shards
        held: list[list[int]] = [[] for _ in range(self.n_shards)]
        for slot in sorted(range(len(new)), key=lambda i: (loads[i], i)):
            held[new[slot]].append(slot)
        given = []
        for shard in range(self.n_shards):
            for slot in reversed(list(held[shard])):
                if 0 < loads[slot] <= now[shard] - target:
                    held[shard].remove(slot)
                    given.append(slot)
                    now[shard] -= loads[slot]
        for slot in sorted(given, key=lambda i: (-loads[i], i)):
            shard = min(range(self.n_shards), key=lambda s: (now[s], s))
            new[slot], now[shard] = shard, now[shard] + loads[slot]
            held[shard].append(slot)
        while True:
            full, light = max(range(self.n_shards), key=lambda s: (now[s], -s)), min(range(self.n_shards), key=lambda s: (now[s], s))
            gap = now[full] - now[light]
            fits = [x for x in held[full] if 0 < loads[x] < gap]
            if not fits:
                break
            slot = min(fits, key=lambda x: (abs(gap - 2 * loads[x]), x))
            held[full].remove(slot)
            held[light].append(slot)
            new[slot], now[full], now[light] = light, now[full] - loads[slot], now[light] + loads[slot]
        moved = tuple(i for i in range(len(new)) if new[i] != self.shard_of[i])
        return SlotMap(tuple(new), self.n_shards, self.version + 1, moved)

    def loads(self, loads: list[int]) -> list[int]:
        out = [0] * self.n_shards
        for slot, shard in enumerate(self.shard_of):
            out[shard] += loads[slot]
        return out

    def grown(self, loads: list[int], more: int = 1) -> SlotMap:
        """``more`` new shards; slots move only into these, from the fullest shards, while that evens the bytes."""
        total, new = sum(loads), list(self.shard_of)
        n, now = self.n_shards + more, [*self.loads(loads), *[0] * more]
        target, moved = total / max(n, 1), []
        held = {s: sorted((x for x in range(len(new)) if new[x] == s), key=lambda x: (loads[x], x)) for s in range(self.n_shards)}
        for fresh in range(self.n_shards, n):
            while now[fresh] < target:
                giver = max(range(self.n_shards), key=lambda s: (now[s], -s))
                fits = [x for x in held[giver] if 0 < loads[x] <= target - now[fresh]]
                if not fits or now[giver] <= target:
                    break
                slot = fits[-1]
                held[giver].remove(slot)
                new[slot], now[giver], now[fresh] = fresh, now[giver] - loads[slot], now[fresh] + loads[slot]
                moved.append(slot)
        return SlotMap(tuple(new), n, self.version + 1, tuple(moved))

    def table(self, spark: SparkSession) -> DataFrame:
        rows = [(self.version, slot, shard) for slot, shard in enumerate(self.shard_of)]
        return spark.createDataFrame(rows, "version int, slot int, shard int")

    def save(self, spark: SparkSession, path: str) -> None:
        """Adds this version to the map's table at ``path``; earlier versions stay, and a version is never written twice."""
        self.table(spark).drop("version").coalesce(1).write.mode("error").parquet(f"{path}/version={self.version}")

    @classmethod
    def load(cls, spark: SparkSession, path: str, version: int | None = None) -> SlotMap:
        """A version of the stored map, or its last."""
        table = spark.read.schema("slot int, shard int, version int").parquet(path)
        if version is None:
            version = table.agg(F.max("version")).first()[0]
        rows = table.filter(F.col("version") == version).select("slot", "shard").orderBy("slot").collect()
        return cls(tuple(r.shard for r in rows), 1 + max(r.shard for r in rows), version)


def with_slots(docs: DataFrame, key: str = "doc_id", text: str = "text", n_slots: int = N_SLOTS) -> DataFrame:
    """(key, size, text_crc32, virtual_slot): the text itself goes no further."""
    value = F.coalesce(F.col(text), F.lit(""))
    return docs.select(
        F.col(key).alias(key),
        (F.octet_length(value).cast("long") + 1).alias("size"),
        F.crc32(F.encode(value, "UTF-8")).alias("text_crc32"),
        F.pmod(F.xxhash64(F.col(key)), F.lit(n_slots)).cast("int").alias("virtual_slot"),
    )


def slot_histogram(slotted: DataFrame, n_slots: int = N_SLOTS) -> tuple[list[int], list[int]]:
    """Bytes and rows of each virtual slot; ``n_slots`` numbers each, on the driver."""
    sizes, rows = [0] * n_slots, [0] * n_slots
    for r in slotted.groupBy("virtual_slot").agg(F.sum("size").alias("bytes"), F.count("*").alias("n")).collect():
        sizes[r.virtual_slot], rows[r.virtual_slot] = r.bytes, r.n
    return sizes, rows


def assign(slotted: DataFrame, key: str, slot_map: SlotMap, rows: list[int]) -> DataFrame:
    """Shard and gapless place in it: the place in the virtual slot after all rows of the shard's earlier slots."""
    spark, filled, table = slotted.sparkSession, [0] * slot_map.n_shards, []
    for slot, shard in enumerate(slot_map.shard_of):
        table.append((slot, shard, filled[shard]))
        filled[shard] += rows[slot]
    offsets = spark.createDataFrame(table, "virtual_slot int, shard int, first long")
    order = W.partitionBy("virtual_slot").orderBy(key, "size", "text_crc32")
    return (
        slotted.withColumn("place", F.row_number().over(order).cast("long") - 1)
        .join(F.broadcast(offsets), "virtual_slot")
        .withColumn("slot", F.col("first") + F.col("place"))
    )


def shard(docs: DataFrame, n_shards: int = 16, key: str = "doc_id", text: str = "text", n_slots: int = N_SLOTS, path: str | None = None) -> tuple[DataFrame, SlotMap]:
    """Rows with shard and place, and the map that decided: the stored one at ``path``, rebalanced by the bytes found.

    Without a stored map one is begun, with slots dealt evenly as its first version.
    """
    spark = docs.sparkSession
    if path is None:
        path = f"{Scratch(spark, 'slots').base}/map"
        SlotMap.even(n_slots, n_shards).save(spark, path)
    slotted = with_slots(docs, key, text, n_slots)
    sizes, rows = slot_histogram(slotted, n_slots)
    SlotMap.load(spark, path).rebalanced(sizes).save(spark, path)
    slot_map = SlotMap.load(spark, path)
    return assign(slotted, key, slot_map, rows), slot_map


def op5_virtual_slots(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, slot_map = shard(documents(spark, sf_dir), 16)
    return rows.select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "virtual_slot", F.lit(slot_map.version).alias("map_version")
    )
