"""Sharding by fixed virtual slots and a versioned slot-to-shard map.

A record's slot is a hash of its doc_id and never changes. Bytes are summed per slot; the map from slots to shards gives
the largest slots first to the shard with the fewest bytes. A new version moves only what its change needs: a grown map
moves slots into the new shard alone, a rebalance moves slots from the fullest to the emptiest shard until they are near.
The map has as many rows as there are slots, a parameter, so the driver may hold it.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import new_path, written

SLOTS = 16_384


@dataclass(frozen=True)
class SlotMap:
    """Version, number of shards, shard of each slot that has records."""

    version: int
    shards: int
    shard_of: dict[int, int]

    def save(self, spark: SparkSession, folder: str | None = None) -> str:
        """Writes this version beside the earlier ones; the newest is the largest version."""
        folder = folder or new_path(spark, "slot-map")
        rows = [(self.version, self.shards, s, k) for s, k in sorted(self.shard_of.items())]
        frame = spark.createDataFrame(rows, "version int, shards int, vslot int, shard int")
        frame.coalesce(1).write.mode("append").parquet(folder)
        return folder

    @staticmethod
    def load(spark: SparkSession, folder: str, version: int | None = None) -> SlotMap:
        rows = spark.read.parquet(folder).collect()  # one row a slot and version
        version = max(r["version"] for r in rows) if version is None else version
        own = [r for r in rows if r["version"] == version]
        return SlotMap(version, own[0]["shards"], {r["vslot"]: r["shard"] for r in own})


def balanced(load: dict[int, int], shards: int, version: int = 1) -> SlotMap:
    """Largest slot first, each to the shard with the fewest bytes; ties to the smaller number."""
    heap = [(0, k) for k in range(shards)]
    out = {}
    for slot, size in sorted(load.items(), key=lambda x: (-x[1], x[0])):
        held, k = heapq.heappop(heap)
        out[slot] = k
        heapq.heappush(heap, (held + size, k))
    return SlotMap(version, shards, out)


def _held(m: SlotMap, load: dict[int, int]) -> list[int]:
    held = [0] * m.shards
    for slot, k in m.shard_of.items():
        held[k] += load.get(slot, 0)
    return held


def grown(m: SlotMap, load: dict[int, int]) -> SlotMap:
    """One more shard: slots move only into it, from the shards above the new mean, until it has its share."""
    held, out, new = [*_held(m, load), 0], dict(m.shard_of), m.shards
    mean = sum(held) / (m.shards + 1)
    for slot, size in sorted(load.items(), key=lambda x: (-x[1], x[0])):
        k = out[slot]
        if held[k] - size >= mean * 0.98 and held[new] + size <= mean * 1.02:
            out[slot] = new
            held[k] -= size
            held[new] += size
    return SlotMap(m.version + 1, m.shards + 1, out)


def rebalanced(m: SlotMap, load: dict[int, int], near: float = 0.01) -> SlotMap:
    """Edits the map for changed loads: slots without a shard get one, then single slots move from fullest to emptiest."""
    held, out = _held(m, load), {s: k for s, k in m.shard_of.items() if s in load}
    for slot in sorted(load.keys() - out.keys(), key=lambda s: (-load[s], s)):
        out[slot] = k = held.index(min(held))
        held[k] += load[slot]
    for _ in range(len(load)):
        most, least = held.index(max(held)), held.index(min(held))
        gap = held[most] - held[least]
        movable = [s for s, k in out.items() if k == most and load[s] < gap]
        if gap <= near * sum(held) / m.shards or not movable:
            break
        slot = min(movable, key=lambda s: (abs(gap / 2 - load[s]), s))
        out[slot] = least
        held[most] -= load[slot]
        held[least] += load[slot]
    return SlotMap(m.version + 1, m.shards, out)


def slotted(docs: DataFrame, slots: int = SLOTS) -> DataFrame:
    """doc_id, size (UTF-8 bytes and one; a null text has none), text_crc32, vslot; written to the shared folder.

    A slot is a hash of doc_id. Rows without an id, of which there may be any number, are told apart by their number."""
    text = F.coalesce(F.col("text"), F.lit(""))
    records = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        (F.octet_length(text).cast("long") + 1).alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.when(F.col("doc_id").isNull(), F.monotonically_increasing_id()).alias("row"),
    )
    return written(records.withColumn("vslot", F.pmod(F.xxhash64("doc_id", "row"), F.lit(slots)).cast("int")).drop("row"), "records")


def slot_loads(records: DataFrame) -> tuple[dict[int, int], dict[int, int]]:
    """Bytes and rows of each slot."""
    rows = records.groupBy("vslot").agg(F.sum("size").alias("b"), F.count(F.lit(1)).alias("n")).collect()
    return {r["vslot"]: r["b"] for r in rows}, {r["vslot"]: r["n"] for r in rows}


def shard(docs: DataFrame, shards: int = 16, slots: int = SLOTS, slot_map: SlotMap | None = None) -> tuple[DataFrame, SlotMap]:
    """Records with their shard and their place in it (gapless from 0, by virtual slot, doc_id, checksum).

    Rows without a doc_id are dealt by their number; rows that repeat an id share its slot, each with a place of its own;
    null and empty texts have size 1; a text of any length is one record of its size, and is not read but for length and
    checksum; equal texts are not kept together, as no law asks for it; an empty table gives no row and an empty map. The one shuffle deals rows by virtual slot, thousands of even runs; a shard is never one task."""
    records = slotted(docs, slots)
    load, rows = slot_loads(records)
    m = slot_map or balanced(load, shards)
    base, filled = {}, [0] * m.shards
    for s in sorted(rows):
        base[s], filled[m.shard_of[s]] = filled[m.shard_of[s]], filled[m.shard_of[s]] + rows[s]
    table = docs.sparkSession.createDataFrame([(s, m.shard_of[s], base[s]) for s in sorted(rows)], "vslot int, shard int, base long")
    place = F.row_number().over(Window.partitionBy("vslot").orderBy("doc_id", "text_crc32", "size"))
    placed = records.withColumn("place", place).join(F.broadcast(table), "vslot")  # as many rows as there are slots
    return placed.select("doc_id", "size", "text_crc32", "vslot", "shard", (F.col("base") + F.col("place") - 1).cast("long").alias("slot")), m
