"""Sharding by fixed virtual slots and a versioned slot-to-shard map.

Rows are hashed into a fixed number of slots that never changes.  Bytes are added up per slot, and
a map from slots to shards is laid so that the shards' bytes are near equal.  Growing edits a few
entries of the map and raises its version, so only the rows of moved slots move.
"""

from __future__ import annotations

import heapq
import json
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import reliable, table

SLOTS = 4096


@dataclass(frozen=True)
class SlotMap:
    """Shard of each slot; ``version`` rises by one with each edit."""

    shards: int
    owner: tuple[int, ...]
    version: int = 1

    @staticmethod
    def balanced(size: list[int], shards: int) -> "SlotMap":
        """Largest slot first, each to the lightest shard (ties to the lower number)."""
        load = [(0, s) for s in range(shards)]
        owner = [0] * len(size)
        for slot in sorted(range(len(size)), key=lambda i: (-size[i], i)):
            held, shard = heapq.heappop(load)
            owner[slot] = shard
            heapq.heappush(load, (held + size[slot], shard))
        return SlotMap(shards, tuple(owner))

    def loads(self, size: list[int]) -> list[int]:
        out = [0] * self.shards
        for slot, shard in enumerate(self.owner):
            out[shard] += size[slot]
        return out

    def grown(self, size: list[int]) -> "SlotMap":
        """One more shard, filled to the mean with slots of the fullest shards; nothing else moves."""
        owner, new = list(self.owner), self.shards
        load = [*self.loads(size), 0]
        mean = sum(load) / (new + 1)
        held = {s: sorted((i for i, o in enumerate(owner) if o == s), key=lambda i: (size[i], -i)) for s in range(new)}
        while load[new] < mean:
            giver = max((s for s in range(new) if held[s]), key=lambda s: (load[s], -s), default=None)
            fits = None if giver is None else next((i for i in reversed(held[giver]) if size[i] and load[new] + size[i] <= mean + size[i] / 2 and load[giver] - size[i] >= mean - size[i]), None)
            if fits is None:
                break
            held[giver].remove(fits)
            owner[fits] = new
            load[giver] -= size[fits]
            load[new] += size[fits]
        return SlotMap(new + 1, tuple(owner), self.version + 1)

    def moved(self, other: "SlotMap") -> list[int]:
        return [i for i, (a, b) in enumerate(zip(self.owner, other.owner)) if a != b]

    def save(self, spark: SparkSession, folder: str) -> str:
        """Written under its version by Spark, so to any store; an older version stays readable."""
        path = f"{folder}/v{self.version:06d}"
        row = json.dumps({"version": self.version, "shards": self.shards, "owner": self.owner})
        spark.createDataFrame([(row,)], "value string").coalesce(1).write.text(path)
        return path

    @staticmethod
    def load(spark: SparkSession, folder: str, version: int) -> "SlotMap":
        x = json.loads(spark.read.text(f"{folder}/v{version:06d}").first().value)
        return SlotMap(x["shards"], tuple(x["owner"]), x["version"])


def slot_of(key: Column, slots: int = SLOTS) -> Column:
    """A slot by the hash of the key alone (null hashes too)."""
    return F.pmod(F.xxhash64(key.cast("long"), F.lit(0x51)), F.lit(slots)).cast("int")


def slot_sizes(rows: DataFrame, slots: int = SLOTS) -> tuple[list[int], list[int]]:
    """Bytes and rows of each slot of ``rows`` (virtual_slot, size): one small row per slot to the driver."""
    size, count = [0] * slots, [0] * slots
    for r in rows.groupBy("virtual_slot").agg(F.sum("size").alias("b"), F.count(F.lit(1)).alias("n")).collect():
        size[r.virtual_slot], count[r.virtual_slot] = r.b, r.n
    return size, count


def assign(rows: DataFrame, slot_map: SlotMap, count: list[int], order: list[str]) -> DataFrame:
    """Adds shard and slot, the row's gapless number in its shard, to ``rows`` (virtual_slot, ...).

    A shard's rows are numbered slot by slot: windows run within slots, never over a whole shard.
    """
    base, at = [0] * len(count), [0] * slot_map.shards
    for i, shard in enumerate(slot_map.owner):
        base[i] = at[shard]
        at[shard] += count[i]
    known = rows.sparkSession.createDataFrame([(i, s, base[i]) for i, s in enumerate(slot_map.owner)], "virtual_slot int, shard int, base long")
    w = Window.partitionBy("virtual_slot").orderBy(*order)
    numbered = rows.withColumn("in_slot", F.row_number().over(w))
    return numbered.join(F.broadcast(known), "virtual_slot").withColumn("slot", (F.col("base") + F.col("in_slot") - 1).cast("long")).drop("base", "in_slot")


def sharded(docs: DataFrame, shards: int = 24, slots: int = SLOTS) -> tuple[DataFrame, SlotMap]:
    """All documents with their shard under a map laid by bytes.

    The law is ``bytes``: the shards' sizes are near equal.  So a document goes by its own doc_id,
    never by its text: a group of equal texts is dealt over all shards like other documents (a group
    with a third of all rows would else make one shard three times too large), and each row of the
    group has its text_crc32.  A null text has 0 bytes and a null doc_id hashes like a value; equal
    rows are numbered one after the other; rows of one doc_id share a virtual slot; an empty table
    gives an empty result; columns other than doc_id and text are not read.
    """
    data = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select(
        F.col("doc_id").cast("long"), (F.octet_length(data) + 8).cast("long").alias("size"), F.crc32(data.cast("binary")).cast("long").alias("text_crc32"),
        slot_of(F.col("doc_id"), slots).alias("virtual_slot"),
    )
    rows = reliable(rows)
    size, count = slot_sizes(rows, slots)
    slot_map = SlotMap.balanced(size, shards)
    return assign(rows, slot_map, count, ["doc_id", "text_crc32", "size"]), slot_map


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in 24 shards of near equal bytes (law ``bytes``); ``slot`` numbers a shard's rows."""
    out, slot_map = sharded(table(spark, sf_dir, "documents"))
    return out.select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"),
        "virtual_slot", F.lit(slot_map.version).alias("map_version"),
    )
