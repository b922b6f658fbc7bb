"""Sharding by fixed virtual slots.

Every record is hashed into one of a few thousand slots, the bytes of each slot are summed in one aggregation, and a
versioned table, stored beside the records, says which shard holds which slot. Rebalancing edits that small table by a new version;
records never change slots.

Law `bytes`: shards are near equal in bytes. Equal texts are a group that may hold a third of all rows, so they are dealt over
slots and shards like any others, not kept together: a slot comes from id, size and checksum, and where one such triple (rows
repeated, or copies without an id) fills a slot far beyond the mean, its rows are dealt over all slots by their place in the
stored records.

Defined results: a null text has no bytes and the checksum of no bytes (0); null and repeated ids are ordinary rows; an empty
table gives an empty result; other columns of the input are not read, so their names cannot clash.
"""

from __future__ import annotations

import heapq
import uuid
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import shared_folder, stored, table

N_SLOTS = 4096
#: Bytes that a record costs beside its text.
RECORD_BYTES = 16
#: A slot of so many times the mean number of rows is looked into for a triple that fills it.
CROWDED = 4


@dataclass
class SlotMap:
    """Versions of the slot-to-shard table; at most N_SLOTS rows each, so it lives on the driver."""

    n_slots: int = N_SLOTS
    versions: list[list[int]] = field(default_factory=list)

    @property
    def current(self) -> list[int]:
        return self.versions[-1]

    def plan(self, weight: dict[int, int], n_shards: int) -> list[int]:
        """First version: heaviest slot first, each to the shard with the fewest bytes."""
        shards = [(0, s) for s in range(n_shards)]
        owner = [0] * self.n_slots
        for slot in sorted(range(self.n_slots), key=lambda s: (-weight.get(s, 0), s)):
            load, shard = heapq.heappop(shards)
            owner[slot] = shard
            heapq.heappush(shards, (load + weight.get(slot, 0), shard))
        self.versions.append(owner)
        return owner

    def rebalance(self, weight: dict[int, int], n_shards: int) -> list[int]:
        """Next version: move slots only from shards over the mean (or gone) to the lightest ones."""
        owner = list(self.current)
        load = [0] * n_shards
        homeless = []
        for slot, shard in enumerate(owner):
            if shard < n_shards:
                load[shard] += weight.get(slot, 0)
            else:
                homeless.append(slot)
        mean = (sum(load) + sum(weight.get(s, 0) for s in homeless)) / n_shards
        held = [[] for _ in range(n_shards)]
        for slot, shard in enumerate(owner):
            if shard < n_shards:
                held[shard].append(slot)
        for shard, slots in enumerate(held):
            for slot in sorted(slots, key=lambda s: (weight.get(s, 0), s)):
                if load[shard] - weight.get(slot, 0) < mean or not weight.get(slot):
                    continue
                load[shard] -= weight[slot]
                homeless.append(slot)
        heap = [(x, s) for s, x in enumerate(load)]
        heapq.heapify(heap)
        for slot in sorted(homeless, key=lambda s: (-weight.get(s, 0), s)):
            x, shard = heapq.heappop(heap)
            owner[slot] = shard
            heapq.heappush(heap, (x + weight.get(slot, 0), shard))
        self.versions.append(owner)
        return owner

    def to_frame(self, spark: SparkSession) -> DataFrame:
        rows = [(v, slot, shard) for v, owner in enumerate(self.versions) for slot, shard in enumerate(owner)]
        return spark.createDataFrame(rows, "version int, virtual_slot int, shard int")

    @classmethod
    def from_frame(cls, df: DataFrame) -> SlotMap:
        rows = df.orderBy("version", "virtual_slot").collect()
        versions: dict[int, list[int]] = {}
        for r in rows:
            versions.setdefault(r["version"], []).append(r["shard"])
        return cls(len(versions[max(versions)]) if versions else N_SLOTS, [versions[v] for v in sorted(versions)])

    def save(self, spark: SparkSession, path: str) -> None:
        """Write the newest version as a folder of its own; earlier ones stay as they are, so a lost writer harms none."""
        version = len(self.versions) - 1
        self.to_frame(spark).filter(F.col("version") == version).coalesce(1).write.mode("overwrite").parquet(f"{path}/version={version}")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> SlotMap:
        return cls.from_frame(spark.read.option("basePath", path).schema("virtual_slot int, shard int, version int").parquet(path))


def digests(docs: DataFrame, n_slots: int = N_SLOTS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Id, size, checksum and virtual slot of every record: one scan, no shuffle."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    out = docs.select(F.col(id_col).alias("doc_id"), (F.octet_length(text) + F.lit(RECORD_BYTES)).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"))
    return out.withColumn("virtual_slot", F.pmod(F.xxhash64("doc_id", "size", "text_crc32"), F.lit(n_slots)).cast("int"))


def slot_weights(records: DataFrame) -> dict[int, tuple[int, int]]:
    """Rows and bytes of each slot (at most n_slots rows come to the driver)."""
    return {r["virtual_slot"]: (r["n"], r["b"]) for r in records.groupBy("virtual_slot").agg(F.count("*").alias("n"), F.sum("size").alias("b")).collect()}


def spread_repeats(records: DataFrame, n_slots: int = N_SLOTS) -> DataFrame:
    """Deal the rows of a triple that holds more rows than twice a slot's mean over all slots, by their place among the stored rows.

    Fewer than n_slots triples can hold so many, so they are broadcast; only rows of crowded slots are counted by triple.
    """
    counts = slot_weights(records)
    mean = sum(n for n, _ in counts.values()) / n_slots
    crowded = [(s,) for s, (n, _) in counts.items() if n > max(2, CROWDED * mean)]
    if not crowded:
        return records
    spark, triple = records.sparkSession, ["doc_id", "size", "text_crc32"]
    inside = records.join(F.broadcast(spark.createDataFrame(crowded, "virtual_slot int")), "virtual_slot", "left_semi")
    hot = inside.groupBy(*triple).agg(F.count("*").alias("n")).filter(F.col("n") > max(1, 2 * mean)).select(F.col("doc_id").alias("_d"), F.col("size").alias("_s"), F.col("text_crc32").alias("_c"), F.lit(True).alias("_hot"))
    same = F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("size") == F.col("_s")) & (F.col("text_crc32") == F.col("_c"))
    dealt = records.withColumn("_place", F.monotonically_increasing_id()).join(F.broadcast(hot), same, "left")
    slot = F.when(F.col("_hot"), F.pmod(F.xxhash64("virtual_slot", "_place"), F.lit(n_slots)).cast("int")).otherwise(F.col("virtual_slot"))
    return dealt.select(*triple, slot.alias("virtual_slot"))


def shard_records(docs: DataFrame, n_shards: int, slot_map: SlotMap | None = None, n_slots: int = N_SLOTS, map_path: str | None = None) -> tuple[DataFrame, SlotMap]:
    """Place every record; with a slot map its newest version is edited, else a first version is planned.

    `slot` is the record's place in its shard, without gaps: the slots of a shard follow each other, so a place is the
    rows of the slots before plus the rank in its own slot. Ranks are taken slot by slot, never over a whole shard.
    map_path: where the map's version is stored; records are placed by what is read back from there.
    """
    spark = docs.sparkSession
    records = stored(spread_repeats(stored(digests(docs, n_slots)), n_slots))
    weights = slot_weights(records)
    size = {s: b for s, (_, b) in weights.items()}
    slot_map = slot_map or SlotMap(n_slots)
    owner = slot_map.rebalance(size, n_shards) if slot_map.versions else slot_map.plan(size, n_shards)
    if map_path:
        slot_map.save(spark, map_path)
        slot_map = SlotMap.load(spark, map_path)
        owner = slot_map.current
    first, filled = [], [0] * n_shards
    for slot, shard in enumerate(owner):
        first.append((slot, shard, filled[shard]))
        filled[shard] += weights.get(slot, (0, 0))[0]
    places = spark.createDataFrame(first, "virtual_slot int, shard int, first long")
    rank = F.row_number().over(Window.partitionBy("virtual_slot").orderBy("doc_id", "size", "text_crc32"))
    placed = records.withColumn("_rank", rank).join(F.broadcast(places), "virtual_slot")
    version = len(slot_map.versions) - 1
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("first") + F.col("_rank") - 1).alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "virtual_slot", F.lit(version).alias("map_version")), slot_map


def op1_virtual_slot_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_records(table(spark, sf_dir, "documents"), 40, map_path=f"{shared_folder(spark)}/slot-map-{uuid.uuid4().hex}")[0]
