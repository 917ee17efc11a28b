"""Sharding by fixed virtual slots, DataFrame functions only.

Records are hashed into a fixed number of virtual slots, far more than shards. A small versioned
map says which shard holds which slot. Version 0 deals slots out in turn; bytes are summed by
slot, and an edit moves slots from shards above the mean to shards below it until no move helps.
Every version is written to a table of maps in the shared folder, and records are placed by the version read from there.
Only the map (a few thousand rows, whatever the data) passes through the driver.

Records that are equal in id and text are numbered, and the number is part of what is hashed, so even a third of all rows being
one repeated record spreads over all slots. They are numbered within the partitions that they lie in and
moved by the counts of the partitions before, so no task holds all of them.

Defined results: a null text has no bytes (size 16, checksum 0); a null id hashes like any value; hot ids,
sources, groups of copies and repeated rows do not meet in a slot; an empty table gives an empty one and a map
with the slots dealt in turn; other columns are not read.
"""

from __future__ import annotations

import json
import uuid
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import cut, shared_folder

VIRTUAL_SLOTS = 4096
OVERHEAD_BYTES = 16


@dataclass(frozen=True)
class SlotMap:
    """``shard_of[slot]``; ``moves``: the slots that this version's edit moved, with their shards before and after."""

    shards: int
    shard_of: tuple[int, ...]
    version: int = 0
    moves: tuple[tuple[int, int, int], ...] = field(default=())

    @staticmethod
    def dealt(shards: int, slots: int = VIRTUAL_SLOTS) -> SlotMap:
        return SlotMap(shards, tuple(s % shards for s in range(slots)))

    def rebalanced(self, weight: dict[int, int], shards: int | None = None) -> SlotMap:
        """The next version: slots move from the heaviest shard to the lightest as long as that brings the two nearer.

        First whole slots go to new or light shards, largest first that fits the gap; then
        pairs of slots are exchanged for the rest. Bounded by slots, not by data."""
        n = shards or self.shards
        of = [s if s < n else i % n for i, s in enumerate(self.shard_of)]
        held: list[dict[int, int]] = [{} for _ in range(n)]
        for slot, shard in enumerate(of):
            held[shard][slot] = weight.get(slot, 0)
        load = [sum(h.values()) for h in held]

        def move(slot: int, a: int, b: int) -> None:
            w = held[a].pop(slot)
            held[b][slot] = w
            load[a] -= w
            load[b] += w

        for _ in range(4 * len(of)):
            a, b = max(range(n), key=lambda s: (load[s], -s)), min(range(n), key=lambda s: (load[s], s))
            gap = load[a] - load[b]
            best = min(((abs(gap - 2 * w), slot) for slot, w in held[a].items() if 0 < w < gap), default=None)
            swap = self._exchange(held[a], held[b], gap) if best is None or best[0] > gap // 64 else None
            if swap and (best is None or swap[0] < best[0]):
                move(swap[1], a, b)
                move(swap[2], b, a)
            elif best and best[0] < gap:
                move(best[1], a, b)
            else:
                break
        after = [0] * len(of)
        for shard, slots in enumerate(held):
            for slot in slots:
                after[slot] = shard
        moves = tuple((i, x, y) for i, (x, y) in enumerate(zip(self.shard_of, after, strict=True)) if x != y)
        return SlotMap(n, tuple(after), self.version + 1, moves)

    @staticmethod
    def _exchange(heavy: dict[int, int], light: dict[int, int], gap: int) -> tuple[int, int, int] | None:
        """Two slots whose exchange leaves the smallest gap, if it leaves a smaller one: one sweep over both sides in order of weight."""
        a, b = sorted((w, s) for s, w in heavy.items()), sorted((w, s) for s, w in light.items())
        best, j = None, 0
        for w, s in a:
            while j + 1 < len(b) and w - b[j + 1][0] >= gap / 2:
                j += 1
            for k in (j, j + 1):
                if k < len(b) and 0 < (d := w - b[k][0]) < gap and (best is None or abs(gap - 2 * d) < best[0]):
                    best = (abs(gap - 2 * d), s, b[k][1])
        return best

    def shard(self, slot: Column) -> Column:
        """The shard of a slot as an expression: the map is a constant of the plan, so no join is needed."""
        return F.get(F.split(F.lit(",".join(map(str, self.shard_of))), ","), slot).cast("int")

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.range(len(self.shard_of)).select(F.lit(self.version).alias("version"), F.col("id").cast("int").alias("slot"), self.shard(F.col("id").cast("int")).alias("shard"))

    def write(self, spark: SparkSession, path: str) -> None:
        """Adds this version to the table of maps at ``path``."""
        row = json.dumps({"version": self.version, "shards": self.shards, "shard_of": self.shard_of, "moves": self.moves})
        spark.range(1).select(F.lit(self.version).alias("version"), F.lit(row).alias("map")).write.mode("append").parquet(path)

    @staticmethod
    def read(spark: SparkSession, path: str, version: int | None = None) -> SlotMap:
        """A version of the map, the last by default."""
        maps = spark.read.parquet(path)
        row = (maps.where(F.col("version") == version) if version is not None else maps).orderBy(F.desc("version")).first()
        m = json.loads(row["map"])
        return SlotMap(m["shards"], tuple(m["shard_of"]), m["version"], tuple(map(tuple, m["moves"])))

    @staticmethod
    def last(spark: SparkSession, path: str) -> SlotMap | None:
        """The last version at ``path``, if there is a table."""
        at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        there = at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(at)
        return SlotMap.read(spark, path) if there else None


def sized(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col, size, text_crc32`` and ``text_hash``, which tells a null text from an empty one."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    return docs.select(
        F.col(id_col),
        (F.octet_length(text) + OVERHEAD_BYTES).cast("bigint").alias("size"),
        F.crc32(text).cast("bigint").alias("text_crc32"),
        F.xxhash64(F.col(text_col), F.col(text_col).isNull()).alias("text_hash"),
    )


def slotted(records: DataFrame, id_col: str = "doc_id", slots: int = VIRTUAL_SLOTS) -> DataFrame:
    """``records`` with ``virtual_slot``: a hash of id, text and the record's number among its equals.

    ``records`` must have fixed partitions, as a checkpoint has."""
    parts = records.withColumn("_part", F.spark_partition_id())
    key = [id_col, "text_hash"]
    inside = Window.partitionBy(*key, "_part").orderBy("text_crc32")
    before = Window.partitionBy(*key).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    counts = parts.groupBy(*key, "_part").agg(F.count("*").alias("n"))
    moved = counts.select(*(F.col(c).alias(f"_{c}") for c in key), F.col("_part").alias("_p"), F.coalesce(F.sum("n").over(before), F.lit(0)).alias("_before"))
    moved = moved.where("_before > 0")  # only what is repeated in several partitions
    same = (F.col("_part") == F.col("_p")) & (F.col("text_hash") == F.col("_text_hash")) & F.col(id_col).eqNullSafe(F.col(f"_{id_col}"))
    numbered = parts.withColumn("_nth", F.row_number().over(inside) - 1).join(moved, same, "left")
    nth = F.col("_nth") + F.coalesce("_before", F.lit(0))
    return numbered.select(*records.columns, F.pmod(F.xxhash64(id_col, "text_hash", nth.cast("bigint")), F.lit(slots)).cast("int").alias("virtual_slot"))


def plan_map(records: DataFrame, shards: int, slots: int = VIRTUAL_SLOTS, before: SlotMap | None = None) -> SlotMap:
    """The map for these records: bytes by slot, then an edit of the map before (version 0 by default)."""
    weights = {r["virtual_slot"]: r["bytes"] for r in records.groupBy("virtual_slot").agg(F.sum("size").alias("bytes")).collect()}  # a row for each slot at most
    return (before or SlotMap.dealt(shards, slots)).rebalanced(weights, shards)


def assign(docs: DataFrame, shards: int = 40, id_col: str = "doc_id", text_col: str = "text", slots: int = VIRTUAL_SLOTS, maps: str | None = None) -> DataFrame:
    """A row for each record: ``id_col, size, text_crc32, virtual_slot, map_version, shard, slot``.

    ``slot``: the record's place in its shard, gapless from 0, by virtual slot and then by id and checksum.
    Places are numbered within virtual slots and moved by the counts of the virtual slots before them, so no task
    ever holds a shard. ``maps``: the table of map versions. If it has a map of as many slots, the last version is edited, else version 0 is
    dealt and written first. Without a path a new table in the shared folder is used."""
    spark = docs.sparkSession
    records = cut(slotted(cut(sized(docs, id_col, text_col)), id_col, slots))
    maps = maps or f"{shared_folder(spark)}/slot-maps-{uuid.uuid4().hex}"
    start = SlotMap.last(spark, maps)
    if start is None or len(start.shard_of) != slots:
        start = SlotMap.dealt(shards, slots)
        start.write(spark, maps)
    plan_map(records, shards, slots, start).write(spark, maps)
    plan = SlotMap.read(spark, maps)
    counts = records.groupBy("virtual_slot").agg(F.count("*").alias("n")).withColumn("shard", plan.shard(F.col("virtual_slot")))
    before = Window.partitionBy("shard").orderBy("virtual_slot").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("virtual_slot", "shard", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("offset"))  # a row for each slot at most
    inside = F.row_number().over(Window.partitionBy("virtual_slot").orderBy(id_col, "text_crc32"))
    numbered = records.withColumn("_inside", inside.cast("bigint"))
    placed = numbered.join(F.broadcast(offsets), "virtual_slot")
    return placed.select(id_col, "size", "text_crc32", "virtual_slot", F.lit(plan.version).alias("map_version"), "shard", (F.col("offset") + F.col("_inside") - 1).cast("bigint").alias("slot"))
