"""Sharding through fixed virtual slots.

Records hash (md5 of the id) into ``SLOTS`` slots that never change. Bytes and rows are summed per slot; the map
from slot to shard is a small versioned table: version 1 spreads the slots so that shards hold nearly
equal bytes, and rebalancing (one more shard, or shards that have drifted apart) writes a new
version that differs in the edited slots only. Placement is a broadcast of that table, bounded by SLOTS.
A slot that null or repeated ids fill beyond an eighth of a shard is spread over all slots again, by id and row.

Places within a shard are numbered from 0 without a sort of the shard: the rows of a slot are ranked
among themselves, after all rows of the shard's slots before it.

Defined results: null text has no bytes and counts as its fixed overhead; null ids share one slot, as do rows of one id,
as long as they are few; equal rows lie in either order; one row that is heavier than a whole share
stays whole; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import fresh_path, stage

SLOTS = 4096
SHARDS = 40
OVERHEAD = 16
#: Rows from which a slot may be spread, and the part of a shard's bytes that it must exceed.
HOT_ROWS, HOT_SHARE = 64, 8


def slot_of(column: str, slots: int = SLOTS):
    """Virtual slot of an id: the first 32 bits of the md5 of its text, modulo the slot count."""
    text = F.coalesce(F.col(column).cast("string"), F.lit(""))
    return F.pmod(F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(slots)).cast("int")


def spread(loads: dict[int, int], shards: int, slots: int = SLOTS) -> dict[int, int]:
    """First map: heaviest slot first, to the lightest shard."""
    heap = [(0, 0, s) for s in range(shards)]
    out = {}
    for slot in sorted(range(slots), key=lambda s: (-loads.get(s, 0), s)):
        size, n, shard = heapq.heappop(heap)
        out[slot] = shard
        heapq.heappush(heap, (size + loads.get(slot, 0), n + 1, shard))
    return out


def grow(placed: dict[int, int], loads: dict[int, int]) -> dict[int, int]:
    """Edit for one more shard: slots move into the new shard only, each from the shard that is fullest then."""
    new = max(placed.values()) + 1
    share = sum(loads.values()) / (new + 1)
    by_shard: dict[int, list] = {}
    for slot, shard in placed.items():
        by_shard.setdefault(shard, []).append((loads.get(slot, 0), slot))
    size = {shard: sum(x for x, _ in rows) for shard, rows in by_shard.items()}
    edited, held = dict(placed), 0
    while True:
        donor = max(size, key=lambda s: (size[s], -s))
        fits = [x for x in by_shard[donor] if x[0] and held + x[0] <= share and size[donor] - x[0] >= 0]
        if not fits or size[donor] <= share:
            return edited
        load, slot = max(fits)
        by_shard[donor].remove((load, slot))
        size[donor] -= load
        held += load
        edited[slot] = new


class SlotMap:
    """The versioned map, as a Parquet table (version, slot, shard) in the shared folder."""

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark, self.path = spark, path or fresh_path(spark, "slot-map")

    def save(self, version: int, placed: dict[int, int]) -> None:
        rows = [(version, slot, shard) for slot, shard in sorted(placed.items())]
        frame = self.spark.createDataFrame(rows, "version int, slot int, shard int")
        frame.coalesce(1).drop("version").write.mode("error").parquet(f"{self.path}/version={version}")

    def load(self, version: int) -> DataFrame:
        return self.spark.read.schema("slot int, shard int").parquet(f"{self.path}/version={version}")

    def as_dict(self, version: int) -> dict[int, int]:
        return {r["slot"]: r["shard"] for r in self.load(version).collect()}

    def edit(self, version: int, change) -> int:
        """Write version + 1 as ``change(map)``; readers of older versions are untouched."""
        self.save(version + 1, change(self.as_dict(version)))
        return version + 1


def slot_loads(rows: DataFrame) -> tuple[dict[int, int], dict[int, int]]:
    """Bytes and rows per slot (SLOTS rows at most)."""
    sums = rows.groupBy("vslot").agg(F.sum("size").alias("bytes"), F.count("*").alias("n")).collect()
    return {r["vslot"]: r["bytes"] for r in sums}, {r["vslot"]: r["n"] for r in sums}


def shard(docs: DataFrame, shards: int = SHARDS, slots: int = SLOTS) -> DataFrame:
    """doc_id, size, text_crc32, vslot, shard, slot (place in the shard), map_version."""
    spark = docs.sparkSession
    raw = F.col("text").cast("binary")
    size = F.coalesce(F.octet_length("text"), F.lit(0)).cast("long") + OVERHEAD
    rows = docs.select("doc_id", size.alias("size"), F.coalesce(F.crc32(raw), F.lit(0)).alias("text_crc32"), slot_of("doc_id", slots).alias("vslot"), F.monotonically_increasing_id().alias("row"))
    rows = stage(rows, "slots")
    loads, counts = slot_loads(rows)
    hot = [s for s, n in counts.items() if n > HOT_ROWS and HOT_SHARE * shards * loads[s] > sum(loads.values())]
    if hot:
        rows = rows.withColumn("own", F.concat_ws("/", F.col("doc_id").cast("string"), F.col("row").cast("string")))
        rows = rows.withColumn("vslot", F.when(F.col("vslot").isin(hot), slot_of("own", slots)).otherwise(F.col("vslot"))).drop("own")
        loads, counts = slot_loads(rows)
    table = SlotMap(spark)
    table.save(1, spread(loads, shards, slots))
    placed = table.as_dict(1)
    before, offset = [0] * shards, []
    for slot in range(slots):
        offset.append((slot, placed[slot], before[placed[slot]]))
        before[placed[slot]] += counts.get(slot, 0)
    side = F.broadcast(spark.createDataFrame(offset, "vslot int, shard int, first long"))
    rank = F.row_number().over(Window.partitionBy("vslot").orderBy("doc_id", "text_crc32", "size", "row"))
    numbered = rows.withColumn("rank", rank).join(side, "vslot")
    return numbered.select("doc_id", "size", "text_crc32", "vslot", "shard", (F.col("first") + F.col("rank") - 1).alias("slot"), F.lit(1).alias("map_version"))
