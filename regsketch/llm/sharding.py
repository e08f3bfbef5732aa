"""Shards by fixed virtual slots.

Records are hashed into some thousands of slots once and for all; bytes are added
up by slot; a versioned map says which shard has each slot. Rebalancing edits the
map, so that only records of moved slots move. The map has a row for each slot, never
one for each record, and so is planned on the driver at any size of the input. ``shard`` stores the
map, reads it back, and stores beside it what the next version would be with one shard more.

The law is near-equal bytes. Groups (equal texts) are not kept together, as one group may hold a third of all rows: their rows are hashed by their own doc_id.

Defined results: a null text has size 1; rows without a doc_id are hashed by their
text; rows with one doc_id share a slot, whose bytes cannot be parted; an empty table gives no rows; extra columns
are ignored.
"""

from __future__ import annotations

import heapq
import os
import uuid

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .storage import shared_folder

SLOTS = 8192
SHARDS = 8
MAP = "version int, slot int, shard int, bytes bigint, records bigint"


def slotted(docs: DataFrame, slots: int = SLOTS) -> DataFrame:
    """(doc_id, size, text_crc32, virtual_slot) for every record."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    key = F.when(F.col("doc_id").isNull(), F.xxhash64(text)).otherwise(F.xxhash64(F.col("doc_id").cast("bigint")))
    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), (F.octet_length(text) + F.lit(1)).cast("bigint").alias("size"), F.crc32(text).alias("text_crc32"), F.pmod(key, F.lit(slots)).cast("int").alias("virtual_slot"))


def slot_totals(records: DataFrame) -> DataFrame:
    """(virtual_slot, bytes, records), a row for each slot in use."""
    return records.groupBy("virtual_slot").agg(F.sum("size").alias("bytes"), F.count(F.lit(1)).alias("records"))


def plan(totals: list[tuple[int, int, int]], shards: int = SHARDS, slots: int = SLOTS) -> list[tuple[int, int, int, int, int]]:
    """The first map (MAP): slots by falling bytes, each to the shard with the fewest bytes so far."""
    known = {s: (b, n) for s, b, n in totals}
    every = sorted(((*known.get(s, (0, 0)), s) for s in range(slots)), key=lambda x: (-x[0], x[2]))
    heap = [(0, 0, k) for k in range(shards)]
    out = []
    for size, n, slot in every:
        load, held, shard = heapq.heappop(heap)
        out.append((1, slot, shard, size, n))
        heapq.heappush(heap, (load + size, held + 1, shard))
    return sorted(out, key=lambda x: x[1])


def rebalanced(old: list[tuple[int, int, int, int, int]], shards: int) -> list[tuple[int, int, int, int, int]]:
    """The next version of a map for this number of shards: slots move only off shards that hold more than their share, or that are gone."""
    version = max((x[0] for x in old), default=0) + 1
    total = sum(x[3] for x in old)
    share = total / shards
    load = [0] * shards
    free, by_shard = [], {k: [] for k in range(shards)}
    for _, slot, shard, size, n in old:
        if shard < shards:
            by_shard[shard].append((size, slot, n))
            load[shard] += size
        else:
            free.append((size, slot, n))
    for shard, own in by_shard.items():
        own.sort()
        while own and load[shard] - own[0][0] >= share:
            # the largest slot that the shard can spare
            at = max(i for i, x in enumerate(own) if load[shard] - x[0] >= share)
            size, slot, n = own.pop(at)
            load[shard] -= size
            free.append((size, slot, n))
    heap = [(load[k], k) for k in range(shards)]
    heapq.heapify(heap)
    for size, slot, n in sorted(free, key=lambda x: (-x[0], x[1])):
        held, shard = heapq.heappop(heap)
        by_shard[shard].append((size, slot, n))
        heapq.heappush(heap, (held + size, shard))
    return sorted(((version, slot, shard, size, n) for shard, own in by_shard.items() for size, slot, n in own), key=lambda x: x[1])


def write_map(spark: SparkSession, rows: list[tuple], path: str) -> None:
    """Store one version of the map in a folder of its own; a version that is there already is never written again, older ones stay readable."""
    (version,) = {r[0] for r in rows}
    spark.createDataFrame(rows, MAP).drop("version").coalesce(1).write.mode("errorifexists").parquet(f"{path}/version={version}")


def read_map(spark: SparkSession, path: str, version: int | None = None) -> list[tuple]:
    """One version of the map, the latest by default; a map with a slot twice or not at all is refused."""
    table = spark.read.parquet(path)
    version = table.agg(F.max("version")).first()[0] if version is None else version
    rows = [(version, r["slot"], r["shard"], r["bytes"], r["records"]) for r in table.where(F.col("version") == version).orderBy("slot").collect()]
    if [r[1] for r in rows] != list(range(len(rows))) or not rows:
        raise ValueError(f"version {version} of the map at {path} does not have every slot once")
    return rows


def assign(records: DataFrame, rows: list[tuple], grown: dict[int, int]) -> DataFrame:
    """Records with shard, with slot, their place in it: 0, 1, ... without gaps, and with rebalanced_shard, the slot's in ``grown``.

    Places are counted within virtual slots and begin after those of the shard's
    earlier slots, so that no shard is sorted in one task.
    """
    first: dict[int, int] = {}
    placed = []
    for version, slot, shard, _, n in rows:
        placed.append((version, slot, shard, first.get(shard, 0), grown[slot]))
        first[shard] = first.get(shard, 0) + n
    table = records.sparkSession.createDataFrame(placed, "map_version int, virtual_slot int, shard int, first_place bigint, rebalanced_shard int")
    own = F.row_number().over(Window.partitionBy("virtual_slot").orderBy("doc_id", "text_crc32", "size"))
    return records.withColumn("own", own).join(F.broadcast(table), "virtual_slot").withColumn("slot", F.col("first_place") + F.col("own") - 1).drop("own", "first_place")


def shard(docs: DataFrame, shards: int = SHARDS, slots: int = SLOTS, path: str | None = None) -> DataFrame:
    """Every record with its virtual slot, shard and place in the shard, and the shard it would have with one shard more (rebalanced_shard).

    The map is planned on the slots' bytes, or, if there is one at ``path``, its latest version is read and edited for this number of shards where it has another.
    """
    spark = docs.sparkSession
    records = slotted(docs, slots)
    path = path or os.path.join(shared_folder(spark), f"slot-map-{uuid.uuid4().hex}")
    try:
        known = read_map(spark, path)
    except AnalysisException:  # there is none yet
        known = None
    totals = [(r["virtual_slot"], r["bytes"], r["records"]) for r in slot_totals(records).collect()]  # at most ``slots`` rows
    if known is None:
        write_map(spark, plan(totals, shards, slots), path)
    else:
        now = {s: (b, n) for s, b, n in totals}
        fresh = [(v, s, k, *now.get(s, (0, 0))) for v, s, k, _, _ in known]
        write_map(spark, rebalanced(fresh, shards), path)
    current = read_map(spark, path)
    proposed = f"{path}-for-{shards + 1}-{current[0][0]}"
    write_map(spark, rebalanced(current, shards + 1), proposed)
    return assign(records, current, {slot: k for _, slot, k, _, _ in read_map(spark, proposed)})
