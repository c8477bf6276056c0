"""Sharding through fixed virtual slots [native].

Records hash into `slots` virtual slots, bytes are added up per slot, and a
versioned map says which shard a slot belongs to. The map holds one row per
slot, so its size is fixed by a parameter and never by the data; it is planned
by giving the heaviest slot to the lightest shard, one slot after another,
which makes the shards' bytes nearly equal. Rebalancing edits the map: to grow by one shard,
slots move into the new shard only. Records never move between slots.

Defined cases: a null text has no bytes and CRC-32 0; size is bytes plus 1, so
empty records count too; rows that share a doc_id are told apart by their
text's hash and get places of their own; a null doc_id hashes as such.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

SLOTS = 4096


def record_size(text: str = "text") -> Column:
    return (F.coalesce(F.octet_length(text), F.lit(0)) + 1).cast("long")


def with_slots(docs: DataFrame, slots: int = SLOTS) -> DataFrame:
    return docs.withColumns({"size": record_size(), "virtual_slot": F.pmod(F.xxhash64("doc_id", "text"), F.lit(slots)).cast("int")})


def slot_loads(records: DataFrame, slots: int = SLOTS) -> DataFrame:
    """virtual_slot, n, bytes for each slot, empty ones included."""
    held = records.groupBy("virtual_slot").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("bytes"))
    every = records.sparkSession.range(slots).select(F.col("id").cast("int").alias("virtual_slot"))
    return every.join(held, "virtual_slot", "left").na.fill(0, ["n", "bytes"])


def plan_map(loads: DataFrame, shards: int, version: int = 1) -> DataFrame:
    """version, virtual_slot, shard, n, bytes: heaviest slot first, each to the shard with the fewest bytes (ties: lowest shard)."""
    one = loads.agg(F.array_sort(F.collect_list(F.struct((-F.col("bytes")).alias("neg"), "virtual_slot", "n", "bytes"))).alias("todo"))
    lightest = lambda acc: (F.array_position(acc["load"], F.array_min(acc["load"])) - 1).cast("int")
    start = F.struct(F.array_repeat(F.lit(0).cast("long"), shards).alias("load"), F.array().cast("array<int>").alias("shard"))

    def give(acc: Column, x: Column) -> Column:
        to = lightest(acc)
        return F.struct(F.transform(acc["load"], lambda v, i: F.when(i == to, v + x["bytes"]).otherwise(v)).alias("load"), F.concat(acc["shard"], F.array(to)).alias("shard"))

    folded = one.select("todo", F.aggregate("todo", start, give)["shard"].alias("shards"))
    rows = folded.select(F.explode(F.arrays_zip("todo", "shards")).alias("r"))
    return rows.select(F.lit(version).alias("version"), F.col("r.todo.virtual_slot"), F.col("r.shards").alias("shard"), F.col("r.todo.n").alias("n"), F.col("r.todo.bytes").alias("bytes"))


def grow_map(slot_map: DataFrame, shards: int) -> DataFrame:
    """The next version for shards + 1 shards: each shard hands its lightest slots, up to its excess over the new mean, to the new shard; no other slot moves."""
    per = Window.partitionBy("shard")
    mean = F.sum("bytes").over(Window.partitionBy()) / (shards + 1)
    excess = F.sum("bytes").over(per) - mean
    before = F.sum("bytes").over(per.orderBy("bytes", "virtual_slot"))
    return slot_map.select((F.col("version") + 1).alias("version"), "virtual_slot", F.when(before <= excess, F.lit(shards)).otherwise(F.col("shard")).alias("shard"), "n", "bytes")


def place(records: DataFrame, slot_map: DataFrame) -> DataFrame:
    """records with shard and slot: places 0, 1, 2, ... of each shard without gaps. The map has a fixed number of rows and is broadcast."""
    first = F.sum("n").over(Window.partitionBy("shard").orderBy("virtual_slot")) - F.col("n")
    offsets = slot_map.select("virtual_slot", "shard", first.alias("first"))
    nth = F.row_number().over(Window.partitionBy("virtual_slot").orderBy("doc_id", "text_crc32", "size")) - 1
    return records.withColumn("nth", nth).join(F.broadcast(offsets), "virtual_slot").withColumn("slot", (F.col("first") + F.col("nth")).cast("long")).drop("first", "nth")


def op5_sharding(spark, sf_dir: str, shards: int = 8) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents").select("doc_id", "text")
    records = with_slots(docs).select("doc_id", "size", F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("text_crc32"), "virtual_slot")
    slot_map = common.stored(spark, plan_map(slot_loads(with_slots(docs)), shards), "slot-map")
    return place(records, slot_map).select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), F.col("shard").cast("int"), "slot", F.lit(None).cast("int").alias("grown_shard"), "virtual_slot")


OP5_SQL = None  # CRC-32 and the hash of the slots aren't in DuckDB; the tests check the law and the places by brute force
