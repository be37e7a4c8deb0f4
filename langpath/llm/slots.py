"""Sharding by fixed virtual slots, in DataFrame functions only.

Each record hashes to one of ``N_SLOTS`` slots.  Bytes and rows are summed per slot, the slots
(a fixed, small number) are dealt to shards, the heaviest first to the lightest shard, and the
map is stored as a versioned table.  Rebalancing edits that map: only the slots of overloaded
shards that must go move, and the edit is a new version.

Defined cases: a null text has size 16 and crc 0; null doc_id hashes as null together with the
text's crc; repeated rows keep one position each; an empty table gives an empty map and no rows;
other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

N_SLOTS = 4096
N_SHARDS = 40
MAP_SCHEMA = "version long, slot int, shard int, slot_bytes long, slot_rows long, first long"


def records(docs: DataFrame, n_slots: int = N_SLOTS, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, size, text_crc32 and virtual slot of each record; texts go no further."""
    body = F.coalesce(F.col(text), F.lit(""))
    row = docs.select(F.col(doc_id).cast("long").alias("doc_id"), (F.octet_length(body).cast("long") + 16).alias("size"), F.crc32(body.cast("binary")).alias("text_crc32"))
    return row.withColumn("vslot", F.pmod(F.xxhash64("doc_id", "text_crc32"), F.lit(n_slots)).cast("int"))


def slot_loads(rows: DataFrame) -> DataFrame:
    return rows.groupBy("vslot").agg(F.sum("size").alias("slot_bytes"), F.count("*").alias("slot_rows"))


def _deal(loads: Column, start: Column) -> Column:
    """Fold over slots (heaviest first): each goes to the shard with the fewest bytes so far."""

    def step(acc: Column, s: Column) -> Column:
        k = F.array_position(acc["bytes"], F.array_min(acc["bytes"])).cast("int")
        put = lambda xs, v: F.transform(xs, lambda x, i: F.when(i + 1 == k, x + v).otherwise(x))
        placed = F.struct(s["slot"].alias("slot"), (k - 1).alias("shard"), s["slot_bytes"].alias("slot_bytes"), s["slot_rows"].alias("slot_rows"))
        return F.struct(put(acc["bytes"], s["slot_bytes"]).alias("bytes"), F.concat(acc["out"], F.array(placed)).alias("out"))

    none = F.array().cast("array<struct<slot:int,shard:int,slot_bytes:bigint,slot_rows:bigint>>")
    return F.aggregate(loads, F.struct(start.alias("bytes"), none.alias("out")), step, lambda acc: acc["out"])


def _with_first(m: DataFrame) -> DataFrame:
    """Add the position within its shard at which each slot's rows begin."""
    w = Window.partitionBy("shard").orderBy("slot")
    return m.withColumn("first", F.coalesce(F.sum("slot_rows").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0).cast("long")))


def new_map(loads: DataFrame, n_shards: int = N_SHARDS, version: int = 0) -> DataFrame:
    """Slot-to-shard map for the loads of at most ``N_SLOTS`` slots."""
    heavy = F.transform(F.array_sort(F.collect_list(F.struct((-F.col("slot_bytes")).alias("w"), F.col("vslot").alias("slot"), "slot_rows"))), lambda x: F.struct(x["slot"].alias("slot"), (-x["w"]).alias("slot_bytes"), x["slot_rows"].alias("slot_rows")))
    m = loads.agg(heavy.alias("s")).select(F.inline(_deal(F.col("s"), F.array_repeat(F.lit(0).cast("long"), n_shards))))
    return _with_first(m).select(F.lit(version).cast("long").alias("version"), "slot", "shard", "slot_bytes", "slot_rows", "first")


def rebalance(old: DataFrame, loads: DataFrame, n_shards: int, slack: float = 0.02) -> DataFrame:
    """The next version of a map for new loads or another number of shards.

    A shard keeps its slots, largest first, as long as they stay under the mean load plus
    ``slack``; the others, and slots of shards that are gone or slots that are new, are dealt anew."""
    now = loads.join(F.broadcast(old.select(F.col("slot").alias("vslot"), "shard", "version")), "vslot", "left")
    total = F.sum("slot_bytes").over(Window.partitionBy())
    w = Window.partitionBy("shard").orderBy(F.desc("slot_bytes"), "vslot")
    now = now.withColumn("limit", total / n_shards * (1 + slack)).withColumn("upto", F.sum("slot_bytes").over(w))
    stays = (F.col("shard") < n_shards) & (F.col("upto") <= F.col("limit"))
    parts = now.agg(
        F.max("version").alias("v"),
        F.collect_list(F.when(stays, F.struct(F.col("vslot").alias("slot"), "shard", "slot_bytes", "slot_rows"))).alias("kept"),
        F.array_sort(F.collect_list(F.when(~F.coalesce(stays, F.lit(False)), F.struct((-F.col("slot_bytes")).alias("w"), F.col("vslot").alias("slot"), "slot_rows")))).alias("moved"),
    )
    start = F.transform(F.sequence(F.lit(0), F.lit(n_shards - 1)), lambda k: F.aggregate(F.col("kept"), F.lit(0).cast("long"), lambda a, x: a + F.when(x["shard"] == k, x["slot_bytes"]).otherwise(0)))
    again = F.transform("moved", lambda x: F.struct(x["slot"].alias("slot"), (-x["w"]).alias("slot_bytes"), x["slot_rows"].alias("slot_rows")))
    m = parts.select("v", F.inline(F.concat(F.col("kept"), _deal(again, start))))
    return _with_first(m).select((F.col("v") + 1).alias("version"), "slot", "shard", "slot_bytes", "slot_rows", "first")


def save_map(m: DataFrame, path: str) -> DataFrame:
    """Append a version to the stored map and return it as read back."""
    m.coalesce(1).write.mode("append").parquet(path)
    return latest_map(m.sparkSession, path)


def latest_map(spark: SparkSession, path: str) -> DataFrame:
    stored = spark.read.schema(MAP_SCHEMA).parquet(path)
    return stored.join(F.broadcast(stored.agg(F.max("version").alias("version"))), "version", "left_semi")


def assign(rows: DataFrame, m: DataFrame) -> DataFrame:
    """Shard and position of each record.  Positions are counted within a slot, so no task
    holds a shard; the map has at most ``N_SLOTS`` rows and is broadcast."""
    w = Window.partitionBy("vslot").orderBy("doc_id", "text_crc32", "size")
    at = rows.withColumn("k", F.row_number().over(w) - 1)
    return at.join(F.broadcast(m.select(F.col("slot").alias("vslot"), "shard", "first", "version")), "vslot").select("doc_id", "size", "text_crc32", "shard", (F.col("first") + F.col("k")).alias("position"), "vslot", F.col("version").alias("map_version"))
