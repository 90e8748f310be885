"""Sharding over fixed virtual slots, in DataFrame expressions only.

A record's virtual slot is a hash of its id and text check value, one of a fixed
number that never changes. Bytes and rows are summed per slot; a map from slots to
shards is kept as a numbered table. A rebalance edits that map (slots move, records
are never re-hashed) and writes the next version.

Rows with equal texts are records of their own: their ids put them in different slots.
Copies of one row (id and text equal) also differ by a number of the row, so that no slot
grows with a group of copies.

Defined cases: a null text has no bytes; a null id hashes like any other value;
repeated rows each get their own place; an empty table gives an empty result and a map
whose slots are empty; further columns of the input are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from prunegraph.llm.common import crc32, materialize, salt, with_copy

SLOTS = 4096
OVERHEAD = 16


def records(docs: DataFrame, slots: int = SLOTS) -> DataFrame:
    """doc_id, size, text_crc32 and the virtual slot of every row."""
    rows = docs.select(
        "doc_id",
        (F.coalesce(F.octet_length("text"), F.lit(0)).cast("long") + OVERHEAD).alias("size"),
        crc32(F.col("text")).alias("text_crc32"),
    )
    numbered = with_copy(materialize(rows, "records"), ["doc_id", "text_crc32"])
    return numbered.withColumn("vslot", salt(F.col("doc_id"), F.col("text_crc32"), F.col("copy"), n=slots))


def slot_bytes(rows: DataFrame, slots: int = SLOTS) -> DataFrame:
    """One row per virtual slot, empty ones included: bytes and rows."""
    every = rows.sparkSession.range(slots).select(F.col("id").cast("int").alias("vslot"))
    found = rows.groupBy("vslot").agg(F.sum("size").alias("bytes"), F.count(F.lit(1)).alias("n"))
    return every.join(found, "vslot", "left").na.fill(0, ["bytes", "n"])


def rebalance(stats: DataFrame, shards: int, previous: DataFrame | None = None, version: int = 1) -> DataFrame:
    """The next version of the map: version, vslot, shard, bytes, n.

    Slots are taken largest first; each goes to the shard with the fewest bytes, or
    stays where ``previous`` has it while that shard is still below an even share. The
    fold runs inside one row, over a number of slots that is fixed."""
    if previous is None:
        before = stats.withColumn("was", F.lit(-1))
    else:
        before = stats.join(previous.select("vslot", F.col("shard").alias("was")), "vslot", "left").na.fill(-1, ["was"])
    one = before.agg(
        F.sort_array(F.collect_list(F.struct(F.col("bytes"), F.col("vslot"), F.col("was"), F.col("n"))), asc=False).alias("slots"),
        (F.sum("bytes") / shards).alias("share"),
    )
    load = f"transform(sequence(1, {shards}), x -> 0L)"
    # every slot adds one entry "shard" to the list; load[shard] grows by its bytes
    folded = F.expr(
        f"""aggregate(slots, named_struct('load', {load}, 'to', cast(array() as array<int>)),
        (s, x) -> named_struct(
            'load', zip_with(s.load, sequence(0, {shards} - 1), (v, k) -> v + if(k = if(x.was >= 0 and x.was < {shards} and s.load[greatest(x.was, 0) % {shards}] + x.bytes <= share, x.was,
                cast(array_position(s.load, array_min(s.load)) - 1 as int)), x.bytes, 0L)),
            'to', concat(s.to, array(if(x.was >= 0 and x.was < {shards} and s.load[greatest(x.was, 0) % {shards}] + x.bytes <= share, x.was,
                cast(array_position(s.load, array_min(s.load)) - 1 as int))))),
        s -> s.to)"""
    )
    return (
        one.withColumn("to", folded)
        .select(F.explode(F.arrays_zip("slots", "to")).alias("e"))
        .select(F.lit(version).alias("version"), F.col("e.slots.vslot").alias("vslot"), F.col("e.to").alias("shard"), F.col("e.slots.bytes").alias("bytes"), F.col("e.slots.n").alias("n"))
    )


def save_map(slot_map: DataFrame, folder: str) -> None:
    """Append a version; older ones stay readable."""
    slot_map.write.mode("append").partitionBy("version").parquet(folder)


def load_map(spark, folder: str, version: int) -> DataFrame:
    return spark.read.parquet(folder).filter(F.col("version") == version)


def place(rows: DataFrame, slot_map: DataFrame) -> DataFrame:
    """Every record with its shard and its place in that shard, gapless from 0.

    A slot's first place is the running row count of the slots before it in its shard,
    so places need a sort within slots only, never within a whole shard."""
    in_shard = Window.partitionBy("shard").orderBy("vslot").rowsBetween(Window.unboundedPreceding, -1)
    starts = slot_map.select("vslot", "shard", F.coalesce(F.sum("n").over(in_shard), F.lit(0)).alias("first"))
    in_slot = Window.partitionBy("vslot").orderBy("doc_id", "text_crc32", "copy")
    ranked = rows.withColumn("k", F.row_number().over(in_slot) - 1)
    # one row per virtual slot: its size is fixed, whatever the input is
    return ranked.join(F.broadcast(starts), "vslot").withColumn("slot", F.col("first") + F.col("k"))


def shard(docs: DataFrame, shards: int = 40, slots: int = SLOTS, previous: DataFrame | None = None, version: int = 1) -> tuple[DataFrame, DataFrame]:
    """(placed rows, slot map) for ``docs``; near-equal bytes per shard."""
    rows = materialize(records(docs, slots), "slotted")
    slot_map = materialize(rebalance(slot_bytes(rows, slots), shards, previous, version), "slot-map")
    return place(rows, slot_map), slot_map


def grow(docs: DataFrame, folder: str, before: int = 39, shards: int = 40, slots: int = SLOTS) -> DataFrame:
    """Placed rows after the map in ``folder`` went from ``before`` to ``shards`` shards.

    Version 1 is stored, then edited into version 2; rows are placed by what is stored."""
    spark = docs.sparkSession
    rows = materialize(records(docs, slots), "slotted")
    stats = materialize(slot_bytes(rows, slots), "slot-bytes")
    save_map(rebalance(stats, before), folder)
    save_map(rebalance(stats, shards, load_map(spark, folder, 1), version=2), folder)
    return place(rows, load_map(spark, folder, 2))
