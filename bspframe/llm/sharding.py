"""Sharding by jump consistent hashing.

A row's key alone and the shard count decide its shard, without a ring table; with one shard more, a row
either stays or moves to the new shard. Slots inside a shard are numbered without gaps by counts of
(shard, bucket) cells, so that no shard is ever sorted in one task.

Defined results: a null doc_id is hashed as the lowest long value; a null text has size 8; rows that repeat
a key share a shard and get slots of their own.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from functools import partial
from pyspark.sql import DataFrame, Window, functions as F

from bspframe.session import ship

#: Multiplier of the generator that the published algorithm uses.
STEP = 2862933555777941757
#: Rows in a numbering cell, about, and cells of a shard at most.
CELL_ROWS, MAX_CELLS = 50_000, 1 << 14


def jump_hash(keys: np.ndarray, shards: int) -> np.ndarray:
    """Shard of each unsigned 64-bit key; a vectorised run of the jump process over the keys still moving."""
    state = keys.astype(np.uint64)
    out = np.zeros(len(state), np.int64)
    live = np.arange(len(state))
    here = np.zeros(len(state), np.int64)
    while len(live):
        out[live] = here
        state[live] = state[live] * np.uint64(STEP) + np.uint64(1)
        leap = float(1 << 31) / ((state[live] >> np.uint64(33)).astype(np.float64) + 1.0)
        here = ((out[live] + 1) * leap).astype(np.int64)
        stay = here < shards
        live, here = live[stay], here[stay]
    return out


def _shards(batches, counts: tuple[int, ...]):
    for batch in batches:
        keys = batch.column(batch.schema.get_field_index("_key")).to_numpy(zero_copy_only=False).view(np.uint64)
        cols = [batch.column(i) for i in range(batch.num_columns)] + [pa.array(jump_hash(keys, c), pa.int32()) for c in counts]
        yield pa.RecordBatch.from_arrays(cols, batch.schema.names + [f"_s{i}" for i in range(len(counts))])


def shard(docs: DataFrame, shards: int = 24, grown: int | None = None, key: str = "doc_id") -> DataFrame:
    """``docs(doc_id, text)`` → doc_id, size, text_crc32, law, shard, slot, grown_shard under the law ``key``."""
    spark = docs.sparkSession
    ship(spark)
    grown = grown or shards + 1
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(F.col(key).alias("doc_id"), F.octet_length(text).cast("long").alias("size"), F.crc32(text).alias("text_crc32"))
    rows = rows.withColumn("size", F.col("size") + 8).withColumn("_key", F.xxhash64(F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63)))))
    schema = ", ".join(f"`{n}` {t}" for n, t in rows.dtypes) + ", _s0 int, _s1 int"
    placed = rows.mapInArrow(partial(_shards, counts=(shards, grown)), schema).withColumnsRenamed({"_s0": "shard", "_s1": "grown_shard"})
    # the counting pass reads the key column only
    n = docs.select(key).count()
    cells = max(1, min(MAX_CELLS, -(-n // (shards * CELL_ROWS))))
    placed = placed.withColumn("_cell", F.pmod(F.shiftright("_key", 7), F.lit(cells)).cast("int"))
    slim = docs.select(F.xxhash64(F.coalesce(F.col(key).cast("long"), F.lit(-(1 << 63)))).alias("_key"))
    counted = slim.mapInArrow(partial(_shards, counts=(shards,)), "_key long, _s0 int").groupBy(F.col("_s0").alias("shard"), F.pmod(F.shiftright("_key", 7), F.lit(cells)).cast("int").alias("_cell")).count()
    before = Window.partitionBy("shard").orderBy("_cell").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counted.select("shard", "_cell", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("_before"))
    inside = Window.partitionBy("shard", "_cell").orderBy("doc_id", "text_crc32", "size")
    numbered = placed.withColumn("_n", F.row_number().over(inside))
    return numbered.join(F.broadcast(offsets), ["shard", "_cell"]).select(  # shards * MAX_CELLS rows at most
        "doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", (F.col("_before") + F.col("_n") - 1).cast("long").alias("slot"), "grown_shard"
    )
