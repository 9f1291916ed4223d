"""String keys to LONG ids."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from bspframe.session import materialise


def id_table(df: DataFrame, cols: list[str], mode: str = "rank") -> DataFrame:
    """(key, id) of all distinct values of ``cols``.

    ``rank``: 0, 1, ... in key order, from a range-partitioned sort with an offset for each partition.
    ``hash``: a 64-bit hash; check :func:`collisions`. Null keys get no id.
    """
    keys = df.select(F.explode(F.array(*[F.col(c).cast("string") for c in cols])).alias("key")).where("key is not null").distinct()
    if mode == "hash":
        return keys.withColumn("id", F.xxhash64("key"))
    if mode != "rank":
        raise ValueError("mode is 'rank' or 'hash'")
    ranged = materialise(keys.repartitionByRange("key").sortWithinPartitions("key").withColumn("part", F.spark_partition_id()), "ids")
    counts = ranged.groupBy("part").agg(F.count("*").alias("n"))  # one row for each partition
    before = counts.withColumn("before", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("part", "before")
    inside = Window.partitionBy("part").orderBy("key")
    return ranged.withColumn("r", F.row_number().over(inside)).join(F.broadcast(before), "part").select("key", (F.col("before") + F.col("r") - 1).alias("id"))


def encode_ids(df: DataFrame, cols: list[str], mode: str = "rank") -> DataFrame:
    """``df`` with ``<col>_id`` for each of ``cols``."""
    table = id_table(df, cols, mode)
    for c in cols:
        df = df.join(table.select(F.col("key").alias(c), F.col("id").alias(f"{c}_id")), c, "left")
    return df


def collisions(table: DataFrame) -> int:
    """How many ids stand for more than one key."""
    return table.groupBy("id").agg(F.countDistinct("key").alias("n")).where("n > 1").count()
