"""Temporal edges: interval joins and as-of joins of events."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F


def interval_edges(df: DataFrame, key: str, ts: str, id_col: str, seconds: int) -> DataFrame:
    """(src, dst): events of one ``key`` at most ``seconds`` apart, earlier to later, ties by id.

    Each event meets its own time bucket and the next one, so the join is an equality on (key, bucket) and no key is
    compared whole. Rows with a null key, time or id have no edge.
    """
    t = df.select(F.col(key).alias("k"), F.unix_micros(F.col(ts).cast("timestamp")).alias("t"), F.col(id_col).alias("i")).dropna()
    width = max(1, seconds) * 1_000_000
    b = F.floor(F.col("t") / width)
    left = t.select("k", F.explode(F.array(b, b + 1)).alias("b"), F.col("t").alias("ta"), F.col("i").alias("src"))
    right = t.select("k", b.alias("b"), F.col("t").alias("tb"), F.col("i").alias("dst"))
    near = (F.col("tb") - F.col("ta") <= seconds * 1_000_000) & ((F.col("tb") > F.col("ta")) | ((F.col("tb") == F.col("ta")) & (F.col("dst") > F.col("src"))))
    return left.join(right, ["k", "b"]).where(near).select("src", "dst")


def asof_edges(left: DataFrame, right: DataFrame, key: str, ts: str, id_col: str) -> DataFrame:
    """(src, dst): each left event to the last right event of its key at or before its time; without one, none.

    A union and one window, so both sides are shuffled once; of right events at one time the largest id counts.
    """
    cols = lambda df, side: df.select(F.col(key).alias("k"), F.col(ts).alias("t"), F.lit(side).alias("s"), F.col(id_col).alias("i"))
    rows = cols(left, 1).union(cols(right, 0)).where("k is not null and t is not null")
    w = Window.partitionBy("k").orderBy("t", "s", "i").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    seen = rows.withColumn("last", F.last(F.when(F.col("s") == 0, F.col("i")), ignorenulls=True).over(w))
    return seen.where("s = 1 and last is not null").select(F.col("i").alias("src"), F.col("last").alias("dst"))


def property_edges(events: DataFrame) -> DataFrame:
    """Edges from an event to the number in its JSON properties, weighted by the event's value."""
    return events.select(F.col("event_id").alias("src"), F.get_json_object("props", "$.k").cast("long").alias("dst"), F.col("value").alias("w")).where("dst is not null")


def bucketed_edges(df: DataFrame, unit: str) -> DataFrame:
    """Edges (src, dst, ts) counted by calendar unit."""
    return df.groupBy("src", "dst", F.date_trunc(unit, "ts").alias("at")).agg(F.count("*").alias("w"))
