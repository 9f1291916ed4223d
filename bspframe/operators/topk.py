"""Top rows inside groups."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F


def topk_by(df: DataFrame, group: str, order: str, k: int, tie: str = "id") -> DataFrame:
    """The k rows of each group with the highest ``order``, ties by ``tie``; Spark keeps k rows of a group before the shuffle."""
    w = Window.partitionBy(group).orderBy(F.desc(order), tie)
    return df.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def set_operations(a: DataFrame, b: DataFrame) -> dict[str, DataFrame]:
    """Vertices in both answers, only in the first, and in either."""
    return {"both": a.select("id").intersect(b.select("id")), "first_only": a.select("id").subtract(b.select("id")), "either": a.select("id").union(b.select("id")).distinct()}
