"""Gapless numbers inside groups without sorting a group in one task."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

#: Rows of a numbering cell, about, and cells of a group at most.
CELL_ROWS, MAX_CELLS = 50_000, 1 << 14


def number_in_groups(df: DataFrame, group: str, order: list[str], out: str, rows: int) -> DataFrame:
    """``df`` with ``out``: 0, 1, ... inside each value of ``group``, by (hash cell of ``order``, ``order``).

    ``df`` is read twice, so it must be cheap or written. ``rows`` is its row count. Groups are dealt to hash
    cells; a cell's first number is the count of the cells before it, and only a cell is sorted in one task.
    """
    cells = max(1, min(MAX_CELLS, -(-rows // CELL_ROWS)))
    dealt = df.withColumn("_cell", F.pmod(F.xxhash64(*order), F.lit(cells)).cast("int"))
    before = Window.partitionBy(group).orderBy("_cell").rowsBetween(Window.unboundedPreceding, -1)
    starts = dealt.groupBy(group, "_cell").count().select(group, "_cell", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("_before"))
    inside = Window.partitionBy(group, "_cell").orderBy(*order)
    return dealt.withColumn("_n", F.row_number().over(inside)).join(starts, [group, "_cell"]).withColumn(out, F.col("_before") + F.col("_n") - 1).drop("_cell", "_n", "_before")
