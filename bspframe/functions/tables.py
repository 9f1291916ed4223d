"""Functions callable from SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession, functions as F
from pyspark.sql.functions import pandas_udf, udtf

from bspframe.functions.hashing import KNUTH


class AdjacencyLine:
    """``adjacency_line('7 1 2')`` gives (7, 1) and (7, 2)."""

    def eval(self, line: str):
        n = [int(x) for x in (line or "").replace(",", " ").split()]
        for d in n[1:]:
            yield n[0], d


def _portable_hash(ids: pd.Series) -> pd.Series:
    return ids.map(lambda x: None if pd.isna(x) else int(x) * KNUTH % (1 << 32)).astype("Int64")


def register_sql(spark: SparkSession) -> None:
    """Registers ``adjacency_line`` and ``portable_hash``."""
    spark.udtf.register("adjacency_line", udtf(AdjacencyLine, returnType="src: bigint, dst: bigint"))
    spark.udf.register("portable_hash", pandas_udf(_portable_hash, "long"))


def register_pagerank(spark: SparkSession, edges_view: str, out_view: str, rounds: int = 20) -> None:
    """Ranks of a view of edges as another view. A table function cannot start jobs, so this is a call."""
    from bspframe.algos.pagerank import pagerank
    from bspframe.graph import Graph

    pagerank(Graph.from_edges(spark.table(edges_view)), max_rounds=rounds).df.withColumn("rank", F.col("rank")).createOrReplaceTempView(out_view)
