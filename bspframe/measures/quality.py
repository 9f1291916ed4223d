"""Measures of partitionings and answers."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from bspframe.graph import Graph


def replicas(parted: DataFrame) -> DataFrame:
    """(id, replicas): parts that hold each vertex."""
    ends = parted.select(F.explode(F.array("src", "dst")).alias("id"), "part").distinct()
    return ends.groupBy("id").agg(F.count("*").alias("replicas"))


def replication_factor(parted: DataFrame) -> DataFrame:
    """One row: vertices, edges, parts in use, mean replicas."""
    r = replicas(parted).agg(F.count("*").alias("vertices"), F.round(F.avg("replicas"), 6).alias("replication_factor"))
    return r.crossJoin(parted.agg(F.count("*").alias("edges"), F.countDistinct("part").alias("parts")))  # one row each


def block_stats(g: Graph, blocks: DataFrame) -> DataFrame:
    """One row: blocks, greatest and mean size, share of edges cut, boundary vertices."""
    b = blocks.select("id", "block")
    sizes = b.groupBy("block").count().agg(F.count("*").alias("blocks"), F.max("count").alias("max_size"), F.round(F.avg("count"), 6).alias("mean_size"))
    e = g.edges.join(b.toDF("src", "sb"), "src").join(b.toDF("dst", "db"), "dst")
    cut = e.agg(F.count("*").alias("edges"), F.count_if(F.col("sb") != F.col("db")).alias("cut_edges"))
    edge = e.where("sb <> db").select(F.explode(F.array("src", "dst")).alias("id")).agg(F.countDistinct("id").alias("boundary_vertices"))
    return sizes.crossJoin(cut).crossJoin(edge)  # one row each


def update_ratio(approx: list, exact: list, vertices: int, spark) -> DataFrame:
    """(round, ratio): vertices that an approximate run computes over those of the exact run, and the whole as round 0.

    An exact round computes every vertex.
    """
    a = {s.round: s.changed for s in approx}
    rows = [(r, float(a.get(r, 0)) / vertices if vertices else 0.0) for r in range(1, max(len(exact), max(a, default=0)) + 1)]
    return spark.createDataFrame([(0, sum(a.values()) / max(1, vertices * len(exact))), *rows], "round int, ratio double")


def rank_error(approx: DataFrame, exact: DataFrame, k: int = 100) -> DataFrame:
    """One row: L1, L-infinity, mean relative error, overlap of the top k, and rank agreement among these."""
    both = approx.select("id", F.col("rank").alias("a")).join(exact.select("id", F.col("rank").alias("e")), "id", "full")
    both = both.select("id", F.coalesce("a", F.lit(0.0)).alias("a"), F.coalesce("e", F.lit(0.0)).alias("e"))
    d = F.abs(F.col("a") - F.col("e"))
    sums = both.agg(F.sum(d).alias("l1"), F.max(d).alias("linf"), F.avg(F.when(F.col("e") != 0, d / F.col("e"))).alias("mean_relative"))
    top = lambda c: both.orderBy(F.desc(c), "id").limit(k).select("id", F.row_number().over(Window.orderBy(F.desc(c), "id")).alias(f"r{c}"))
    met = top("a").join(top("e"), "id").agg(F.count("*").alias("top_overlap"), F.corr("ra", "re").alias("top_rank_agreement"))
    return sums.crossJoin(met)  # one row each


def cost_factor(single_s: float, parallel_s: float, inverse: bool = False) -> float:
    """Single-thread time over parallel time; the inverse on request."""
    return parallel_s / single_s if inverse else single_s / parallel_s


def round_budget(limit_s: float, rounds: int) -> float:
    """Seconds a round may take."""
    return limit_s / rounds


def expansion(memory_bytes: float, input_bytes: float) -> float:
    """Cluster memory over input bytes."""
    return memory_bytes / input_bytes


def answers_agree(a: DataFrame, b: DataFrame) -> int:
    """Rows that one of two answers has and the other has not."""
    return a.exceptAll(b).count() + b.exceptAll(a).count()
