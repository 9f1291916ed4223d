"""Vertex-centric supersteps: edges join the senders, messages are combined, receivers apply."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from bspframe.engines.dealing import deal, held
from bspframe.engines.program import Program, first_state, message_edges
from bspframe.graph import Graph, Result
from bspframe.loop import Adaptive, Truncate, pin, superstep_loop

CHANGE = "case when value is null or old is null then 0D else abs(cast(value as double) - cast(old as double)) end"


def run_vertex(g: Graph, p: Program, combiner: bool = True, frontier: bool | None = None, truncate: Truncate | None = None, partitions: int | None = None, start: DataFrame | None = None, resume_from: str | None = None, save_to: str | None = None, hub_edges: int | None = None) -> Result:
    """Run a program in synchronous rounds.

    Edges are pinned by source and state by id, so a round has one exchange: the combined messages. Edges of sources
    with more than a share of a partition (and ``hub_edges``) are spread, and meet those sources' values by broadcast.
    Without ``combiner`` messages are gathered in lists first. ``frontier`` (default: the program's) lets only
    changed vertices send.
    """
    spark = g.spark
    use = p.frontier if frontier is None else frontier
    with Adaptive(spark):
        n = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
        kept = held(g, n, p.both, hub_edges)
        edges = deal(message_edges(kept.graph, p, kept.hubs), "src", n, kept.hubs)
        state = first_state(kept.graph, p) if start is None else start
        state = pin(state.withColumn("old", F.col("value")), "id", n)

        def step(s: DataFrame, _: int) -> DataFrame:
            senders = s.where("changed") if use else s
            sent = edges.meet(senders.select("id", "value")).select(F.col("dst").alias("id"), F.expr(p.send).cast(p.kind).alias("m"))
            if combiner:
                got = sent.groupBy("id").agg(p.combiner("m").alias("msg"))
            else:
                fold = {"sum": "aggregate(ms, cast(0 as %s), (a, x) -> a + x)" % p.kind, "min": "array_min(ms)", "max": "array_max(ms)"}[p.combine]
                got = sent.groupBy("id").agg(F.collect_list("m").alias("ms")).select("id", F.expr(fold).alias("msg"))
            new = s.select("id", F.col("value").alias("old")).join(got, "id", "left")
            new = new.select("id", F.expr(p.apply.replace("value", "old")).cast(p.kind).alias("value"), "old")
            return new.select("id", "value", F.expr(p.changed).alias("changed"), "old")

        state, done, stats = superstep_loop(state, step, p.halt, p.max_rounds, truncate, change=CHANGE, resume_from=resume_from, save_to=save_to)
        edges.unpersist()
        kept.release()
    return Result(state.select("id", "value"), done, stats)
