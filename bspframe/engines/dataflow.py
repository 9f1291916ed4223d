"""Bounded dataflow: bulk iteration over the whole state, or a workset with a solution set."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Observation, functions as F

from bspframe.engines.dealing import deal, held
from bspframe.engines.program import Program, first_state, message_edges
from bspframe.engines.vertex import CHANGE
from bspframe.graph import Graph, Result
from bspframe.loop import Adaptive, RoundStat, Truncate, pin
from bspframe.session import checkpointed, drop_checkpoint, shared_dir

#: Rounds that one job of a bulk iteration pipelines when their number is fixed beforehand.
CHAIN = 5


def run_dataflow(g: Graph, p: Program, kind: str | None = None, truncate: Truncate | None = None, chain: int = CHAIN) -> Result:
    """``bulk`` passes the whole state through every round; ``delta`` passes the workset only and merges it."""
    kind = kind or ("delta" if p.frontier else "bulk")
    return _bulk(g, p, chain) if kind == "bulk" else _delta(g, p, truncate)


def _bulk(g: Graph, p: Program, chain: int) -> Result:
    """The state as a stream of records through a static plan: each record meets its target list, goes on as itself and
    as its messages, and both are reduced by id.

    The state is read once in a round, so rounds of a fixed number are chained in one job of up to ``chain`` without
    being stored in between; a run that ends by a test makes one round a job. Hubs' targets are kept as rows apart and
    meet the hubs' records by broadcast, one round a job.
    """
    spark = g.spark
    shared_dir(spark)
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    with Adaptive(spark):
        kept = held(g, n, p.both)
        edges = message_edges(kept.graph, p, kept.hubs)
        hub = F.col("src").isin(kept.hubs)
        lists = (edges.where(~hub) if kept.hubs else edges).groupBy(F.col("src").alias("id")).agg(F.collect_list(F.struct("dst", "w")).alias("to"))
        lists = pin(lists, "id", n)
        heavy = deal(edges.where(hub), "src", n, kept.hubs) if kept.hubs else None
        state = pin(first_state(kept.graph, p).select("id", "value", "changed", F.col("value").alias("old")), "id", n)
        own = F.struct(F.col("id"), F.col("value").alias("own"), F.lit(None).cast(p.kind).alias("m"), F.lit(True).alias("self"))
        message = lambda e: F.struct(e["dst"].alias("id"), F.lit(None).cast(p.kind).alias("own"), _sent(p, e).alias("m"), F.lit(False).alias("self"))

        def once(s: DataFrame) -> DataFrame:
            met = s.join(lists, "id", "left")
            talks = F.col("changed") & F.col("to").isNotNull() if p.frontier else F.col("to").isNotNull()
            rows = met.select(F.explode(F.when(talks, F.concat(F.array(own), F.transform("to", message))).otherwise(F.array(own))).alias("x")).select("x.*")
            if heavy is not None:
                more = heavy.meet((s.where("changed") if p.frontier else s).select("id", "value"))
                rows = rows.union(more.select(F.col("dst").alias("id"), F.lit(None).cast(p.kind), F.expr(p.send).cast(p.kind), F.lit(False)))
            got = rows.groupBy("id").agg(F.max("own").alias("old"), p.combiner("m").alias("msg"), F.bool_or("self").alias("_self"))
            new = got.where("_self").withColumn("value", F.expr(p.apply.replace("value", "old")).cast(p.kind))
            return new.select("id", "value", F.expr(p.changed).alias("changed"), "old")

        stats, number = [], 0
        while number < p.max_rounds:
            began = time.perf_counter()
            steps = min(chain, p.fixed - number) if p.fixed and heavy is None else 1
            fresh = state
            for _ in range(steps):
                fresh = once(fresh)
            number += steps
            seen = Observation()
            fresh = checkpointed(fresh.observe(seen, F.count_if("changed").alias("changed"), F.coalesce(F.max(F.expr(CHANGE)), F.lit(0.0)).alias("change")))
            drop_checkpoint(state)
            state = fresh
            got = seen.get
            stats.append(RoundStat(number, got["changed"], got["changed"], float(got["change"]), time.perf_counter() - began))
            if p.halt(stats[-1]):
                break
        lists.unpersist()
        if heavy is not None:
            heavy.unpersist()
        kept.release()
    return Result(state.select("id", "value"), number, stats)


def _sent(p: Program, edge):
    """The message of a record along ``edge`` (a struct of dst and w)."""
    if p.weight == "none":
        return F.expr(p.send).cast(p.kind)
    if p.send == "value * w":
        return (F.col("value") * edge["w"]).cast(p.kind)
    if p.send == "value + w":
        return (F.col("value") + edge["w"]).cast(p.kind)
    raise ValueError(f"bulk iteration has no form of the message {p.send!r}")


def _delta(g: Graph, p: Program, truncate: Truncate | None) -> Result:
    if p.combine != "min":
        raise ValueError("delta iteration takes programs that combine by min")
    every = (truncate or Truncate.auto()).every
    shared_dir(g.spark)
    n = int(g.spark.conf.get("spark.sql.shuffle.partitions"))
    with Adaptive(g.spark):
        kept = held(g, n, p.both)
        edges = deal(message_edges(kept.graph, p, kept.hubs), "src", n, kept.hubs)
        solution: DataFrame = pin(first_state(kept.graph, p).where("value is not null").select("id", "value"), "id", n)
        work = solution if p.name == "wcc" else solution.where(p.active)
        stats, number = [], 0
        while number < p.max_rounds:
            number += 1
            began = time.perf_counter()
            offers = edges.meet(work).select(F.col("dst").alias("id"), F.expr(p.send).cast(p.kind).alias("m")).groupBy("id").agg(F.min("m").alias("m"))
            better = offers.join(solution, "id", "left").where("value is null or m < value").select("id", F.col("m").alias("value")).persist()
            changed = better.count()
            merged = solution.join(better.select("id"), "id", "left_anti").union(better).repartition(n, "id")
            fresh = checkpointed(merged) if number % every == 0 else merged.persist()
            solution, work = fresh, better
            stats.append(RoundStat(number, changed, changed, 0.0, time.perf_counter() - began))
            if not changed or p.halt(stats[-1]):
                break
        edges.unpersist()
        full = checkpointed(kept.graph.vertices.join(solution, "id", "left").select("id", "value"))
        kept.release()
    return Result(full, number, stats)
