"""Map/reduce over files: plain, and loop-aware with cached invariants, cached last result and co-location."""

from __future__ import annotations

import time

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Observation, functions as F

from bspframe.engines.dealing import held
from bspframe.engines.program import Program, first_state, message_edges
from bspframe.engines.vertex import CHANGE
from bspframe.graph import Graph, Result
from bspframe.loop import Adaptive, RoundStat
from bspframe.session import checkpointed, drop_checkpoint, drop_table, shared_dir, table_path


#: Neighbours in one row of a hub's list.
LIST = 10_000


def _lists(g: Graph, p: Program, hubs: list[int]) -> tuple[DataFrame, DataFrame | None]:
    """(id, nbrs) of every vertex, null for sinks and hubs; and the hubs' lists cut into rows of about LIST."""
    edges = message_edges(g, p, hubs)
    hub = F.col("src").isin(hubs)
    gathered = lambda e, *by: e.groupBy(F.col("src").alias("id"), *by).agg(F.collect_list(F.struct("dst", "w")).alias("nbrs"))
    lists = g.vertices.join(gathered(edges.where(~hub) if hubs else edges), "id", "left")
    if not hubs:
        return lists, None
    rows = max(1, edges.where(hub).groupBy("src").count().agg(F.max("count")).first()[0] // LIST)
    return lists, gathered(edges.where(hub), F.pmod(F.xxhash64("dst"), F.lit(rows)).alias("_part")).drop("_part")


def _messages(p: Program, lists: DataFrame) -> DataFrame:
    """(id, m) for each neighbour in rows of (value, nbrs)."""
    sent = lists.select("value", F.explode("nbrs").alias("e"))
    return sent.select(F.col("e.dst").alias("id"), F.expr(p.send.replace("w", "e.w") if p.weight != "none" else p.send).cast(p.kind).alias("m"))


def _hub_messages(p: Program, heavy: DataFrame, state: DataFrame, hubs: list[int]) -> DataFrame:
    return _messages(p, heavy.join(F.broadcast(state.where(F.col("id").isin(hubs)).select("id", "value")), "id"))


def _write(df: DataFrame, path: str) -> Observation:
    seen = Observation()
    df.observe(seen, F.count_if("changed").alias("changed"), F.coalesce(F.max(F.expr(CHANGE)), F.lit(0.0)).alias("change")).write.parquet(path)
    return seen


def run_mapreduce(g: Graph, p: Program, workdir: str | None = None, hub_edges: int | None = None) -> Result:
    """Every round reads graph and state from files, maps, shuffles both, reduces, and writes both.

    A hub's list is kept as many rows in a table of its own, which is read and written in each round as well.
    """
    spark = g.spark
    base = workdir or table_path(spark, "mapreduce")
    path = f"{base}/round=0"
    kept = held(g, int(spark.conf.get("spark.sql.shuffle.partitions")), p.both, hub_edges)
    lists, heavy = _lists(kept.graph, p, kept.hubs)
    first_state(kept.graph, p).join(lists, "id").select("id", "value", "changed", F.col("value").alias("old"), "nbrs").write.parquet(path)
    if heavy is not None:
        heavy.write.parquet(f"{path}-hubs")
        wide = heavy.schema
    kept.release()
    schema = spark.read.parquet(path).schema
    stats, number = [], 0
    while number < p.max_rounds:
        number += 1
        began = time.perf_counter()
        rows = spark.read.schema(schema).parquet(path)
        # map: the record itself, and a message for each neighbour
        record = rows.select("id", F.struct("value", "nbrs").alias("rec"), F.lit(None).cast(p.kind).alias("m"))
        senders = rows.where("changed") if p.frontier else rows
        sent = _messages(p, senders)
        if kept.hubs:
            heavy = spark.read.schema(wide).parquet(f"{path}-hubs")
            sent = sent.union(_hub_messages(p, heavy, senders, kept.hubs))
        sent = sent.select("id", F.lit(None).cast(record.schema["rec"].dataType).alias("rec"), "m")
        # reduce
        got = record.union(sent).groupBy("id").agg(F.first("rec", ignorenulls=True).alias("rec"), p.combiner("m").alias("msg"))
        new = got.select("id", F.col("rec.value").alias("old"), "msg", F.col("rec.nbrs").alias("nbrs"))
        new = new.withColumn("value", F.expr(p.apply.replace("value", "old")).cast(p.kind)).withColumn("changed", F.expr(p.changed)).select("id", "value", "changed", "old", "nbrs")
        fresh = f"{base}/round={number}"
        seen = _write(new, fresh).get
        drop_table(path, spark)
        if kept.hubs:
            heavy.write.parquet(f"{fresh}-hubs")
            drop_table(f"{path}-hubs", spark)
        path = fresh
        stats.append(RoundStat(number, seen["changed"], seen["changed"], float(seen["change"]), time.perf_counter() - began))
        if p.halt(stats[-1]):
            break
    return Result(spark.read.schema(schema).parquet(path).select("id", "value"), number, stats)


def run_loop_mapreduce(g: Graph, p: Program, cache_invariant: bool = True, cache_last: bool = True, colocate: bool = True, cache_level: str = "DISK_ONLY", workdir: str | None = None, hub_edges: int | None = None) -> Result:
    """As plain map/reduce, with three features that can be switched off one by one.

    ``cache_invariant`` keeps the graph dealt and sorted by id between rounds, so only messages are shuffled; without it
    the graph is read from its file and dealt anew in every round. ``cache_last`` keeps the last answer beside the new
    one, so that the round's own job tests for the fixpoint; without it the state carries no old value, and a second job
    reads both answers back from files and compares them. ``colocate`` deals the state as the graph is dealt.
    ``cache_level='MEMORY_AND_DISK'`` keeps the graph in memory.
    """
    spark = g.spark
    shared_dir(spark)
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    level = getattr(StorageLevel, cache_level)
    base = workdir or table_path(spark, "loop-mapreduce")
    with Adaptive(spark):
        kept = held(g, n, p.both, hub_edges)
        lists, heavy = _lists(kept.graph, p, kept.hubs)
        lists = lists.where("nbrs is not null")
        if cache_invariant:
            graph = lists.repartition(n, "id").sortWithinPartitions("id").persist(level)
            heavy = heavy.repartition(n).persist(level) if heavy is not None else None
        else:
            lists.write.parquet(f"{base}/graph")
            if heavy is not None:
                heavy.write.parquet(f"{base}/graph-hubs")
                heavy = spark.read.schema(heavy.schema).parquet(f"{base}/graph-hubs")
            graph = spark.read.schema(lists.schema).parquet(f"{base}/graph")
        path = f"{base}/round=0"
        columns = ["id", "value", "changed", "old"]
        first = first_state(kept.graph, p).withColumn("old", F.col("value")).select(*columns).repartition(n, "id")
        if cache_last:
            s = checkpointed(first)
        else:
            first.write.parquet(path)
            s = spark.read.schema(first.schema).parquet(path)
        stats, number = [], 0
        while number < p.max_rounds:
            number += 1
            began = time.perf_counter()
            near = s if colocate else s.repartition(n)
            senders = near.where("changed") if p.frontier else near
            sent = _messages(p, graph.join(senders.select("id", "value"), "id"))
            if heavy is not None:
                sent = sent.union(_hub_messages(p, heavy, senders, kept.hubs))
            got = sent.groupBy("id").agg(p.combiner("m").alias("msg"))
            new = near.select("id", F.col("value").alias("old")).join(got, "id", "left").withColumn("value", F.expr(p.apply.replace("value", "old")).cast(p.kind))
            new = new.select("id", "value", F.expr(p.changed).alias("changed"), "old")
            if cache_last:
                seen = Observation()
                fresh = checkpointed(new.observe(seen, F.count_if("changed").alias("changed"), F.coalesce(F.max(F.expr(CHANGE)), F.lit(0.0)).alias("change")))  # the round's files
                moved, change = seen.get["changed"], seen.get["change"]
                drop_checkpoint(s)
            else:
                following = f"{base}/round={number}"
                new.write.parquet(following)
                fresh = spark.read.schema(new.schema).parquet(following)
                both = fresh.select("id", "value").join(s.select("id", F.col("value").alias("old")), "id")
                moved, change = both.agg(F.count_if(F.expr(p.changed)), F.coalesce(F.max(F.expr(CHANGE)), F.lit(0.0))).first()
                drop_table(path, spark)
                path = following
            s = fresh
            stats.append(RoundStat(number, moved, moved, float(change), time.perf_counter() - began))
            if p.halt(stats[-1]):
                break
        s.select("id", "value").write.parquet(f"{base}/answer")
        for df in (graph, heavy):
            if df is not None and cache_invariant:
                df.unpersist()
        drop_checkpoint(s)
        kept.release()
    return Result(spark.read.schema(f"id long, value {p.kind}").parquet(f"{base}/answer"), number, stats)
