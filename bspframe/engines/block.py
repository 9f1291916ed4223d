"""Block-centric rounds: a serial kernel runs to its fixpoint inside every block, messages pass between blocks.

For programs that take minima (components, distances). Only blocks with an improved vertex run again.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F

from bspframe.engines.program import Program, first_state, message_edges
from bspframe.graph import Graph, Result
from bspframe.loop import Adaptive, Truncate, fixpoint, superstep_loop
from bspframe.partitioners.blocks import blocks_connected, blocks_voronoi, partition_mincut
from bspframe.session import materialise

#: Ids in a range of the default blocks.
RANGE = 256
#: Calls of the kernel for each partition; one call takes all blocks that a hash deals to it.
CALLS = 8


def run_block(g: Graph, p: Program, blocks: DataFrame | str | None = None, handoff: str = "memory", mode: str = "sync", truncate: Truncate | None = None) -> Result:
    """``blocks(id, block)``, by default the connected pieces of id ranges; 'voronoi' and 'mincut' make them so.

    ``handoff='storage'`` writes and rereads the blocked edges first. ``mode='async'`` lets two classes of blocks run in
    turn, so that the second reads what the first has just found.
    """
    if p.combine != "min":
        raise ValueError("the block engine takes programs that combine by min; see pagerank_block")
    n = int(g.spark.conf.get("spark.sql.shuffle.partitions"))
    if blocks is None:
        blocks = blocks_connected(g, g.vertices.select("id", F.floor(F.col("id") / RANGE).alias("block")))
    elif blocks == "voronoi":
        blocks = blocks_voronoi(g, rate=1 / RANGE)
    elif blocks == "mincut":
        blocks = partition_mincut(g, n)
    turns = {"sync": 1, "async": 2}[mode]
    step_cost = 0.0 if p.name == "wcc" else 1.0
    limit = float(p.max_rounds) if p.name == "khop" else np.inf
    weighted = p.weight == "given"

    def local(key, edges: pd.DataFrame, state: pd.DataFrame) -> pd.DataFrame:
        """Relax inside the blocks of one call until nothing changes; then one message for each edge that leaves an improved vertex.

        No inner edge crosses two blocks, so blocks side by side end as each would alone.
        """
        ids = state["id"].to_numpy()
        order = np.argsort(ids)
        ids = ids[order]
        value = state["value"].to_numpy(dtype=float)[order]
        value = np.where(np.isnan(value), np.inf, value)
        first = value.copy()
        changed = state["changed"].to_numpy(dtype=bool)[order]
        src = np.searchsorted(ids, edges["src"].to_numpy())
        cost = edges["w"].to_numpy() if weighted else np.full(len(edges), step_cost)
        inside = edges["inside"].to_numpy(dtype=bool)
        a, c = src[inside], cost[inside]
        b = np.searchsorted(ids, edges["dst"].to_numpy()[inside])
        by = np.argsort(a, kind="stable")
        a, b, c = a[by], b[by], c[by]
        start = np.searchsorted(a, np.arange(len(ids) + 1))
        hot = np.flatnonzero(changed)
        while len(hot) and len(a):
            lens = start[hot + 1] - start[hot]
            use = np.arange(int(lens.sum())) + np.repeat(start[hot] - np.cumsum(lens) + lens, lens)
            to, offer = b[use], value[a[use]] + c[use]
            ok = (offer <= limit) & (offer < value[to])
            to, offer = to[ok], offer[ok]
            np.minimum.at(value, to, offer)
            hot = np.unique(to)
        better = changed | (value < first)
        out = ~inside & better[src]
        sent = value[src[out]] + cost[out]
        ok = np.isfinite(sent) & (sent <= limit)
        rows = pd.DataFrame({"id": ids, "value": value, "message": False})
        return pd.concat([rows, pd.DataFrame({"id": edges["dst"].to_numpy()[out][ok], "value": sent[ok], "message": True})])

    with Adaptive(g.spark):
        of = materialise(blocks.select("id", "block"), "blocks")  # three joins read it
        e = message_edges(g, p).join(of.withColumnsRenamed({"id": "src", "block": "block"}), "src").join(of.withColumnsRenamed({"id": "dst", "block": "other"}), "dst")
        e = e.select("block", "src", "dst", "w", (F.col("block") == F.col("other")).alias("inside"))
        e = materialise(e.repartition(n, "block"), "blocked-edges") if handoff == "storage" else e
        e = e.repartition(n, "block").persist()
        state = first_state(g, p).join(of, "id").select("id", F.col("value").cast("double").alias("value"), "changed", "block", F.lit(None).cast("double").alias("old")).repartition(n, "block").persist()

        def step(s: DataFrame, number: int) -> DataFrame:
            turn = F.pmod(F.xxhash64("block"), F.lit(turns)) == number % turns
            live = s.where("changed").where(turn).select("block").distinct()
            call = F.pmod(F.xxhash64("block", F.lit(1)), F.lit(CALLS * n)).alias("call")
            of_call = lambda df: df.join(live, "block", "left_semi").withColumn("call", call).groupBy("call")
            ran = of_call(e).cogroup(of_call(s)).applyInPandas(local, "id long, value double, message boolean")
            merged = ran.groupBy("id").agg(F.min(F.when(~F.col("message"), F.col("value"))).alias("own"), F.min(F.when(F.col("message"), F.col("value"))).alias("sent"))
            new = s.select("id", "block", F.col("value").alias("old"), (F.col("changed") & ~turn).alias("waits")).join(merged, "id", "left")
            bad = lambda c: F.when(F.col(c) != float("inf"), F.col(c))
            base = F.coalesce(bad("own"), F.col("old"))
            new = new.withColumn("base", base).withColumn("value", F.least("base", "sent"))
            return new.select("id", "value", F.expr("waits or (sent is not null and (base is null or sent < base))").alias("changed"), "block", "old")

        state, done, stats = superstep_loop(state, step, fixpoint(), 10_000, truncate)
        e.unpersist()
    return Result(state.select("id", F.col("value").cast(p.kind).alias("value")), done, stats)
