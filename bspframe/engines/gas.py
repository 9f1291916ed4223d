"""Gather-apply-scatter, synchronous with vertex cuts, and asynchronous as ordered sweeps or partition-local passes."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F

from bspframe.engines.dealing import Dealt, deal, held, hub_ids, spread_join
from bspframe.engines.program import Program, first_state, message_edges
from bspframe.engines.vertex import CHANGE
from bspframe.graph import Graph, Result
from bspframe.loop import Adaptive, Truncate, fixpoint, pin, superstep_loop
from bspframe.partitioners.cuts import vertex_cut

#: Odd multiplier that deals ids to sweep classes.
DEAL = 2654435761
#: Edges that a part of a partition-local run has about at most: a part is one task's pandas table.
PART_EDGES = 500_000


def run_gas(g: Graph, p: Program, mode: str = "sync", cut: str = "random", machines: int = 8, stop: str = "I", tol: float = 1e-3, sweeps: int = 2, inner: int = 2, gather: str = "in", scatter: str = "out", truncate: Truncate | None = None, max_rounds: int | None = None) -> Result:
    """Gather over in-edges, apply, scatter over out-edges to wake neighbours.

    ``cut`` (random, grid, pds, greedy, auto, none) places edges; each part sums what it gathers and the parts' sums are
    merged by vertex, in every mode. ``stop='T'`` lets vertices whose change is at most ``tol`` go quiet until a neighbour
    scatters to them: a round reads the out-edges of moved vertices and the in-edges of woken ones, no others. ``'I'`` keeps
    the program's own halting. ``mode='async'`` runs ``sweeps`` classes of vertices one after the other inside a
    round, each reading the newest values; ``'async-local'`` makes ``inner`` passes inside each part between exchanges.
    ``gather='both'`` reads each edge from both ends; ``scatter`` (out, in, both) says along which edges neighbours are woken.
    """
    if gather == "both" and not p.both:
        g = g.undirect()
    rounds = max_rounds or p.max_rounds
    if mode == "async-local":
        return _local(g, p, machines, inner, tol, truncate, rounds)
    n = int(g.spark.conf.get("spark.sql.shuffle.partitions"))
    with Adaptive(g.spark):
        kept = held(g, n, p.both)
        placed = message_edges(kept.graph, p, kept.hubs)
        if cut != "none":
            placed = vertex_cut(Graph(placed), machines, cut).select("src", "dst", "w", "part")
        edges = deal(placed, "src", n, kept.hubs)
        state = pin(first_state(kept.graph, p).withColumn("old", F.col("value")), "id", n)
        keys = ["dst"] if cut == "none" else ["part", "dst"]

        def merged(sent: DataFrame) -> DataFrame:
            """(id, msg): sums of the parts, then of the replicas."""
            got = sent.groupBy(*keys).agg(p.combiner(F.expr(p.send).cast(p.kind)).alias("msg"))
            return (got if cut == "none" else got.groupBy("dst").agg(p.combiner("msg").alias("msg"))).withColumnRenamed("dst", "id")

        if mode == "async":
            run = _sweeps(p, edges, merged, state, sweeps, tol if stop == "T" or p.combine == "sum" else 0.0, truncate, rounds)
            edges.unpersist()
            kept.release()
            return run
        quiet = stop == "T" and p.combine == "sum"
        moved = f"abs(value - old) > {tol!r}D" if quiet else p.changed
        into = deal(placed, "dst", n, hub_ids(kept.graph.edges, "dst", n)) if quiet else None

        def step(s: DataFrame, number: int) -> DataFrame:
            if quiet and number > 1:
                loud = s.where("changed").select("id")
                along = [(edges, "dst")] if scatter != "in" else []
                along += [(into, "src")] if scatter != "out" else []
                hit = None
                for side, end in along:
                    one = side.meet(loud).select(F.col(end).alias("id"))
                    hit = one if hit is None else hit.union(one)
                hit = hit.distinct()
                read = into.meet(hit).select("src", "dst", "w", *keys[:-1])
                got = merged(spread_join(read, s.select(F.col("id").alias("src"), "value"), "src", kept.hubs))
                new = s.select("id", F.col("value").alias("old")).join(got, "id", "left").join(hit.withColumn("woken", F.lit(True)), "id", "left")
                value = F.when(F.col("woken"), F.expr(p.apply.replace("value", "old")).cast(p.kind)).otherwise(F.col("old"))
            else:
                got = merged(edges.meet((s.where("changed") if p.frontier else s).select("id", "value")))
                new = s.select("id", F.col("value").alias("old")).join(got, "id", "left")
                value = F.expr(p.apply.replace("value", "old")).cast(p.kind)
            return new.withColumn("value", value).select("id", "value", F.expr(moved).alias("changed"), "old")

        halt = (lambda st: st.changed == 0) if stop == "T" else p.halt
        state, done, stats = superstep_loop(state, step, halt, rounds, truncate or (Truncate() if quiet else None), change=CHANGE)  # a quiet round reads the state often
        for dealt in (edges, into):
            if dealt is not None:
                dealt.unpersist()
        kept.release()
    return Result(state.select("id", "value"), done, stats)


def _sweeps(p: Program, edges: Dealt, merged, state: DataFrame, sweeps: int, tol: float, truncate: Truncate | None, rounds: int) -> Result:
    """Deterministic Gauss-Seidel: class after class of ids joins the latest state; no locks."""
    cls = lambda c: F.pmod(F.col(c) * F.lit(DEAL), F.lit(sweeps))

    def step(s: DataFrame, number: int) -> DataFrame:
        j = (number - 1) % sweeps
        if j == 0:
            s = s.withColumn("begin", F.col("value"))
        got = merged(edges.meet(s.select("id", "value")).where(cls("dst") == j))
        new = s.select("id", F.col("value").alias("old"), "begin").join(got, "id", "left")
        value = F.when(cls("id") == j, F.expr(p.apply.replace("value", "old")).cast(p.kind)).otherwise(F.col("old"))
        return new.withColumn("value", value).select("id", "value", F.expr(p.changed).alias("changed"), "old", "begin")

    last: list = []

    def halt(st) -> bool:
        last.append(st)
        full = last[-sweeps:]
        if st.round % sweeps:
            return False
        return max(x.max_change for x in full) < tol if tol else sum(x.changed for x in full) == 0

    state = state.withColumn("begin", F.col("value"))
    state, done, stats = superstep_loop(state, step, halt, rounds * sweeps, truncate, change=CHANGE)
    return Result(state.select("id", "value"), -(-done // sweeps), stats)


def parts_of(edges: int, machines: int) -> int:
    return max(machines, -(-edges // PART_EDGES))


def _local(g: Graph, p: Program, machines: int, inner: int, tol: float, truncate: Truncate | None, rounds: int) -> Result:
    """Values are fresh inside a part and one round old outside: ``inner`` passes inside a part for each exchange.

    There are at least ``machines`` parts, and more where one would get over PART_EDGES edges.
    """
    combine_sum = p.combine == "sum"
    _, send, combine, apply = p.py
    limit = float(p.max_rounds) if p.name == "khop" else np.inf  # inner passes may go further

    def passes(pdf: pd.DataFrame) -> pd.DataFrame:
        ids, at = np.unique(pdf["dst"].to_numpy(), return_inverse=True)
        own = pdf[pdf["src"].isna()]
        value = np.full(len(ids), np.inf if not combine_sum else 0.0)
        value[np.searchsorted(ids, own["dst"].to_numpy())] = own["value"].fillna(np.inf if not combine_sum else 0.0).to_numpy(dtype=float)
        e = pdf[~pdf["src"].isna()]
        dst = np.searchsorted(ids, e["dst"].to_numpy())
        src = np.minimum(np.searchsorted(ids, e["src"].to_numpy(dtype="int64")), len(ids) - 1)
        inside = ids[src] == e["src"].to_numpy(dtype="int64")
        w, outer = e["w"].to_numpy(), e["value"].to_numpy(dtype=float)
        old = value.copy()
        hop = send(0.0, 1.0) if not combine_sum else 0.0
        for _ in range(inner):
            v = np.where(inside, value[src], outer)
            if combine_sum:
                got = np.bincount(dst, v * w, len(ids))
                value = np.array([apply(None, m) for m in (0.0, 1.0)])
                value = value[0] + (value[1] - value[0]) * got
            else:
                got = np.full(len(ids), np.inf)
                offer = np.where(np.isnan(v), np.inf, v) + hop
                np.minimum.at(got, dst, np.where(offer <= limit, offer, np.inf))
                value = np.minimum(value, got)
        return pd.DataFrame({"id": ids, "value": value, "old": old})

    with Adaptive(g.spark):
        edges = pin(message_edges(g, p), "src")
        parts = parts_of(edges.count(), machines)
        state = pin(first_state(g, p).select("id", F.col("value").cast("double").alias("value"), F.col("value").cast("double").alias("old"), "changed"), "id")
        part = lambda c: F.pmod(F.xxhash64(c), F.lit(parts))

        def step(s: DataFrame, _: int) -> DataFrame:
            sent = edges.join(s.select(F.col("id").alias("src"), "value"), "src").select("src", "dst", "w", "value")
            rows = sent.union(s.select(F.lit(None).cast("long"), F.col("id"), F.lit(0.0), "value")).withColumn("part", part("dst"))
            out = rows.groupBy("part").applyInPandas(passes, "id long, value double, old double")
            bad = lambda c: F.when(F.col(c) != float("inf"), F.col(c))
            return out.select("id", bad("value").alias("value"), bad("old").alias("old")).withColumn("changed", F.expr("not (value <=> old)"))

        halt = (lambda st: st.max_change < tol) if combine_sum else fixpoint()
        state, done, stats = superstep_loop(state, step, halt, rounds, truncate, change=CHANGE)
        edges.unpersist()
    return Result(state.select("id", F.col("value").cast(p.kind).alias("value")), done, stats)
