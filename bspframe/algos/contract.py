"""Connected components by hooking, pointer jumping and contraction, on plain edge DataFrames.

Every round each vertex hooks to its least neighbour, the resulting trees are flattened by
pointer jumping, and the edges are rewritten to roots; at least half of the vertices that
still have an edge vanish, so the rounds are logarithmic whatever the diameter. Tables of a
round are written to the shared folder, which keeps lineage flat and survives lost executors.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from bspframe.loop import Adaptive
from bspframe.session import drop_table, materialise, materialise_counting, tidy

#: Edges from which a round's shuffle files are deleted as soon as it is over.
MANY = 1_000_000


def contract_components(edges: DataFrame, max_rounds: int = 64, trace: list | None = None, finish_below: int = 0) -> DataFrame:
    """``(src, dst)`` edges, direction ignored → ``(id, component)`` with component = least id reachable.

    Vertices are the ends of the edges; self-edges, repeated edges and edges with a null end are
    allowed (the last are ignored). An empty input gives an empty result.
    ``trace`` collects one dict for each round. ``finish_below`` (off by default) lets one task end the work by a
    serial kernel as soon as so few edges are left (16 bytes each); no registered query uses it.
    """
    with Adaptive(edges.sparkSession, on=True):  # its skew join splits the rows of a hub
        return _contract(edges, max_rounds, trace, finish_below)


def _contract(edges: DataFrame, max_rounds: int, trace: list | None, finish_below: int) -> DataFrame:
    both = edges.select(F.col("src").cast("long").alias("a"), F.col("dst").cast("long").alias("b")).dropna()
    whole = both.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    whole, seen = materialise_counting(whole, "cc-edges", live="a <> b", loops="a = b")
    work = whole.where("a <> b") if seen["loops"] else whole
    live, labels, number = seen["live"], None, 0
    while live:
        number += 1
        if number > max_rounds:
            raise RuntimeError(f"not converged after {max_rounds} rounds")
        serial = live <= finish_below
        if serial:
            hook, jumps, following = materialise(work.repartition(1).mapInArrow(_serial, "v long, p long"), "cc-hook"), 0, None
        else:
            hook, jumps = _flat(work)
            moved = (
                work.join(hook.select(F.col("v").alias("a"), F.col("p").alias("pa")), "a")
                .join(hook.select(F.col("v").alias("b"), F.col("p").alias("pb")), "b")
                .where("pa <> pb")
                .select(F.greatest("pa", "pb").alias("a"), F.least("pa", "pb").alias("b"))
                .distinct()
            )
            following, left = materialise_counting(moved, "cc-edges", live="true")
        if trace is not None:
            trace.append({"round": number, "jumps": jumps, "edges": live, **({"serial": live} if serial else {})})
        if labels is None:  # the first round's trees are the labels
            labels = hook.select(F.col("v").alias("id"), F.col("p").alias("root"))
            if seen["loops"]:
                alone = whole.where("a = b").select(F.col("a").alias("id")).join(labels, "id", "left_anti")
                labels = materialise(labels.union(alone.select("id", F.col("id").alias("root"))), "cc-labels")
                drop_table(hook)
        else:
            fresh = labels.join(hook.select(F.col("v").alias("root"), "p"), "root", "left").select("id", F.coalesce("p", "root").alias("root"))
            fresh = materialise(fresh, "cc-labels")
            drop_table(labels)
            drop_table(hook)
            labels = fresh
        drop_table(work)
        if live > MANY:
            tidy(edges.sparkSession)
        work, live = following, 0 if serial else left["live"]
    if labels is None:
        return whole.select(F.col("a").alias("id"), F.col("a").alias("component"))
    if work is not None:
        drop_table(work)
    return labels.select("id", F.col("root").alias("component"))


def _serial(batches):
    """Least end of each component of a bounded number of edges."""
    import numpy as np
    import pyarrow as pa

    from bspframe.engines.serial import single_wcc

    parts = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches]
    if parts:
        a, b = (np.concatenate(x) for x in zip(*parts))
        ids, at = np.unique(np.concatenate([a, b]), return_inverse=True)
        least = ids[single_wcc(at[: len(a)], at[len(a) :], len(ids))]
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(least)], ["v", "p"])


def _flat(edges: DataFrame) -> tuple[DataFrame, int]:
    """Each vertex with the root of the tree that hooking to the least neighbour puts it in.

    Only vertices below another one that is no root can move, so a root's many children meet no row in the join.
    """
    ends = edges.select(F.col("a").alias("v"), F.col("b").alias("n")).union(edges.select("b", "a"))
    hook = materialise(ends.groupBy("v").agg(F.least(F.min("n"), F.first("v")).alias("p")), "cc-hook")
    jumps = 0
    while True:
        up = hook.where("v <> p").select(F.col("v").alias("p"), F.col("p").alias("q"))
        jump = hook.join(up, "p", "left").select("v", F.coalesce("q", "p").alias("p"), F.col("q").isNotNull().alias("moved"))
        far, seen = materialise_counting(jump, "cc-hook", moved="moved")
        jumps += 1
        drop_table(hook)
        hook = far.select("v", "p")
        if not seen["moved"]:
            return hook, jumps
