"""Immutable RDDs for each round, with lineage that grows: the baseline whose subject is just that.

A part of an RDD is one record of arrays, so the work of a round is done by a few array operations in each task.
"""

from __future__ import annotations

import time
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from bspframe.engines.program import Program, first_state, message_edges
from bspframe.graph import Graph, Result
from bspframe.loop import RoundStat
from bspframe.session import ship

#: Edges that a part has about at most, edges that no task is worth, and rows that are packed at once.
PART_EDGES, PART_LEAST, PACK = 1_000_000, 50_000, 500_000


def parts_of(edges: int, given: int) -> int:
    """``given`` parts, fewer where these would be too small for tasks of their own, more where they would be too large."""
    return max(1, min(given, -(-edges // PART_LEAST)), -(-edges // PART_EDGES))


def _mixed(ids: np.ndarray) -> np.ndarray:
    x = ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return x ^ (x >> np.uint64(29))


def _owner(ids: np.ndarray, n: int) -> np.ndarray:
    """The part that keeps a vertex."""
    return (_mixed(ids) % np.uint64(n)).astype(np.int64)


def _pack(batches, n: int, by: tuple[str, ...], kinds: tuple[str, ...], absent):
    """Columns of Arrow batches → (part, bytes of each column), dealt by the ``by`` columns; nulls become ``absent``."""
    held, rows = [], 0

    def flush():
        columns = [np.concatenate(c) for c in zip(*held)]
        key = _mixed(columns[0]) if len(by) == 1 else _mixed(_mixed(columns[0]) + columns[1].astype(np.uint64))
        part = (key % np.uint64(n)).astype(np.int64)
        order = np.argsort(part, kind="stable")
        edges = np.searchsorted(part[order], np.arange(n + 1))
        for k in np.flatnonzero(np.diff(edges)).tolist():
            at = order[edges[k] : edges[k + 1]]
            yield k, [c[at].tobytes() for c in columns]

    def batch_of(found):
        found = list(found)
        return pa.RecordBatch.from_arrays([pa.array([k for k, _ in found], pa.int32()), pa.array([b for _, b in found], pa.list_(pa.binary()))], ["part", "columns"])

    for b in batches:
        held.append([(c.fill_null(absent) if c.null_count else c).to_numpy(zero_copy_only=False).astype(k) for c, k in zip(b.columns, kinds)])
        rows += b.num_rows
        if rows >= PACK:
            yield batch_of(flush())
            held, rows = [], 0
    if rows:
        yield batch_of(flush())


def _parts(df, n: int, by: tuple[str, ...], kinds: tuple[str, ...], build, absent=None):
    """An RDD of exactly one (part, build(columns)) in each of ``n`` parts."""
    packed = df.mapInArrow(partial(_pack, n=n, by=by, kinds=kinds, absent=absent), "part int, columns array<binary>")

    def whole(k, pieces):
        got = [[np.frombuffer(b, t) for b, t in zip(p, kinds)] for _, p in pieces]
        yield k, build([np.concatenate(c) for c in zip(*got)] if got else [np.empty(0, t) for t in kinds])

    return packed.rdd.map(lambda r: (r[0], r[1])).partitionBy(n).mapPartitionsWithIndex(whole, preservesPartitioning=True)


def _together(one, other, n: int):
    """(part, (the record of ``one``, all records of ``other``)): ``other`` is dealt first, so that ``one`` never moves."""

    def met(k, found):
        own, got = None, []
        for _, (first, x) in found:
            if first:
                own = x
            else:
                got.append(x)
        yield k, (own, got)

    tagged = one.mapValues(lambda x: (True, x)), other.partitionBy(n).mapValues(lambda x: (False, x))
    return tagged[0].union(tagged[1]).mapPartitionsWithIndex(met, preservesPartitioning=True)


def _edge_block(columns):
    """(sources, index of each edge's source, targets, where each target's edges begin, weights), sorted by target."""
    src, dst, w = columns
    order = np.argsort(dst, kind="stable")
    sources, at = np.unique(src[order], return_inverse=True)
    targets, starts = np.unique(dst[order], return_index=True)
    return sources, at.astype(np.int32), targets, starts, w[order]


def _state_block(columns):
    ids, value, changed = columns
    order = np.argsort(ids)
    return ids[order], value[order], changed[order], value[order]


def run_rdd(g: Graph, p: Program, checkpoint_every: int | None = None, num_partitions: int | None = None, cut: str = "vertex") -> Result:
    """State and edges as RDDs. ``checkpoint_every`` cuts lineage, 2 or 10 as published.

    ``cut='vertex'`` (the family's own) keeps each edge in a part by the hash of both ends; a routing table says which
    parts read a vertex, its value is copied to these, and messages are combined inside a part before they leave it.
    ``'edge'`` keeps edges with their source. There are ``num_partitions`` parts; by default as many as the session
    shuffles to, within PART_LEAST and PART_EDGES edges for each.
    """
    if cut not in ("vertex", "edge"):
        raise ValueError("cut is 'vertex' or 'edge'")
    spark = g.spark
    ship(spark)
    kind, send, apply = p.arrays
    combine = {"sum": np.add, "min": np.minimum, "max": np.maximum}[p.combine]
    absent = p.absent
    frontier, known = p.frontier, p.combine == "sum"
    edges = message_edges(g, p).persist()
    n = num_partitions or parts_of(edges.count(), int(spark.conf.get("spark.sql.shuffle.partitions")))
    state = _parts(first_state(g, p).select("id", F.col("value").cast("double" if kind == "float64" else "bigint").alias("value"), "changed"), n, ("id",), ("int64", kind, "bool"), _state_block, absent).persist()
    blocks = _parts(edges, n, ("src", "dst") if cut == "vertex" else ("src",), ("int64", "int64", "float64"), _edge_block).persist()
    fixed = [blocks]

    def speaking(row):
        """Which vertices have something to say this round."""
        _, value, changed, _ = row
        said = changed if frontier else np.ones(len(value), bool)
        return said if known else said & (value != absent)

    def messages(block, ids, values):
        """(owner, (targets, combined messages)) of one part's edges, given values of some of its sources."""
        sources, at, targets, starts, w = block
        if not len(targets) or not len(ids):
            return
        where = np.minimum(np.searchsorted(sources, ids), len(sources) - 1)
        fit = sources[where] == ids
        value = np.full(len(sources), absent, kind)
        value[where[fit]] = values[fit]
        told = np.zeros(len(sources), bool)
        told[where[fit]] = True
        sent = np.where(told[at], send(value[at], w), absent).astype(kind)
        got = combine.reduceat(sent, starts)
        there = np.logical_or.reduceat(told[at], starts) if known else got != absent
        yield from _dealt(targets[there], got[there])

    def _dealt(ids, values):
        owner = _owner(ids, n)
        order = np.argsort(owner, kind="stable")
        bound = np.searchsorted(owner[order], np.arange(n + 1))
        for k in np.flatnonzero(np.diff(bound)).tolist():
            mine = order[bound[k] : bound[k + 1]]
            yield k, (ids[mine], values[mine])

    if cut == "edge":

        def sent(now):
            def out(pair):
                block, (row,) = pair[1]
                said = speaking(row)
                yield from messages(block, row[0][said], row[1][said])

            return _together(blocks, now, n).flatMap(out)

    else:

        def readers(part):
            """Each owner learns which of its vertices a part reads."""
            k, block = part
            for owner, (ids, _) in _dealt(block[0], block[0]):
                yield owner, (k, ids)

        def table(k, found):
            yield k, [x for _, x in found]

        routes = blocks.flatMap(readers).partitionBy(n).mapPartitionsWithIndex(table, preservesPartitioning=True).persist()
        fixed.append(routes)

        def sent(now):
            def copies(pair):
                where, (row,) = pair[1]
                said = speaking(row)
                for part, ids in where:
                    at = np.searchsorted(row[0], ids)
                    at = at[said[at]]
                    if len(at):
                        yield part, (row[0][at], row[1][at])

            def inside(pair):
                block, got = pair[1]
                if got:
                    yield from messages(block, *(np.concatenate(c) for c in zip(*got)))

            return _together(blocks, _together(routes, now, n).flatMap(copies), n).flatMap(inside)

    def applied(pair):
        """New state of a part; the replicas' messages meet here."""
        (ids, value, _, _), got = pair
        msg = np.full(len(ids), absent, kind)
        for to, m in got:
            at = np.searchsorted(ids, to)
            msg[at] = combine(msg[at], m)
        new = apply(value, msg).astype(kind)
        return ids, new, new != value, value

    def moved(part):
        _, new, changed, old = part[1]
        both = changed if known else changed & (old != absent) & (new != absent)
        return int(changed.sum()), float(np.abs(new[both] - old[both]).max()) if both.any() else 0.0

    stats, number = [], 0
    while number < p.max_rounds:
        number += 1
        began = time.perf_counter()
        fresh = _together(state, sent(state), n).mapValues(applied).persist()
        if checkpoint_every and number % checkpoint_every == 0:
            fresh.checkpoint()
        changed, change = fresh.map(moved).fold((0, 0.0), lambda a, b: (a[0] + b[0], max(a[1], b[1])))
        state.unpersist()
        state = fresh
        if number == 1:
            edges.unpersist()
        stats.append(RoundStat(number, changed, changed, change, time.perf_counter() - began))
        if p.halt(stats[-1]):
            break
    for rdd in fixed:
        rdd.unpersist()
    whole = p.kind != "double"

    def rows(part):
        ids, value, _, _ = part[1]
        given = [True] * len(ids) if known else (value != absent).tolist()
        for i, v, there in zip(ids.tolist(), value.tolist(), given):
            yield i, (int(v) if whole else v) if there else None

    return Result(spark.createDataFrame(state.flatMap(rows), f"id long, value {p.kind}", verifySchema=False), number, stats)
