"""Workloads as algebraic vertex programs that every engine can interpret.

A program is four SQL expressions: the start value over ``id``, the message over ``value`` and ``w``, the combiner's
name, and the new value over ``value`` and ``msg`` (null when nothing came). Engines differ in how they execute
it, not in what it means.
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from typing import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F

from bspframe.graph import Graph
from bspframe.loop import Halt, fixpoint, max_delta, rounds

COMBINERS = {"sum": F.sum, "min": F.min, "max": F.max}


@dataclass(frozen=True)
class Program:
    name: str
    kind: str  # SQL type of the value
    init: str
    send: str
    combine: str
    apply: str
    changed: str  # over value (new) and old
    both: bool = False  # messages go along both directions
    weight: str = "none"  # none, share (1/out-degree or weight over their sum), given
    frontier: bool = False  # only changed vertices need to send
    active: str = "true"  # which vertices send in the first round, over id
    halt: Halt = fixpoint()
    max_rounds: int = 10_000
    fixed: int | None = None  # rounds, where nothing else ends the run
    # the same in Python, for the engines whose subject is not Catalyst
    py: tuple[Callable, Callable, Callable, Callable] | None = None  # init(id), send(value, w), combine(a, b), apply(value, msg)
    arrays: tuple[str, Callable, Callable] | None = None  # type, send(values, ws), apply(values, msgs) over NumPy arrays

    @property
    def absent(self) -> float | int:
        """In arrays: no value, or no message; what the combiner leaves other messages unchanged by."""
        if self.combine == "sum":
            return 0.0
        if self.arrays[0] == "float64":
            return np.inf if self.combine == "min" else -np.inf
        return np.iinfo(np.int64).max if self.combine == "min" else np.iinfo(np.int64).min

    def combiner(self, c: str | Column) -> Column:
        return COMBINERS[self.combine](c)

    def sends(self, value: str = "value", w: str = "w") -> Column:
        return F.expr(self.send).cast(self.kind) if (value, w) == ("value", "w") else F.expr(self.send.replace("value", value).replace("w", w)).cast(self.kind)


def pagerank_program(delta: float = 0.15, init: float = 1.0, tol: float | None = None, k: int | None = None, max_rounds: int = 1000) -> Program:
    """rank = delta + (1 - delta) * sum of shares; stops after ``k`` rounds or when no rank moves by ``tol``."""
    halt = rounds(k) if k is not None else max_delta(tol if tol is not None else init)
    d = repr(1 - delta)
    return Program(
        "pagerank", "double", repr(float(init)) + "D", "value * w", "sum", f"{delta!r}D + {d}D * coalesce(msg, 0D)", "value <> old", weight="share",
        halt=halt, max_rounds=k or max_rounds, fixed=k, py=(lambda i: float(init), lambda v, w: v * w, lambda a, b: a + b, lambda v, m: delta + (1 - delta) * (m or 0.0)),
        arrays=("float64", lambda v, w: v * w, lambda v, m: delta + (1 - delta) * m),
    )


def wcc_program(directed: bool = False) -> Program:
    """Least label reachable; ``directed`` is the known wrong form that follows edges one way only."""
    return Program("wcc", "bigint", "id", "value", "min", "least(value, msg)", "value <> old", both=not directed, frontier=True, py=(lambda i: i, lambda v, w: v, min, lambda v, m: v if m is None else min(v, m)), arrays=("int64", lambda v, w: v, np.minimum))


def hops_program(source: int, k: int | None = None, weighted: bool = False) -> Program:
    """Distances from ``source``; null is unreached. ``k`` bounds the hops."""
    kind, one = ("double", "w") if weighted else ("int", "1")
    step = f"value + {one}" if k is None or weighted else f"if(value < {int(k)}, value + 1, null)"  # a round may pass several hops
    return Program(
        "sssp" if k is None else "khop", kind, f"case when id = {int(source)} then cast(0 as {kind}) end", step, "min", "least(value, msg)", "not (value <=> old)", weight="given" if weighted else "none",
        frontier=True, active=f"id = {int(source)}", halt=fixpoint() if k is None else (lambda s: s.changed == 0 or s.round >= k), max_rounds=10_000 if k is None else k,
        py=(lambda i: (0 if not weighted else 0.0) if i == source else None, lambda v, w: None if v is None or (k is not None and not weighted and v >= k) else v + (w if weighted else 1), lambda a, b: b if a is None else a if b is None else min(a, b), lambda v, m: m if v is None else v if m is None else min(v, m)),
        arrays=("float64", (lambda v, w: v + w) if weighted else (lambda v, w: v + 1) if k is None else (lambda v, w: np.where(v < k, v + 1, np.inf)), np.minimum),
    )


def message_edges(g: Graph, p: Program, hubs: list[int] | None = None) -> DataFrame:
    """(src, dst, w) along which the program's messages go; the loop-invariant side of every engine.

    ``hubs`` are sources whose edges must not meet in one task.
    """
    from bspframe.engines.dealing import spread_join

    e = g.edges
    given = "w" in e.columns
    if p.weight == "share":
        by = F.sum("w") if given else F.count("*")
        total = e.groupBy("src").agg(by.alias("_t"))
        e = spread_join(e, total, "src", hubs or []).select("src", "dst", ((F.col("w") if given else F.lit(1.0)) / F.col("_t")).alias("w"))
    else:
        e = e.select("src", "dst", (F.col("w") if given and p.weight == "given" else F.lit(1.0)).alias("w"))
    if p.both and p.weight == "none":  # each pair moves once, before there are two rows of it
        pairs = e.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "w").distinct()
        e = Graph(pairs).undirect().edges
    elif p.both:
        e = Graph(e).undirect().edges.where("src <> dst").select("src", "dst", "w").distinct()
    return e


def first_state(g: Graph, p: Program) -> DataFrame:
    return g.vertices.select("id", F.expr(p.init).cast(p.kind).alias("value"), F.expr(p.active).alias("changed"))


def with_rounds(p: Program, k: int) -> Program:
    return replace(p, halt=rounds(k), max_rounds=k, fixed=k)
