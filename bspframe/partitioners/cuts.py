"""Edge cuts and vertex cuts: (src, dst, ..., part) and the tables behind them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, functions as F

from bspframe.functions.hashing import portable_edge_hash, portable_hash
from bspframe.graph import Graph

#: Edges of a greedy stream, about, and vertices that it remembers.
STREAM, KNOWN = 4_000_000, 2_000_000


def edge_cut_random(g: Graph, p: int, portable: bool = False) -> DataFrame:
    """A vertex is hashed to a part and its out-edges follow."""
    h = portable_hash("src") if portable else F.xxhash64("src")
    return g.edges.withColumn("part", F.pmod(h, F.lit(p)).cast("int"))


def vertex_cut_random(g: Graph, p: int, canonical: bool = False, portable: bool = False) -> DataFrame:
    """An edge is hashed to a part; ``canonical`` puts both directions of a pair together."""
    a, b = (F.least("src", "dst"), F.greatest("src", "dst")) if canonical else (F.col("src"), F.col("dst"))
    h = portable_edge_hash(a, b) if portable else F.xxhash64(a, b)
    return g.edges.withColumn("part", F.pmod(h, F.lit(p)).cast("int"))


def grid_shape(p: int) -> tuple[int, int]:
    """Height and width with product ``p`` that differ by two at most; raises if there are none."""
    for x in range(int(p**0.5), 0, -1):
        if p % x == 0:
            if p // x - x <= 2:
                return x, p // x
            break
    raise ValueError(f"{p} parts have no grid whose sides differ by two at most")


def grid_candidates(p: int) -> list[list[int]]:
    """Parts in the row or column of each cell."""
    x, y = grid_shape(p)
    return [sorted({c // y * y + j for j in range(y)} | {i * y + c % y for i in range(x)}) for c in range(p)]


def _prime(q: int) -> bool:
    return q > 1 and all(q % d for d in range(2, int(q**0.5) + 1))


def pds_order(p: int) -> int:
    """The prime q with ``p = q*q + q + 1``; raises if there is none."""
    q = int((p - 1) ** 0.5)
    for c in (q - 1, q, q + 1):
        if c > 1 and c * c + c + 1 == p and _prime(c):
            return c
    raise ValueError(f"{p} parts are no q*q + q + 1 of a prime q")


def perfect_difference_set(q: int) -> list[int]:
    """q + 1 residues modulo q*q + q + 1 of which each nonzero residue is a difference exactly once, by search."""
    p = q * q + q + 1
    chosen, used = [0, 1], {1, p - 1}

    def grow(low: int) -> bool:
        if len(chosen) == q + 1:
            return True
        for c in range(low, p):
            fresh = {(c - x) % p for x in chosen} | {(x - c) % p for x in chosen}
            if len(fresh) == 2 * len(chosen) and not fresh & used:
                chosen.append(c)
                used.update(fresh)
                if grow(c + 1):
                    return True
                chosen.pop()
                used.difference_update(fresh)
        return False

    if not grow(2):
        raise ValueError(f"no perfect difference set for {q}")
    return chosen


def pds_candidates(p: int) -> list[list[int]]:
    """For each home part h, the set shifted by h."""
    s = perfect_difference_set(pds_order(p))
    return [sorted((x + h) % p for x in s) for h in range(p)]


def _common(g: Graph, p: int, candidates: list[list[int]], pick: str, portable: bool) -> DataFrame:
    """Each edge to a part that both ends' candidates share; p*p small constant lists, so no shuffle."""
    table = F.array(*[F.array(*[F.lit(x) for x in c]) for c in candidates])
    h = portable_hash if portable else (lambda c: F.xxhash64(F.col(c)))
    home = lambda c: F.get(table, F.pmod(h(c), F.lit(p)).cast("int"))
    both = F.array_sort(F.array_intersect(home("src"), home("dst")))
    e = portable_edge_hash("src", "dst") if portable else F.xxhash64("src", "dst")
    at: Column = F.pmod(e, F.size("_both")).cast("int") if pick == "hash" else F.lit(0)
    return g.edges.withColumn("_both", both).withColumn("part", F.get("_both", at)).drop("_both")


def vertex_cut_grid(g: Graph, p: int, pick: str = "hash", portable: bool = False) -> DataFrame:
    return _common(g, p, grid_candidates(p), pick, portable)


def vertex_cut_pds(g: Graph, p: int, portable: bool = False) -> DataFrame:
    return _common(g, p, pds_candidates(p), "hash", portable)


class Greedy:
    """Sequential placement by the replica sets of both ends; the least loaded wins, ties by part number."""

    def __init__(self, p: int):
        self.p, self.all, self.load, self.where = p, (1 << p) - 1, [0] * p, {}

    def place(self, u: int, v: int) -> int:
        su, sv = self.where.get(u, 0), self.where.get(v, 0)
        allowed = su & sv or su | sv or self.all
        best = min((x for x in range(self.p) if allowed >> x & 1), key=self.load.__getitem__)
        self.load[best] += 1
        self.where[u] = su | 1 << best
        self.where[v] = sv | 1 << best
        return best

    def forget(self) -> None:
        self.where.clear()


def _greedy(batches: Iterator[pd.DataFrame], p: int, known: int) -> Iterator[pd.DataFrame]:
    state = Greedy(p)
    for pdf in batches:
        if len(state.where) > known:
            state.forget()
        yield pdf.assign(part=np.array([state.place(u, v) for u, v in zip(pdf["src"].tolist(), pdf["dst"].tolist())], np.int32))


def vertex_cut_greedy(g: Graph, p: int, streams: int | None = None, known: int = KNOWN) -> DataFrame:
    """Greedy placement in parallel streams, each oblivious of the others; ``streams=1`` is the reference order.

    By default there is a stream for each STREAM edges (8 at least). A stream remembers the parts of about ``known``
    vertices and then begins anew with its loads, so its memory is bounded; every edge is placed all the same.
    """
    from bspframe.session import ship

    ship(g.spark)
    if streams is None:
        streams = max(8, -(-g.edges.count() // STREAM))
    dealt = g.edges.repartition(streams, "src").sortWithinPartitions("src", "dst")
    schema = ", ".join(f"{n} {t}" for n, t in g.edges.dtypes) + ", part int"
    return dealt.mapInPandas(lambda it: _greedy(it, p, known), schema)


def auto_choice(p: int) -> str:
    """pds if ``p`` fits, else grid if it fits, else greedy."""
    for name, fits in (("pds", pds_order), ("grid", grid_shape)):
        try:
            fits(p)
            return name
        except ValueError:
            pass
    return "greedy"


def vertex_cut(g: Graph, p: int, how: str = "auto") -> DataFrame:
    how = auto_choice(p) if how == "auto" else how
    return {"random": vertex_cut_random, "grid": vertex_cut_grid, "pds": vertex_cut_pds, "greedy": vertex_cut_greedy}[how](g, p)


def vertex_cut_auto(g: Graph, p: int) -> tuple[DataFrame, str]:
    how = auto_choice(p)
    return vertex_cut(g, p, how), how
