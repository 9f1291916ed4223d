"""Edges dealt for rounds: by one end, with the edges of hubs spread over all partitions.

A hub is a vertex whose edges alone would fill a good part of a partition. There are at most ``n / SHARE`` of them for
n partitions whatever the graph, so their ids can be held by the driver and their state can be broadcast. Hubs that
receive need no such care: every engine's combiner sums inside the sending task first.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark import StorageLevel
from pyspark.sql import DataFrame, functions as F

from bspframe.graph import Graph
from bspframe.loop import pin

#: Share of a mean partition from which a vertex counts as a hub, and edges that no task minds.
SHARE, LEAST = 0.5, 100_000


def hold(df: DataFrame) -> tuple[DataFrame, bool]:
    """``df`` persisted, and whether that was done here."""
    level = df.storageLevel
    if level.useMemory or level.useDisk:
        return df, False
    return df.persist(StorageLevel.MEMORY_AND_DISK), True


def hub_ids(edges: DataFrame, key: str, n: int, least: int | None = None) -> list[int]:
    """Values of ``key`` with more than SHARE of a mean partition's edges (and more than ``least``): n / SHARE at most."""
    least = LEAST if least is None else least
    per = edges.groupBy(F.col(key).alias("id")).agg(F.count("*").alias("n"))
    total, top = per.agg(F.sum("n"), F.max("n")).first()
    if top is None or top <= max(least, SHARE * total / n):
        return []
    return [r[0] for r in per.where(F.col("n") > max(least, SHARE * total / n)).select("id").collect()]


def spread_join(left: DataFrame, right: DataFrame, key: str, hubs: list[int]) -> DataFrame:
    """Inner join on ``key``; rows of hubs stay where they are and meet a broadcast."""
    if not hubs:
        return left.join(right, key)
    hub = F.col(key).isin(hubs)
    return left.where(~hub).join(right, key).unionByName(left.where(hub).join(F.broadcast(right.where(hub)), key))


@dataclass
class Dealt:
    """Edges pinned by ``key``; those of ``hubs`` apart and spread evenly."""

    light: DataFrame
    heavy: DataFrame | None
    key: str
    hubs: list[int]

    def meet(self, state: DataFrame) -> DataFrame:
        """The edges joined with ``state(id, ...)`` on the pinned end; light edges are not moved, heavy ones neither."""
        s = state.withColumnRenamed("id", self.key)
        out = self.light.join(s, self.key)
        if self.heavy is not None:
            out = out.unionByName(self.heavy.join(F.broadcast(s.where(F.col(self.key).isin(self.hubs))), self.key))
        return out

    def unpersist(self) -> None:
        for df in (self.light, self.heavy):
            if df is not None:
                df.unpersist()


def deal(edges: DataFrame, key: str, n: int, hubs: list[int]) -> Dealt:
    if not hubs:
        return Dealt(pin(edges, key, n), None, key, [])
    hub = F.col(key).isin(hubs)
    other = "dst" if key == "src" else "src"
    return Dealt(pin(edges.where(~hub), key, n), edges.where(hub).repartition(n, key, other).persist(StorageLevel.MEMORY_AND_DISK), key, hubs)


@dataclass
class Held:
    """A graph whose edges are kept while a run reads them several times, with its hubs in the messages' direction."""

    graph: Graph
    hubs: list[int]
    own: bool

    def release(self) -> None:
        if self.own:
            self.graph.edges.unpersist()


def held(g: Graph, n: int, both: bool = False, least: int | None = None) -> Held:
    edges, own = hold(g.edges)
    ends = edges.select(F.explode(F.array("src", "dst")).alias("src")) if both else edges
    return Held(replace(g, edges=edges), hub_ids(ends, "src", n, least), own)
