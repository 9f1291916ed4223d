"""The graph abstraction: an edge relation, a vertex relation and verbs over them. Everything stays lazy."""

from __future__ import annotations

from dataclasses import dataclass, replace
from typing import Any, NamedTuple

from pyspark.sql import Column, DataFrame, functions as F


class Result(NamedTuple):
    """What an engine gives back: the answer, the number of rounds and one record for each round."""

    df: DataFrame
    rounds: int
    stats: list


@dataclass(frozen=True)
class Graph:
    """Directed multigraph: ``edges(src, dst[, w])`` and ``vertices(id)``; ids are LONG and never null."""

    edges: DataFrame
    extra: DataFrame | None = None
    name: str = "graph"

    @staticmethod
    def from_edges(edges: DataFrame, extra: DataFrame | None = None, self_edges: str = "keep", simple: bool = False, name: str = "graph") -> "Graph":
        """Prune to the edge columns, drop edges with a null end, and settle self-edges and parallel edges.

        ``extra`` adds vertices (column id) that no edge touches.
        """
        cols = [F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")] + ([F.col("w").cast("double").alias("w")] if "w" in edges.columns else [])
        e = edges.select(*cols).dropna(subset=["src", "dst"])
        if self_edges == "drop":
            e = e.where("src <> dst")
        elif self_edges != "keep":
            raise ValueError("self_edges is 'keep' or 'drop'")
        g = Graph(e, extra.select(F.col("id").cast("long").alias("id")).dropna() if extra is not None else None, name)
        return g.simplify() if simple else g

    @property
    def spark(self):
        return self.edges.sparkSession

    @property
    def vertices(self) -> DataFrame:
        """Both ends of all edges and the extra vertices, once each."""
        ends = self.edges.select(F.explode(F.array("src", "dst")).alias("id"))
        return (ends if self.extra is None else ends.union(self.extra)).distinct()

    def validate(self) -> "Graph":
        want = {"src": "bigint", "dst": "bigint", "w": "double"}
        for name, kind in self.edges.dtypes:
            if want.get(name) != kind:
                raise TypeError(f"edge column {name} has type {kind}")
        return self

    def where(self, condition: str | Column) -> "Graph":
        return replace(self, edges=self.edges.where(condition))

    def reverse(self) -> "Graph":
        return replace(self, edges=self.edges.withColumnsRenamed({"src": "dst", "dst": "src"}).select(*self.edges.columns))

    def undirect(self) -> "Graph":
        """Each edge in both directions, by one pass over the edges."""
        rest = [c for c in self.edges.columns if c not in ("src", "dst")]
        both = self.edges.select(F.explode(F.array(F.struct(F.col("src").alias("s"), F.col("dst").alias("d")), F.struct(F.col("dst").alias("s"), F.col("src").alias("d")))).alias("_e"), *rest)
        return replace(self, edges=both.select(F.col("_e.s").alias("src"), F.col("_e.d").alias("dst"), *rest))

    def simplify(self) -> "Graph":
        """Parallel edges become one; weights add up."""
        if "w" in self.edges.columns:
            return replace(self, edges=self.edges.groupBy("src", "dst").agg(F.sum("w").alias("w")))
        return replace(self, edges=self.edges.distinct())

    def subgraph(self, keep: DataFrame) -> "Graph":
        """Edges with both ends among ``keep(id)``."""
        k = keep.select("id")
        e = self.edges.join(k.withColumnRenamed("id", "src"), "src", "left_semi").join(k.withColumnRenamed("id", "dst"), "dst", "left_semi")
        return replace(self, edges=e.select(*self.edges.columns), extra=k)

    def out_degrees(self) -> DataFrame:
        return self.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("out_degree"))

    def in_degrees(self) -> DataFrame:
        return self.edges.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("in_degree"))

    def degrees(self) -> DataFrame:
        """Every vertex with both degrees, from one pass over the edges."""
        ends = self.edges.select(F.explode(F.array(F.struct(F.col("src").alias("id"), F.lit(1).alias("o"), F.lit(0).alias("i")), F.struct(F.col("dst").alias("id"), F.lit(0).alias("o"), F.lit(1).alias("i")))).alias("x")).select("x.*")
        if self.extra is not None:
            ends = ends.union(self.extra.select("id", F.lit(0), F.lit(0)))
        return ends.groupBy("id").agg(F.sum("o").alias("out_degree"), F.sum("i").alias("in_degree"))

    def degree_sketch(self) -> DataFrame:
        """Approximate distinct neighbours and degree quantiles."""
        d = self.degrees().select(F.percentile_approx(F.col("out_degree") + F.col("in_degree"), [0.5, 0.9, 0.99, 1.0], 1000).alias("degree_quantiles"))
        return d.crossJoin(self.edges.agg(F.approx_count_distinct("dst").alias("distinct_targets")))  # one row each

    def sinks(self) -> DataFrame:
        return self.vertices.join(self.edges.select(F.col("src").alias("id")), "id", "left_anti")

    def adjacency(self) -> DataFrame:
        """(id, nbrs) of vertices with an out-edge, neighbours sorted."""
        return self.edges.groupBy(F.col("src").alias("id")).agg(F.array_sort(F.collect_list("dst")).alias("nbrs"))

    def adjacency_long(self) -> DataFrame:
        """(id, deg, nbrs) of every vertex."""
        full = self.vertices.join(self.adjacency(), "id", "left")
        return full.select("id", F.coalesce(F.size("nbrs"), F.lit(0)).alias("deg"), F.coalesce("nbrs", F.array().cast("array<bigint>")).alias("nbrs"))

    def contract(self, blocks: DataFrame) -> DataFrame:
        """(bsrc, bdst, w): number of edges between different blocks of ``blocks(id, block)``."""
        b = blocks.select("id", "block")
        e = self.edges.join(b.select(F.col("id").alias("src"), F.col("block").alias("bsrc")), "src").join(b.select(F.col("id").alias("dst"), F.col("block").alias("bdst")), "dst")
        return e.where("bsrc <> bdst").groupBy("bsrc", "bdst").agg(F.count("*").alias("w"))

    def copies(self, times: int, apart: int = 1 << 40) -> "Graph":
        """``times`` disjoint copies, each with its ids moved by ``apart``: data that grows without changing its shape."""
        if times == 1:
            return self
        n = F.explode(F.sequence(F.lit(0), F.lit(times - 1)))
        moved = lambda c: (F.col(c) + F.col("_n") * F.lit(apart)).alias(c)
        e = self.edges.withColumn("_n", n).select(*[moved(c) if c in ("src", "dst") else F.col(c) for c in self.edges.columns])
        return replace(self, edges=e, extra=None if self.extra is None else self.extra.withColumn("_n", n).select(moved("id")))

    def sample(self, rate: float, seed: int = 7) -> "Graph":
        """Edges whose hash falls under ``rate``; the same on every retry."""
        top = 1 << 30
        return self.where(F.pmod(F.xxhash64("src", "dst", F.lit(seed)), F.lit(top)) < int(rate * top))

    def stats(self) -> DataFrame:
        """One row: vertices, edges, mean and greatest degrees, self-edges and sinks."""
        d = self.degrees().agg(
            F.count("*").alias("vertices"), F.sum("out_degree").cast("long").alias("edges"), F.round(F.avg("out_degree"), 6).alias("avg_out_degree"),
            F.max("out_degree").cast("long").alias("max_out_degree"), F.max("in_degree").cast("long").alias("max_in_degree"), F.count_if(F.col("out_degree") == 0).alias("sinks"),
        )
        return d.crossJoin(self.edges.agg(F.count_if(F.col("src") == F.col("dst")).alias("self_edges")))  # one row each


def as_dict(row: Any) -> dict:
    return row.asDict()
