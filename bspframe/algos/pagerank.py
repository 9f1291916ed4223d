"""PageRank in its exact, approximate, asynchronous and block forms."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F

from bspframe.engines import run
from bspframe.engines.dealing import deal, held
from bspframe.engines.program import message_edges, pagerank_program
from bspframe.engines.serial import single_pagerank
from bspframe.graph import Graph, Result
from bspframe.loop import Adaptive, RoundStat, Truncate, pin, superstep_loop
from bspframe.session import materialise, ship


def _named(r: Result) -> Result:
    return Result(r.df.select("id", F.col("value").alias("rank")), r.rounds, r.stats)


def pagerank(g: Graph, delta: float = 0.15, init: float = 1.0, tol: float | None = None, max_rounds: int | None = None, engine: str = "vertex", self_edges: str = "keep", **how) -> Result:
    """Exact ranks, not divided by the vertex count and without redistribution from sinks.

    With ``max_rounds`` and no ``tol``: that many rounds. Else until no rank moves by ``tol`` (default ``init``).
    ``self_edges='drop'`` is the known wrong control. A weight column ``w`` splits shares by weight.
    """
    if self_edges == "drop":
        g = g.where("src <> dst")
    if engine.startswith("gas") and tol is not None:
        how = {"tol": tol, **how}  # also when a vertex goes quiet, or a sweep is the last
    p = pagerank_program(delta, init, tol, max_rounds if tol is None else None, max_rounds or 1000)
    return _named(run(engine, g, p, **how))


#: Vertices at work, up to which their ids (8 bytes each) are broadcast to the edges.
FEW = 100_000


def pagerank_approx(g: Graph, eps: float, reactivate: bool = False, delta: float = 0.15, init: float = 1.0, max_rounds: int = 100, truncate: Truncate | None = None) -> Result:
    """Approximate ranks: a vertex whose change is at most ``eps`` stops computing.

    For good, or (``reactivate``) until an in-neighbour moves by more. Neighbours still read its last rank.
    """
    p = pagerank_program(delta, init, k=1)
    spark = g.spark
    with Adaptive(spark):
        n = int(spark.conf.get("spark.sql.shuffle.partitions"))
        kept = held(g, n)
        out = deal(message_edges(kept.graph, p, kept.hubs), "src", n, kept.hubs)
        state = pin(kept.graph.vertices.select("id", F.lit(float(init)).alias("value"), F.lit(True).alias("active"), F.lit(True).alias("moved"), F.lit(float(init)).alias("old"), F.lit(True).alias("worked")), "id", n)
        last: list[RoundStat] = []

        def step(s: DataFrame, number: int) -> DataFrame:
            if number == 1:
                work = s.select("id")
            elif reactivate:  # a vertex that moved wakes those it points to
                work = s.where("active").select("id").union(out.meet(s.where("moved").select("id")).select(F.col("dst").alias("id"))).distinct()
            else:
                work = s.where("active").select("id")
            sent = out.meet(s.select("id", "value"))  # edges stay; only sums move
            if not reactivate and last and last[-1].active <= FEW:
                sent = sent.join(F.broadcast(work.withColumnRenamed("id", "dst")), "dst", "left_semi")  # in-edges of vertices at work, no others
            got = sent.groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("value") * F.col("w")).alias("msg"))
            new = s.select("id", F.col("value").alias("old")).join(work.withColumn("_on", F.lit(True)), "id", "left").join(got, "id", "left")
            new = new.select("id", "old", F.coalesce("_on", F.lit(False)).alias("worked"), "msg")
            new = new.withColumn("value", F.when(F.col("worked"), delta + (1 - delta) * F.coalesce("msg", F.lit(0.0))).otherwise(F.col("old")))
            moved = F.abs(F.col("value") - F.col("old")) > eps
            return new.select("id", "value", (F.col("worked") & moved).alias("active"), moved.alias("moved"), "old", "worked")

        def halt(st: RoundStat) -> bool:
            last.append(st)
            return st.active == 0

        state, done, stats = superstep_loop(state, step, halt, max_rounds, truncate or Truncate(), changed="worked", change="abs(value - old)", active="active")
        out.unpersist()
        kept.release()
    return Result(state.select("id", F.col("value").alias("rank")), done, stats)


#: Start values of the last phase, over vertex rank ``vr``, block rank ``br`` and ``out_degree``.
STARTS = {"product": "vr * br", "block": "br", "vertex": "vr", "degree": "vr * br * (1 + out_degree) / avg(1 + out_degree) over (partition by block)"}


def pagerank_block(g: Graph, blocks: DataFrame, init_fn: str = "product", tol: float = 1e-3, delta: float = 0.15, step_rounds: tuple[int, int, int] | None = None, max_rounds: int = 200, local: str = "serial") -> Result:
    """Block form in two steps: local ranks in each block and ranks of the block graph give the start of a whole-graph run.

    ``blocks(id, block)``. ``local='serial'`` runs a serial kernel in each block (a block must fit one task, as the blocks
    of a partitioner with a size bound do); ``'rounds'`` runs supersteps over the inner edges of all blocks instead.
    ``init_fn`` mixes vertex rank ``vr``, block rank ``br`` and ``out_degree``: product; block; vertex; degree (the
    product, tilted to vertices with more out-edges than their block's mean); or any SQL over these. ``step_rounds`` fixes the
    rounds of the three phases. Stats carry the phase.
    """
    from bspframe.engines.vertex import run_vertex

    b = blocks.select("id", "block").persist()
    ends = g.edges.join(b.select(F.col("id").alias("src"), F.col("block").alias("sb")), "src").join(b.select(F.col("id").alias("dst"), F.col("block").alias("db")), "dst")
    inner = ends.where("sb = db").select("src", "dst", F.col("sb").alias("block"))
    fixed = step_rounds or (None, None, None)
    program = lambda k: pagerank_program(delta, 1.0, None if k else tol, k, max_rounds)
    if local == "serial":
        ranks, local_rounds, local_stats = _local_ranks(inner, b, delta, tol, fixed[0], max_rounds)
    elif local == "rounds":
        r = run_vertex(Graph(inner.select("src", "dst"), extra=g.vertices), program(fixed[0]))
        ranks, local_rounds, local_stats = r.df.withColumnRenamed("value", "vr").join(b, "id"), r.rounds, r.stats
    else:
        raise ValueError("local is 'serial' or 'rounds'")
    between = Graph(g.contract(b).select(F.col("bsrc").alias("src"), F.col("bdst").alias("dst"), F.col("w").cast("double").alias("w")), extra=b.select(F.col("block").alias("id")).distinct())
    over = run_vertex(between, program(fixed[1]))
    start = (
        ranks.join(over.df.select(F.col("id").alias("block"), F.col("value").alias("br")), "block")
        .join(g.out_degrees(), "id", "left").withColumn("out_degree", F.coalesce("out_degree", F.lit(0)))
        .select("id", F.expr(STARTS.get(init_fn, init_fn)).cast("double").alias("value"), F.lit(True).alias("changed"))
    )
    whole = run_vertex(g, program(fixed[2]), start=start)
    b.unpersist()
    return Result(whole.df.select("id", F.col("value").alias("rank")), local_rounds + over.rounds + whole.rounds, [("local", local_stats), ("blocks", over.stats), ("whole", whole.stats)])


def _local_ranks(inner: DataFrame, blocks: DataFrame, delta: float, tol: float, k: int | None, most: int) -> tuple[DataFrame, int, list]:
    """Ranks over each block's inner edges, by the serial kernel where the block lies: (id, vr, block)."""
    ship(inner.sparkSession)

    def one(key, vertices: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
        ids = np.sort(vertices["id"].to_numpy())
        at = lambda c: np.searchsorted(ids, edges[c].to_numpy())
        vr, done = single_pagerank(at("src"), at("dst"), len(ids), delta, 1.0, None if k else tol, k or None, most)
        return pd.DataFrame({"id": ids, "vr": vr, "block": key[0], "rounds": done})

    found = blocks.groupBy("block").cogroup(inner.groupBy("block")).applyInPandas(one, "id long, vr double, block long, rounds int")
    found = materialise(found, "local-ranks")
    rounds, n = found.agg(F.coalesce(F.max("rounds"), F.lit(0)), F.count("*")).first()
    return found.drop("rounds"), rounds, [RoundStat(rounds, n, n, 0.0, 0.0)]


def top_ranked(df: DataFrame, k: int, value: str = "rank") -> DataFrame:
    """The k highest, ties by id."""
    return df.orderBy(F.desc(value), "id").limit(k)
