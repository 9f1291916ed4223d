"""Single-source shortest paths by hops or weights, and K-hop neighbourhoods."""

from __future__ import annotations

import time
import uuid
from dataclasses import replace

from pyspark.sql import DataFrame, Observation, Window, functions as F

from bspframe.engines import run
from bspframe.engines.program import hops_program
from bspframe.graph import Graph, Result
from bspframe.loop import TIDY, Adaptive, RoundStat, Truncate, pin
from bspframe.session import checkpointed, drop_checkpoint, drop_table, materialise, materialise_counting, shared_dir, table_path, tidy

#: A frontier up to so many vertices (8 MB) is broadcast, and the edges are read as they lie.
SMALL = 1_000_000
#: Levels after which method='auto' takes the graph for one of long diameter.
PATIENCE = 24
#: Rows of a level's state from which its shuffle files are deleted as soon as it is over.
MANY = 1_000_000


def pick_source(g: Graph, seed: int = 1) -> int:
    """A random vertex of the graph, the same for the same seed."""
    return g.vertices.agg(F.min_by("id", F.xxhash64("id", F.lit(seed)))).first()[0]


def _with_source(g: Graph, source: int) -> Graph:
    one = g.spark.createDataFrame([(int(source),)], "id long")
    return replace(g, extra=one if g.extra is None else g.extra.select("id").union(one))


def _finish(r: Result, include_unreached: bool, g: Graph) -> Result:
    df = r.df.select("id", F.col("value").alias("dist"))
    return Result(df if include_unreached else df.where("dist is not null"), r.rounds, r.stats)


def sssp(g: Graph, source: int, engine: str = "frontier", method: str = "top_down", weight: bool = False, include_unreached: bool = False, with_parent: bool = False, max_rounds: int | None = None, alpha: float = 15.0, beta: float = 18.0, **how) -> Result:
    """Distances from ``source``.

    ``engine='frontier'`` keeps visited and frontier apart and touches only the frontier's edges each round; the other
    engines interpret the same program. ``method='dir_opt'`` switches to scanning the unvisited when the frontier is
    wide; ``'contract'`` follows unique predecessors by pointer jumping and searches what is left, so that chains and trees
    cost the logarithm of their length; ``'auto'`` goes top down for PATIENCE levels and contracts the rest. The source is
    always in the answer, also when the graph does not have it. ``weight`` relaxes the edge weights. ``with_parent`` adds the least predecessor on a shortest path.
    A hit ``max_rounds`` leaves the last round's ``changed`` above zero: the answer is then not complete.
    """
    if engine == "frontier" and not weight:
        if method in ("contract", "auto") and max_rounds is None:
            first = _frontier(g, source, 0 if method == "contract" else PATIENCE, False, alpha, beta, **how)
            r = first if method == "auto" and not first.stats[-1].changed else _contracted(g, first)
        else:
            r = _frontier(g, source, max_rounds, method == "dir_opt", alpha, beta, **how)
        if include_unreached:
            r = Result(g.vertices.join(r.df, "id", "left"), r.rounds, r.stats)
    else:
        g = _with_source(g, source)
        p = hops_program(source, weighted=weight)
        r = _finish(run("vertex" if engine == "frontier" else engine, g, p, **how), include_unreached, g)
    if with_parent:
        at = r.df.select("id", "dist")
        cost = F.col("w") if weight else F.lit(1)
        steps = g.edges.join(at.toDF("src", "ds"), "src").join(at.toDF("dst", "dd"), "dst").where(F.col("ds") + cost == F.col("dd"))
        r = Result(r.df.join(steps.groupBy(F.col("dst").alias("id")).agg(F.min_by("src", F.struct("ds", "src")).alias("parent")), "id", "left"), r.rounds, r.stats)
    return r


def khop(g: Graph, source: int, k: int = 3, engine: str = "frontier", levels: bool = False, **how) -> Result:
    """Vertices within ``k`` hops and their distances; ``levels`` counts them by distance instead."""
    if engine == "frontier":
        r = _frontier(g, source, k, False, 15.0, 18.0, **how)
    elif engine == "recursive_sql":
        from bspframe.engines.relational import run_recursive_sql

        r = Result(run_recursive_sql(g.spark, g, source, k), k, [])
    else:
        r = _finish(run(engine, _with_source(g, source), hops_program(source, k), **how), False, g)
    return Result(khop_counts(r.df), r.rounds, r.stats) if levels else r


def khop_counts(found: DataFrame) -> DataFrame:
    return found.groupBy("dist").agg(F.count("*").alias("vertices"))


def khop_many(g: Graph, sources: DataFrame, k: int = 3) -> Result:
    """(source, id, dist) for every ``sources(id)``: state and visited test are keyed by (source, id)."""
    spark = g.spark
    shared_dir(spark)
    with Adaptive(spark):
        edges = pin(g.edges.select("src", "dst").distinct(), "src")
        seen = checkpointed(sources.select(F.col("id").cast("long").alias("source"), F.col("id").cast("long").alias("id"), F.lit(0).alias("dist")).distinct())
        front, stats = seen, []
        for level in range(1, k + 1):
            began = time.perf_counter()
            found = edges.join(front.select("source", F.col("id").alias("src")), "src").select("source", F.col("dst").alias("id")).distinct()
            count = Observation()
            fresh = found.join(seen.select("source", "id"), ["source", "id"], "left_anti").withColumn("dist", F.lit(level))
            front = checkpointed(fresh.observe(count, F.count("*").alias("n")))
            n = count.get["n"]
            seen = seen.union(front)
            stats.append(RoundStat(level, n, n, 1.0, time.perf_counter() - began))
            if not n:
                break
            if level % 8 == 0:
                seen = checkpointed(seen)
        edges.unpersist()
    return Result(seen, len(stats), stats)


def _frontier(g: Graph, source: int, max_rounds: int | None, switch: bool, alpha: float, beta: float, truncate: Truncate | None = None) -> Result:
    """Breadth-first levels: expand, distinct, drop the visited. One job a level; levels are folded every few rounds."""
    spark = g.spark
    shared_dir(spark)
    every = (truncate or Truncate(8)).every
    with Adaptive(spark):
        n = int(spark.conf.get("spark.sql.shuffle.partitions"))
        edges = g.edges.select("src", "dst").where("src <> dst").persist()
        dealt = None  # by source, from the first frontier on that is too large to broadcast
        back = pin(edges.select("dst", "src"), "dst", n) if switch else None
        total = edges.count() if switch else 0
        front = spark.createDataFrame([(int(source), 0)], "id long, dist int")
        visited = front
        stats, level, size, up, left = [], 0, 1, False, total
        while max_rounds is None or level < max_rounds:
            level += 1
            began = time.perf_counter()
            if switch:
                work = edges.join(F.broadcast(front.select(F.col("id").alias("src"))), "src", "left_semi").count() if size <= SMALL else total
                left -= work
                up = work > left / alpha if not up else size > total / beta
            lead = front.select(F.col("id").alias("src"))
            lead = F.broadcast(lead) if size <= SMALL else lead
            if up:  # scan what is unvisited for a parent in the frontier
                open_ = back.join(visited.select(F.col("id").alias("dst")), "dst", "left_anti")
                found = open_.join(lead, "src", "left_semi").select(F.col("dst").alias("id")).distinct()
            else:
                if size > SMALL and dealt is None:
                    dealt = pin(edges, "src", n)
                found = (edges if size <= SMALL else dealt).join(lead, "src", "left_semi").select(F.col("dst").alias("id")).distinct()
                found = found.join(visited.select("id"), "id", "left_anti")
            seen = Observation()
            front = checkpointed(found.withColumn("dist", F.lit(level)).observe(seen, F.count("*").alias("n")))
            size = seen.get["n"]
            stats.append(RoundStat(level, size, size, 1.0, time.perf_counter() - began))
            visited = visited.union(front)
            if level % every == 0:
                visited = checkpointed(visited.repartition(n, "id"))
            if not size:
                break
        for df in (edges, dealt, back):
            if df is not None:
                df.unpersist()
    return Result(visited.select("id", "dist"), level, stats)


def _contracted(g: Graph, first: Result) -> Result:
    """Goes on from the levels in ``first`` in a number of rounds that does not grow with the length of chains.

    Of the unvisited vertices, one with a single in-edge lies one hop behind its predecessor. Jumping along these
    predecessors gives each such vertex its anchor and the hops from there; anchors are the last level and the vertices with
    several in-edges. Distances of the anchors follow from the edges between them, weighted by the hops that they stand
    for. A ring that nothing enters never meets an anchor and is not reached.
    """
    spark = g.spark
    last = len(first.stats)
    seen = materialise(first.df, "visited")
    edge_of = seen.where(F.col("dist") == last).select("id", "dist")
    e = g.edges.select("src", "dst").where("src <> dst").distinct()
    open_ = e.join(seen.select(F.col("id").alias("dst")), "dst", "left_anti")
    inner = seen.where(F.col("dist") < last).select(F.col("id").alias("src"))  # all that these reach is visited
    open_ = materialise(open_.join(inner, "src", "left_anti").select("src", "dst"), "open-edges")
    single = open_.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("n"), F.min("src").alias("up"))
    up = materialise(single.where("n = 1").select("id", "up", F.lit(1).cast("long").alias("hops")), "up")
    stats, jumps = list(first.stats), 0
    most = max(1, up.count()).bit_length() + 1
    while jumps < most:  # a row that still moves after that goes round a ring
        jumps += 1
        began = time.perf_counter()
        far = up.select(F.col("id").alias("up"), F.col("up").alias("_up"), F.col("hops").alias("_hops"))
        step = up.join(far, "up", "left").select("id", F.coalesce("_up", "up").alias("up"), (F.col("hops") + F.coalesce("_hops", F.lit(0))).alias("hops"), F.col("_up").isNotNull().alias("moved"))
        fresh, count = materialise_counting(step, "up", moved="moved")
        drop_table(up)
        up = fresh.select("id", "up", "hops")
        stats.append(RoundStat(last + jumps, count["moved"], count["moved"], 1.0, time.perf_counter() - began))
        if not count["moved"]:
            break
    settled = up if not stats or not stats[-1].changed else up.join(up.select(F.col("id").alias("up")), "up", "left_anti").select("id", "up", "hops")
    many = single.where("n > 1").select("id")
    # edges into anchors, from the anchor of their source
    into = open_.join(many.select(F.col("id").alias("dst")), "dst", "left_semi").join(settled.select(F.col("id").alias("src"), "up", "hops"), "src", "left")
    into = into.select(F.coalesce("up", "src").alias("src"), "dst", (F.coalesce("hops", F.lit(0)) + 1).cast("double").alias("w")).groupBy("src", "dst").agg(F.min("w").alias("w"))
    anchors = many.select("id", F.lit(None).cast("double").alias("value")).union(edge_of.select("id", F.col("dist").cast("double").alias("value")))
    start = anchors.withColumn("changed", F.col("value").isNotNull())
    reduced = run("vertex", Graph(materialise(into, "anchor-edges"), extra=anchors.select("id"), name=g.name), hops_program(0, weighted=True), start=start) if not many.isEmpty() else None
    at = reduced.df.where("value is not null") if reduced else start.select("id", "value")
    behind = settled.join(at.withColumnRenamed("id", "up"), "up").select("id", (F.col("value") + F.col("hops")).cast("int").alias("dist"))
    reached = at.select("id", F.col("value").cast("int").alias("dist")).join(edge_of.select("id"), "id", "left_anti")
    return Result(seen.union(reached).union(behind), last + jumps + (reduced.rounds if reduced else 0), stats + (reduced.stats if reduced else []))


def pair_counts(g: Graph, sources: DataFrame, max_rounds: int = 1 << 30) -> list[RoundStat]:
    """For each level the number of (source, vertex) pairs first met there; the pairs themselves are never rows.

    64 sources share a row: ``state(word, id, seen, front)`` has a bit for each. An edge carries the bits of its source's
    front, and those that meet in a vertex are combined before they leave their task. Edges are files clustered by
    source, so the shuffle files of building them are deleted before the first level, and those of a level within seconds.
    """
    spark = g.spark
    shared_dir(spark)
    made = materialise(g.edges.select("src", "dst").where("src <> dst").distinct(), "edges")
    tidy(spark)
    name, files = f"dealt_{uuid.uuid4().hex[:8]}", table_path(spark, "dealt-edges")
    with Adaptive(spark):
        n = int(spark.conf.get("spark.sql.shuffle.partitions"))
        made.repartition(n, "src").write.bucketBy(n, "src").sortBy("src").option("path", files).saveAsTable(name)
        drop_table(made)
        tidy(spark)
        tidied = time.perf_counter()
        edges = spark.table(name)
        own = sources.select(F.col("id").cast("long").alias("id")).dropna().distinct().repartitionByRange(max(1, n // 4), "id").sortWithinPartitions("id")
        own = checkpointed(own.withColumn("number", F.monotonically_increasing_id()))  # numbers are settled by that
        bit = own.select(F.expr("shiftright(number, 6)").alias("word"), "id", F.expr("shiftleft(1L, cast(number & 63 as int))").alias("seen"))
        state = checkpointed(bit.withColumn("front", F.col("seen")))
        stats = []
        while len(stats) < max_rounds:
            began = time.perf_counter()
            front = state.where("front <> 0").select("word", F.col("id").alias("src"), "front")
            found = edges.join(front, "src").groupBy("word", F.col("dst").alias("id")).agg(F.bit_or("front").alias("found"))
            both = state.select("word", "id", "seen").join(found, ["word", "id"], "full_outer").na.fill(0, ["seen", "found"])
            count = Observation()
            fresh = both.select("word", "id", F.expr("seen | found").alias("seen"), F.expr("found & ~seen").alias("front"))
            last, state = state, checkpointed(fresh.observe(count, F.coalesce(F.sum(F.bit_count("front")), F.lit(0)).alias("pairs"), F.count("*").alias("rows")))
            got = count.get
            drop_checkpoint(last)
            if got["rows"] > MANY or time.perf_counter() - tidied > TIDY:
                last = front = found = both = fresh = None
                tidy(spark)
                tidied = time.perf_counter()
            if not got["pairs"]:
                break
            stats.append(RoundStat(len(stats) + 1, got["pairs"], got["pairs"], 1.0, time.perf_counter() - began))
        drop_checkpoint(state)
        drop_checkpoint(own)
        spark.sql(f"DROP TABLE {name}")
        drop_table(files, spark)
    return stats


def diameter(g: Graph, sources: DataFrame | None = None, samples: int = 32, share: float = 0.9, seed: int = 7) -> DataFrame:
    """One row: sources, reached pairs, the longest distance found, and the distance within which ``share`` of the pairs lie.

    Breadth-first search from ``sources(id)`` or from ``samples`` vertices by hash; the longest is a lower bound of the
    diameter. ``effective`` is the least whole distance, ``effective_smooth`` interpolates between it and the one before.
    """
    if sources is None:
        sources = g.vertices.orderBy(F.xxhash64("id", F.lit(seed)), "id").limit(samples)
    by = g.spark.createDataFrame([(x.round, x.changed) for x in pair_counts(g, sources)], "dist int, n long")  # one row for each distance
    upto = by.withColumn("upto", F.sum("n").over(Window.orderBy("dist"))).withColumn("all", F.sum("n").over(Window.partitionBy()))
    goal = F.col("all") * F.lit(share)
    smooth = F.col("dist") - (F.col("upto") - goal) / F.col("n")
    got = upto.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("pairs"), F.max("dist").alias("longest"), F.min(F.when(F.col("upto") >= goal, F.col("dist"))).alias("effective"), F.round(F.min(F.when(F.col("upto") >= goal, smooth)), 6).alias("effective_smooth"))
    return sources.agg(F.countDistinct("id").alias("sources")).crossJoin(got)  # one row each
