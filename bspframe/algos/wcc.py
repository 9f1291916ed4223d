"""Weakly connected components; every method gives (id, component) with component = least id in it."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from bspframe.algos.contract import contract_components
from bspframe.engines import run
from bspframe.engines.program import wcc_program
from bspframe.graph import Graph, Result
from bspframe.loop import Adaptive, RoundStat, Truncate, fixpoint, pin, superstep_loop
from bspframe.session import drop_table, materialise, ship


def wcc(g: Graph, method: str | None = None, engine: str = "vertex", directed: bool = False, reverse: str = "pre", **how) -> Result:
    """``method``: hook_jump (default), min_label, hash_to_min, star, block, auto.

    ``engine`` selects who runs min_label. ``reverse`` says where the reverse edges come from: ``pre`` stores them,
    ``first_round`` makes them from uncombined messages of an extra round, ``gather_both`` reads each stored edge from both
    ends every round. ``directed`` follows edges one way: the known wrong control.
    """
    method = method or ("min_label" if directed or engine != "vertex" else "hook_jump")
    if method == "auto":
        return _auto(g)
    if method == "hook_jump":
        return hook_jump(g, **how)
    if method == "star":
        return star(g)
    if method == "hash_to_min":
        return hash_to_min(g, **how)
    if method == "block":
        engine = "block"
    p = wcc_program(directed)
    if not directed and reverse == "first_round":
        g = _reverse_by_messages(g)
    elif not directed and reverse == "gather_both" and engine == "vertex":
        return _gather_both(g, **how)
    r = run(engine, g, p, **how)
    return Result(r.df.select("id", F.col("value").alias("component")), r.rounds + (reverse == "first_round"), r.stats)


def _reverse_by_messages(g: Graph) -> Graph:
    """Reverse edges made in a first round: each vertex tells its targets its id, and the lists are kept as edges."""
    found = g.edges.groupBy("dst").agg(F.collect_set("src").alias("heard"))  # no combiner can merge these
    back = found.select(F.col("dst").alias("src"), F.explode("heard").alias("dst"))
    return Graph(g.edges.select("src", "dst").union(back), g.extra, g.name)


def _gather_both(g: Graph, truncate: Truncate | None = None) -> Result:
    """Min labels where each round reads every stored edge from both ends; no reverse copy is held."""
    with Adaptive(g.spark):
        edges = pin(g.edges.select("src", "dst").distinct(), "src")
        state = pin(g.vertices.select("id", F.col("id").alias("value"), F.lit(True).alias("changed"), F.col("id").alias("old")), "id")

        def step(s: DataFrame, _: int) -> DataFrame:
            lab = s.select("id", "value")
            out = edges.join(lab.withColumnRenamed("id", "src"), "src").select(F.col("dst").alias("id"), "value")
            back = edges.join(lab.withColumnRenamed("id", "dst"), "dst").select(F.col("src").alias("id"), "value")
            got = out.union(back).groupBy("id").agg(F.min("value").alias("msg"))
            new = s.select("id", F.col("value").alias("old")).join(got, "id", "left").withColumn("value", F.least("old", "msg"))
            return new.select("id", "value", F.expr("value <> old").alias("changed"), "old")

        state, done, stats = superstep_loop(state, step, fixpoint(), 10_000, truncate)
        edges.unpersist()
    return Result(state.select("id", F.col("value").alias("component")), done, stats)


def hook_jump(g: Graph, finish_below: int = 0) -> Result:
    """Hooking, pointer jumping and contraction: logarithmic rounds whatever the diameter.

    ``finish_below`` is the explicit wish for a serial end once so few edges are left.
    """
    trace: list = []
    ship(g.spark)
    found = contract_components(g.edges, trace=trace, finish_below=finish_below)
    df = found if g.extra is None else found.union(g.extra.distinct().join(found, "id", "left_anti").select("id", F.col("id").alias("component")))
    return Result(df, len(trace), trace)


def star(g: Graph, max_rounds: int = 100) -> Result:
    """Alternating large-star and small-star operations on the edge set until it is a forest of stars."""
    work = materialise(g.edges.select(F.greatest("src", "dst").alias("a"), F.least("src", "dst").alias("b")).where("a <> b").distinct(), "star")
    stats = []
    for number in range(1, max_rounds + 1):
        both = work.select(F.col("a").alias("u"), F.col("b").alias("v")).union(work.select("b", "a"))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("a"), F.col("m").alias("b")).distinct()
        m = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(m, "a").select(F.when(F.col("b") == F.col("m"), F.col("a")).otherwise(F.col("b")).alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        fresh = materialise(small, "star")
        changed = fresh.exceptAll(work).count() + work.exceptAll(fresh).count()
        drop_table(work)
        work = fresh
        stats.append(RoundStat(number, changed, changed, 0.0, 0.0))
        if not changed:
            break
    alone = g.vertices.join(work.select(F.col("a").alias("id")), "id", "left_anti").select("id", F.col("id").alias("component"))
    return Result(work.select(F.col("a").alias("id"), F.col("b").alias("component")).union(alone), len(stats), stats)


def hash_to_min(g: Graph, max_rounds: int = 100) -> Result:
    """Each vertex holds a set that starts as its closed neighbourhood; every round the whole set goes to its least
    member and the least member to all members. Sets are flat rows (owner, member), so no array grows."""
    und = g.edges.select("src", "dst").where("src <> dst")
    own = g.vertices.select(F.col("id").alias("owner"), F.col("id").alias("member"))
    sets = materialise(und.toDF("owner", "member").union(und.select("dst", "src")).union(own).distinct(), "hash-to-min")
    stats, last = [], sets.count()
    for number in range(1, max_rounds + 1):
        low = sets.groupBy("owner").agg(F.min("member").alias("low"))
        tagged = sets.join(low, "owner")
        fresh = materialise(tagged.select(F.col("low").alias("owner"), "member").union(tagged.select(F.col("member").alias("owner"), F.col("low").alias("member"))).distinct(), "hash-to-min")
        now = fresh.count()
        same = now == last and fresh.join(sets, ["owner", "member"], "left_anti").isEmpty()
        drop_table(sets)
        sets, last = fresh, now
        stats.append(RoundStat(number, 0 if same else now, now, 0.0, 0.0))
        if same:
            break
    return Result(sets.groupBy(F.col("owner").alias("id")).agg(F.min("member").alias("component")), len(stats), stats)


def _auto(g: Graph, probe: int = 8, share: float = 0.05) -> Result:
    """Min labels first; a long diameter (many still changing after ``probe`` rounds) goes on by contraction of labels."""
    from bspframe.engines.program import with_rounds
    from bspframe.engines.vertex import run_vertex

    first = run_vertex(g, with_rounds(wcc_program(), probe))
    if first.stats[-1].changed <= share * g.vertices.count():
        r = run_vertex(g, wcc_program(), start=first.df.withColumn("changed", F.lit(True)))
        return Result(r.df.select("id", F.col("value").alias("component")), first.rounds + r.rounds, first.stats + r.stats)
    lab = first.df.select("id", F.col("value").alias("l"))
    e = g.edges.join(lab.toDF("src", "ls"), "src").join(lab.toDF("dst", "ld"), "dst").select(F.col("ls").alias("src"), F.col("ld").alias("dst"))
    trace: list = []
    ship(g.spark)
    roots = contract_components(e, trace=trace)
    df = lab.join(roots.toDF("l", "component"), "l", "left").select("id", F.coalesce("component", "l").alias("component"))
    return Result(df, first.rounds + len(trace), first.stats + trace)
