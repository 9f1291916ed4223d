"""Blocks: connected or located groups of vertices, as (id, block)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from bspframe.algos.contract import contract_components
from bspframe.graph import Graph
from bspframe.session import drop_table, materialise

#: Gains told apart when movers are admitted, and hash cells of movers of one gain.
GAINS, CELLS = 64, 64


def blocks_voronoi(g: Graph, rate: float = 0.001, growth: float = 2.0, max_size: int | None = None, max_rounds: int = 20, seed: int = 7) -> DataFrame:
    """Sampled seeds claim what they reach first; too large blocks are dissolved and the rest is sampled at a higher rate.

    Sizes are counted where the blocks are; nothing but the number of uncovered vertices reaches the driver. What is left
    at the round cap is split by its connected components. Blocks are connected.
    """
    total = g.vertices.count()
    most = max_size or max(1, total // 10)
    und = materialise(g.undirect().edges.select("src", "dst").where("src <> dst").distinct(), "voronoi-edges")
    open_ = materialise(g.vertices, "voronoi-open")
    covered = None
    for number in range(max_rounds):
        seeds = open_.where(F.pmod(F.xxhash64("id", F.lit(seed + number)), F.lit(1 << 30)) < int(rate * (1 << 30)))
        part = und.join(open_.toDF("src"), "src", "left_semi").join(open_.toDF("dst"), "dst", "left_semi")
        claimed = materialise(seeds.select("id", F.col("id").alias("block"), F.lit(0).alias("hop")), "voronoi-claims")
        hop = 0
        while True:  # first arrival wins, ties by the least seed
            hop += 1
            front = claimed.where(F.col("hop") == hop - 1)
            found = part.join(front.select(F.col("id").alias("src"), "block"), "src").groupBy(F.col("dst").alias("id")).agg(F.min("block").alias("block"))
            found = materialise(found.join(claimed.select("id"), "id", "left_anti").withColumn("hop", F.lit(hop)), "voronoi-front")
            if found.isEmpty():
                drop_table(found)
                break
            fresh = materialise(claimed.unionByName(found), "voronoi-claims")
            drop_table(claimed)
            drop_table(found)
            claimed = fresh
        small = claimed.groupBy("block").count().where(F.col("count") <= most).select("block")
        kept = claimed.join(small, "block", "left_semi").select("id", "block")
        covered = materialise(kept if covered is None else covered.union(kept), "voronoi")
        rest = materialise(open_.join(covered, "id", "left_anti"), "voronoi-open")
        drop_table(claimed)
        drop_table(open_)
        open_ = rest
        if open_.isEmpty():
            return covered
        rate = min(1.0, rate * growth)
    part = und.join(open_.toDF("src"), "src", "left_semi").join(open_.toDF("dst"), "dst", "left_semi")
    comp = contract_components(part)
    alone = open_.join(comp.select("id"), "id", "left_anti").select("id", F.col("id").alias("block"))
    return covered.union(comp.select("id", F.col("component").alias("block"))).union(alone)


def blocks_connected(g: Graph, blocks: DataFrame) -> DataFrame:
    """The connected pieces of ``blocks(id, block)``: vertices of one block that reach each other inside it."""
    b = blocks.select("id", "block")
    inner = g.edges.select("src", "dst").join(b.toDF("src", "sb"), "src").join(b.toDF("dst", "db"), "dst").where("sb = db and src <> dst")
    pieces = contract_components(inner.select("src", "dst"))
    return b.select("id").join(pieces.select("id", F.col("component").alias("block")), "id", "left").select("id", F.coalesce("block", "id").alias("block"))


def blocks_2d(coords: DataFrame, nx: int, ny: int) -> DataFrame:
    """Cells of an nx by ny grid over ``coords(id, x, y)``: equal widths between the least and the greatest coordinates."""
    lim = coords.agg(F.min("x").alias("x0"), F.max("x").alias("x1"), F.min("y").alias("y0"), F.max("y").alias("y1"))
    cell = lambda v, a, b, n: F.when(F.col(b) > F.col(a), F.least(F.floor((F.col(v) - F.col(a)) / (F.col(b) - F.col(a)) * n), F.lit(n - 1))).otherwise(0)
    return coords.crossJoin(F.broadcast(lim)).select("id", (cell("x", "x0", "x1", nx) * ny + cell("y", "y0", "y1", ny)).cast("long").alias("block"))  # one row


def blocks_url(urls: DataFrame, depth: int = 1) -> DataFrame:
    """``urls(id, url)`` by host and the first ``depth`` path parts; the block is the least id of the prefix."""
    host = F.regexp_extract("url", "://([^/?#]*)", 1)
    path = F.regexp_extract("url", "://[^/?#]*([^?#]*)", 1)
    prefix = F.concat_ws("/", host, F.array_join(F.slice(F.split(path, "/"), 2, depth), "/"))
    keyed = urls.select("id", prefix.alias("prefix"))
    return keyed.join(keyed.groupBy("prefix").agg(F.min("id").alias("block")), "prefix").select("id", "block")


def partition_mincut(g: Graph, k: int, balance: float = 1.1, passes: int = 5, seed: int = 7) -> DataFrame:
    """k parts by label propagation under a size cap: each pass a vertex may move to the part most of its neighbours are in.

    Movers to a part are admitted by gain, cell after cell of a hash, up to the room under ``balance * n / k``; odd and even
    ids move in turn, so two neighbours do not swap for ever.
    """
    n = g.vertices.count()
    cap = int(balance * n / k) + 1
    und = materialise(g.undirect().edges.select("src", "dst").where("src <> dst"), "mincut-edges")
    lab = materialise(g.vertices.select("id", F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(k)).alias("block")), "mincut")
    for number in range(passes):
        votes = und.join(lab.toDF("src", "b"), "src").groupBy(F.col("dst").alias("id"), "b").agg(F.count("*").alias("v"))
        best = votes.groupBy("id").agg(F.max_by("b", F.struct("v", -F.col("b"))).alias("b"), F.max("v").alias("v"))
        here = votes.join(lab, "id").where("b = block").select("id", F.col("v").alias("stay"))
        wish = lab.join(best, "id").join(here, "id", "left").where("b <> block and v > coalesce(stay, 0)").where(F.pmod("id", F.lit(2)) == number % 2)
        wish = materialise(wish.select("id", "b", F.least(F.col("v") - F.coalesce("stay", F.lit(0)), F.lit(GAINS)).alias("gain"), F.pmod(F.xxhash64("id"), F.lit(CELLS)).alias("cell")), "mincut-wish")
        sizes = lab.groupBy(F.col("block").alias("b")).agg(F.count("*").alias("size"))  # k rows
        # room is given to cells of equal gain, highest gain first: k * GAINS * CELLS counts at most, and no movers are sorted
        counts = wish.groupBy("b", "gain", "cell").agg(F.count("*").alias("n"))
        before = F.sum("n").over(Window.partitionBy("b").orderBy(F.desc("gain"), "cell"))
        open_ = counts.withColumn("upto", before).join(F.broadcast(sizes), "b").where(F.col("upto") <= F.lit(cap) - F.col("size")).select("b", "gain", "cell")
        admitted = wish.join(F.broadcast(open_), ["b", "gain", "cell"], "left_semi").select("id", F.col("b").alias("to"))
        fresh = materialise(lab.join(admitted, "id", "left").select("id", F.coalesce("to", "block").alias("block")), "mincut")
        drop_table(lab)
        drop_table(wish)
        lab = fresh
    drop_table(und)
    return lab
