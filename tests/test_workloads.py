"""Every engine against hand graphs with known answers, and invariants."""

import pytest
from pyspark.sql import functions as F

from bspframe import builders as B
from bspframe.algos.pagerank import pagerank, pagerank_approx, pagerank_block, top_ranked
from bspframe.algos.sssp import khop, khop_many, pick_source, sssp
from bspframe.algos.wcc import wcc
from bspframe.graph import Graph
from tests.helpers import HAND, hand

RANK_ENGINES = ["vertex", "gas", "gas-async", "gas-async-local", "mr", "mr-loop", "rdd", "sql", "dataflow", "single"]
MIN_ENGINES = [*RANK_ENGINES, "block"]


def ranks(r):
    return {i: v for i, v in r.df.collect()}


@pytest.mark.parametrize("name", list(HAND))
def test_hand_graphs_vertex(spark, name):
    _, _, rank, comp, dist = HAND[name]
    g = hand(spark, name)
    got = ranks(pagerank(g, tol=1e-9, max_rounds=200))
    assert got.keys() == rank.keys() and all(abs(got[i] - rank[i]) < 1e-5 for i in rank)
    for method in ("hook_jump", "min_label", "star", "hash_to_min"):
        assert {i: c for i, c in wcc(g, method=method).df.collect()} == comp, method
    assert {r["id"]: r["dist"] for r in sssp(g, 0).df.collect()} == dist


@pytest.mark.parametrize("engine", RANK_ENGINES)
def test_rank_engines(spark, engine):
    g = hand(spark, "self_loop")
    how = {"max_rounds": 25} if engine != "gas-async-local" else {"tol": 1e-6}
    if engine == "gas-async":
        how = {"tol": 1e-6}
    got = ranks(pagerank(g, engine=engine, **how))
    assert all(abs(v - 0.260870) < 1e-5 for v in got.values()) and len(got) == 2


@pytest.mark.parametrize("engine", MIN_ENGINES)
def test_min_engines(spark, engine):
    g = hand(spark, "against")
    assert {i: c for i, c in wcc(g, engine=engine, method="min_label" if engine != "block" else "block").df.collect()} == HAND["against"][3]
    g = hand(spark, "two_triangles")
    assert {r["id"]: r["dist"] for r in sssp(g, 0, engine=engine).df.collect()} == {0: 0, 1: 1, 2: 2}
    assert {r["id"]: r["dist"] for r in khop(g, 0, 1, engine=engine).df.collect()} == {0: 0, 1: 1}


def test_negative_controls(spark):
    g = hand(spark, "fork")
    assert {i: c for i, c in wcc(g, directed=True).df.collect()} == {0: 0, 1: 1, 2: 2}
    got = ranks(pagerank(hand(spark, "self_loop"), tol=1e-9, max_rounds=50, self_edges="drop"))
    assert abs(got[1] - 0.2775) < 1e-6


def test_rank_invariants(spark, sf):
    g = B.co_purchase(spark, sf)
    r = pagerank(g, max_rounds=40)
    n = g.vertices.count()
    kept = r.df.join(g.sinks(), "id", "left_anti").agg(F.sum("rank")).first()[0]
    total, least = r.df.agg(F.sum("rank"), F.min("rank")).first()
    assert abs(total - (0.15 * n + 0.85 * kept)) < 1e-6 * n and least >= 0.15 - 1e-12
    assert [x.round for x in r.stats] == list(range(1, 41))
    assert top_ranked(r.df, 3).count() == 3


def test_approximate_forms(spark, sf):
    g = B.co_purchase(spark, sf)
    exact = ranks(pagerank(g, tol=1e-10, engine="single"))
    for wake, bound in ((False, 0.05), (True, 0.01)):
        r = pagerank_approx(g, 1e-4, reactivate=wake)
        got = ranks(r)
        assert max(abs(got[i] - exact[i]) for i in exact) < bound
        assert r.stats[0].changed == len(exact) and r.stats[-1].changed <= len(exact)


def test_block_pagerank_is_close(spark):
    g = hand(spark, "two_triangles")
    blocks = spark.createDataFrame([(i, i // 3) for i in range(6)], "id long, block long")
    r = pagerank_block(g, blocks, tol=1e-9)
    assert all(abs(v - 1) < 1e-6 for v in ranks(r).values()) and [p for p, _ in r.stats] == ["local", "blocks", "whole"]
    for fn in ("block", "vertex", "degree"):
        assert all(abs(v - 1) < 1e-6 for v in ranks(pagerank_block(g, blocks, init_fn=fn, tol=1e-9)).values())


def test_distance_invariants(spark, sf):
    g = B.handoff(spark, sf)
    full = sssp(g, 0, with_parent=True).df.persist()
    d = full.select("id", "dist")
    bad = g.edges.join(d.toDF("src", "a"), "src").join(d.toDF("dst", "b"), "dst", "left").where("b is null or b > a + 1")
    assert bad.count() == 0
    assert full.where("dist > 0 and parent is null").count() == 0
    near = khop(g, 0, 1).df
    assert near.exceptAll(d.where("dist <= 1")).count() == 0
    many = khop_many(g, spark.createDataFrame([(0,), (1,)], "id long"), 1).df
    assert many.where("source = 0").select("id", "dist").exceptAll(near).count() == 0
    assert pick_source(g, 3) == pick_source(g, 3)
    assert sssp(g, 0, include_unreached=True).df.count() == g.vertices.count()


def test_weighted_paths(spark):
    e = spark.createDataFrame([(0, 1, 5.0), (0, 2, 1.0), (2, 1, 1.5)], "src long, dst long, w double")
    assert {r["id"]: r["dist"] for r in sssp(Graph.from_edges(e), 0, weight=True).df.collect()} == {0: 0.0, 1: 2.5, 2: 1.0}


def test_contraction_without_the_serial_end(spark, sf):
    from bspframe.algos.contract import contract_components

    g, trace = B.order_ladder(spark, sf), []
    assert {r[1] for r in contract_components(g.edges, trace=trace).collect()} == {g.vertices.agg(F.min("id")).first()[0]}
    assert 1 < len(trace) < 20 and not any("serial" in t for t in trace)
    ends = contract_components(g.edges, trace=(t := []), finish_below=800)
    assert ends.select("component").distinct().count() == 1 and t[-1]["serial"] <= 800


def test_empty_graph(spark):
    g = Graph.from_edges(spark.createDataFrame([], "src long, dst long"))
    assert pagerank(g, max_rounds=2).df.count() == 0 and wcc(g).df.count() == 0
    assert [tuple(r) for r in sssp(g, 0).df.collect()] == [(0, 0)]


def test_nulls_and_extra_columns(spark):
    e = spark.createDataFrame([(0, 1, "x"), (None, 1, "y"), (1, None, None)], "src long, dst long, id string")
    assert Graph.from_edges(e).validate().edges.collect()[0].asDict() == {"src": 0, "dst": 1}


def _tables_read(monkeypatch):
    """Names of the given tables that a query reads through Spark, as they are read."""
    from bspframe import builders, queries

    names, real = [], queries.read_table
    seen = lambda s, d, t: (names.append(t), real(s, d, t))[1]
    monkeypatch.setattr(queries, "read_table", seen)
    monkeypatch.setattr(builders, "read_table", seen)
    return names


def test_partition_rule_reads_tables(spark, sf, monkeypatch):
    from bspframe import queries

    names = _tables_read(monkeypatch)
    rows = queries.QUERIES["partition_rule"](spark, sf).collect()
    assert len(rows) == 12 and set(names) == {"lineitem", "events", "pages"}


def test_report_cube_reads_tables(spark, sf, monkeypatch):
    from bspframe import queries

    names = _tables_read(monkeypatch)
    rows = queries.QUERIES["report_cube"](spark, sf).where("level = 7").collect()
    assert names == ["lineitem"] and [r["runs"] for r in rows] == [spark.read.parquet(f"{sf}/lineitem.parquet").count()]


@pytest.mark.parametrize("name,rows", [("scaling_strong", 3), ("scaling_weak", 3), ("cores_reserved", 4)])
def test_scaling_runs_in_the_session(spark, sf, monkeypatch, name, rows):
    """The session at hand reads the tables and runs the rounds; no other process does."""
    import subprocess

    from bspframe import queries

    monkeypatch.setattr(subprocess, "run", lambda *a, **k: (_ for _ in ()).throw(AssertionError("another process")))
    names, was = _tables_read(monkeypatch), spark.conf.get("spark.sql.shuffle.partitions")
    got = queries.QUERIES[name](spark, sf).collect()
    assert len(got) == rows and all(r["seconds"] > 0 for r in got) and {"orders", "lineitem"} <= set(names)
    assert spark.conf.get("spark.sql.shuffle.partitions") == was


def test_weak_scaling_builds_its_graph_once(spark, sf, monkeypatch):
    from bspframe import queries

    names = _tables_read(monkeypatch)
    assert queries.QUERIES["scaling_weak"](spark, sf).count() == 3 and names.count("lineitem") == 1
