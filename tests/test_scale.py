"""Hubs, long diameters, checkpoints and the forms that save work."""

import pytest
from pyspark.sql import functions as F

from bspframe import builders as B
from bspframe.algos.pagerank import pagerank, pagerank_approx, pagerank_block
from bspframe.algos.sssp import diameter, khop, sssp
from bspframe.algos.wcc import wcc
from bspframe.engines.dealing import deal, hub_ids
from bspframe.engines.program import message_edges, pagerank_program, wcc_program
from bspframe.graph import Graph
from bspframe.loop import Interval, Truncate


def star_and_ring(spark, leaves=4000, ring=400):
    """Vertex 0 points to all leaves; a ring beside it."""
    out = spark.range(1, leaves + 1).selectExpr("0L as src", "id as dst")
    more = spark.range(ring).selectExpr(f"id + {leaves + 1} as src", f"(id + 1) % {ring} + {leaves + 1} as dst")
    return Graph.from_edges(out.union(more), name="star")


def rows_by_task(df):
    return sorted(r[1] for r in df.groupBy(F.spark_partition_id()).count().collect())


def test_a_hubs_edges_are_spread(spark):
    g = star_and_ring(spark)
    hubs = hub_ids(g.edges, "src", 8, least=100)
    assert hubs == [0]
    dealt = deal(message_edges(g, pagerank_program(k=1), hubs), "src", 8, hubs)
    rows = rows_by_task(dealt.heavy)
    assert len(rows) == 8 and rows[-1] < 1.5 * rows[len(rows) // 2]
    assert dealt.light.count() == 400
    dealt.unpersist()


@pytest.mark.parametrize("engine", ["vertex", "gas", "mr", "mr-loop", "dataflow"])
def test_engines_agree_on_a_graph_with_a_hub(spark, engine, monkeypatch):
    from bspframe.engines import dealing, mapreduce

    g = star_and_ring(spark, 500, 50)
    want = {i: round(v, 9) for i, v in pagerank(g, max_rounds=4, engine="single").df.collect()}
    monkeypatch.setattr(dealing, "LEAST", 50)
    monkeypatch.setattr(mapreduce, "LIST", 64)
    assert {i: round(v, 9) for i, v in pagerank(g, max_rounds=4, engine=engine).df.collect()} == want
    got = {r["id"]: r["dist"] for r in sssp(g, 0, engine=engine).df.collect()}
    assert got == {0: 0} | dict.fromkeys(range(1, 501), 1)


def test_components_come_from_hooking_alone(spark, sf):
    for name in ("co_purchase", "session_chains", "page_links", "geo_hub"):
        r = wcc(B.GRAPHS[name](spark, sf))
        assert r.stats and all("serial" not in t and t["jumps"] >= 1 for t in r.stats), name


def test_contraction_of_paths_rings_and_joins(spark):
    e = [(0, 1), (1, 2), (2, 3), (3, 4), (0, 5), (5, 4), (4, 6), (20, 21), (21, 20), (6, 2), (7, 0), (9, 9)]
    g = Graph.from_edges(spark.createDataFrame(e, "src long, dst long"))
    for method in ("contract", "auto", "top_down"):
        assert {r["id"]: r["dist"] for r in sssp(g, 0, method=method).df.collect()} == {0: 0, 1: 1, 2: 2, 3: 3, 4: 2, 5: 1, 6: 3}, method
    assert {r["id"]: r["dist"] for r in sssp(g, 20, method="contract").df.collect()} == {20: 0, 21: 1}
    assert [tuple(r) for r in sssp(g, 99, method="contract").df.collect()] == [(99, 0)]
    path = Graph.from_edges(spark.range(300).selectExpr("id as src", "id + 1 as dst"))
    r = sssp(path, 0, method="contract")
    assert {x["id"]: x["dist"] for x in r.df.collect()} == {i: i for i in range(301)} and r.rounds < 15


def test_a_source_outside_the_graph_is_its_own_answer(spark):
    g = Graph.from_edges(spark.createDataFrame([(1, 2)], "src long, dst long"))
    for engine in ("frontier", "vertex", "sql"):
        assert [tuple(r) for r in sssp(g, 0, engine=engine).df.collect()] == [(0, 0)]
        assert [tuple(r) for r in khop(g, 0, 2, engine=engine).df.collect()] == [(0, 0)]


def test_sampled_diameter(spark):
    g = Graph.from_edges(spark.range(9).selectExpr("id as src", "id + 1 as dst"))
    r = diameter(g, spark.createDataFrame([(0,)], "id long")).first()
    assert (r["sources"], r["pairs"], r["longest"], r["effective"]) == (1, 9, 9, 9) and abs(r["effective_smooth"] - 8.1) < 1e-9
    assert diameter(g, samples=10).first()["longest"] == 9


def test_block_starts_differ_and_end_alike(spark):
    e = [(0, 1), (1, 2), (2, 0), (2, 3), (3, 4), (4, 5), (5, 3), (0, 4), (1, 0), (0, 2), (3, 1), (5, 6), (6, 7), (7, 8), (8, 6), (0, 7)]
    g = Graph.from_edges(spark.createDataFrame(e, "src long, dst long"))
    blocks = spark.createDataFrame([(i, i // 3) for i in range(9)], "id long, block long")
    exact = {i: v for i, v in pagerank(g, tol=1e-10).df.collect()}
    starts = {}
    for fn in ("product", "block", "vertex", "degree"):
        once = pagerank_block(g, blocks, init_fn=fn, step_rounds=(3, 3, 1))
        starts[fn] = tuple(round(v, 9) for _, v in sorted(once.df.collect()))
        got = {i: v for i, v in pagerank_block(g, blocks, init_fn=fn, tol=1e-10).df.collect()}
        assert all(abs(got[i] - exact[i]) < 1e-7 for i in exact), fn
    assert len(set(starts.values())) == 4
    by_rounds = pagerank_block(g, blocks, step_rounds=(3, 3, 1), local="rounds")
    assert tuple(round(v, 9) for _, v in sorted(by_rounds.df.collect())) == starts["product"]


def test_long_runs_do_not_plan_longer(spark, sf):
    """Sizes that checkpoints inherit would make the 25th round take minutes to plan."""
    r = pagerank_approx(B.session_chains(spark, sf), 0.0, reactivate=True, max_rounds=25)
    assert r.rounds == 25 and max(s.seconds for s in r.stats[15:]) < 10


def test_interval_settles_by_measured_costs():
    for cost, growth, want in ((0.0, 0.1, 1), (10.0, 0.2, 10)):
        iv = Interval(Truncate.auto())
        for _ in range(12):
            whole = iv.due()
            iv.took(whole, 1.0 + (cost if whole else growth * iv.since))
        assert not iv.probing and iv.every == want
    assert [Interval(Truncate(3)).due() for _ in range(1)] == [False]


def test_copies_are_disjoint(spark):
    g = Graph.from_edges(spark.createDataFrame([(0, 1), (1, 2)], "src long, dst long")).copies(3)
    assert wcc(g).df.select("component").distinct().count() == 3 and g.edges.count() == 6


def test_a_shared_folder_is_required_off_local_masters(spark, monkeypatch):
    from bspframe import session

    class Fake:
        class sparkContext:
            master = "spark://host:7077"
            getConf = staticmethod(lambda: type("C", (), {"get": staticmethod(lambda *_: None)}))

        class conf:
            get = staticmethod(lambda *_: None)

    with pytest.raises(RuntimeError):
        session.shared_dir(Fake)


def test_rdd_parts_are_bounded_and_edges_stay(spark, monkeypatch):
    """Parts of the RDD engine grow in number with the edges; a round's messages come to the edges, which never move."""
    from bspframe.engines import rdd

    monkeypatch.setattr(rdd, "PART_EDGES", 100)
    g = star_and_ring(spark, leaves=300, ring=50)
    for cut in ("vertex", "edge"):
        r = rdd.run_rdd(g, wcc_program(), cut=cut)
        assert r.df.rdd.getNumPartitions() == 7  # 700 edges in both directions
        assert {c for _, c in r.df.collect()} == {0, 301}
    parts = spark.sparkContext.parallelize([(k, k) for k in range(4)], 2).partitionBy(4).mapPartitions(list, preservesPartitioning=True)
    met = rdd._together(parts, spark.sparkContext.parallelize([(3, "a"), (3, "b")], 2), 4)
    assert met.getNumPartitions() == 4 and met.partitioner == parts.partitioner
    assert dict(met.collect())[3] == (3, ["a", "b"])


def test_rdd_engine_sums_parallel_edges_and_leaves_the_unreached_null(spark):
    g = Graph.from_edges(spark.createDataFrame([(-5, 7), (-5, 7), (7, 7), (7, -9), (4, 4)], "src long, dst long"))
    for cut in ("vertex", "edge"):
        got = dict(sssp(g, -5, engine="rdd", cut=cut).df.collect())
        assert {k: v for k, v in got.items() if v is not None} == {-5: 0, 7: 1, -9: 2}
        ranks = dict(pagerank(g, engine="rdd", cut=cut, max_rounds=3).df.collect())
        want = dict(pagerank(g, engine="vertex", max_rounds=3).df.collect())
        assert ranks.keys() == want.keys() and all(abs(ranks[k] - want[k]) < 1e-9 for k in want)


@pytest.mark.parametrize("frontier", ["temp", "filter"])
def test_views_in_memory_do_not_carry_the_plans_of_all_rounds(spark, frontier):
    g = Graph.from_edges(spark.range(6).selectExpr("id as src", "id + 1 as dst"))
    r = wcc(g, engine="sql", update="memory", frontier=frontier)
    assert r.rounds > 5 and {x["id"]: x["component"] for x in r.df.collect()} == dict.fromkeys(range(7), 0)
    assert len(r.df._jdf.queryExecution().analyzed().toString().splitlines()) < 10
    assert not [t.name for t in spark.catalog.listTables() if t.name.startswith(("active_", "change_", "vertex_"))]


def test_a_matrix_builds_each_graph_once(spark, sf, monkeypatch):
    from bspframe import harness

    built = []
    monkeypatch.setitem(B.GRAPHS, "handoff", lambda s, d: built.append(d) or B.handoff(s, d))
    rows = harness.matrix(spark, sf, ("handoff",), ("khop", "wcc"), ("vertex", "sql", "single")).collect()
    assert built == [sf] and len(rows) == 6 and {r["outcome"] for r in rows} == {"OK"}
    assert {r["edges"] for r in rows} == {B.handoff(spark, sf).edges.count()}


def test_a_loop_keeps_the_files_of_its_last_checkpoint_only(spark):
    import os

    from bspframe.session import shared_dir

    folder = spark.sparkContext._jsc.sc().getCheckpointDir().get() if shared_dir(spark) else None
    folder = folder.removeprefix("file:")
    count = lambda: len([x for x in os.listdir(folder) if x.startswith("rdd-")]) if os.path.isdir(folder) else 0
    g = Graph.from_edges(spark.range(6).selectExpr("id as src", "id + 1 as dst"))
    before = count()
    r = pagerank(g, max_rounds=5, truncate=Truncate())
    assert r.rounds == 5 and count() == before + 1
    assert r.df.count() == 7


def test_approximate_ranks_do_not_move_edges(spark, monkeypatch):
    from bspframe.algos import pagerank as module

    g = star_and_ring(spark, 40, 10)
    keys, real = [], module.deal
    monkeypatch.setattr(module, "deal", lambda e, key, *a: keys.append(key) or real(e, key, *a))
    for few in (0, 100_000):
        monkeypatch.setattr(module, "FEW", few)
        for wake in (False, True):
            got = {x["id"]: x["rank"] for x in pagerank_approx(g, 1e-9, reactivate=wake).df.collect()}
            want = {x["id"]: x["rank"] for x in pagerank(g, tol=1e-9).df.collect()}
            assert got.keys() == want.keys() and max(abs(got[i] - want[i]) for i in want) < 1e-6
    assert keys == ["src"] * 4  # they lie by source once, whatever a round reads


def test_slow_rounds_are_all_checkpointed():
    i = Interval(Truncate.auto())
    for _ in range(3):  # two checkpointed rounds, then a persisted one
        i.took(i.due(), Interval.SLOW + (8 if len(i.full) < 2 else 1))
    assert not i.probing and i.due() and i.every == 1


def test_a_failed_run_is_not_a_result(spark, sf, monkeypatch):
    from bspframe import harness
    from bspframe.measures.runs import Outcome
    from bspframe.queries import QUERIES

    def fails(name, g, engine, **how):
        raise MemoryError("planted")

    monkeypatch.setattr(harness, "workload", fails)
    for query in ("engine_resources", "cost", "ablation_combiner"):
        with pytest.raises(MemoryError):
            QUERIES[query](spark, sf)
    row = harness.matrix(spark, sf, ("handoff",), ("khop",), ("vertex",)).first()
    assert row["outcome"] == "OOM" and row["edges"] is row["total"] is row["load"] is row["peak_memory"] is None
    planted = RuntimeError("Job aborted: ZeroDivisionError\n\tat org.apache.spark.scheduler.ShuffleMapTask.runTask(ShuffleMapTask.scala:104)")
    with pytest.raises(RuntimeError):
        Outcome.classify(planted, 1)
    for text in ("Missing an output location for shuffle 3", "cannot read shuffle block", "FetchFailed(null, shuffleId=1)"):
        assert Outcome.classify(RuntimeError(text), 1) == "SHFL"


def test_matrices_run_every_family_for_all_rounds(spark, sf, monkeypatch):
    from bspframe import harness
    from bspframe.queries import QUERIES, ROUNDS

    for graph in ("social", "web", "road"):
        cells = []
        monkeypatch.setattr(harness, "run_one", lambda s, d, g, w, e, **how: cells.append((g, w, e, how.get("rounds"))) or {"graph": g})
        QUERIES[f"matrix_{graph}"](spark, sf)
        engines = {"vertex", "gas", "block", "mr-loop", "rdd", "sql", "dataflow", "single"}
        assert set(cells) == {(graph, w, e, ROUNDS) for w in harness.WORKLOADS for e in engines} - {(graph, "pagerank", "block", ROUNDS)}


def test_a_small_graph_is_not_dealt_to_all_parts(spark):
    from bspframe.engines import rdd

    g = Graph.from_edges(spark.range(700).selectExpr("id as src", "(id + 1) % 700 as dst"))
    assert int(spark.conf.get("spark.sql.shuffle.partitions")) > 1
    r = rdd.run_rdd(g, pagerank_program(k=2))
    assert r.df.rdd.getNumPartitions() == 1 and {round(x["value"], 9) for x in r.df.collect()} == {1.0}
    assert rdd.parts_of(120_000, 12) == 3 and rdd.parts_of(10**6, 12) == 12 and rdd.parts_of(10**8, 12) == 100


def test_a_search_from_many_sources_leaves_no_files(spark):
    import os

    from bspframe.algos.sssp import pair_counts
    from bspframe.session import shared_dir

    top = shared_dir(spark).removeprefix("file://")
    kept = lambda: sorted(f for at, _, names in os.walk(top) for f in names if "code-" not in at)
    g = Graph.from_edges(spark.range(6).selectExpr("id as src", "id + 1 as dst"))
    before = kept()
    assert [x.changed for x in pair_counts(g, spark.range(2))] == [2, 2, 2, 2, 2, 1]
    assert kept() == before
    assert not [t.name for t in spark.catalog.listTables() if t.name.startswith("dealt_")]
