"""Partitioners, formats, measures, loop, streams."""

import pytest
from pyspark.sql import functions as F

from bspframe import builders as B
from bspframe.algos.pagerank import pagerank
from bspframe.algos.wcc import wcc
from bspframe.functions.ids import encode_ids, id_table
from bspframe.functions.tables import register_pagerank, register_sql
from bspframe.graph import Graph
from bspframe.measures import quality
from bspframe.measures.runs import Outcome, Recorder, Sampler, run_limited
from bspframe.operators.temporal import asof_edges, interval_edges
from bspframe.partitioners import blocks as bl
from bspframe.partitioners import cuts
from bspframe.plans import planner
from bspframe.session import table_path
from bspframe.sources import edges as src
from tests.helpers import hand


@pytest.mark.parametrize("q", [2, 3, 5, 7])
def test_perfect_difference_sets(q):
    s, p = cuts.perfect_difference_set(q), q * q + q + 1
    assert len(s) == q + 1 and sorted((a - b) % p for a in s for b in s if a != b) == list(range(1, p))
    shifts = cuts.pds_candidates(p)
    assert all(len(set(shifts[a]) & set(shifts[b])) == 1 for a in range(p) for b in range(a))


def test_auto_choice_and_impossible_counts():
    assert [cuts.auto_choice(p) for p in (7, 16, 32, 64, 128)] == ["pds", "grid", "greedy", "grid", "greedy"]
    assert [cuts.grid_shape(p) for p in (6, 8, 9)] == [(2, 3), (2, 4), (3, 3)]
    for bad in (lambda: cuts.grid_shape(32), lambda: cuts.pds_order(16)):
        with pytest.raises(ValueError):
            bad()


def test_greedy_rules():
    g = cuts.Greedy(4)
    assert g.place(0, 1) == 0  # nobody placed: least loaded of all
    assert g.place(0, 2) == 0  # one end placed: where it is
    assert g.place(3, 4) == 1  # nobody placed again
    assert g.place(0, 3) == 1  # placed apart: least loaded of either
    assert g.place(0, 3) == 1  # in common


def test_cuts_keep_edges(spark, sf):
    g = B.handoff(spark, sf)
    n = g.edges.count()
    for how, p in (("random", 8), ("grid", 9), ("pds", 7), ("greedy", 8)):
        parted = cuts.vertex_cut(g, p, how)
        row = quality.replication_factor(parted).first()
        assert parted.count() == n and 1 <= row["replication_factor"] <= p and parted.where(f"part < 0 or part >= {p}").count() == 0


def test_blocks(spark, sf):
    g = B.session_chains(spark, sf)
    b = bl.blocks_voronoi(g, rate=0.05, max_rounds=4)
    assert b.count() == g.vertices.count() == b.select("id").distinct().count()
    inner = g.edges.join(b.toDF("src", "x"), "src").join(b.toDF("dst", "y"), "dst").where("x = y").select("src", "dst")
    comps = wcc(Graph(inner, extra=b.select("id"))).df.join(b, "id")
    assert comps.groupBy("block").agg(F.countDistinct("component").alias("n")).where("n > 1").count() == 0  # connected
    m = bl.partition_mincut(g, 3, balance=1.2)
    sizes = [r["count"] for r in m.groupBy("block").count().collect()]
    assert m.count() == g.vertices.count() and max(sizes) <= 1.2 * g.vertices.count() / 3 + 2 + 60
    w = g.contract(m).agg(F.sum("w")).first()[0] or 0
    st = quality.block_stats(g, m).first()
    assert st["cut_edges"] == w and st["edges"] == g.edges.count()


def test_partition_rule():
    assert planner.choose_partitions(440 * 64 * planner.MB, 64) == 128 and planner.choose_partitions(240 * 64 * planner.MB, 512) == 240
    assert planner.choose_partitions(0, 8, floor=True) == 8


@pytest.mark.parametrize("form", ["edge", "adj", "adj_long"])
def test_text_formats(spark, form):
    g = hand(spark, "against")
    path = table_path(spark, f"text-{form}")
    src.save(g, path, form)
    back = {"edge": src.read_edges, "adj": src.read_adj, "adj_long": src.read_adj_long}[form](spark, path)
    assert sorted(map(tuple, back.edges.collect())) == [(1, 0), (2, 1)]
    want = {0, 1, 2, 9} if form == "adj_long" else {0, 1, 2}
    assert {r["id"] for r in back.vertices.collect()} == want


def test_adjacency_count_is_checked(spark, tmp_path):
    (tmp_path / "a.txt").write_text("1 2 5\n")
    with pytest.raises(Exception, match="neighbour count"):
        src.read_adj_long(spark, str(tmp_path / "a.txt")).edges.collect()


def test_chunks_and_buckets(spark, sf, tmp_path):
    g = B.handoff(spark, sf)
    n = src.write_chunks(g.edges, str(tmp_path / "c"), chunk_bytes=1024)
    assert spark.read.parquet(str(tmp_path / "c")).count() == g.edges.count() and n > 1


def test_one_exchange_a_round(spark, sf):
    """Pinned edges and state: only the combined messages are exchanged."""
    from bspframe.engines.program import first_state, message_edges, pagerank_program
    from bspframe.loop import Adaptive, pin

    p, g = pagerank_program(k=2), B.handoff(spark, sf)
    with Adaptive(spark):
        edges = pin(message_edges(g, p), "src")
        state = pin(first_state(g, p), "id").checkpoint(eager=True)
        sent = edges.join(state.select(F.col("id").alias("src"), "value"), "src").select(F.col("dst").alias("id"), F.expr(p.send).alias("m"))
        new = state.select("id", F.col("value").alias("old")).join(sent.groupBy("id").agg(F.sum("m").alias("msg")), "id", "left")
        plan = new._jdf.queryExecution().executedPlan().toString()
        top = plan.split("InMemoryTableScan")[0] if "InMemoryTableScan" not in plan else "\n".join(x for x in plan.splitlines() if not x.startswith("            "))
        assert top.count("Exchange hashpartitioning(id") == 1 and "Exchange hashpartitioning(src" not in top.split("InMemoryRelation")[0]
        edges.unpersist()


def test_resume(spark, sf, tmp_path):
    g = B.handoff(spark, sf)
    whole = pagerank(g, max_rounds=6).df
    pagerank(g, max_rounds=3, save_to=str(tmp_path / "s"))
    rest = pagerank(g, max_rounds=6, resume_from=str(tmp_path / "s"))
    a, b = ({r[0]: round(r[1], 9) for r in x.collect()} for x in (whole, rest.df))
    assert a == b and rest.stats[0].round == 4


def test_aqe_is_restored(spark, sf):
    was = spark.conf.get("spark.sql.adaptive.enabled")
    pagerank(B.handoff(spark, sf), max_rounds=1)
    assert spark.conf.get("spark.sql.adaptive.enabled") == was


def test_recorder_and_outcomes(spark):
    r = Recorder()
    with r.phase("load"), Sampler(0.05) as s:
        spark.range(100_000).selectExpr("sum(id)").collect()
    with r.phase("execute"):
        pass
    r.finish()
    assert abs(sum(r.phases.values()) + r.overhead - r.total) < 1e-9 and s.peak_memory > 0
    assert Outcome.classify(MemoryError(), 1) == "OOM" and Outcome.classify(None, 99, 10) == "TO" and Outcome.classify(None, 1) == "OK"
    assert Outcome.classify(RuntimeError("FetchFailed"), 1) == "SHFL" and Outcome.classify(RuntimeError("RpcTimeout"), 1) == "MSG"
    assert run_limited(spark, lambda: spark.range(1 << 40).selectExpr("sum(hash(id))").collect(), 0.5)[0] == "TO"
    assert quality.cost_factor(10, 4) == 2.5 and quality.cost_factor(10, 4, inverse=True) == 0.4 and quality.round_budget(86_400, 36_000) == 2.4


def test_rank_error(spark):
    a = spark.createDataFrame([(1, 1.0), (2, 2.0)], "id long, rank double")
    e = spark.createDataFrame([(1, 1.0), (2, 2.5), (3, 0.5)], "id long, rank double")
    row = quality.rank_error(a, e, 2).first()
    assert (row["l1"], row["linf"], row["top_overlap"]) == (1.0, 0.5, 2)
    assert quality.answers_agree(a, a) == 0 and quality.answers_agree(a, e) == 3


def test_ids(spark):
    df = spark.createDataFrame([("b",), ("a",), (None,), ("b",)], "k string")
    assert {(r["k"], r["k_id"]) for r in encode_ids(df, ["k"]).collect()} == {("a", 0), ("b", 1), (None, None)}
    assert id_table(df, ["k"], "hash").count() == 2


def test_temporal(spark):
    ev = spark.createDataFrame([(1, 1, 0), (2, 1, 5), (3, 1, 5), (4, 1, 30), (5, 2, 6), (6, None, 6)], "i long, k int, s long").withColumn("ts", F.timestamp_seconds("s"))
    assert sorted(map(tuple, interval_edges(ev, "k", "ts", "i", 10).collect())) == [(1, 2), (1, 3), (2, 3)]
    left, right = ev.where("i in (4, 5)"), ev.where("i in (1, 2, 3)")
    assert [tuple(r) for r in asof_edges(left, right, "k", "ts", "i").collect()] == [(4, 3)]


def _knn_brute(rows, k):
    from decimal import ROUND_HALF_UP, Decimal

    def near(x, y):
        if x is None or y is None or len(x) != len(y) or None in x or None in y:
            return -9
        dot = lambda p, q: sum((i * j for i, j in zip(p, q)), 0.0)
        a, b = dot(x, x) ** 0.5, dot(y, y) ** 0.5
        return Decimal(repr(dot(x, y) / a / b)).quantize(Decimal("1e-9"), ROUND_HALF_UP) if a and b else -9

    out = []
    for i, x in rows:
        best = sorted((-near(x, y), j) for j, y in rows if i is not None and j is not None and j != i)[:k]
        out += [(i, j, n + 1) for n, (_, j) in enumerate(best)] if i is not None else []
    return sorted(out)


def test_knn_in_blocks(spark, monkeypatch):
    """Ties, copies, null and zero vectors, other widths, a null id; more blocks than one on either side."""
    import random

    from bspframe.operators import knn

    rng = random.Random(5)
    rows = [(i, [rng.gauss(0, 1) for _ in range(6)]) for i in range(90)] + [(i, [float(rng.randrange(-1, 2)) for _ in range(6)]) for i in range(90, 180)]
    rows += [(180, None), (181, [0.0] * 6), (182, [1.0, 2.0]), (183, [2.0, 4.0]), (184, [1.0, None, 1.0, 1.0, 1.0, 1.0]), (185, []), (None, [1.0] * 6)]
    df = spark.createDataFrame(rows, "id long, embedding array<double>")
    for block, queries in ((8192, 256), (40, 7)):
        monkeypatch.setattr(knn, "BLOCK", block)
        monkeypatch.setattr(knn, "QUERIES", queries)
        assert sorted(map(tuple, knn.knn_edges(df, 5).collect())) == _knn_brute(rows, 5)
    assert knn.knn_edges(df.limit(0), 5).count() == 0


def test_knn_has_no_row_limit(spark):
    """On the unit circle the nearest two of a point are its neighbours: 8e-9 from it in cosine, the next 3e-8."""
    from bspframe.operators.knn import knn_edges

    n = 50_100
    df = spark.range(n).select("id", F.expr(f"array(cos(2 * pi() * id / {n}), sin(2 * pi() * id / {n}))").alias("embedding"))
    got = knn_edges(df, 2)
    far = F.abs(F.col("src") - F.col("dst"))
    assert got.agg(F.count("*"), F.sum((F.least(far, n - far) > 1).cast("int"))).first() == (2 * n, 0)


def test_sql_functions(spark, sf):
    register_sql(spark)
    assert [tuple(r) for r in spark.sql("SELECT * FROM adjacency_line('7 1 2')").collect()] == [(7, 1), (7, 2)]
    assert spark.sql("SELECT portable_hash(3L)").first()[0] == 3 * 2654435761 % 2**32
    B.handoff(spark, sf).edges.createOrReplaceTempView("e")
    register_pagerank(spark, "e", "r", 2)
    assert spark.table("r").count() == 15


def test_hub_join_and_two_levels(spark, sf):
    g = B.handoff(spark, sf)
    state = g.vertices.withColumn("value", F.lit(1.0))
    hubs = g.degrees().where("out_degree > 14").select("id")
    joined = planner.salted_join(g.edges, state, hubs)
    assert joined.count() == g.edges.count()
    two = planner.two_level_sum(joined.select("dst", "value"), "dst", "value")
    assert quality.answers_agree(two, joined.groupBy("dst").agg(F.sum("value").alias("value"))) == 0


def test_streams(spark, tmp_path):
    from bspframe.streaming.graphs import dedupe_edges, stream_components, to_table

    path = str(tmp_path / "in")
    for n, rows in enumerate([[(5, 6)], [(1, 2), (5, 6)], [(2, 5), (8, 8)]]):
        spark.createDataFrame([(a, b, n) for a, b in rows], "src long, dst long, s long").select("src", "dst", F.timestamp_seconds("s").alias("ts")).coalesce(1).write.mode("append").parquet(path)
    s = src.read_edge_stream(spark, path, files_per_trigger=1)
    t = stream_components(s, str(tmp_path / "st"), str(tmp_path / "cp"))
    assert {i: c for i, c in t.before().collect()} == {1: 1, 2: 1, 5: 1, 6: 1, 8: 8}
    stream_components(src.read_edge_stream(spark, path), str(tmp_path / "st"), str(tmp_path / "cp"))  # nothing new
    assert t.before().count() == 5
    to_table(dedupe_edges(src.read_edge_stream(spark, path)), str(tmp_path / "out"), str(tmp_path / "cp2"))
    assert spark.read.parquet(str(tmp_path / "out")).count() == 4


def test_report(spark):
    from bspframe import report

    svg = report.stacked_bars([{"name": "a", "load": 1, "execute": 2, "save": 0.5, "overhead": 0.1}, {"name": "b", "outcome": "OOM"}], "runs")
    assert svg.count("<rect") >= 8 and "OOM" in svg
    runs = spark.createDataFrame([("a", "g", "w", 1.0), ("b", "g", "w", 2.0)], "engine string, graph string, workload string, total double")
    assert report.matrix(runs, "graph", "engine", "total").first().asDict() == {"graph": "g", "a": 1.0, "b": 2.0}


def test_block_kernel_calls(spark):
    """Two thousand blocks of one vertex cost a bounded number of kernel calls, not one each."""
    from pyspark.sql import functions as F

    from bspframe.engines import block
    from bspframe.engines.program import wcc_program
    from bspframe.graph import Graph

    g = Graph.from_edges(spark.range(2000).select((F.col("id") + 1).alias("src"), F.lit(0).alias("dst")))
    calls, real = spark.sparkContext.accumulator(0), block.pd.concat

    class Counting:
        """pandas as the kernel sees it; each call of the kernel joins its rows and messages once."""

        DataFrame = block.pd.DataFrame

        @staticmethod
        def concat(frames):
            calls.add(1)
            return real(frames)

    was, block.pd = block.pd, Counting
    try:
        r = block.run_block(g, wcc_program(), blocks=g.vertices.select("id", F.col("id").alias("block")))
        assert r.df.count() == 2001 and r.df.where("value <> 0").isEmpty()
    finally:
        block.pd = was
    assert 0 < calls.value <= 3 * r.rounds * block.CALLS * int(spark.conf.get("spark.sql.shuffle.partitions"))


def test_single_components_stream(spark, monkeypatch):
    """The serial kernel gets its edges piece by piece, and the driver none of them."""
    from bspframe.engines import serial
    from bspframe.engines.program import wcc_program
    from bspframe.graph import Graph

    monkeypatch.setattr(serial, "to_arrays", lambda g: (_ for _ in ()).throw(MemoryError("the driver holds the graph")))
    e = [(i, i + 1) for i in range(0, 100)] + [(i, i - 1) for i in range(300, 200, -1)] + [(500, 500)]
    g = Graph.from_edges(spark.createDataFrame(e, "src long, dst long"), extra=spark.createDataFrame([(900,), (3,)], "id long"))
    want = [(i, 0) for i in range(101)] + [(i, 200) for i in range(200, 301)] + [(500, 500), (900, 900)]
    assert sorted(map(tuple, serial.run_single(g, wcc_program()).df.collect())) == want
    import pyarrow as pa

    monkeypatch.setattr(serial, "CHUNK", 7)
    batches = [pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*e[i : i + 3])], ["src", "dst"]) for i in range(0, len(e), 3)]
    got = [x for b in serial._stream_wcc(batches) for x in zip(*b.to_pydict().values())]
    assert sorted(got) == want[:-1]


def test_khop_async_stops_at_k(spark):
    """Asynchronous rounds pass several hops of a chain at once; what lies further than k is not an answer."""
    from bspframe.algos.sssp import khop
    from bspframe.graph import Graph

    g = Graph.from_edges(spark.createDataFrame([(i, i + 1) for i in range(40)], "src long, dst long"))
    for engine in ("gas-async", "gas-async-local"):
        got = khop(g, 0, 3, engine=engine, **({"machines": 1, "inner": 5} if engine.endswith("local") else {"sweeps": 2})).df
        assert sorted(map(tuple, got.collect())) == [(i, i) for i in range(4)], engine


def test_async_local_parts_are_bounded(spark, monkeypatch):
    """Parts grow in number with the edges."""
    from bspframe.algos.wcc import wcc
    from bspframe.engines import gas
    from bspframe.graph import Graph

    monkeypatch.setattr(gas, "PART_EDGES", 20)
    g = Graph.from_edges(spark.createDataFrame([(0, i) for i in range(1, 200)], "src long, dst long"))
    r = wcc(g, engine="gas-async-local", machines=1)
    assert r.df.count() == 200 and r.df.where("component <> 0").isEmpty()
    assert gas.parts_of(398, 1) == 20 and gas.parts_of(398, 32) == 32


def test_diameter_keeps_no_pairs(spark, monkeypatch):
    """Pairs are counted by bits, 64 sources in a row; the counts are those of the searches one by one."""
    from bspframe.algos import sssp
    from bspframe.graph import Graph

    g = Graph.from_edges(spark.createDataFrame([(i, (i * 7 + k) % 150) for i in range(150) for k in (1, 5)] + [(149, 149), (150, 0)], "src long, dst long"))
    sources = spark.createDataFrame([(i,) for i in [*range(0, 151, 2), 0, 999]], "id long")
    found = sssp.khop_many(g, sources, 1 << 30).df.where("dist > 0").groupBy("dist").count().orderBy("dist").collect()
    monkeypatch.setattr(sssp, "khop_many", lambda *a, **k: (_ for _ in ()).throw(AssertionError("a row for each pair")))
    assert [(x.round, x.changed) for x in sssp.pair_counts(g, sources)] == [tuple(r) for r in found]
    got = sssp.diameter(g, sources).first()
    assert (got["sources"], got["pairs"], got["longest"]) == (77, sum(r["count"] for r in found), found[-1]["dist"])
