"""Registered queries of the graph engine and their SQL counterparts."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from bspframe import builders as B
from bspframe import oracles as O
from bspframe.algos import pagerank as pr
from bspframe.algos import sssp as sp
from bspframe.algos import wcc as wc
from bspframe.graph import Graph
from bspframe.measures import quality
from bspframe.partitioners import blocks as bl
from bspframe.partitioners import cuts
from bspframe.plans import planner
from bspframe.sources.tables import read_table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
ROUNDS = 20


def query(name: str, fn: Query, oracle: str | None = None) -> None:
    QUERIES[name] = fn
    if oracle:
        ORACLES[name] = oracle


def _ranks(df: DataFrame) -> DataFrame:
    return df.select("id", (F.round("rank", 6) + 0.0).alias("rank"))


def _graph(name: str, both: bool = False) -> Callable[[SparkSession, str], Graph]:
    def make(s: SparkSession, d: str) -> Graph:
        g = B.GRAPHS[name](s, d)
        return g.undirect() if both else g

    return make


# PageRank
for key, name, both in (("social", "co_purchase", False), ("web", "page_links", True), ("road", "session_chains", False), ("terms", "doc_terms", True), ("handoff", "handoff", False)):
    query(f"pr_{key}", lambda s, d, g=_graph(name, both): _ranks(pr.pagerank(g(s, d), max_rounds=ROUNDS).df), O.pagerank(name, ROUNDS, both))
TOL = 0.01
query("pr_tol_social", lambda s, d: _ranks(pr.pagerank(B.co_purchase(s, d), tol=TOL).df), O.pagerank_until("co_purchase", TOL, 60))
query("pr_selfedge_keep", lambda s, d: _ranks(pr.pagerank(B.handoff(s, d), max_rounds=ROUNDS).df), O.pagerank("handoff", ROUNDS))
query("pr_selfedge_drop", lambda s, d: _ranks(pr.pagerank(B.handoff(s, d), max_rounds=ROUNDS, self_edges="drop").df), O.pagerank("handoff", ROUNDS, drop_self=True))
query("pr_parallel", lambda s, d: _ranks(pr.pagerank(B.trade(s, d, distinct=False), max_rounds=ROUNDS).df), O.pagerank("trade", ROUNDS, edges=B.SQL["trade_multi"]))
for key, how in {
    "gas": {"engine": "gas"}, "gas_auto": {"engine": "gas", "cut": "auto", "machines": 7}, "sql": {"engine": "sql"}, "mr": {"engine": "mr"}, "mrloop": {"engine": "mr-loop"},
    "rdd": {"engine": "rdd"}, "dataflow": {"engine": "dataflow"}, "single": {"engine": "single"}, "nocombiner": {"combiner": False},
}.items():
    query(f"pr_{key}", lambda s, d, how=how: _ranks(pr.pagerank(B.handoff(s, d), max_rounds=ROUNDS, **how).df), O.pagerank("handoff", ROUNDS))
query("pr_gas_t", lambda s, d: _ranks(pr.pagerank(B.handoff(s, d), engine="gas", stop="T", tol=1e-6, max_rounds=100).df), O.pagerank_quiet("handoff", 1e-6, 60, "scatter"))
query("pr_async", lambda s, d: _ranks(pr.pagerank(B.co_purchase(s, d), engine="gas-async", tol=1e-4).df))
query("pr_async_local", lambda s, d: _ranks(pr.pagerank(B.handoff(s, d), engine="gas-async-local", tol=1e-6).df))
query("pr_approx_optout", lambda s, d: _ranks(pr.pagerank_approx(B.co_purchase(s, d), 1e-3).df), O.pagerank_quiet("co_purchase", 1e-3, 100, "never"))
query("pr_approx_wake", lambda s, d: _ranks(pr.pagerank_approx(B.co_purchase(s, d), 1e-3, reactivate=True).df), O.pagerank_quiet("co_purchase", 1e-3, 100, "moved"))
query("pr_weighted", lambda s, d: _ranks(pr.pagerank(Graph(B.trade(s, d, distinct=False).edges.withColumn("w", F.lit(1.0)), name="trade").simplify(), max_rounds=ROUNDS).df), O.pagerank("trade", ROUNDS, edges=B.SQL["trade_multi"]))


def _update_ratio(name: str, both: bool = False) -> Query:
    def go(s: SparkSession, d: str) -> DataFrame:
        g = _graph(name, both)(s, d)
        exact = pr.pagerank(g, tol=1e-3)
        approx = pr.pagerank_approx(g, 1e-3, max_rounds=exact.rounds)
        return quality.update_ratio(approx.stats, exact.stats, g.vertices.count(), s)

    return go


def _rank_error(s: SparkSession, d: str) -> DataFrame:
    g = B.co_purchase(s, d)
    return quality.rank_error(pr.pagerank_approx(g, 1e-3).df, pr.pagerank(g, tol=1e-6).df)


def _url_blocks(s: SparkSession, d: str) -> DataFrame:
    """Pages and tokens by the least page of the page's host and first path part; a token joins its least page's block."""
    pages = read_table(s, d, "pages").select((F.col("page_id") * 2).alias("id"), "url")
    of = bl.blocks_url(pages, 1)
    g = B.page_links(s, d)
    tokens = g.edges.groupBy(F.col("dst").alias("t")).agg(F.min("src").alias("id")).join(of, "id").select(F.col("t").alias("id"), "block")
    return of.union(tokens)


def _page_graph(s: SparkSession, d: str) -> Graph:
    pages = read_table(s, d, "pages").select((F.col("page_id") * 2).alias("id"))
    return Graph(B.page_links(s, d).undirect().edges, extra=pages, name="page_links")


query("pr_update_ratio", _update_ratio("co_purchase"))
query("pr_update_ratio_web", _update_ratio("page_links", True))
query("pr_update_ratio_road", _update_ratio("session_chains"))
query("pr_rank_error", _rank_error)
query("pr_block", lambda s, d: _ranks(pr.pagerank_block(_page_graph(s, d), _url_blocks(s, d)).df))
query("pr_block_rounds", lambda s, d: _ranks(pr.pagerank_block(_page_graph(s, d), _url_blocks(s, d), step_rounds=(10, 10, 20)).df))

# components
for key, name in (("social", "co_purchase"), ("web", "page_links"), ("road", "session_chains"), ("hub", "geo_hub"), ("dup", "near_dup"), ("knn", "knn"), ("turns", "turn_chains"), ("ladder", "order_ladder")):
    query(f"wcc_{key}", lambda s, d, n=name: wc.wcc(B.GRAPHS[n](s, d)).df, O.wcc(name) if key != "ladder" else f"SELECT id, min(id) OVER () AS component FROM (SELECT src AS id FROM ({B.SQL[name]}) UNION SELECT dst FROM ({B.SQL[name]}))")
for key, how in {
    "minlabel": {"method": "min_label"}, "firstround": {"method": "min_label", "reverse": "first_round"}, "gatherboth": {"method": "min_label", "reverse": "gather_both"},
    "hashtomin": {"method": "hash_to_min"}, "star": {"method": "star"}, "auto": {"method": "auto"}, "gas": {"engine": "gas"}, "async": {"engine": "gas-async"}, "async_local": {"engine": "gas-async-local"},
    "sql": {"engine": "sql"}, "sql_merge": {"engine": "sql", "update": "merge", "frontier": "filter"}, "mr": {"engine": "mr"}, "mrloop": {"engine": "mr-loop"}, "rdd": {"engine": "rdd", "checkpoint_every": 2},
    "dataflow": {"engine": "dataflow"}, "block": {"engine": "block"}, "block_async": {"engine": "block", "mode": "async"}, "block_voronoi": {"engine": "block", "blocks": "voronoi"}, "block_mincut": {"engine": "block", "blocks": "mincut"},
    "block_mincut_async": {"engine": "block", "blocks": "mincut", "mode": "async"}, "rdd_edge_cut": {"engine": "rdd", "cut": "edge"}, "single": {"engine": "single"},
}.items():
    query(f"wcc_{key}", lambda s, d, how=how: wc.wcc(B.trade(s, d), **how).df, O.wcc("trade"))
query("wcc_forward_only", lambda s, d: wc.wcc(B.trade(s, d), directed=True).df, O.wcc("trade", directed=True))

# distances
for key, name, both, source in (("social", "co_purchase", False, 0), ("web", "page_links", True, 0), ("road", "session_chains", False, 0), ("handoff", "handoff", False, 0), ("knn", "knn", False, 0)):
    query(f"sssp_{key}", lambda s, d, g=_graph(name, both), v=source: sp.sssp(g(s, d), v).df, O.hops(name, source, both))
    query(f"khop3_{key}", lambda s, d, g=_graph(name, both), v=source: sp.khop(g(s, d), v, 3).df, O.hops(name, source, both, 3))
    query(f"khop_counts_{key}", lambda s, d, g=_graph(name, both), v=source: sp.khop(g(s, d), v, 3, levels=True).df, O.hops(name, source, both, 3, "SELECT dist::INTEGER AS dist, count(*) AS vertices FROM d GROUP BY dist"))
for key, how in {
    "vertex": {"engine": "vertex"}, "full": {"engine": "vertex", "frontier": False}, "gas": {"engine": "gas"}, "async": {"engine": "gas-async"}, "sql": {"engine": "sql"}, "mr": {"engine": "mr"}, "mrloop": {"engine": "mr-loop"},
    "rdd": {"engine": "rdd", "checkpoint_every": 10}, "dataflow": {"engine": "dataflow"}, "block": {"engine": "block"}, "single": {"engine": "single"},
}.items():
    query(f"sssp_{key}", lambda s, d, how=how: sp.sssp(B.handoff(s, d), 0, **how).df, O.hops("handoff", 0))
    query(f"khop3_{key}", lambda s, d, how=how: sp.khop(B.handoff(s, d), 0, 3, **how).df, O.hops("handoff", 0, k=3))
query("sssp_diropt", lambda s, d: sp.sssp(B.co_purchase(s, d), 0, method="dir_opt").df, O.hops("co_purchase", 0))
query("sssp_weighted", lambda s, d: sp.sssp(Graph(B.handoff(s, d).edges.withColumn("w", F.lit(1.0)), name="handoff"), 0, weight=True).df.select("id", F.col("dist").cast("int").alias("dist")), O.hops("handoff", 0))
query("sssp_parent", lambda s, d: sp.sssp(B.handoff(s, d), 0, with_parent=True).df, O.hops_with_parent("handoff", 0))
query("sssp_block_voronoi", lambda s, d: sp.sssp(B.handoff(s, d), 0, engine="block", blocks="voronoi").df, O.hops("handoff", 0))
query("sssp_block_mincut", lambda s, d: sp.sssp(B.handoff(s, d), 0, engine="block", blocks="mincut", mode="async").df, O.hops("handoff", 0))
for key, name, both in (("social", "co_purchase", False), ("web", "page_links", True), ("road", "session_chains", False)):
    query(f"sssp_contract_{key}", lambda s, d, g=_graph(name, both): sp.sssp(g(s, d), 0, method="contract").df, O.hops(name, 0, both))
query("khop5_social", lambda s, d: sp.khop(B.co_purchase(s, d), 0, 5).df, O.hops("co_purchase", 0, k=5))


def _ladder(s: SparkSession, d: str) -> DataFrame:
    """Distances from the ladder's head, the first order of the first customer; over a thousand hops."""
    head = read_table(s, d, "orders").agg(F.min_by("o_orderkey", F.struct("o_custkey", "o_orderdate", "o_orderkey"))).first()[0]
    return sp.sssp(B.order_ladder(s, d), head, method="auto").df


query("sssp_ladder", _ladder, """SELECT o_orderkey AS id, (dense_rank() OVER (ORDER BY o_custkey) + row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) - 2)::INTEGER AS dist FROM orders""")
query("khop_recursive", lambda s, d: sp.khop(B.handoff(s, d), 0, 2, engine="recursive_sql").df, O.hops("handoff", 0, k=2))
query("khop_many_social", lambda s, d: sp.khop_many(B.co_purchase(s, d), read_table(s, d, "part").where("p_partkey < 50").select(F.col("p_partkey").alias("id")), 2).df, O.khop_many("co_purchase", "SELECT p_partkey AS id FROM part WHERE p_partkey < 50", 2))
query("khop_many_every50_social", lambda s, d: sp.khop_many(B.co_purchase(s, d), read_table(s, d, "part").where("p_partkey % 50 = 0").select(F.col("p_partkey").alias("id")), 2).df, O.khop_many("co_purchase", "SELECT p_partkey AS id FROM part WHERE p_partkey % 50 = 0", 2))

# partitioners and their measures
_rf = lambda how, p, **k: lambda s, d: quality.replication_factor(how(B.co_purchase(s, d), p, **k))
query("rf_random", _rf(cuts.vertex_cut_random, 16, portable=True), O.replication("co_purchase", O.random_part(16)))
query("rf_grid", _rf(cuts.vertex_cut_grid, 16, portable=True), O.replication("co_purchase", O.common_part(cuts.grid_candidates(16))))
query("rf_pds", _rf(cuts.vertex_cut_pds, 13, portable=True), O.replication("co_purchase", O.common_part(cuts.pds_candidates(13))))
query("rf_edge_cut", _rf(cuts.edge_cut_random, 16, portable=True), O.replication("co_purchase", f"({O._hash('src')} % 16)"))
query("rf_greedy", _rf(cuts.vertex_cut_greedy, 8))
query("rf_auto", lambda s, d: quality.replication_factor(cuts.vertex_cut_auto(B.co_purchase(s, d), 32)[0]))
_CORES = {16: 64, 32: 128, 64: 256, 128: 512}
#: Rows of a block of the tables that the graphs come from.
_BLOCK_ROWS = {"social": ("lineitem", "l_orderkey", 2000), "road": ("events", "event_id", 1000), "web": ("pages", "page_id", 10)}


def _partition_rule(s: SparkSession, d: str) -> DataFrame:
    """Partitions for each graph's table, cut into blocks of rows, on clusters of several sizes."""
    cells = []
    for graph, (table, key, rows) in _BLOCK_ROWS.items():
        n = read_table(s, d, table).where(F.col(key).isNotNull()).count()
        cells += [(graph, nodes, planner.partition_rule(-(-n // rows), cores)) for nodes, cores in _CORES.items()]
    return s.createDataFrame(cells, "graph string, nodes int, partitions int")


query(
    "partition_rule",
    _partition_rule,
    "SELECT g AS graph, n::INTEGER AS nodes, least(b, 2 * c)::INTEGER AS partitions FROM ("
    + " UNION ALL ".join(f"SELECT '{g}' AS g, ceil(count({c}) / {r}.0)::BIGINT AS b FROM {t}" for g, (t, c, r) in _BLOCK_ROWS.items())
    + ") CROSS JOIN (VALUES " + ", ".join(f"({n}, {c})" for n, c in _CORES.items()) + ") AS t(n, c)",
)
query(
    "blocks_url",
    lambda s, d: bl.blocks_url(read_table(s, d, "pages").select(F.col("page_id").alias("id"), "url"), 1),
    """SELECT page_id AS id, min(page_id) OVER (PARTITION BY regexp_extract(url, '://([^/?#]*)', 1), coalesce(string_split(regexp_extract(url, '://[^/?#]*([^?#]*)', 1), '/')[2], '')) AS block FROM pages""",
)
query(
    "block_graph",
    lambda s, d: B.handoff(s, d).contract(B.handoff(s, d).vertices.select("id", (F.col("id") % 10).alias("block"))),
    f"SELECT src % 10 AS bsrc, dst % 10 AS bdst, count(*) AS w FROM ({B.SQL['handoff']}) WHERE src % 10 <> dst % 10 GROUP BY ALL",
)
query("block_stats", lambda s, d: quality.block_stats(B.co_purchase(s, d), B.co_purchase(s, d).vertices.select("id", F.floor(F.col("id") / 100).alias("block"))),
      f"""WITH e AS MATERIALIZED ({B.SQL['co_purchase']}), v AS (SELECT src AS id FROM e UNION SELECT dst FROM e), s AS (SELECT id // 100 AS b, count(*) AS n FROM v GROUP BY ALL)
      SELECT count(*) AS blocks, max(n) AS max_size, round(avg(n), 6) AS mean_size, (SELECT count(*) FROM e) AS edges, (SELECT count(*) FROM e WHERE src // 100 <> dst // 100) AS cut_edges,
      (SELECT count(DISTINCT id) FROM (SELECT src AS id FROM e WHERE src // 100 <> dst // 100 UNION ALL SELECT dst FROM e WHERE src // 100 <> dst // 100)) AS boundary_vertices FROM s""")  # fmt: skip
query(
    "blocks_2d",
    lambda s, d: bl.blocks_2d(read_table(s, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding")[0].cast("double").alias("x"), F.col("embedding")[1].cast("double").alias("y")), 4, 4),
    """WITH c AS (SELECT vec_id AS id, embedding[1]::DOUBLE AS x, embedding[2]::DOUBLE AS y FROM embeddings), m AS (SELECT min(x) x0, max(x) x1, min(y) y0, max(y) y1 FROM c)
    SELECT id, (least(floor((x - x0) / (x1 - x0) * 4), 3) * 4 + least(floor((y - y0) / (y1 - y0) * 4), 3))::BIGINT AS block FROM c, m""",
)
query("blocks_voronoi", lambda s, d: bl.blocks_voronoi(B.handoff(s, d), rate=0.1))
query("blocks_mincut", lambda s, d: bl.partition_mincut(B.co_purchase(s, d), 4))

# statistics and formats
for name in ("co_purchase", "trade", "supply", "handoff", "session_chains", "order_ladder", "page_links", "doc_terms", "geo_hub", "turn_chains", "knn", "near_dup"):
    query(f"graph_stats_{name}", lambda s, d, n=name: B.GRAPHS[n](s, d).stats(), O.stats(name))
for name in ("co_purchase", "trade"):
    query(f"adj_{name}", lambda s, d, n=name: B.GRAPHS[n](s, d).adjacency().select("id", F.concat_ws(" ", F.transform("nbrs", lambda x: x.cast("string"))).alias("nbrs")), O.adjacency(name, False))
    query(f"adj_long_{name}", lambda s, d, n=name: B.GRAPHS[n](s, d).adjacency_long().select("id", "deg", F.concat_ws(" ", F.transform("nbrs", lambda x: x.cast("string"))).alias("nbrs")), O.adjacency(name, True))


# measures, ablations and runs
def _phases(s: SparkSession, d: str) -> DataFrame:
    from bspframe import harness

    return harness.table(
        s, [harness.run_one(s, d, "handoff", w, e, **({"rounds": 5} if w == "pagerank" else {})) for w in harness.WORKLOADS for e in ("vertex", "single")]
    )


def _cost(s: SparkSession, d: str) -> DataFrame:
    from bspframe import harness

    rows = []
    for w in harness.WORKLOADS:
        one, many = (harness.run_one(s, d, "handoff", w, e, **({"rounds": 5} if w == "pagerank" else {})) for e in ("single", "vertex"))
        rows.append((w, one["total"], many["total"], quality.cost_factor(one["total"], many["total"]), quality.cost_factor(one["total"], many["total"], inverse=True)))
    return s.createDataFrame(rows, "workload string, single_s double, parallel_s double, single_over_parallel double, parallel_over_single double")


def _outcomes(s: SparkSession, d: str) -> DataFrame:
    from bspframe.measures.runs import run_limited

    ok = run_limited(s, lambda: B.handoff(s, d).edges.count(), 120)
    late = run_limited(s, lambda: s.range(1 << 40).selectExpr("sum(hash(id))").collect(), 1.0)
    return s.createDataFrame([("count", ok[0]), ("endless", late[0])], "run string, outcome string")


def _memory(s: SparkSession, d: str) -> DataFrame:
    from bspframe.measures.runs import Sampler
    from bspframe.session import table_path
    from bspframe.sources.edges import format_bytes

    g = B.handoff(s, d)
    with Sampler(0.2) as m:
        pr.pagerank(g, max_rounds=3).df.count()
    size = format_bytes(g, table_path(s, "formats"))
    return s.createDataFrame([(k, v, quality.expansion(m.peak_memory, v)) for k, v in size.items()], "form string, bytes long, expansion double")


def _format_bytes(s: SparkSession, d: str) -> DataFrame:
    from bspframe.session import table_path
    from bspframe.sources.edges import format_bytes

    return s.createDataFrame(list(format_bytes(B.trade(s, d), table_path(s, "formats")).items()), "form string, bytes long")


def _rounds_table(s: SparkSession, d: str) -> DataFrame:
    r = pr.pagerank(B.handoff(s, d), tol=1e-3)
    return s.createDataFrame([(x.round, x.changed, x.active, x.max_change, x.seconds, quality.round_budget(86_400, r.rounds)) for x in r.stats], "round int, changed long, active long, max_change double, seconds double, budget double")


_SCALE = """
import os, sys, time, json
sys.path.insert(0, {repo!r})
from pyspark.sql import SparkSession
s = SparkSession.builder.master(os.environ['BSPFRAME_MASTER']).config('spark.sql.shuffle.partitions', '4').config('spark.ui.enabled', 'false').config('spark.driver.memory', '2g').getOrCreate()
from bspframe import builders as B
from bspframe.algos.pagerank import pagerank
g = B.trade(s, {sf!r}).copies({times})
mode = {mode!r}
run = lambda k: pagerank(g, max_rounds=k) if mode == 'sync' else pagerank(g, engine='gas' if mode == 'gas' else 'gas-async', tol=1e-9, max_rounds=k)
run(1).df.count()
at = time.perf_counter()
run(3).df.count()
print(json.dumps({{'seconds': time.perf_counter() - at}}))
s.stop()
"""


def _scale_code(sf: str, times: int = 1, mode: str = "sync") -> str:
    import os

    return _SCALE.format(repo=os.path.dirname(os.path.dirname(os.path.abspath(__file__))), sf=sf, times=times, mode=mode)


def _timed(s: SparkSession, trade: Graph, tasks: int, times: int = 1, mode: str = "sync") -> float:
    """Seconds of three rounds of ranks over ``times`` copies of the graph, with ``tasks`` tasks at work at a time.

    The session's own cores run them: edges and state are dealt to ``tasks`` partitions, so no more cores can be busy.
    Only the rounds are held to that; ``trade`` comes from its edge files.
    """
    import time

    edges = trade.copies(times).edges.repartition(tasks).persist()
    edges.count()
    was = s.conf.get("spark.sql.shuffle.partitions")
    s.conf.set("spark.sql.shuffle.partitions", str(tasks))
    try:
        g = Graph(edges, name="trade")
        at = time.perf_counter()
        if mode == "sync":
            r = pr.pagerank(g, max_rounds=3)
        else:
            r = pr.pagerank(g, engine="gas" if mode == "gas" else "gas-async", tol=1e-9, max_rounds=3)
        r.df.write.format("noop").mode("overwrite").save()
        took = time.perf_counter() - at
    finally:
        s.conf.set("spark.sql.shuffle.partitions", was)
        edges.unpersist()
    return took


def _scaling(s: SparkSession, d: str) -> DataFrame:
    from bspframe import harness

    with harness.Datasets(s, d) as data:
        took = {k: _timed(s, data.graph("trade"), k) for k in (1, 2, 4)}
    return s.createDataFrame([(k, "vertical", t, took[1] / t, took[1] / t / k) for k, t in took.items()], "cores int, axis string, seconds double, speed_up double, efficiency double")


def _weak(s: SparkSession, d: str) -> DataFrame:
    """As many disjoint copies of the graph as cores, so that a core's load stays the same."""
    from bspframe import harness

    with harness.Datasets(s, d) as data:
        took = {k: _timed(s, data.graph("trade"), k, times=k) for k in (1, 2, 4)}
    return s.createDataFrame([(k, k, t, took[1] / t) for k, t in took.items()], "times int, cores int, seconds double, efficiency double")


def _reserved(s: SparkSession, d: str) -> DataFrame:
    """All cores computing, or two of them held back, with synchronous and asynchronous rounds."""
    cores = max(3, min(8, s.sparkContext.defaultParallelism))
    from bspframe import harness

    with harness.Datasets(s, d) as data:
        rows = [(mode, label, k, _timed(s, data.graph("trade"), k, mode=mode)) for mode in ("gas", "async") for label, k in (("all", cores), ("two reserved", cores - 2))]
    return s.createDataFrame(rows, "mode string, cores string, computing int, seconds double")


def _resources(s: SparkSession, d: str) -> DataFrame:
    """What the relational engine uses beside others as the graph grows: CPU, I/O wait, memory, traffic, files written."""
    from bspframe import harness

    with harness.Datasets(s, d) as data:
        rows = [harness.run_one(s, d, "handoff", "pagerank", e, sample=True, copies=c, data=data, rounds=5) for c in (1, 4, 16) for e in ("sql", "vertex", "gas", "mr")]
    names = ["engine", "edges", "total", "user_max", "io_wait_max", "peak_memory", "network", "disk_written"]
    return s.createDataFrame([tuple(r.get(n) for n in names) for r in rows], "engine string, edges long, total double, user_max double, io_wait_max double, peak_memory double, network double, disk_written double")


query("phases", _phases)
query("cost", _cost)
query("outcomes", _outcomes, "SELECT * FROM (VALUES ('count', 'OK'), ('endless', 'TO')) AS t(run, outcome)")
query("memory_expansion", _memory)
query("format_bytes", _format_bytes)
query("rounds_table", _rounds_table)
query("scaling_strong", _scaling)
query("scaling_weak", _weak)
query("cores_reserved", _reserved)
query("engine_resources", _resources)
query("balance", lambda s, d: planner.partition_balance(B.co_purchase(s, d).edges.repartition(16, "src")))


def _ablation(name: str) -> Query:
    def go(s: SparkSession, d: str) -> DataFrame:
        from bspframe import harness

        return harness.ablation(s, d, name)

    return go


for name in ("cut", "stop", "mode", "handoff", "loop_cache", "rdd_checkpoint", "wcc_method", "update", "combiner", "exact", "blocks"):
    query(f"ablation_{name}", _ablation(name))


def _matrix(graph: str) -> Query:
    def go(s: SparkSession, d: str) -> DataFrame:
        from bspframe import harness

        return harness.matrix(s, d, (graph,), engines=_FAMILIES, rounds=ROUNDS)

    return go


#: One engine of each family; plain map/reduce and asynchronous sweeps have queries of their own on smaller graphs.
_FAMILIES = ("vertex", "gas", "block", "mr-loop", "rdd", "sql", "dataflow", "single")
for name in ("social", "web", "road"):
    query(f"matrix_{name}", _matrix(name))
query("partition_sweep", lambda s, d: _sweep(s, d))
query("ablation_session", lambda s, d: _session(s, d))


def _sweep(s: SparkSession, d: str) -> DataFrame:
    from bspframe import harness

    return harness.partition_sweep(s, d)


def _session(s: SparkSession, d: str) -> DataFrame:
    """A run in a session of its own, start included, against the same run in the session at hand."""
    import time

    from bspframe.measures.runs import strong_scaling

    at = time.perf_counter()
    inner = strong_scaling(_scale_code(d), [4])[0].get("seconds")
    fresh = time.perf_counter() - at
    g = B.trade(s, d)
    pr.pagerank(g, max_rounds=1).df.count()
    at = time.perf_counter()
    pr.pagerank(g, max_rounds=3).df.count()
    return s.createDataFrame([("fresh", fresh, inner), ("reused", time.perf_counter() - at, None)], "session string, seconds double, run_only double")


for key, name, table, column, every in (("social", "co_purchase", "part", "p_partkey", 500), ("handoff", "handoff", "events", "user_id", 50)):
    query(
        f"diameter_{key}",
        lambda s, d, n=name, t=table, c=column, k=every: sp.diameter(B.GRAPHS[n](s, d), read_table(s, d, t).where(f"{c} % {k} = 0").select(F.col(c).alias("id")).distinct()),
        O.diameter(name, f"SELECT DISTINCT {column} AS id FROM {table} WHERE {column} % {every} = 0"),
    )
query("diameter_web", lambda s, d: sp.diameter(_graph("page_links", True)(s, d)))
query("diameter_road", lambda s, d: sp_diameter(s, d))


def sp_diameter(s: SparkSession, d: str) -> DataFrame:
    """Diameter of a forest of chains, exact: the longest chain's edges."""
    g = B.session_chains(s, d)
    sizes = wc.wcc(g).df.groupBy("component").count()
    return sizes.agg((F.max("count") - 1).alias("diameter"))


ORACLES["diameter_road"] = "SELECT max(n) - 1 AS diameter FROM (SELECT count(*) AS n FROM events GROUP BY user_id)"


# surrounding operators
def _interval(s: SparkSession, d: str) -> DataFrame:
    from bspframe.operators.temporal import interval_edges

    return interval_edges(read_table(s, d, "events"), "user_id", "ts", "event_id", 86_400)


def _asof(s: SparkSession, d: str) -> DataFrame:
    from bspframe.operators.temporal import asof_edges

    e = read_table(s, d, "events").select("event_id", "ts", "user_id", "event_type")
    low = e.agg(F.min("event_type")).first()[0]
    return asof_edges(e.where(F.col("event_type") != low), e.where(F.col("event_type") == low), "user_id", "ts", "event_id")


query("interval_edges", _interval, "SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN events b ON a.user_id = b.user_id AND (b.ts > a.ts OR (b.ts = a.ts AND b.event_id > a.event_id)) AND b.ts <= a.ts + INTERVAL 86400 SECONDS")
query(
    "asof_edges",
    _asof,
    """WITH low AS (SELECT min(event_type) AS t FROM events), l AS (SELECT * FROM events, low WHERE event_type <> t), r AS (SELECT * FROM events, low WHERE event_type = t)
    SELECT l.event_id AS src, arg_max(r.event_id, (r.ts, r.event_id)) AS dst FROM l JOIN r ON l.user_id = r.user_id AND r.ts <= l.ts GROUP BY l.event_id""",
)


def _ids(s: SparkSession, d: str) -> DataFrame:
    from bspframe.functions.ids import encode_ids

    return encode_ids(read_table(s, d, "part").select("p_partkey", "p_brand"), ["p_brand"]).select("p_partkey", "p_brand", F.col("p_brand_id").cast("long").alias("p_brand_id"))


query("encode_ids", _ids, "SELECT p_partkey, p_brand, dense_rank() OVER (ORDER BY p_brand) - 1 AS p_brand_id FROM part")
query("top_ranked", lambda s, d: _ranks(pr.top_ranked(pr.pagerank(B.handoff(s, d), max_rounds=ROUNDS).df, 10)), f"SELECT id, rank FROM ({O.pagerank('handoff', ROUNDS)}) ORDER BY rank DESC, id LIMIT 10")
query("property_edges", lambda s, d: _props(s, d), "SELECT event_id AS src, (props::JSON->>'k')::BIGINT AS dst, value AS w FROM events WHERE (props::JSON->>'k') IS NOT NULL")


def _props(s: SparkSession, d: str) -> DataFrame:
    from bspframe.operators.temporal import property_edges

    return property_edges(read_table(s, d, "events"))


# streams
def _stream(s: SparkSession, d: str):
    from bspframe.session import table_path
    from bspframe.sources.edges import read_edge_stream

    path = table_path(s, "edge-stream")
    B.handoff(s, d, keep_ts=True).withColumn("ts", F.col("ts").cast("timestamp")).repartition(3).write.parquet(path)
    return read_edge_stream(s, path, late=None, files_per_trigger=1), (lambda n: table_path(s, n))


def _stream_components(s: SparkSession, d: str) -> DataFrame:
    from bspframe.streaming.graphs import stream_components

    edges, new = _stream(s, d)
    return stream_components(edges, new("state"), new("checkpoint")).before()


def _stream_degrees(s: SparkSession, d: str) -> DataFrame:
    from bspframe.streaming.graphs import stream_degrees

    edges, new = _stream(s, d)
    return stream_degrees(edges, new("state"), new("checkpoint")).before()


def _stream_khop(s: SparkSession, d: str) -> DataFrame:
    from bspframe.streaming.graphs import stream_khop

    edges, new = _stream(s, d)
    return stream_khop(edges, 0, 3, new("state"), new("edges"), new("checkpoint")).before()


def _stream_pagerank(s: SparkSession, d: str) -> DataFrame:
    from bspframe.streaming.graphs import stream_pagerank

    edges, new = _stream(s, d)
    return _ranks(stream_pagerank(edges, new("state"), new("edges"), new("checkpoint"), tol=1e-6).before())


def _stream_windows(s: SparkSession, d: str) -> DataFrame:
    from bspframe.session import table_path
    from bspframe.streaming.graphs import Versions, windowed_edges

    edges, new = _stream(s, d)
    out = table_path(s, "windows")
    counted = windowed_edges(edges.withWatermark("ts", "3650 days"), "30 days")
    table = Versions(s, out, "start TIMESTAMP, end TIMESTAMP, src BIGINT, dst BIGINT, n BIGINT")
    w = counted.writeStream.foreachBatch(lambda batch, number: table.put(batch, number)).outputMode("complete")
    w.option("checkpointLocation", new("checkpoint")).trigger(availableNow=True).start().awaitTermination()
    return table.before().groupBy("src", "dst").agg(F.sum("n").alias("n"))


_MULTI = "SELECT user_id AS src, nxt AS dst FROM (SELECT user_id, lead(user_id) OVER (ORDER BY ts, event_id) AS nxt FROM events) WHERE nxt IS NOT NULL"
query("stream_components", _stream_components, O.wcc("handoff"))
query("stream_degrees", _stream_degrees, f"WITH e AS ({_MULTI}) SELECT id, sum(o)::BIGINT AS out_degree, sum(i)::BIGINT AS in_degree FROM (SELECT src AS id, 1 AS o, 0 AS i FROM e UNION ALL SELECT dst, 0, 1 FROM e) GROUP BY id")
query("stream_khop", _stream_khop, O.hops("handoff", 0, k=3))
query("stream_pagerank", _stream_pagerank)
query("stream_windows", _stream_windows, f"SELECT src, dst, count(*) AS n FROM ({_MULTI}) GROUP BY ALL")


# reports
def _cube(s: SparkSession, d: str) -> DataFrame:
    """The cube of phase times over order lines: a line stands for a run, its whole-numbered columns for the phases."""
    from bspframe import report

    li = read_table(s, d, "lineitem")
    whole = lambda c: F.pmod(F.col(c), F.lit(1000)).cast("double")
    runs = li.select(
        F.col("l_returnflag").alias("engine"), F.col("l_linestatus").alias("graph"), F.pmod("l_suppkey", F.lit(7)).cast("string").alias("workload"),
        whole("l_orderkey").alias("load"), whole("l_partkey").alias("execute"), whole("l_suppkey").alias("save"), F.col("l_linenumber").cast("double").alias("overhead"),
    )
    return report.phases_cube(runs)


query("report_cube", _cube, """SELECT engine, graph, workload, grouping(engine, graph, workload) AS level, round(avg(load), 6) AS load, round(avg(execute), 6) AS execute, round(avg(save), 6) AS save, round(avg(overhead), 6) AS overhead, count(*) AS runs
  FROM (SELECT l_returnflag AS engine, l_linestatus AS graph, (l_suppkey % 7)::VARCHAR AS workload, (l_orderkey % 1000)::DOUBLE AS load, (l_partkey % 1000)::DOUBLE AS execute, (l_suppkey % 1000)::DOUBLE AS save, l_linenumber::DOUBLE AS overhead FROM lineitem) GROUP BY CUBE (engine, graph, workload)""")  # fmt: skip
