"""The experiment matrix: engines by workloads by graphs, with phases, outcomes and ablations."""

from __future__ import annotations

import itertools
import time

from pyspark.sql import DataFrame, SparkSession, functions as F

from bspframe import builders as B
from bspframe.algos.pagerank import pagerank, pagerank_approx
from bspframe.algos.sssp import khop, sssp
from bspframe.algos.wcc import wcc
from bspframe.graph import Graph
from bspframe.measures.runs import Outcome, Recorder, Sampler
from bspframe.session import drop_table, materialise, table_path, tidy

ENGINES = ("vertex", "gas", "gas-async", "block", "mr", "mr-loop", "rdd", "sql", "dataflow", "single")
WORKLOADS = ("pagerank", "wcc", "sssp", "khop")
STAND_INS = {"social": "co_purchase", "web": "page_links", "road": "session_chains", "terms": "doc_terms", "handoff": "handoff", "trade": "trade"}
#: PageRank has a block form of its own.
SKIP = {("block", "pagerank")}
#: Settings of an engine in a matrix: lineage over some 80 rounds of a long graph is cut as published.
SETTINGS = {"rdd": {"checkpoint_every": 10}}
#: Seconds of a run from which its shuffle files are deleted before the next.
SLOW = 5.0


def workload(name: str, g: Graph, engine: str, rounds: int = 20, source: int = 0, **how):
    if name == "pagerank_approx":
        return pagerank_approx(g, **how)
    if name == "pagerank":
        if engine.startswith("gas-async"):  # its runs end by a tolerance
            how = {"tol": 1e-9, **how}
        return pagerank(g, engine=engine, max_rounds=rounds, **how)
    if name == "wcc":
        return wcc(g, engine=engine, method=how.pop("method", "min_label"), **how)
    if name == "sssp":
        return sssp(g, source, engine=engine, **how)
    return khop(g, source, 3, engine=engine, **how)


class Datasets:
    """Graphs built from the tables once and kept as edge files in the shared folder, for all cells that run on them."""

    def __init__(self, spark: SparkSession, sf: str):
        self.spark, self.sf, self.made = spark, sf, {}

    def __enter__(self) -> "Datasets":
        return self

    def __exit__(self, *_):
        for g in self.made.values():
            drop_table(g.edges)
            if g.extra is not None:
                drop_table(g.extra)

    def graph(self, name: str, copies: int = 1) -> Graph:
        name = STAND_INS.get(name, name)
        if (name, 1) not in self.made:
            g = B.GRAPHS[name](self.spark, self.sf)
            edges = materialise(g.edges.sortWithinPartitions("src", "dst"), "graph")
            self.made[name, 1] = Graph(edges, materialise(g.extra, "graph-extra") if g.extra is not None else None, g.name)
            tidy(self.spark)
        return self.made[name, 1].copies(copies)


def run_one(spark: SparkSession, sf: str, graph: str, name: str, engine: str, sample: bool = False, copies: int = 1, data: Datasets | None = None, record: bool = False, **how) -> dict:
    """One cell: load, execute and save times, overhead, outcome, rounds, peak memory and network bytes.

    A run that fails raises its error. With ``record`` a failure that has a name among the outcomes gives a row with that
    outcome and without figures instead, so that it cannot be read as a measurement.
    ``copies`` runs on so many disjoint copies of the graph; ``sample`` adds peaks of CPU and I/O wait and bytes written.
    The graph is loaded from its edge files in ``data``, where given, else from the tables.
    """
    if data is not None:
        data.graph(graph)  # built before the clock starts
    rec, outcome, r, g = Recorder(f"{graph}/{name}/{engine}"), "OK", None, None
    sampler = Sampler(0.5)
    began = time.perf_counter()
    with sampler:
        try:
            with rec.phase("load"):
                g = data.graph(graph, copies) if data is not None else B.GRAPHS[STAND_INS.get(graph, graph)](spark, sf).copies(copies)
                g = Graph(g.edges.persist(), g.extra, g.name)
                edges = g.edges.count()
            with rec.phase("execute"):
                r = workload(name, g, engine, **how)
                r.df.write.format("noop").mode("overwrite").save()
            with rec.phase("save"):
                saved = table_path(spark, "result")
                r.df.write.parquet(saved)
        except Exception as e:  # noqa: BLE001 - classified, or raised again
            if not record:
                raise
            outcome = Outcome.classify(e, time.perf_counter() - began)
        finally:
            if g is not None:
                g.edges.unpersist()
    row = rec.finish().row()
    rounds = r.rounds if r else None
    if outcome == "OK":
        drop_table(saved, spark)  # only the figures are asked for
    r = g = None
    if row["total"] > SLOW:
        tidy(spark)
    if outcome != "OK":
        return {"graph": graph, "workload": name, "engine": engine, "outcome": outcome, "name": row["name"]}
    if sample:
        peak = lambda k: float(max((x[k] for x in sampler.samples), default=0.0))
        row |= {"user_max": peak("user"), "io_wait_max": peak("io_wait"), "disk_written": float(sampler.disk_written)}
    return {"graph": graph, "workload": name, "engine": engine, "edges": edges, "rounds": rounds, "outcome": outcome, **row, "peak_memory": float(sampler.peak_memory), "network": float(sampler.network)}


def matrix(spark: SparkSession, sf: str, graphs=("handoff",), workloads=WORKLOADS, engines=ENGINES, **how) -> DataFrame:
    """Runs as a table; a cell that fails by time, memory, messages or shuffle has that outcome and no figures."""
    with Datasets(spark, sf) as data:
        rows = [run_one(spark, sf, g, w, e, data=data, record=True, **{**SETTINGS.get(e, {}), **how}) for g, w, e in itertools.product(graphs, workloads, engines) if (e, w) not in SKIP]
    return table(spark, rows)


def table(spark: SparkSession, rows: list[dict]) -> DataFrame:
    schema = "graph string, workload string, engine string, edges long, rounds int, outcome string, name string, load double, execute double, save double, overhead double, total double, peak_memory double, network double"
    names = [c.split()[0] for c in schema.split(", ")]
    return spark.createDataFrame([tuple(r.get(n) for n in names) for r in rows], schema)


#: (label, graph, workload, engine, settings) of each ablation.
ABLATIONS = {
    "cut": [("random", "handoff", "pagerank", "gas", {"cut": "random", "machines": 16}), ("auto", "handoff", "pagerank", "gas", {"cut": "auto", "machines": 16})],
    "stop": [("I", "handoff", "pagerank", "gas", {"stop": "I"}), ("T", "handoff", "pagerank", "gas", {"stop": "T", "tol": 1e-3})],
    "mode": [("sync", "handoff", "pagerank", "gas", {}), ("async", "handoff", "pagerank", "gas-async", {})],
    "handoff": [("memory", "trade", "wcc", "block", {"handoff": "memory"}), ("storage", "trade", "wcc", "block", {"handoff": "storage"})],
    "loop_cache": [("all", "handoff", "pagerank", "mr-loop", {}), ("no_last", "handoff", "pagerank", "mr-loop", {"cache_last": False}), ("no_colocate", "handoff", "pagerank", "mr-loop", {"colocate": False}), ("none", "handoff", "pagerank", "mr-loop", {"cache_invariant": False}), ("memory", "handoff", "pagerank", "mr-loop", {"cache_level": "MEMORY_AND_DISK"})],
    "rdd_checkpoint": [("never", "handoff", "wcc", "rdd", {}), ("2", "handoff", "wcc", "rdd", {"checkpoint_every": 2}), ("10", "handoff", "wcc", "rdd", {"checkpoint_every": 10})],
    "wcc_method": [(m, "trade", "wcc", "vertex", {"method": m}) for m in ("min_label", "hash_to_min", "hook_jump", "star")],
    "update": [(f"{u}-{f}", "trade", "wcc", "sql", {"update": u, "frontier": f}) for u in ("replace", "merge", "auto", "memory") for f in ("temp", "filter")],
    "exact": [("exact", "social", "pagerank", "vertex", {"tol": 1e-3, "rounds": 100}), ("opt-out", "social", "pagerank_approx", "vertex", {"eps": 1e-3}), ("wake", "social", "pagerank_approx", "vertex", {"eps": 1e-3, "reactivate": True})],
    "blocks": [(f"{b}-{m}", "trade", "wcc", "block", {"blocks": b, "mode": m}) for b in ("voronoi", "mincut") for m in ("sync", "async")],
    "combiner": [("on", "trade", "wcc", "vertex", {}), ("off", "trade", "wcc", "vertex", {"combiner": False})],
}


def ablation(spark: SparkSession, sf: str, name: str) -> DataFrame:
    with Datasets(spark, sf) as data:
        rows = [run_one(spark, sf, g, w, e, data=data, **dict(how)) | {"name": label} for label, g, w, e, how in ABLATIONS[name]]
    return table(spark, rows).withColumn("ablation", F.lit(name))


def partition_sweep(spark: SparkSession, sf: str, counts=(4, 8, 16, 32)) -> DataFrame:
    """PageRank under several partition counts."""
    was = spark.conf.get("spark.sql.shuffle.partitions")
    rows = []
    try:
        with Datasets(spark, sf) as data:
            for n in counts:
                spark.conf.set("spark.sql.shuffle.partitions", n)
                rows.append(run_one(spark, sf, "handoff", "pagerank", "vertex", data=data) | {"name": str(n)})
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", was)
    return table(spark, rows)
