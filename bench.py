"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = int(os.environ.get("BENCH_CPUS", "8"))


def main() -> None:
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", str(CPUS)).config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "12g"))
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from bspframe import builders as B
    from bspframe.algos.pagerank import pagerank
    from bspframe.algos.sssp import khop, sssp
    from bspframe.algos.wcc import wcc
    from bspframe.graph import Graph

    def loaded(name: str, both: bool = False) -> Graph:
        g = B.GRAPHS[name](spark, SF)
        g = g.undirect() if both else g
        e = g.edges.persist()
        e.count()
        return Graph(e, g.extra, g.name)

    seconds: dict[str, float] = {}

    def timed(name: str, fn) -> None:
        at = time.perf_counter()
        fn().df.write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - at, 3)

    at = time.perf_counter()
    social, web, road, terms, ladder, hand = (loaded(*x) for x in (("co_purchase",), ("page_links", True), ("session_chains",), ("doc_terms", True), ("order_ladder",), ("handoff",)))
    seconds["load_all"] = round(time.perf_counter() - at, 3)
    head = ladder.edges.selectExpr("min(src)").first()[0]
    for key, g in (("social", social), ("web", web), ("road", road), ("bigweb", terms)):
        timed(f"pr_{key}", lambda g=g: pagerank(g, max_rounds=20))
        timed(f"wcc_{key}", lambda g=g: wcc(g))
        timed(f"sssp_{key}", lambda g=g: sssp(g, 0))
        timed(f"khop3_{key}", lambda g=g: khop(g, 0, 3))
    timed("wcc_ladder", lambda: wcc(ladder))
    timed("khop3_ladder", lambda: khop(ladder, head, 3))
    timed("sssp_ladder", lambda: sssp(ladder, head, method="auto"))
    timed("sssp_road_contract", lambda: sssp(road, 0, method="contract"))
    for engine in ("vertex", "gas", "sql", "mr", "mr-loop", "rdd", "dataflow", "single"):
        timed(f"pr_handoff_{engine}", lambda e=engine: pagerank(hand, max_rounds=10, engine=e))
    for engine in ("vertex", "block", "gas", "mr-loop", "single"):
        timed(f"wcc_social_{engine}", lambda e=engine: wcc(social, engine=e, method="min_label"))
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": SF.rsplit("sf", 1)[-1]}))
    spark.stop()


if __name__ == "__main__":
    main()
