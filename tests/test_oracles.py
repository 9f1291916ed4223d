"""A share of the registered queries against their SQL counterparts on the smallest tables."""

import pytest

from bspframe import queries as Q
from tests.helpers import duck, same

NAMES = [
    "pr_handoff", "pr_selfedge_drop", "pr_sql", "pr_single", "wcc_road", "wcc_hub", "wcc_dup", "wcc_turns", "wcc_block", "wcc_sql_merge", "wcc_forward_only", "sssp_handoff", "sssp_diropt", "khop3_web",
    "khop_many_social", "khop_recursive", "rf_random", "rf_grid", "rf_pds", "partition_rule", "blocks_url", "block_graph", "block_stats", "blocks_2d", "graph_stats_trade", "graph_stats_page_links", "adj_trade",
    "adj_long_trade", "interval_edges", "asof_edges", "encode_ids", "stream_components", "stream_degrees", "report_cube", "diameter_road", "property_edges",
]


@pytest.fixture(scope="module")
def con(sf):
    return duck(sf)


@pytest.mark.parametrize("name", NAMES)
def test_oracle(spark, sf, con, name):
    assert same(con, Q.ORACLES[name], Q.QUERIES[name](spark, sf))


def test_many_sources_over_the_whole_table(spark, sf, con):
    """Every source whose id is divisible by 50, against its SQL and against plain breadth-first search."""
    from bspframe import builders as B

    got = Q.QUERIES["khop_many_every50_social"](spark, sf)
    assert same(con, Q.ORACLES["khop_many_every50_social"], got)
    out: dict = {}
    for a, b in B.co_purchase(spark, sf).edges.select("src", "dst").collect():
        out.setdefault(a, set()).add(b)
    want = set()
    for (v,) in con.sql("select p_partkey from part where p_partkey % 50 = 0").fetchall():
        seen, front = {v: 0}, {v}
        for k in (1, 2):
            front = {y for x in front for y in out.get(x, ())} - seen.keys()
            seen.update(dict.fromkeys(front, k))
        want |= {(v, i, n) for i, n in seen.items()}
    assert {(r["source"], r["id"], r["dist"]) for r in got.collect()} == want and max(w[0] for w in want) >= 50


def test_tolerance_run_has_its_rounds(spark, sf):
    from bspframe import builders as B
    from bspframe.algos.pagerank import pagerank

    r = pagerank(B.co_purchase(spark, sf), tol=Q.TOL)
    assert r.stats[-1].max_change < Q.TOL <= r.stats[-2].max_change


def test_every_query_without_the_text_operators_is_registered():
    assert len(Q.QUERIES) > 150 and not any(n.startswith("op") for n in Q.QUERIES)
