"""Hand graphs with exact answers, and a DuckDB connection over the tables."""

from bspframe.graph import Graph

HAND = {
    # name: edges, extra vertices, ranks at the fixpoint, components, distances from 0
    "path3": ([(0, 1), (1, 2)], [], {0: 0.15, 1: 0.2775, 2: 0.385875}, {0: 0, 1: 0, 2: 0}, {0: 0, 1: 1, 2: 2}),
    "cycle2": ([(0, 1), (1, 0)], [], {0: 1, 1: 1}, {0: 0, 1: 0}, {0: 0, 1: 1}),
    "in_star": ([(1, 0), (2, 0), (3, 0)], [], {0: 0.15 + 0.1275 * 3, 1: 0.15, 2: 0.15, 3: 0.15}, dict.fromkeys(range(4), 0), {0: 0}),
    "self_loop": ([(0, 0), (0, 1)], [], {0: 0.260870, 1: 0.260870}, {0: 0, 1: 0}, {0: 0, 1: 1}),
    "parallel": ([(0, 1), (0, 1), (0, 2)], [], {0: 0.15, 1: 0.235, 2: 0.1925}, dict.fromkeys(range(3), 0), {0: 0, 1: 1, 2: 1}),
    "two_triangles": ([(0, 1), (1, 2), (2, 0), (3, 4), (4, 5), (5, 3)], [], dict.fromkeys(range(6), 1), {0: 0, 1: 0, 2: 0, 3: 3, 4: 3, 5: 3}, {0: 0, 1: 1, 2: 2}),
    "against": ([(1, 0), (2, 1)], [9], {0: 0.385875, 1: 0.2775, 2: 0.15, 9: 0.15}, {0: 0, 1: 0, 2: 0, 9: 9}, {0: 0}),
    "fork": ([(2, 0), (2, 1)], [], {0: 0.21375, 1: 0.21375, 2: 0.15}, {0: 0, 1: 0, 2: 0}, {0: 0}),
}


def hand(spark, name):
    edges, extra = HAND[name][:2]
    x = spark.createDataFrame([(i,) for i in extra], "id long") if extra else None
    return Graph.from_edges(spark.createDataFrame(edges, "src long, dst long"), extra=x, name=name)


def duck(sf):
    import duckdb

    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.sql(f"create view {t} as select * from read_parquet('{sf}/{t}.parquet')")
    return con


def same(con, sql, df):
    """Rows of a query and of its SQL counterpart, both sorted as text."""
    cols = sorted(df.columns)
    want = con.sql(f"select {', '.join(cols)} from ({sql})").fetchall()
    got = [tuple(r[c] for c in cols) for r in df.collect()]
    return sorted(map(str, got)) == sorted(map(str, want))
