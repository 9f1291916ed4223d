"""Graphs built from the given tables; ``SQL`` has each one's edge query for the SQL counterparts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from bspframe.functions.ids import id_table
from bspframe.graph import Graph
from bspframe.sources.tables import read_table


def _g(df: DataFrame, name: str, **how) -> Graph:
    return Graph.from_edges(df, name=name, **how)


def co_purchase(spark: SparkSession, sf: str) -> Graph:
    """Parts bought on one order, low to high; a part on one order twice or more gets a self-edge."""
    lines = read_table(spark, sf, "lineitem").select("l_orderkey", "l_partkey").repartition("l_orderkey")  # dealt once, for both groupings
    once = lines.groupBy("l_orderkey", "l_partkey").agg(F.count("*").alias("n"))
    lists = once.groupBy("l_orderkey").agg(F.array_sort(F.collect_list(F.struct(F.col("l_partkey").alias("p"), "n"))).alias("ps"))
    pairs = lists.select(F.explode(F.expr("flatten(transform(ps, (a, i) -> transform(filter(ps, (b, j) -> j > i or (j = i and a.n > 1)), b -> struct(a.p as src, b.p as dst))))")).alias("e"))
    return _g(pairs.select("e.src", "e.dst").distinct(), "co_purchase")


def trade(spark: SparkSession, sf: str, distinct: bool = True) -> Graph:
    """Customer (2k) to supplier (2k+1)."""
    o = read_table(spark, sf, "orders").select("o_orderkey", "o_custkey")
    li = read_table(spark, sf, "lineitem").select("l_orderkey", "l_suppkey")
    e = o.join(li, o.o_orderkey == li.l_orderkey).select((F.col("o_custkey") * 2).alias("src"), (F.col("l_suppkey") * 2 + 1).alias("dst"))
    return _g(e.distinct() if distinct else e, "trade")


def supply(spark: SparkSession, sf: str, distinct: bool = True) -> Graph:
    """Supplier (2k+1) to part (2k)."""
    e = read_table(spark, sf, "lineitem").select((F.col("l_suppkey") * 2 + 1).alias("src"), (F.col("l_partkey") * 2).alias("dst"))
    return _g(e.distinct() if distinct else e, "supply")


def _lead(df: DataFrame, by: list[str], order: list, value: str) -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*order)
    return df.withColumn("dst", F.lead(value).over(w)).where("dst is not null").select(F.col(value).alias("src"), "dst", *[c for c in df.columns if c == "ts"])


def handoff(spark: SparkSession, sf: str, keep_ts: bool = False) -> Graph | DataFrame:
    """User of an event to the user of the next event by (ts, event_id).

    The global order is cut at days; each day's last event is joined to the next day's first.
    """
    ev = read_table(spark, sf, "events").select("event_id", "ts", "user_id").withColumn("day", F.to_date("ts"))
    inside = Window.partitionBy("day").orderBy("ts", "event_id")
    marked = ev.withColumn("dst", F.lead("user_id").over(inside))
    firsts = ev.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"))
    days = firsts.withColumn("next_first", F.lead("first").over(Window.orderBy("day"))).select("day", "next_first")  # one row for each day
    full = marked.join(days, "day").withColumn("dst", F.coalesce("dst", "next_first")).where("dst is not null").select(F.col("user_id").alias("src"), "dst", "ts")
    return full if keep_ts else _g(full.select("src", "dst").distinct(), "handoff")


def session_chains(spark: SparkSession, sf: str) -> Graph:
    """Event to the same user's next event."""
    ev = read_table(spark, sf, "events").select("event_id", "ts", "user_id")
    return _g(_lead(ev, ["user_id"], ["ts", "event_id"], "event_id").select("src", "dst"), "session_chains", extra=ev.select(F.col("event_id").alias("id")))


def order_ladder(spark: SparkSession, sf: str) -> Graph:
    """Order to the same customer's next order, and a customer's first order to the next customer's first."""
    o = read_table(spark, sf, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    chain = _lead(o, ["o_custkey"], ["o_orderdate", "o_orderkey"], "o_orderkey").select("src", "dst")
    first = o.groupBy("o_custkey").agg(F.min_by("o_orderkey", F.struct("o_orderdate", "o_orderkey")).alias("f"))
    # customers are dealt to ranges of their key; a range's last row meets the next range's first
    bucket = F.floor(F.col("o_custkey") / 1000)
    inside = Window.partitionBy("b").orderBy("o_custkey")
    led = first.withColumn("b", bucket).withColumn("dst", F.lead("f").over(inside))
    heads = led.groupBy("b").agg(F.min_by("f", "o_custkey").alias("h"))
    heads = heads.withColumn("nh", F.lead("h").over(Window.orderBy("b"))).select("b", "nh")
    steps = led.join(heads, "b").select(F.col("f").alias("src"), F.coalesce("dst", "nh").alias("dst")).where("dst is not null")
    return _g(chain.union(steps), "order_ladder")


def _page_tokens(spark: SparkSession, sf: str) -> DataFrame:
    p = read_table(spark, sf, "pages").select("page_id", "html")
    return p.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("token")).distinct()


def page_links(spark: SparkSession, sf: str) -> Graph:
    """Page (2k) to href token (2r+1, r = rank of the token)."""
    t = _page_tokens(spark, sf)
    ids = id_table(t, ["token"]).select(F.col("key").alias("token"), F.col("id").alias("r"))  # numbered by ranges, joined by shuffle
    e = t.join(ids, "token").select((F.col("page_id") * 2).alias("src"), (F.col("r") * 2 + 1).cast("long").alias("dst"))
    return _g(e, "page_links")


def doc_terms(spark: SparkSession, sf: str) -> Graph:
    """Document (2k) to token hash (2h+1): lower-cased words of letters, two characters or more."""
    d = read_table(spark, sf, "documents").select("doc_id", "text")
    words = F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}{2,})"), 1))
    t = d.select("doc_id", F.explode(words).alias("token"))
    h = F.conv(F.substring(F.md5("token"), 1, 13), 16, 10).cast("long")
    return _g(t.select((F.col("doc_id") * 2).alias("src"), (h * 2 + 1).alias("dst")), "doc_terms")


def geo_hub(spark: SparkSession, sf: str) -> Graph:
    """Customer (3k) to nation (3k+1) to region (3k+2)."""
    c = read_table(spark, sf, "customer").select((F.col("c_custkey") * 3).alias("src"), (F.col("c_nationkey") * 3 + 1).cast("long").alias("dst"))
    n = read_table(spark, sf, "nation").select((F.col("n_nationkey") * 3 + 1).cast("long").alias("src"), (F.col("n_regionkey") * 3 + 2).cast("long").alias("dst"))
    return _g(c.union(n), "geo_hub")


def turn_chains(spark: SparkSession, sf: str) -> Graph:
    """Turn of a conversation to the next turn."""
    t = read_table(spark, sf, "conversations").select("conv_id", "turn").distinct().withColumn("id", F.col("conv_id") * 1000 + F.col("turn"))
    return _g(_lead(t, ["conv_id"], ["turn"], "id").select("src", "dst"), "turn_chains", extra=t.select("id"))


def knn(spark: SparkSession, sf: str, k: int = 5) -> Graph:
    """Each embedding to its k nearest others by cosine, ties by id."""
    from bspframe.operators.knn import knn_edges

    return _g(knn_edges(read_table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), "embedding"), k).select("src", "dst"), "knn")


def near_dup(spark: SparkSession, sf: str) -> Graph:
    """Documents with equal texts: each to the least id of its text."""
    d = read_table(spark, sf, "documents").select("doc_id", F.md5("text").alias("h"))
    low = d.groupBy("h").agg(F.min("doc_id").alias("low"))
    return _g(d.join(low, "h").where("doc_id <> low").select(F.col("doc_id").alias("src"), F.col("low").alias("dst")), "near_dup", extra=d.select(F.col("doc_id").alias("id")))


GRAPHS = {f.__name__: f for f in (co_purchase, trade, supply, handoff, session_chains, order_ladder, page_links, doc_terms, geo_hub, turn_chains, knn, near_dup)}

#: DuckDB edge queries (src, dst); vertices beyond the edges' ends are in EXTRA.
SQL = {
    "co_purchase": """WITH op AS (SELECT l_orderkey o, l_partkey p, count(*) n FROM lineitem GROUP BY ALL)
        SELECT DISTINCT a.p AS src, b.p AS dst FROM op a JOIN op b ON a.o = b.o AND (a.p < b.p OR (a.p = b.p AND a.n > 1))""",
    "trade": "SELECT DISTINCT o_custkey * 2 AS src, l_suppkey * 2 + 1 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "trade_multi": "SELECT o_custkey * 2 AS src, l_suppkey * 2 + 1 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "supply": "SELECT DISTINCT l_suppkey * 2 + 1 AS src, l_partkey * 2 AS dst FROM lineitem",
    "handoff": "SELECT DISTINCT user_id AS src, nxt AS dst FROM (SELECT user_id, lead(user_id) OVER (ORDER BY ts, event_id) AS nxt FROM events) WHERE nxt IS NOT NULL",
    "session_chains": "SELECT event_id AS src, nxt AS dst FROM (SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nxt FROM events) WHERE nxt IS NOT NULL",
    "order_ladder": """SELECT o_orderkey AS src, nxt AS dst FROM (SELECT o_orderkey, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS nxt FROM orders) WHERE nxt IS NOT NULL
        UNION ALL SELECT f, nf FROM (SELECT f, lead(f) OVER (ORDER BY o_custkey) AS nf FROM (SELECT o_custkey, arg_min(o_orderkey, (o_orderdate, o_orderkey)) AS f FROM orders GROUP BY o_custkey)) WHERE nf IS NOT NULL""",
    "page_links": """WITH t AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS token FROM pages),
        r AS (SELECT token, row_number() OVER (ORDER BY token) - 1 AS r FROM (SELECT DISTINCT token FROM t))
        SELECT page_id * 2 AS src, (r * 2 + 1)::BIGINT AS dst FROM t JOIN r USING (token)""",
    "doc_terms": r"""SELECT DISTINCT doc_id * 2 AS src, ('0x' || md5(token)[1:13])::BIGINT * 2 + 1 AS dst
        FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '(\p{L}{2,})', 1)) AS token FROM documents)""",
    "geo_hub": """SELECT c_custkey * 3 AS src, (c_nationkey * 3 + 1)::BIGINT AS dst FROM customer
        UNION ALL SELECT (n_nationkey * 3 + 1)::BIGINT, (n_regionkey * 3 + 2)::BIGINT FROM nation""",
    "turn_chains": """SELECT id AS src, nxt AS dst FROM (SELECT id, lead(id) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt
        FROM (SELECT DISTINCT conv_id, turn, conv_id * 1000 + turn AS id FROM conversations)) WHERE nxt IS NOT NULL""",
    "knn": """SELECT src, dst FROM (SELECT a.vec_id AS src, b.vec_id AS dst, row_number() OVER (PARTITION BY a.vec_id ORDER BY
        round(list_dot_product(a.v, b.v) / sqrt(list_dot_product(a.v, a.v)) / sqrt(list_dot_product(b.v, b.v)), 9) DESC, b.vec_id) AS k
        FROM (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings) a JOIN (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings) b ON a.vec_id <> b.vec_id) WHERE k <= 5""",
    "near_dup": "SELECT doc_id AS src, low AS dst FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY md5(text)) AS low FROM documents) WHERE doc_id <> low",
}
EXTRA = {
    "session_chains": "SELECT event_id AS id FROM events",
    "turn_chains": "SELECT DISTINCT conv_id * 1000 + turn AS id FROM conversations",
    "near_dup": "SELECT doc_id AS id FROM documents",
}


def both_ways(name: str) -> str:
    return f"SELECT src, dst FROM ({SQL[name]}) UNION ALL SELECT dst, src FROM ({SQL[name]})"
