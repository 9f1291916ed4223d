"""One SQL statement a round over vertex and edge tables; and one recursive statement for shallow searches."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import DataFrame, Observation, SparkSession, functions as F

from bspframe.engines.program import Program, first_state, message_edges
from bspframe.engines.vertex import CHANGE
from bspframe.graph import Graph, Result
from bspframe.loop import RoundStat
from bspframe.session import cut, drop_table, materialise, table_path


def run_sql(g: Graph, p: Program, update: str = "auto", frontier: str = "temp", share: float = 0.2) -> Result:
    """Join the vertex table with the edge table, make the new answer column, and put it in place.

    ``update``: replace (write the whole vertex table anew), merge (keep unchanged rows, add the changed), auto (merge while
    fewer than ``share`` of the rows changed last round), memory (views only). ``frontier``: temp (a table of active
    vertices starts the join) or filter (a predicate on the vertex table).
    """
    spark = g.spark
    tag = uuid.uuid4().hex[:8]
    vertex, edge, active = f"vertex_{tag}", f"edge_{tag}", f"active_{tag}"
    n, files = int(spark.conf.get("spark.sql.shuffle.partitions")), table_path(spark, "edge-table")
    # clustered by the join's key, so that no round moves it
    message_edges(g, p).repartition(n, "src").write.bucketBy(n, "src").sortBy("src").option("path", files).saveAsTable(edge)
    keep = _viewed if update == "memory" else (lambda df: (materialise(df, "vertex-table"), None))
    table, cached = keep(first_state(g, p).withColumn("old", F.col("value")))
    total = table.count()
    stats, number, last = [], 0, total
    combine = {"sum": "sum", "min": "min", "max": "max"}[p.combine]
    while number < p.max_rounds:
        number += 1
        began = time.perf_counter()
        table.createOrReplaceTempView(vertex)
        source, only = vertex, ""
        if p.frontier and frontier == "temp":
            senders, sending = keep(spark.sql(f"SELECT id, value FROM {vertex} WHERE changed"))
            senders.createOrReplaceTempView(active)
            source = active
        elif p.frontier:
            only = "WHERE s.changed"
        hint = f"/*+ BROADCAST(s) */" if source == active and last <= 10_000 else ""
        answer = spark.sql(f"""
            SELECT v.id, {p.apply.replace("value", "v.value").replace("msg", "a.msg")} AS value, v.value AS old
            FROM {vertex} v LEFT JOIN (
                SELECT {hint} e.dst AS id, {combine}(CAST({p.send.replace("value", "s.value")} AS {p.kind})) AS msg
                FROM {edge} e JOIN {source} s ON e.src = s.id {only} GROUP BY e.dst) a ON v.id = a.id""")
        answer = answer.select("id", F.col("value").cast(p.kind).alias("value"), "old").withColumn("changed", F.expr(p.changed)).select("id", "value", "changed", "old")
        how = update if update != "auto" else ("merge" if last <= share * total and number > 1 else "replace")
        if how == "merge":
            answer = answer.persist()
            answer.where("changed").createOrReplaceTempView(f"change_{tag}")
            answer_full = answer
            answer = spark.sql(f"SELECT v.id, v.value, false AS changed, v.value AS old FROM {vertex} v LEFT ANTI JOIN change_{tag} c ON v.id = c.id UNION ALL SELECT id, value, changed, old FROM change_{tag}")
        seen = Observation()
        fresh = answer.observe(seen, F.count_if("changed").alias("changed"), F.coalesce(F.max(F.expr(CHANGE)), F.lit(0.0)).alias("change"))
        fresh, held = keep(fresh)
        got = seen.get
        if how == "merge":
            answer_full.unpersist()
        if update == "memory":
            cached.unpersist()
            if source == active:
                sending.unpersist()
        else:
            drop_table(table)
            if source == active:
                drop_table(senders)
        table, cached, last = fresh, held, got["changed"]
        stats.append(RoundStat(number, last, last, float(got["change"]), time.perf_counter() - began))
        if p.halt(stats[-1]):
            break
    for name in (vertex, active, f"change_{tag}"):
        spark.catalog.dropTempView(name)
    if update != "memory":  # there the answer is what was written; views may be computed anew
        spark.sql(f"DROP TABLE {edge}")
        drop_table(files, spark)
    return Result(table.select("id", "value"), number, stats)


def _viewed(df: DataFrame) -> tuple[DataFrame, DataFrame]:
    """``df`` computed and kept by the executors: as it is to be read, and as it is to be let go."""
    df = df.persist()
    df.write.format("noop").mode("overwrite").save()
    return cut(df), df


def run_recursive_sql(spark: SparkSession, g: Graph, source: int, k: int) -> DataFrame:
    """K-hop by one recursive statement. It repeats walks, so it is for shallow searches only."""
    tag = uuid.uuid4().hex[:8]
    g.edges.select("src", "dst").distinct().createOrReplaceTempView(f"e_{tag}")
    return spark.sql(f"""
        WITH RECURSIVE walk(id, dist) AS (
            SELECT CAST({int(source)} AS BIGINT), 0
            UNION ALL SELECT e.dst, w.dist + 1 FROM walk w JOIN e_{tag} e ON e.src = w.id WHERE w.dist < {int(k)})
        SELECT id, min(dist) AS dist FROM walk GROUP BY id""")
