"""Edge sources and sinks: edge text, adjacency text in two forms, parquet chunks, bucketed tables, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.types import StructType

from bspframe.graph import Graph

EDGE_SCHEMA = "src BIGINT, dst BIGINT"
MB = 1 << 20


def _numbers(spark: SparkSession, path: str) -> DataFrame:
    """Lines of numbers as arrays; blank lines and lines that begin with # are skipped."""
    lines = spark.read.text(path).select(F.trim("value").alias("v")).where("v <> '' and not startswith(v, '#')")
    return lines.select(F.transform(F.split("v", r"[\s,]+"), lambda x: x.cast("long")).alias("n"))


def read_edges(spark: SparkSession, path: str, sep: str = r"\s+") -> Graph:
    """One edge on a line: source, target and perhaps a weight."""
    lines = spark.read.text(path).select(F.trim("value").alias("v")).where("v <> '' and not startswith(v, '#')")
    p = lines.select(F.split("v", sep).alias("p"))
    e = p.select(F.get("p", F.lit(0)).cast("long").alias("src"), F.get("p", F.lit(1)).cast("long").alias("dst"), F.get("p", F.lit(2)).cast("double").alias("w"))
    weighted = not e.where("w is not null").isEmpty()
    return Graph.from_edges(e if weighted else e.drop("w"))


def explode_adj(lines: DataFrame) -> DataFrame:
    """(id, nbrs) lines to (src, dst) rows."""
    return lines.select(F.col("id").alias("src"), F.explode("nbrs").alias("dst"))


def read_adj(spark: SparkSession, path: str) -> Graph:
    """A vertex and its neighbours on a line; a vertex without out-edges may have no line."""
    n = _numbers(spark, path).select(F.get("n", F.lit(0)).alias("id"), F.slice("n", F.lit(2), F.greatest(F.size("n") - 1, F.lit(0))).alias("nbrs"))
    return Graph.from_edges(explode_adj(n), extra=n.select("id"))


def read_adj_long(spark: SparkSession, path: str) -> Graph:
    """A vertex, the number of its neighbours and the neighbours on a line, for every vertex; a wrong number is an error."""
    n = _numbers(spark, path)
    got = n.select(F.get("n", F.lit(0)).alias("id"), F.get("n", F.lit(1)).alias("deg"), F.slice("n", F.lit(3), F.greatest(F.size("n") - 2, F.lit(0))).alias("nbrs"))
    wrong = F.raise_error(F.concat(F.lit("stated neighbour count does not fit at vertex "), F.col("id").cast("string"))).cast("array<bigint>")
    got = got.withColumn("nbrs", F.when(F.col("deg") == F.size("nbrs"), F.col("nbrs")).otherwise(wrong))
    return Graph.from_edges(explode_adj(got), extra=got.select("id"))


def save(what: Graph | DataFrame, path: str, form: str = "parquet", mode: str = "errorifexists") -> None:
    """``parquet``, ``csv`` and ``json`` for any result; ``edge``, ``adj`` and ``adj_long`` text for graphs."""
    text = lambda a: F.transform(a, lambda x: x.cast("string"))
    if isinstance(what, Graph):
        if form == "edge":
            df = what.edges.select(F.concat_ws(" ", *[F.col(c).cast("string") for c in what.edges.columns]).alias("value"))
        elif form == "adj":
            df = what.adjacency().select(F.concat_ws(" ", F.col("id").cast("string"), text("nbrs")).alias("value"))
        elif form == "adj_long":
            df = what.adjacency_long().select(F.concat_ws(" ", F.col("id").cast("string"), F.col("deg").cast("string"), text("nbrs")).alias("value"))
        else:
            return save(what.edges, path, form, mode)
        df.write.mode(mode).text(path)
        return None
    getattr(what.write.mode(mode), form)(path)
    return None


def write_chunks(df: DataFrame, path: str, chunk_bytes: int = 64 * MB, row_bytes: int = 16, key: str | None = None) -> int:
    """Parquet files of similar size; returns how many were asked for."""
    n = max(1, -(-df.count() * row_bytes // chunk_bytes))
    dealt = df.repartitionByRange(n, key) if key else df.repartition(n)
    dealt.write.option("maxRecordsPerFile", max(1, 2 * chunk_bytes // row_bytes)).parquet(path)
    return n


def save_bucketed(g: Graph, name: str, p: int) -> DataFrame:
    """Edges as a table bucketed and sorted by source, so that joins on it need no exchange of the edges.

    One task for each bucket writes, so there is one file a bucket and open files stay bounded.
    """
    g.edges.repartition(p, "src").write.bucketBy(p, "src").sortBy("src").mode("overwrite").saveAsTable(name)
    return g.spark.table(name)


def read_edge_stream(spark: SparkSession, path: str, schema: str | StructType = "src BIGINT, dst BIGINT, ts TIMESTAMP", late: str | None = "10 minutes", files_per_trigger: int | None = None) -> DataFrame:
    """Edges as they arrive in a folder of parquet files; edges later than ``late`` are dropped by stateful operators."""
    reader = spark.readStream.schema(schema)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    s = reader.parquet(path)
    return s.withWatermark("ts", late) if late else s


def read_event_log(spark: SparkSession, path: str) -> DataFrame:
    """Task metrics of an event log: stage, task times, shuffle and spill bytes."""
    j = spark.read.schema(
        "Event STRING, `Stage ID` INT, `Task Info` STRUCT<`Launch Time`: BIGINT, `Finish Time`: BIGINT, `Executor ID`: STRING>, "
        "`Task Metrics` STRUCT<`Executor Run Time`: BIGINT, `Executor CPU Time`: BIGINT, `JVM GC Time`: BIGINT, `Disk Bytes Spilled`: BIGINT, "
        "`Shuffle Read Metrics`: STRUCT<`Remote Bytes Read`: BIGINT, `Local Bytes Read`: BIGINT>, `Shuffle Write Metrics`: STRUCT<`Shuffle Bytes Written`: BIGINT>>"
    ).json(path)
    m = "`Task Metrics`"
    return j.where("Event = 'SparkListenerTaskEnd'").select(
        F.col("`Stage ID`").alias("stage"), F.col("`Task Info`.`Executor ID`").alias("executor"), F.col("`Task Info`.`Launch Time`").alias("launched"),
        F.col(f"{m}.`Executor Run Time`").alias("run_ms"), (F.col(f"{m}.`Executor CPU Time`") / 1e6).alias("cpu_ms"), F.col(f"{m}.`JVM GC Time`").alias("gc_ms"),
        (F.col(f"{m}.`Shuffle Read Metrics`.`Remote Bytes Read`") + F.col(f"{m}.`Shuffle Read Metrics`.`Local Bytes Read`")).alias("shuffle_read"),
        F.col(f"{m}.`Shuffle Write Metrics`.`Shuffle Bytes Written`").alias("shuffle_written"), F.col(f"{m}.`Disk Bytes Spilled`").alias("spilled"),
    )


def format_bytes(g: Graph, base: str) -> dict[str, int]:
    """Bytes of the three text forms, written under ``base``."""
    jvm, conf = g.spark.sparkContext._jvm, g.spark.sparkContext._jsc.hadoopConfiguration()
    out = {}
    for form in ("edge", "adj", "adj_long"):
        save(g, f"{base}/{form}", form, "overwrite")
        p = jvm.org.apache.hadoop.fs.Path(f"{base}/{form}")
        out[form] = p.getFileSystem(conf).getContentSummary(p).getLength()
    return out
