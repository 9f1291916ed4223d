"""Answers kept up to date on a stream of edges (insert only).

State lives in tables of changes: a micro-batch adds the rows that it touched as ``<state>/batch=N``, and every few batches
the newest row of each key is folded into ``<state>/base=N``. A batch that is run again writes the same number again, so
restarts do not count twice.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from bspframe.algos.contract import contract_components
from bspframe.algos.pagerank import pagerank
from bspframe.graph import Graph

#: Batches between two foldings of a table.
FOLD = 8


class Versions:
    """Rows by key with the changes of each micro-batch. Without ``keys`` a batch replaces the whole table."""

    def __init__(self, spark: SparkSession, path: str, schema: str, keys: tuple[str, ...] = (), fold: int = FOLD):
        self.spark, self.path, self.schema, self.keys, self.fold = spark, path, schema, keys, fold
        self._fs_path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path

    def _fs(self):
        p = self._fs_path(self.path)
        return p.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()), p

    def numbers(self, kind: str = "batch") -> list[int]:
        fs, p = self._fs()
        if not fs.exists(p):
            return []
        names = [s.getPath().getName() for s in fs.listStatus(p)]
        return sorted(int(n.split("=")[1]) for n in names if n.startswith(f"{kind}=") and fs.exists(self._fs_path(f"{self.path}/{n}/_SUCCESS")))

    def _read(self, name: str) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(f"{self.path}/{name}")

    def before(self, batch: int | None = None) -> DataFrame:
        """The rows as they were before ``batch`` (or are now)."""
        old = lambda kind: [n for n in self.numbers(kind) if batch is None or n < batch]
        known, base = old("batch"), old("base")
        if not known and not base:
            return self.spark.createDataFrame([], self.schema)
        if not self.keys:
            return self._read(f"batch={known[-1]}")
        parts = [(-1, self._read(f"base={base[-1]}"))] if base else []
        parts += [(n, self._read(f"batch={n}")) for n in known if not base or n > base[-1]]
        if len(parts) == 1:
            return parts[0][1]
        whole = None
        for n, df in parts:
            df = df.withColumn("_batch", F.lit(n))
            whole = df if whole is None else whole.union(df)
        rest = [c for c in whole.columns if c not in self.keys and c != "_batch"]
        if not rest:
            return whole.select(*self.keys).distinct()
        newest = whole.groupBy(*self.keys).agg(F.max_by(F.struct(*rest), "_batch").alias("_x"))
        return newest.select(*self.keys, *[F.col(f"_x.{c}").alias(c) for c in rest]).select(*[c for c in whole.columns if c != "_batch"])

    def put(self, changes: DataFrame, batch: int, keep: int = 2) -> None:
        changes.write.mode("overwrite").parquet(f"{self.path}/batch={batch}")
        fs, _ = self._fs()
        base = self.numbers("base")
        if not self.keys:
            gone = [f"batch={n}" for n in self.numbers()[:-keep]]
        elif len([n for n in self.numbers() if not base or n > base[-1]]) >= self.fold:
            self.before().write.mode("overwrite").parquet(f"{self.path}/base={batch}")
            gone = [f"base={n}" for n in base[:-1]] + [f"batch={n}" for n in self.numbers() if base and n <= base[-1]]
        else:
            gone = []
        for name in gone:
            fs.delete(self._fs_path(f"{self.path}/{name}"), True)


def _start(stream: DataFrame, each: Callable[[DataFrame, int], None], checkpoint: str, once: bool = True):
    w = stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint)
    q = (w.trigger(availableNow=True) if once else w).start()
    if once:
        q.awaitTermination()
    return q


def stream_components(stream: DataFrame, state: str, checkpoint: str, once: bool = True) -> Versions:
    """(id, component) after each batch: new edges are mapped to labels, those few labels are merged, and only members of
    merged components change and are written."""
    table = Versions(stream.sparkSession, state, "id BIGINT, component BIGINT", ("id",))

    def each(batch: DataFrame, number: int) -> None:
        old = table.before(number)
        e = batch.select("src", "dst").dropna().distinct().persist()
        ends = e.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
        fresh = ends.join(old, "id", "left_anti").select("id", F.col("id").alias("component"))
        known = old.unionByName(fresh)
        lab = lambda c: known.select(F.col("id").alias(c), F.col("component").alias(f"l{c}"))
        met = e.join(lab("src"), "src").join(lab("dst"), "dst").where("lsrc <> ldst").select(F.col("lsrc").alias("src"), F.col("ldst").alias("dst"))
        roots = contract_components(met).select(F.col("id").alias("component"), F.col("component").alias("root"))
        moved = old.join(roots.where("root <> component"), "component").select("id", F.col("root").alias("component"))
        new = fresh.join(roots, "component", "left").select("id", F.coalesce("root", "component").alias("component"))
        table.put(moved.union(new), number)
        e.unpersist()

    _start(stream, each, checkpoint, once)
    return table


def stream_degrees(stream: DataFrame, state: str, checkpoint: str, once: bool = True) -> Versions:
    """(id, out_degree, in_degree) after each batch; vertices of the batch are written, no others."""
    table = Versions(stream.sparkSession, state, "id BIGINT, out_degree BIGINT, in_degree BIGINT", ("id",))

    def each(batch: DataFrame, number: int) -> None:
        more = Graph.from_edges(batch.select("src", "dst")).degrees()
        old = table.before(number).select("id", F.col("out_degree").alias("_o"), F.col("in_degree").alias("_i"))
        sums = [(F.col(c) + F.coalesce(o, F.lit(0))).alias(c) for c, o in (("out_degree", "_o"), ("in_degree", "_i"))]
        table.put(more.join(old, "id", "left").select("id", *sums), number)

    _start(stream, each, checkpoint, once)
    return table


def stream_khop(stream: DataFrame, source: int, k: int, state: str, edges: str, checkpoint: str, once: bool = True) -> Versions:
    """(id, dist) within ``k`` hops after each batch: only what the new edges bring nearer is searched on."""
    spark = stream.sparkSession
    table, known = Versions(spark, state, "id BIGINT, dist INT", ("id",)), Versions(spark, edges, "src BIGINT, dst BIGINT", ("src", "dst"))

    def each(batch: DataFrame, number: int) -> None:
        e = known.before(number).union(batch.select("src", "dst").dropna()).distinct().persist()
        before = table.before(number)
        dist = before.union(spark.createDataFrame([(int(source), 0)], "id BIGINT, dist INT")).groupBy("id").agg(F.min("dist").alias("dist")).persist()
        front = dist.join(batch.select(F.col("src").alias("id")).distinct(), "id", "left_semi")
        for _ in range(k):
            offer = e.join(front.toDF("src", "d"), "src").where(F.col("d") < k).groupBy(F.col("dst").alias("id")).agg((F.min("d") + 1).alias("dist"))
            front = offer.join(dist.toDF("id", "old"), "id", "left").where("old is null or dist < old").select("id", "dist").persist()
            if front.isEmpty():
                break
            dist = dist.union(front).groupBy("id").agg(F.min("dist").alias("dist")).persist()
        known.put(batch.select("src", "dst").dropna().distinct(), number)
        table.put(dist.join(before.toDF("id", "_d"), "id", "left").where("_d is null or dist < _d").select("id", "dist"), number)
        e.unpersist()

    _start(stream, each, checkpoint, once)
    return table


def stream_pagerank(stream: DataFrame, state: str, edges: str, checkpoint: str, tol: float = 1e-3, once: bool = True) -> Versions:
    """(id, rank) after each batch, starting from the ranks of the batch before."""
    spark = stream.sparkSession
    table, known = Versions(spark, state, "id BIGINT, rank DOUBLE"), Versions(spark, edges, "src BIGINT, dst BIGINT", ("src", "dst"))

    def each(batch: DataFrame, number: int) -> None:
        known.put(batch.select("src", "dst").dropna().distinct(), number)
        g = Graph(known.before(number + 1))
        old = table.before(number).withColumnRenamed("rank", "value")
        start = g.vertices.join(old, "id", "left").select("id", F.coalesce("value", F.lit(1.0)).alias("value"), F.lit(True).alias("changed"))
        table.put(pagerank(g, tol=tol, start=start).df, number)

    _start(stream, each, checkpoint, once)
    return table


def windowed_edges(stream: DataFrame, size: str, slide: str | None = None, gap: str | None = None) -> DataFrame:
    """Edge counts by tumbling or sliding window, or by session with ``gap``; the stream must carry a watermark on ts."""
    w = F.session_window("ts", gap) if gap else F.window("ts", size, slide) if slide else F.window("ts", size)
    return stream.groupBy(w.alias("w"), "src", "dst").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "src", "dst", "n")


def dedupe_edges(stream: DataFrame) -> DataFrame:
    """The same edge again within the watermark is dropped."""
    return stream.dropDuplicatesWithinWatermark(["src", "dst"])


def to_table(stream: DataFrame, path: str, checkpoint: str, mode: str = "append"):
    """Write a stream to a parquet folder until its input is used up."""
    q = stream.writeStream.format("parquet").outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start(path)
    q.awaitTermination()
    return q


def late_rows(query) -> int:
    """Rows that a finished query dropped for being late."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for op in (p.get("stateOperators", []) if isinstance(p, dict) else []))
