"""Session helpers: shipping the package to executors and finding the shared folder."""

from __future__ import annotations

import gc
import io
import os
import tempfile
import uuid
import zipfile

from pyspark.sql import DataFrame, Observation, SparkSession, functions as F

_PACKAGE = os.path.dirname(os.path.abspath(__file__))


def ship(spark: SparkSession) -> None:
    """Make this package importable by Python workers of any executor.

    The sources go into one zip in the shared folder, once for each application, so that no executor needs a copy of
    the repository.
    """
    sc = spark.sparkContext
    if getattr(sc, "_bspframe_shipped", False):
        return
    packed = io.BytesIO()
    with zipfile.ZipFile(packed, "w") as z:
        for top, _, names in os.walk(_PACKAGE):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(top, name)
                    z.write(full, os.path.relpath(full, os.path.dirname(_PACKAGE)))
    target = f"{shared_dir(spark).rstrip('/')}/bspframe/code-{uuid.uuid4().hex}/bspframe.zip"
    path = sc._jvm.org.apache.hadoop.fs.Path(target)
    out = path.getFileSystem(sc._jsc.hadoopConfiguration()).create(path)
    out.write(bytearray(packed.getvalue()))
    out.close()
    sc.addPyFile(target)
    sc._bspframe_shipped = True


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` of the session.

    Only under a local master, where driver and executors are one machine, is a temporary folder made where it is unset.
    """
    sc = spark.sparkContext
    base = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
    if not base:
        base = getattr(sc, "_bspframe_shared", None)
        if base is None:
            if not sc.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
            base = sc._bspframe_shared = "file://" + tempfile.mkdtemp(prefix="bspframe-")
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        sc.setCheckpointDir(base)
    return base


def table_path(spark: SparkSession, name: str) -> str:
    """A fresh path in the shared folder."""
    return f"{shared_dir(spark).rstrip('/')}/bspframe/{name}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = table_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def materialise_counting(df: DataFrame, name: str, **counts: str) -> tuple[DataFrame, dict[str, int]]:
    """As :func:`materialise`; the same job counts the rows for which each of the SQL conditions ``counts`` holds."""
    seen = Observation()
    path = table_path(df.sparkSession, name)
    df.observe(seen, *[F.count_if(F.expr(sql)).alias(k) for k, sql in counts.items()]).write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path), seen.get


def checkpointed(df: DataFrame) -> DataFrame:
    """``df.checkpoint()`` without the size estimate that it inherits.

    A checkpoint keeps the estimated size of its plan, which multiplies at every join: after k rounds of a loop the figure
    has some 2**k digits, and planning takes longer than the round. The same files, partitioning and order are
    wrapped anew with an unknown size.
    """
    shared_dir(df.sparkSession)
    done = df.checkpoint(eager=True)
    plan = done._jdf.queryExecution().analyzed()
    if plan.getClass().getSimpleName() != "LogicalRDD":
        return done
    jvm = df.sparkSession.sparkContext._jvm
    none = jvm.scala.Option.empty()
    session = done._jdf.sparkSession()
    bare = jvm.org.apache.spark.sql.execution.LogicalRDD(plan.output(), plan.rdd(), plan.outputPartitioning(), plan.outputOrdering(), False, plan.stream(), session, none, none)
    out = DataFrame(jvm.org.apache.spark.sql.classic.Dataset.ofRows(session, bare), df.sparkSession)
    file = plan.rdd().getCheckpointFile()
    out._checkpoint_files = file.get() if file.isDefined() else None
    return out


def drop_checkpoint(df: DataFrame) -> None:
    """Delete the files of :func:`checkpointed`, as soon as nothing reads ``df`` any more: Spark keeps them for good."""
    files = getattr(df, "_checkpoint_files", None)
    if files:
        drop_table(files, df.sparkSession)


def cut(df: DataFrame) -> DataFrame:
    """A persisted ``df`` as a relation of its own: what reads it is planned without the plans that it came from.

    Where a loop reads its last state more than once, those multiply from round to round. Lost blocks are still computed anew.
    """
    jvm = df.sparkSession.sparkContext._jvm
    none = jvm.scala.Option.empty()
    done = df.select("*")._jdf.queryExecution()  # planned after the persisting
    plan, session = done.executedPlan(), df._jdf.sparkSession()
    bare = jvm.org.apache.spark.sql.execution.LogicalRDD(done.analyzed().output(), done.toRdd(), plan.outputPartitioning(), plan.outputOrdering(), False, none, session, none, none)
    return DataFrame(jvm.org.apache.spark.sql.classic.Dataset.ofRows(session, bare), df.sparkSession)


def drop_table(df_or_path, spark: SparkSession | None = None) -> None:
    """Delete what :func:`materialise` wrote, as soon as nothing reads it any more."""
    if isinstance(df_or_path, DataFrame):
        spark = df_or_path.sparkSession
        paths = {os.path.dirname(f) for f in df_or_path.inputFiles()}
    else:
        paths = {df_or_path}
    jvm = spark.sparkContext._jvm
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for p in paths:
        path = jvm.org.apache.hadoop.fs.Path(p)
        path.getFileSystem(conf).delete(path, True)


def tidy(spark: SparkSession) -> None:
    """Have the shuffle files of finished jobs deleted now.

    Spark deletes them once the driver's JVM has collected the plans that made them, which on a quiet driver takes longer
    than the next jobs need to fill the disk. Python's references to plans go first.
    """
    gc.collect()
    spark.sparkContext._jvm.System.gc()
