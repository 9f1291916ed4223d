"""Choices made before a run: partition counts, balance, engines."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

MB = 1 << 20


def choose_partitions(input_bytes: int, cores: int, block: int = 64 * MB, floor: bool = False) -> int:
    """As many partitions as input blocks, at most twice the cores; ``floor`` keeps at least one for each core."""
    n = min(max(1, -(-input_bytes // block)), 2 * cores)
    return max(n, cores) if floor else n


def partition_rule(blocks: int, cores: int) -> int:
    return min(blocks, 2 * cores)


def partition_balance(df: DataFrame) -> DataFrame:
    """One row: partitions, mean and greatest rows, and their ratio."""
    per = df.groupBy(F.spark_partition_id().alias("p")).agg(F.count("*").alias("n"))
    return per.agg(F.count("*").alias("partitions"), F.avg("n").alias("mean_rows"), F.max("n").alias("max_rows"), (F.max("n") / F.avg("n")).alias("max_over_mean"))


def rebalance(df: DataFrame, key: str, limit: float = 2.0) -> DataFrame:
    """Dealt anew by ``key`` if the fullest partition holds more than ``limit`` times the mean."""
    got = partition_balance(df).first()
    return df.repartition(got["partitions"], key) if got["max_over_mean"] and got["max_over_mean"] > limit else df


def executor_memory(spark) -> int:
    sc = spark.sparkContext
    status = sc._jsc.sc().getExecutorMemoryStatus()
    it, total = status.valuesIterator(), 0
    while it.hasNext():
        total += it.next()._1()
    return total


def choose_engine(g, replication: float = 3.0, row_bytes: int = 16) -> str:
    """The in-memory engine if edges with their replicas fit half of the executors' memory, else the file-based one."""
    need = g.edges.count() * row_bytes * replication
    return "vertex" if need < executor_memory(g.spark) / 2 else "mr-loop"


def hub_threshold(g, share: float = 0.999) -> int:
    """Degree above which a vertex counts as a hub."""
    return int(g.degrees().agg(F.percentile_approx(F.col("out_degree") + F.col("in_degree"), share, 1000)).first()[0])


def salted_join(edges: DataFrame, state: DataFrame, hubs: DataFrame, key: str = "src", limit: int = 1_000_000) -> DataFrame:
    """``edges`` join ``state(id, ...)`` on ``key`` with hub rows broadcast and the rest joined by shuffle.

    ``hubs(id)`` is broadcast, so its size is checked.
    """
    n = hubs.count()
    if n > limit:
        raise ValueError(f"{n} hubs; {limit} may be broadcast")
    h = F.broadcast(hubs.select(F.col("id").alias(key)))
    s = state.withColumnRenamed("id", key)
    heavy = edges.join(h, key, "left_semi").join(F.broadcast(s.join(h, key, "left_semi")), key)
    return heavy.unionByName(edges.join(h, key, "left_anti").join(s, key))


def two_level_sum(df: DataFrame, key: str, value: str, salts: int = 16) -> DataFrame:
    """Sum by key in two steps, so that a hub's messages meet in ``salts`` tasks first."""
    part = df.groupBy(key, F.pmod(F.xxhash64(*df.columns), F.lit(salts)).alias("_salt")).agg(F.sum(value).alias(value))
    return part.groupBy(key).agg(F.sum(value).alias(value))


def exchanges(df: DataFrame) -> int:
    """Shuffle exchanges in the physical plan."""
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning")
