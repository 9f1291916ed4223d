"""The superstep loop: rounds, halting, observation, plan truncation and resuming."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Observation, SparkSession, functions as F

from bspframe.session import checkpointed, drop_checkpoint, shared_dir, tidy


@dataclass
class RoundStat:
    round: int
    changed: int
    active: int
    max_change: float
    seconds: float


@dataclass(frozen=True)
class Truncate:
    """When a round's state is checkpointed to the shared folder; in between it is only persisted."""

    every: int = 1
    level: StorageLevel = field(default_factory=lambda: StorageLevel.MEMORY_AND_DISK)
    adaptive: bool = False

    @staticmethod
    def auto() -> "Truncate":
        """Begins with every round and settles the interval by what this run's own rounds cost (see :class:`Interval`)."""
        return Truncate(adaptive=True)

    @staticmethod
    def never() -> "Truncate":
        return Truncate(1 << 30)


class Interval:
    """Rounds between checkpoints. An adaptive one measures first: two checkpointed rounds, then up to three persisted ones.

    A checkpoint costs ``c`` seconds more than persisting, and each persisted round makes the next ``g`` seconds dearer, as
    its plan grows; the mean cost of a round, ``c / every + g * every / 2``, is least at ``sqrt(2 c / g)``. A persisted
    round that saves nothing ends the measuring at once: every round is checkpointed then.
    """

    PROBE, MOST = 3, 25
    #: Seconds of a persisted round from which an adaptive run checkpoints every round: plans not cut hold their shuffle files.
    SLOW = 5.0

    def __init__(self, truncate: Truncate):
        self.every, self.probing = truncate.every, truncate.adaptive
        self.adaptive = truncate.adaptive
        self.full: list[float] = []
        self.light: list[float] = []
        self.since = 0

    def due(self) -> bool:
        """Whether the coming round is checkpointed."""
        self.since += 1
        if self.probing:
            return len(self.full) < 2
        return self.since >= self.every

    def took(self, checkpointed: bool, seconds: float) -> None:
        if checkpointed:
            self.since = 0
        if self.adaptive and not checkpointed and seconds >= self.SLOW:
            self.every, self.probing = 1, False
        if not self.probing:
            return
        (self.full if checkpointed else self.light).append(seconds)
        if not self.light:
            return
        cost = self.full[-1] - self.light[0]
        if cost <= 0:
            self.every, self.probing = 1, False
        elif len(self.light) > 1:
            growth = max((self.light[-1] - self.light[0]) / (len(self.light) - 1), 0.01)
            self.every = max(1, min(self.MOST, round((2 * cost / growth) ** 0.5)))
            self.probing = len(self.light) < self.PROBE and self.every > self.since


#: Seconds after which a loop has the shuffle files of its finished rounds deleted.
TIDY = 10.0

Halt = Callable[[RoundStat], bool]


def fixpoint() -> Halt:
    return lambda s: s.changed == 0


def rounds(k: int) -> Halt:
    return lambda s: s.round >= k


def max_delta(tolerance: float) -> Halt:
    """Stops when the largest change of any value is below ``tolerance``."""
    return lambda s: s.max_change < tolerance


class Adaptive:
    """Switches adaptive execution off inside a loop, so that pinned partitioning survives, and back on after it."""

    def __init__(self, spark: SparkSession, on: bool = False):
        self.spark, self.want = spark, on

    def __enter__(self):
        self.was = self.spark.conf.get("spark.sql.adaptive.enabled")
        self.spark.conf.set("spark.sql.adaptive.enabled", str(self.want).lower())

    def __exit__(self, *_):
        self.spark.conf.set("spark.sql.adaptive.enabled", self.was)


def pin(df: DataFrame, key: str, partitions: int | None = None) -> DataFrame:
    """Loop-invariant data: dealt by ``key``, sorted, kept in memory and on disk."""
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return df.repartition(n, key).sortWithinPartitions(key).persist(StorageLevel.MEMORY_AND_DISK)


def superstep_loop(
    state: DataFrame,
    step: Callable[[DataFrame, int], DataFrame],
    halt: Halt,
    max_rounds: int,
    truncate: Truncate | None = None,
    changed: str = "changed",
    change: str = "0.0D",
    active: str = "changed",
    resume_from: str | None = None,
    save_to: str | None = None,
) -> tuple[DataFrame, int, list[RoundStat]]:
    """Run ``step(state, round)`` until ``halt`` or ``max_rounds``; one job a round, measured by an observation.

    ``changed``, ``change`` and ``active`` are SQL over the new state. ``save_to`` keeps the state of every
    checkpoint round (every round, if ``truncate`` is not given) as parquet under ``round=N``; ``resume_from`` starts from the last such state.
    """
    spark = state.sparkSession
    truncate = truncate or (Truncate() if save_to else Truncate.auto())
    shared_dir(spark)
    stats: list[RoundStat] = []
    done = 0
    if resume_from:
        saved = spark.read.parquet(resume_from)
        done = saved.agg(F.max("round")).first()[0]
        state = saved.where(F.col("round") == done).select(*state.columns)
    held: list[DataFrame] = []
    stale: list[DataFrame] = []
    number = done
    interval = Interval(truncate)
    kept: DataFrame | None = None  # this loop's last checkpoint
    tidied = time.perf_counter()
    while number < max_rounds:
        number += 1
        began = time.perf_counter()
        seen = Observation()
        fresh = step(state, number).observe(
            seen, F.expr(f"count_if({changed})").alias("changed"), F.expr(f"count_if({active})").alias("active"), F.expr(f"coalesce(max({change}), 0.0D)").alias("change")
        )
        whole = interval.due()
        if whole:
            fresh = checkpointed(fresh)
            stale = held
            held = []
            if save_to:
                fresh.write.mode("overwrite").parquet(f"{save_to}/round={number}")
        else:
            fresh = fresh.persist(truncate.level)
            fresh.write.format("noop").mode("overwrite").save()
            held.append(fresh)
        for df in stale:
            df.unpersist()
        stale = []
        got = seen.get
        stats.append(RoundStat(number, got["changed"], got["active"], float(got["change"]), time.perf_counter() - began))
        interval.took(whole, stats[-1].seconds)
        state = fresh
        if whole:
            if kept is not None:
                drop_checkpoint(kept)
            kept = fresh
            if time.perf_counter() - tidied > TIDY:
                seen = got = None
                tidy(spark)
                tidied = time.perf_counter()
        if halt(stats[-1]):
            break
    return state, number, stats

