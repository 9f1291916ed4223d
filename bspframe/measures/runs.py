"""Phases, resource samples, outcomes and scaling of runs."""

from __future__ import annotations

import json
import os
import re
import subprocess
import sys
import threading
import time
from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

PHASES = ("load", "execute", "save")


@dataclass
class Recorder:
    """Times of a run's phases and its total on a clock of its own."""

    name: str = "run"
    phases: dict[str, float] = field(default_factory=dict)
    began: float = field(default_factory=time.perf_counter)
    total: float = 0.0

    @contextmanager
    def phase(self, name: str):
        if name not in PHASES:
            raise ValueError(f"phase {name!r}")
        at = time.perf_counter()
        try:
            yield self
        finally:
            self.phases[name] = self.phases.get(name, 0.0) + time.perf_counter() - at

    def finish(self) -> "Recorder":
        self.total = time.perf_counter() - self.began
        return self

    @property
    def overhead(self) -> float:
        """Total less the phases."""
        return self.total - sum(self.phases.values())

    def row(self) -> dict:
        return {"name": self.name, **{p: self.phases.get(p, 0.0) for p in PHASES}, "overhead": self.overhead, "total": self.total}


def _proc(path: str) -> str:
    try:
        with open(path) as f:
            return f.read()
    except OSError:
        return ""


class Sampler:
    """CPU shares, memory and network of this machine once a period, in a thread; on a cluster one runs on each node."""

    def __init__(self, every: float = 1.0):
        self.every, self.samples, self._stop = every, [], threading.Event()

    @staticmethod
    def _cpu() -> list[int]:
        line = _proc("/proc/stat").split("\n")[0].split()[1:]
        return [int(x) for x in line] or [0] * 8

    @staticmethod
    def _net() -> int:
        lines = [x.split(":") for x in _proc("/proc/net/dev").splitlines() if ":" in x]
        return sum(int(v.split()[0]) + int(v.split()[8]) for _, v in lines)

    @staticmethod
    def _memory() -> int:
        m = dict(x.split(":") for x in _proc("/proc/meminfo").splitlines() if ":" in x)
        return (int(m["MemTotal"].split()[0]) - int(m["MemAvailable"].split()[0])) * 1024 if m else 0

    @staticmethod
    def _written() -> int:
        """Bytes that this machine's disks wrote since it started."""
        rows = [x.split() for x in _proc("/proc/diskstats").splitlines()]
        return 512 * sum(int(r[9]) for r in rows if len(r) > 9 and not r[2][-1:].isdigit())

    def __enter__(self) -> "Sampler":
        self.net_before, self.disk_before, last = self._net(), self._written(), self._cpu()
        began = time.perf_counter()

        def loop():
            nonlocal last
            while not self._stop.wait(self.every):
                now = self._cpu()
                d = [b - a for a, b in zip(last, now)]
                last, total = now, max(1, sum(d))
                self.samples.append({"t": time.perf_counter() - began, "user": (d[0] + d[1]) / total, "system": d[2] / total, "idle": d[3] / total, "io_wait": d[4] / total, "memory": self._memory()})

        self._thread = threading.Thread(target=loop, daemon=True)
        self._thread.start()
        return self

    def __exit__(self, *_):
        self._stop.set()
        self._thread.join()
        self.network = self._net() - self.net_before
        self.disk_written = self._written() - self.disk_before

    def table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([tuple(float(s[k]) for k in ("t", "user", "system", "idle", "io_wait", "memory")) for s in self.samples], "t double, user double, system double, idle double, io_wait double, memory double")

    @property
    def peak_memory(self) -> int:
        return max((s["memory"] for s in self.samples), default=self._memory())


class Outcome:
    """OK, TO (over the time limit), OOM, MSG (messages), SHFL (shuffle)."""

    @staticmethod
    def classify(exc: BaseException | None, elapsed: float, limit: float = 86_400.0) -> str:
        if elapsed > limit or isinstance(exc, TimeoutError):
            return "TO"
        if exc is None:
            return "OK"
        # a stack names shuffle classes whatever went wrong, so only the errors' own lines count
        text = "\n".join(x for x in f"{type(exc).__name__} {exc}".splitlines() if not x.lstrip().startswith("at "))
        if any(x in text for x in ("OutOfMemory", "MemoryError", "Java heap space", "GC overhead")):
            return "OOM"
        if re.search(r"FetchFailed|(?i:missing an output location for shuffle|shuffle ?(?:block|file|fetch))", text):
            return "SHFL"
        if any(x in text for x in ("RpcTimeout", "SparkRpc", "Connection reset", "rpc.message")):
            return "MSG"
        raise exc


def run_limited(spark: SparkSession, fn, limit: float) -> tuple[str, float, object]:
    """(outcome, seconds, value) of ``fn()``; its Spark jobs are cancelled at the limit."""
    sc, group = spark.sparkContext, f"limited-{time.time_ns()}"
    sc.setJobGroup(group, "limited run", True)
    over = threading.Event()

    def stop():
        over.set()
        sc.cancelJobGroup(group)

    timer = threading.Timer(limit, stop)
    timer.start()
    at = time.perf_counter()
    value, exc = None, None
    try:
        value = fn()
    except Exception as e:  # noqa: BLE001 - classified below
        exc = TimeoutError(str(e)) if over.is_set() else e
    finally:
        timer.cancel()
        for key in ("spark.jobGroup.id", "spark.job.description", "spark.job.interruptOnCancel"):
            sc.setLocalProperty(key, None)
    took = time.perf_counter() - at
    return Outcome.classify(exc, took, limit), took, value


def strong_scaling(code: str, cores: list[int], timeout: float = 600) -> list[dict]:
    """Run ``code`` (Python that prints one JSON line with ``seconds``) under ``local[k]`` for each k, in fresh processes."""
    out = []
    for k in cores:
        env = os.environ | {"BSPFRAME_MASTER": f"local[{k}]"}
        said = subprocess.run([sys.executable, "-c", code], env=env, capture_output=True, text=True, timeout=timeout)
        line = next((x for x in reversed(said.stdout.splitlines()) if x.startswith("{")), None)
        out.append({"cores": k, "axis": "vertical", **(json.loads(line) if line else {"seconds": None, "error": said.stderr[-500:]})})
    base = out[0].get("seconds") if out else None
    for row in out:
        if base and row.get("seconds"):
            row["speed_up"] = base / row["seconds"]
            row["efficiency"] = row["speed_up"] * cores[0] / row["cores"]
    return out


def weak_scaling(code_for, steps: list[tuple[int, int]], timeout: float = 600) -> list[dict]:
    """As strong scaling with the data grown with the cores: ``steps`` of (cores, times the data); ``code_for(times)``.

    ``efficiency`` is the first step's time over a step's: 1 where a core's own share of the data costs the same.
    """
    out = [{"times": times, **strong_scaling(code_for(times), [k], timeout)[0]} for k, times in steps]
    base = out[0].get("seconds") if out else None
    for row in out:
        row["efficiency"] = base / row["seconds"] if base and row.get("seconds") else None
    return out
