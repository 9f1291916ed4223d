"""From run tables to matrices, cubes, time lines and stacked bars."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

PHASES = ("load", "execute", "save", "overhead")
COLOURS = ("#4878a8", "#e49444", "#6a9f58", "#a87c9f")


def matrix(runs: DataFrame, rows: str, cols: str, value: str) -> DataFrame:
    """Pivoted results, rows by columns."""
    return runs.groupBy(rows).pivot(cols).agg(F.round(F.first(value), 3)).orderBy(rows)


def phases_cube(runs: DataFrame) -> DataFrame:
    """Mean phase times for every combination of engine, graph and workload; ``level`` tells the grouping."""
    return runs.cube("engine", "graph", "workload").agg(F.grouping_id().alias("level"), *[F.round(F.avg(p), 6).alias(p) for p in PHASES], F.count("*").alias("runs"))


def phases_rollup(runs: DataFrame) -> DataFrame:
    return runs.rollup("graph", "workload", "engine").agg(F.grouping_id().alias("level"), F.round(F.avg("total"), 6).alias("total"), F.count("*").alias("runs"))


def timeline(samples: DataFrame, value: str = "memory", rows: int = 5) -> DataFrame:
    """Moving mean over ``rows`` samples and the running maximum."""
    w = Window.orderBy("t")  # one run's samples: one for each second
    return samples.select("t", value, F.avg(value).over(w.rowsBetween(-rows + 1, 0)).alias("mean"), F.max(value).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("peak"))


def compare(runs: DataFrame, base: str) -> DataFrame:
    """Each engine's total over that of ``base`` in the same cell."""
    b = runs.where(F.col("engine") == base).select("graph", "workload", F.col("total").alias("base_total"))
    return runs.join(b, ["graph", "workload"]).select("graph", "workload", "engine", "outcome", "total", (F.col("total") / F.col("base_total")).alias("ratio"))


def stacked_bars(rows: list[dict], title: str, width: int = 720) -> str:
    """An SVG of phase times, one bar for each run; failed runs carry their outcome instead."""
    top = max([sum(r[p] for p in PHASES) for r in rows if r.get("outcome", "OK") == "OK"] or [1.0]) or 1.0
    line, left = 22, 220
    parts = [f'<svg xmlns="http://www.w3.org/2000/svg" width="{width}" height="{line * (len(rows) + 3)}" font-family="sans-serif" font-size="12">', f'<text x="8" y="18" font-weight="bold">{title}</text>']
    for i, r in enumerate(rows):
        y, x = line * (i + 2), float(left)
        parts.append(f'<text x="8" y="{y + 13}">{r["name"]}</text>')
        if r.get("outcome", "OK") != "OK":
            parts.append(f'<text x="{left}" y="{y + 13}" fill="#b00">{r["outcome"]}</text>')
            continue
        for p, c in zip(PHASES, COLOURS):
            w = max(0.0, r[p]) / top * (width - left - 80)
            parts.append(f'<rect x="{x:.1f}" y="{y}" width="{w:.1f}" height="{line - 6}" fill="{c}"><title>{p} {r[p]:.2f} s</title></rect>')
            x += w
        parts.append(f'<text x="{x + 6:.1f}" y="{y + 13}">{sum(r[p] for p in PHASES):.2f} s</text>')
    for i, (p, c) in enumerate(zip(PHASES, COLOURS)):
        parts.append(f'<rect x="{left + i * 110}" y="8" width="12" height="12" fill="{c}"/><text x="{left + i * 110 + 16}" y="18">{p}</text>')
    return "\n".join([*parts, "</svg>"])


def event_summary(tasks: DataFrame) -> DataFrame:
    """Per stage of an event log: tasks, run time, slowest task over mean, shuffle and spill bytes."""
    return tasks.groupBy("stage").agg(
        F.count("*").alias("tasks"), F.sum("run_ms").alias("run_ms"), (F.max("run_ms") / F.avg("run_ms")).alias("slowest_over_mean"),
        F.sum("shuffle_read").alias("shuffle_read"), F.sum("shuffle_written").alias("shuffle_written"), F.sum("spilled").alias("spilled"),
    )
