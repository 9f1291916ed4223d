"""Computation models. ``run`` picks one by name; all take a graph and a program and give a Result."""

from __future__ import annotations


def run(engine: str, g, p, **how):
    from bspframe.engines import block, dataflow, gas, mapreduce, rdd, relational, serial, vertex

    table = {
        "vertex": vertex.run_vertex,
        "gas": gas.run_gas,
        "gas-async": lambda g, p, **k: gas.run_gas(g, p, **{"mode": "async", **k}),
        "gas-async-local": lambda g, p, **k: gas.run_gas(g, p, **{"mode": "async-local", **k}),
        "block": block.run_block,
        "mr": mapreduce.run_mapreduce,
        "mr-loop": mapreduce.run_loop_mapreduce,
        "rdd": rdd.run_rdd,
        "sql": relational.run_sql,
        "dataflow": dataflow.run_dataflow,
        "single": serial.run_single,
    }
    if engine == "auto":
        from bspframe.plans.planner import choose_engine

        engine = choose_engine(g)
    if engine not in table:
        raise ValueError(f"no engine {engine!r}; one of {sorted(table)} or auto")
    return table[engine](g, p, **how)
