"""Single-thread kernels on arrays: the base of the cost comparison. The whole graph must fit one machine (for components: its vertices)."""

from __future__ import annotations

import time

import numpy as np

from bspframe.engines.program import Program
from bspframe.graph import Graph, Result
from bspframe.loop import RoundStat


def to_arrays(g: Graph) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, src, dst) with ends as positions in the sorted ids."""
    e = g.edges.select("src", "dst").toArrow()
    src, dst = e["src"].to_numpy(), e["dst"].to_numpy()
    more = g.extra.toArrow()["id"].to_numpy() if g.extra is not None else np.zeros(0, np.int64)
    ids = np.unique(np.concatenate([src, dst, more]))
    return ids, np.searchsorted(ids, src), np.searchsorted(ids, dst)


def single_pagerank(src, dst, n: int, delta: float = 0.15, init: float = 1.0, tol: float | None = None, k: int | None = None, most: int | None = None):
    """The same recurrence; returns ranks and rounds (``most`` at most where a tolerance ends it)."""
    share = 1.0 / np.maximum(np.bincount(src, minlength=n), 1)
    rank, done = np.full(n, init), 0
    while k is None or done < k:
        new = delta + (1 - delta) * np.bincount(dst, (rank * share)[src], n)
        done += 1
        moved = np.abs(new - rank).max(initial=0.0)
        rank = new
        if k is None and (moved < (tol if tol is not None else init) or done == most):
            break
    return rank, done


def _rows(src, dst, n: int):
    order = np.argsort(src, kind="stable")
    start = np.zeros(n + 1, np.int64)
    np.cumsum(np.bincount(src, minlength=n), out=start[1:])
    return start, dst[order]


def _targets(start, dst, front):
    lens = start[front + 1] - start[front]
    off = np.repeat(start[front] - np.cumsum(lens) + lens, lens)
    return dst[off + np.arange(int(lens.sum()))], np.repeat(front, lens)


def single_sssp(src, dst, n: int, source: int, k: int | None = None, alpha: float = 15.0, beta: float = 18.0):
    """Hop distances (-1 unreached), switching between expanding the frontier and scanning the unvisited.

    Goes bottom-up when the frontier's edges pass the unexplored edges over ``alpha``, back when it falls under n / ``beta``.
    """
    out_at, out_to = _rows(src, dst, n)
    in_at, in_to = _rows(dst, src, n)
    degree = np.diff(out_at)
    dist = np.full(n, -1, np.int64)
    dist[source] = 0
    front, level, left, up = np.array([source]), 0, int(degree.sum()), False
    while len(front) and (k is None or level < k):
        level += 1
        work = int(degree[front].sum())
        left -= work
        up = work > left / alpha if not up else len(front) > n / beta
        if up:
            unseen = np.flatnonzero(dist < 0)
            frm, owner = _targets(in_at, in_to, unseen)
            front = np.unique(owner[dist[frm] == level - 1])
        else:
            to, _ = _targets(out_at, out_to, front)
            front = np.unique(to[dist[to] < 0])
        dist[front] = level
    return dist


def single_khop(src, dst, n: int, source: int, k: int = 3):
    return single_sssp(src, dst, n, source, k)


def single_wcc(src, dst, n: int, method: str = "hook_jump", sample: int = 2):
    """Least position in each component, by hooking and jumping with neighbour sampling, or by union-find."""
    label = np.arange(n)
    if method == "union_find":
        root = list(range(n))

        def find(a):
            while root[a] != a:
                root[a] = root[root[a]]
                a = root[a]
            return a

        for a, b in zip(src.tolist(), dst.tolist()):
            a, b = find(a), find(b)
            if a != b:
                root[max(a, b)] = min(a, b)
        return np.array([find(a) for a in range(n)])

    def link(a, b):
        while len(a):
            la, lb = label[a], label[b]
            np.minimum.at(label, np.maximum(la, lb), np.minimum(la, lb))
            while True:
                nxt = label[label]
                if (nxt == label).all():
                    break
                label[:] = nxt
            live = label[a] != label[b]
            a, b = a[live], b[live]

    order = np.argsort(src, kind="stable")
    s, d = src[order], dst[order]
    start = np.searchsorted(s, s)
    few = np.arange(len(s)) - start < sample  # a few neighbours each settle the giant component
    link(s[few], d[few])
    giant = np.bincount(label, minlength=n).argmax() if n else 0
    rest = ~few & ~((label[s] == giant) & (label[d] == giant))
    link(s[rest], d[rest])
    return label


#: Edges that the streamed kernel links at a time, 16 bytes each.
CHUNK = 2_000_000


def _stream_wcc(batches):
    """Least id of each component; edges pass by, only (id, component) of the vertices seen is held."""
    import pyarrow as pa

    ids = label = np.zeros(0, np.int64)
    held, rows = [], 0

    def link():
        src = np.concatenate([ids, *[a for a, _ in held]])
        dst = np.concatenate([label, *[b for _, b in held]])
        names, at = np.unique(np.concatenate([src, dst]), return_inverse=True)
        return names, names[single_wcc(at[: len(src)], at[len(src) :], len(names))]

    for batch in batches:
        held.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
        rows += batch.num_rows
        if rows >= CHUNK:
            ids, label = link()
            held, rows = [], 0
    if held:
        ids, label = link()
    for i in range(0, len(ids), 1 << 16):
        yield pa.RecordBatch.from_arrays([pa.array(ids[i : i + (1 << 16)]), pa.array(label[i : i + (1 << 16)])], ["id", "value"])


def _single_wcc(g: Graph) -> Result:
    """The serial kernel in one task that the edges are streamed to: neither it nor the driver holds the graph."""
    from bspframe.session import materialise, ship

    began = time.perf_counter()
    ship(g.spark)
    e = g.edges.select("src", "dst")
    if g.extra is not None:
        e = e.union(g.extra.select("id", "id"))
    df = materialise(e.repartition(1).mapInArrow(_stream_wcc, "id long, value long"), "single")
    return Result(df, 1, [RoundStat(1, 0, df.count(), 0.0, time.perf_counter() - began)])


def run_single(g: Graph, p: Program) -> Result:
    if p.name == "wcc" and p.both:
        return _single_wcc(g)
    ids, src, dst = to_arrays(g)
    n, began = len(ids), time.perf_counter()
    rounds = 1
    if p.name == "pagerank":
        k = p.max_rounds if p.max_rounds < 1000 else 200
        value, rounds = single_pagerank(src, dst, n, float(p.py[3](0.0, 0.0)), float(p.py[0](0)), k=k)
        out = value.astype(float)
    elif p.name == "wcc":
        out = ids[single_wcc(src, dst, n)]
    else:
        source = next((int(i) for i in ids if p.py[0](int(i)) is not None), None)
        dist = single_sssp(src, dst, n, int(np.searchsorted(ids, source)), p.max_rounds if p.name == "khop" else None) if source is not None else np.full(n, -1)
        out = np.where(dist < 0, None, dist)
    import pyarrow as pa

    kind = {"double": pa.float64(), "bigint": pa.int64(), "int": pa.int32()}[p.kind]
    df = g.spark.createDataFrame(pa.table({"id": pa.array(ids, pa.int64()), "value": pa.array(out.tolist(), kind)}))
    return Result(df, rounds, [RoundStat(rounds, 0, n, 0.0, time.perf_counter() - began)])
