"""SQL counterparts of the workloads, for DuckDB."""

from __future__ import annotations

from bspframe.builders import EXTRA, SQL, both_ways


def edges_of(name: str, both: bool = False) -> str:
    return both_ways(name) if both else SQL[name]


def _vertices(name: str) -> str:
    extra = f" UNION SELECT id FROM ({EXTRA[name]})" if name in EXTRA else ""
    return f"SELECT src AS id FROM e UNION SELECT dst FROM e{extra}"


def pagerank(name: str, rounds: int, both: bool = False, drop_self: bool = False, delta: float = 0.15, edges: str | None = None, column: str = "rank") -> str:
    """A chain of materialised tables, one for each round."""
    only = " WHERE src <> dst" if drop_self else ""
    parts = [
        f"e AS MATERIALIZED (SELECT src::BIGINT AS src, dst::BIGINT AS dst FROM ({edges or edges_of(name, both)}){only})",
        f"v AS MATERIALIZED ({_vertices(name)})",
        "x AS MATERIALIZED (SELECT src, dst, 1.0::DOUBLE / count(*) OVER (PARTITION BY src) AS w FROM e)",
        "r0 AS (SELECT id, 1.0::DOUBLE AS rank FROM v)",
    ]
    for k in range(1, rounds + 1):
        parts.append(f"r{k} AS MATERIALIZED (SELECT v.id, {delta} + {1 - delta} * coalesce(m.s, 0) AS rank FROM v LEFT JOIN (SELECT dst, sum(rank * w) AS s FROM x JOIN r{k - 1} ON src = id GROUP BY dst) m ON v.id = m.dst)")
    return f"WITH {', '.join(parts)} SELECT id, round(rank, 6) + 0.0 AS {column} FROM r{rounds}"


def _unrolled(name: str, rounds: int, step, last: str) -> str:
    """Rounds as a chain of tables r0, r1, ...; ``step(k)`` is the query of r<k> over r<k-1>, edges x(src, dst, w) and v(id)."""
    parts = [
        f"e AS MATERIALIZED (SELECT src::BIGINT AS src, dst::BIGINT AS dst FROM ({edges_of(name)}))",
        f"v AS MATERIALIZED ({_vertices(name)})",
        "x AS MATERIALIZED (SELECT src, dst, 1.0::DOUBLE / count(*) OVER (PARTITION BY src) AS w FROM e)",
        "r0 AS (SELECT id, 1.0::DOUBLE AS rank, true AS moved, true AS active FROM v)",
    ]
    parts += [f"r{k} AS MATERIALIZED ({step(k)})" for k in range(1, rounds + 1)]
    return f"WITH {', '.join(parts)} {last}"


def _sums(k: int, only: str = "") -> str:
    return f"(SELECT dst, sum(rank * w) AS s FROM x JOIN r{k - 1} ON src = id {only} GROUP BY dst)"


def pagerank_until(name: str, tol: float, most: int, delta: float = 0.15) -> str:
    """Ranks of the first round in which no rank moves by ``tol``."""
    step = lambda k: f"SELECT v.id, {delta} + {1 - delta} * coalesce(m.s, 0) AS rank FROM v LEFT JOIN {_sums(k)} m ON v.id = m.dst"
    ends = " UNION ALL ".join(f"SELECT {k} AS k, max(abs(a.rank - b.rank)) AS d FROM r{k} a JOIN r{k - 1} b USING (id)" for k in range(1, most + 1))
    every = " UNION ALL ".join(f"SELECT {k} AS k, id, rank FROM r{k}" for k in range(1, most + 1))
    return _unrolled(name, most, step, f"SELECT id, round(rank, 6) + 0.0 AS rank FROM ({every}) WHERE k = (SELECT min(k) FROM ({ends}) WHERE d < {tol})")


def pagerank_quiet(name: str, eps: float, rounds: int, wake: str, delta: float = 0.15) -> str:
    """Vertices that moved by ``eps`` at most stop. ``wake``: never; moved (work again when an in-neighbour moved); scatter
    (work only when one did). Rounds beyond the last move change nothing."""

    def step(k: int) -> str:
        woken = f"id IN (SELECT dst FROM x JOIN r{k - 1} ON src = id WHERE moved)"
        on = "true" if k == 1 else {"never": "active", "moved": f"(active OR {woken})", "scatter": woken}[wake]
        new = f"SELECT p.id, p.rank AS old, {on} AS works, CASE WHEN {on} THEN {delta} + {1 - delta} * coalesce(m.s, 0) ELSE p.rank END AS rank FROM r{k - 1} p LEFT JOIN {_sums(k)} m ON p.id = m.dst"
        return f"SELECT id, rank, abs(rank - old) > {eps} AS moved, works AND abs(rank - old) > {eps} AS active FROM ({new})"

    return _unrolled(name, rounds, step, f"SELECT id, round(rank, 6) + 0.0 AS rank FROM r{rounds}")


def wcc(name: str, directed: bool = False, edges: str | None = None) -> str:
    both = "SELECT src AS a, dst AS b FROM e" + ("" if directed else " UNION ALL SELECT dst, src FROM e")
    return f"""WITH RECURSIVE e AS MATERIALIZED (SELECT src::BIGINT AS src, dst::BIGINT AS dst FROM ({edges or SQL[name]})),
      v AS MATERIALIZED ({_vertices(name)}), u AS MATERIALIZED (SELECT DISTINCT a, b FROM ({both})),
      c(id, component) USING KEY (id) AS (
        SELECT id, id FROM v
        UNION SELECT u.b, min(c.component) FROM c JOIN u ON c.id = u.a JOIN recurring.c AS r ON r.id = u.b WHERE c.component < r.component GROUP BY u.b)
      SELECT id, component FROM c"""


def hops(name: str, source: int, both: bool = False, k: int | None = None, select: str = "SELECT id, dist::INTEGER AS dist FROM d") -> str:
    bound = f" AND d.dist < {k}" if k is not None else ""
    return f"""WITH RECURSIVE e AS MATERIALIZED (SELECT DISTINCT src::BIGINT AS src, dst::BIGINT AS dst FROM ({edges_of(name, both)})),
      d(id, dist) USING KEY (id) AS (
        SELECT {source}::BIGINT, 0
        UNION SELECT e.dst, min(d.dist + 1) FROM d JOIN e ON d.id = e.src LEFT JOIN recurring.d AS r ON r.id = e.dst
        WHERE (r.dist IS NULL OR r.dist > d.dist + 1){bound} GROUP BY e.dst)
      {select}"""


def hops_with_parent(name: str, source: int) -> str:
    return hops(name, source, select="SELECT d.id, d.dist::INTEGER AS dist, min(p.src) AS parent FROM d LEFT JOIN (SELECT e.src, e.dst, s.dist FROM e JOIN d s ON s.id = e.src) p ON p.dst = d.id AND p.dist + 1 = d.dist GROUP BY d.id, d.dist")


def diameter(name: str, sources: str, share: float = 0.9) -> str:
    inner = khop_many(name, sources, 1_000_000)
    return f"""WITH f AS MATERIALIZED (SELECT * FROM ({inner}) WHERE dist > 0), b AS (SELECT dist, count(*) AS n FROM f GROUP BY dist),
      u AS (SELECT dist, n, sum(n) OVER (ORDER BY dist) AS upto, sum(n) OVER () AS whole FROM b)
      SELECT (SELECT count(DISTINCT id) FROM ({sources})) AS sources, coalesce(sum(n), 0)::BIGINT AS pairs, max(dist)::INTEGER AS longest,
        min(dist) FILTER (WHERE upto >= whole * {share})::INTEGER AS effective, round(min(dist - (upto - whole * {share}) / n) FILTER (WHERE upto >= whole * {share}), 6)::DOUBLE AS effective_smooth FROM u"""


def khop_many(name: str, sources: str, k: int) -> str:
    return f"""WITH RECURSIVE e AS MATERIALIZED (SELECT DISTINCT src::BIGINT AS src, dst::BIGINT AS dst FROM ({SQL[name]})),
      d(source, id, dist) USING KEY (source, id) AS (
        SELECT id::BIGINT, id::BIGINT, 0 FROM ({sources})
        UNION SELECT d.source, e.dst, min(d.dist + 1) FROM d JOIN e ON d.id = e.src LEFT JOIN recurring.d AS r ON r.id = e.dst AND r.source = d.source
        WHERE (r.dist IS NULL OR r.dist > d.dist + 1) AND d.dist < {k} GROUP BY d.source, e.dst)
      SELECT source, id, dist::INTEGER AS dist FROM d"""


def stats(name: str) -> str:
    return f"""WITH e AS MATERIALIZED (SELECT src::BIGINT AS src, dst::BIGINT AS dst FROM ({SQL[name]})), v AS ({_vertices(name)}),
      o AS (SELECT src AS id, count(*) AS n FROM e GROUP BY src), i AS (SELECT dst AS id, count(*) AS n FROM e GROUP BY dst)
      SELECT count(*) AS vertices, sum(coalesce(o.n, 0))::BIGINT AS edges, round(avg(coalesce(o.n, 0)), 6) AS avg_out_degree,
        max(coalesce(o.n, 0))::BIGINT AS max_out_degree, max(coalesce(i.n, 0))::BIGINT AS max_in_degree,
        count(*) FILTER (WHERE o.n IS NULL) AS sinks, (SELECT count(*) FROM e WHERE src = dst) AS self_edges
      FROM v LEFT JOIN o USING (id) LEFT JOIN i USING (id)"""


def adjacency(name: str, long: bool) -> str:
    if not long:
        return f"SELECT src::BIGINT AS id, array_to_string(list(dst ORDER BY dst), ' ') AS nbrs FROM ({SQL[name]}) GROUP BY src"
    return f"""WITH e AS MATERIALIZED ({SQL[name]}), v AS ({_vertices(name)})
      SELECT v.id::BIGINT AS id, count(dst)::INTEGER AS deg, coalesce(array_to_string(list(dst ORDER BY dst) FILTER (WHERE dst IS NOT NULL), ' '), '') AS nbrs FROM v LEFT JOIN e ON e.src = v.id GROUP BY v.id"""


KNUTH = 2654435761


def _hash(c: str) -> str:
    return f"(({c} * {KNUTH}) % 4294967296)"


def replication(name: str, part: str) -> str:
    """``part`` is SQL over src and dst."""
    return f"""WITH p AS MATERIALIZED (SELECT src, dst, {part} AS part FROM ({SQL[name]})),
      r AS (SELECT id, count(DISTINCT part) AS n FROM (SELECT src AS id, part FROM p UNION ALL SELECT dst, part FROM p) GROUP BY id)
      SELECT count(*) AS vertices, round(avg(n), 6) AS replication_factor, (SELECT count(*) FROM p) AS edges, (SELECT count(DISTINCT part) FROM p) AS parts FROM r"""


def random_part(p: int) -> str:
    return f"((({_hash('src')} * 31 + {_hash('dst')}) % 4294967296) % {p})"


def common_part(candidates: list[list[int]]) -> str:
    p = len(candidates)
    table = "[" + ", ".join("[" + ", ".join(map(str, c)) + "]" for c in candidates) + "]"
    home = lambda c: f"{table}[{_hash(c)} % {p} + 1]"
    both = f"list_sort(list_intersect({home('src')}, {home('dst')}))"
    return f"{both}[(({_hash('src')} * 31 + {_hash('dst')}) % 4294967296) % len({both}) + 1]"
