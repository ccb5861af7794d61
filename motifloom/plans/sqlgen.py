"""ANSI SQL that says what a query should return, for the oracles."""

from __future__ import annotations

from motifloom.plans.ir import relation, use_symmetry
from motifloom.plans.pattern import QueryGraph
from motifloom.sources.builders import BUILDERS, TYPE_BASE


def graph_ctes(name: str) -> str:
    """Relations ids (k, d, id), e (src, dst) and s (u, v: both directions, or one if directed)."""
    b = BUILDERS[name]
    ends = "CAST(x.id AS BIGINT) AS src, CAST(y.id AS BIGINT) AS dst" if b.directed else "CAST(least(x.id, y.id) AS BIGINT) AS src, CAST(greatest(x.id, y.id) AS BIGINT) AS dst"
    label = f"CAST(k // {TYPE_BASE} AS INTEGER)" if b.label else "CAST(NULL AS INTEGER)"
    both = "SELECT src AS u, dst AS v FROM e" + ("" if b.directed else " UNION ALL SELECT dst, src FROM e")
    return (
        f"pairs AS MATERIALIZED ({b.sql}), deg AS (SELECT k, count(*) AS d FROM (SELECT a AS k FROM pairs UNION ALL SELECT b FROM pairs) AS t GROUP BY k),"
        f" ids AS MATERIALIZED (SELECT k, d, {label} AS label, row_number() OVER (ORDER BY d, k) AS id FROM deg),"
        f" e AS MATERIALIZED (SELECT {ends} FROM pairs JOIN ids AS x ON pairs.a = x.k JOIN ids AS y ON pairs.b = y.k),"
        f" s AS MATERIALIZED ({both})"
    )


def _label_ctes(q: QueryGraph) -> str:
    """Arcs between each pair of labels that the pattern uses."""
    out = []
    for la, lb in sorted({(q.label(a), q.label(b)) for a, b in q.edges}):
        out.append(f"s_{la}_{lb} AS MATERIALIZED (SELECT u, v FROM s JOIN ids AS x ON s.u = x.id JOIN ids AS y ON s.v = y.id WHERE x.label = {la} AND y.label = {lb})")
    return ", ".join(out)


def match_body(q: QueryGraph, symmetry: str = "auto", select: str | None = None) -> str:
    """A join of one arc relation per query edge, with order and injectivity."""
    home: dict[int, str] = {}
    where, froms = [], []
    left = sorted(q.edges)
    i = 0
    while left:
        edge = min((e for e in left if not home or set(e) & set(home)), key=lambda e: (-len(set(e) & set(home)), e))
        left.remove(edge)
        i += 1
        rel = f"s_{q.label(edge[0])}_{q.label(edge[1])}" if q.labelled else "s"
        froms.append(f"{rel} AS r{i}")
        for v, column in zip(edge, "uv"):
            if v in home:
                where.append(f"r{i}.{column} = {home[v]}")
            else:
                home[v] = f"r{i}.{column}"
    ordered = use_symmetry(q, symmetry)
    for a in q.vertices:
        for b in range(a + 1, q.n + 1):
            how = relation(q, a, b, ordered)
            if how:
                where.append(f"{home[a]} {'<>' if how == '!=' else how} {home[b]}")
    columns = select or ", ".join(f"CAST({home[v]} AS BIGINT) AS v{v}" for v in q.vertices)
    return f"SELECT {columns} FROM {', '.join(froms)} WHERE {' AND '.join(where) if where else 'true'}"


def oracle(graph: str, q: QueryGraph, mode: str = "rows", symmetry: str = "auto") -> str:
    ctes = graph_ctes(graph) + (", " + _label_ctes(q) if q.labelled else "")
    body = match_body(q, symmetry, "CAST(count(*) AS BIGINT) AS matches" if mode == "count" else None)
    return f"WITH {ctes} {body}"


_COMMON = "t AS MATERIALIZED (SELECT e.src AS a, e.dst AS b, count(*) AS c FROM e JOIN s AS x ON x.u = e.src JOIN s AS y ON y.u = e.dst AND y.v = x.v GROUP BY e.src, e.dst)"
_TRIANGLES = "tri AS MATERIALIZED (SELECT x.src AS x, x.dst AS y, y.dst AS z FROM e AS x JOIN e AS y ON x.dst = y.src JOIN e AS w ON w.src = x.src AND w.dst = y.dst)"
_AROUND = "k AS MATERIALIZED (SELECT x, y, z, count(*) AS c FROM tri JOIN s AS a ON a.u = x JOIN s AS b ON b.u = y AND b.v = a.v JOIN s AS d ON d.u = z AND d.v = a.v GROUP BY x, y, z)"
#: Counts from common neighbours of pairs, edges and triangles, for graphs on which a join per edge takes minutes.
_CLOSED = {
    "q1": ("", "SELECT CAST(coalesce(sum(c * (c - 1) / 2) / 2, 0) AS BIGINT) AS matches FROM (SELECT count(*) AS c FROM s AS x JOIN s AS y ON x.u = y.u AND x.v < y.v GROUP BY x.v, y.v) AS p"),
    "q2": (_COMMON, "SELECT CAST(coalesce(sum(c * (c - 1) / 2), 0) AS BIGINT) AS matches FROM t"),
    "q3": (f"{_TRIANGLES}, {_AROUND}", "SELECT CAST(coalesce(sum(c) / 4, 0) AS BIGINT) AS matches FROM k"),
    "q5": (
        f"{_COMMON}, {_TRIANGLES}, {_AROUND}",
        "SELECT CAST(coalesce((SELECT sum((p.c - 1) * (q.c - 1) + (p.c - 1) * (r.c - 1) + (q.c - 1) * (r.c - 1)) FROM tri JOIN t AS p ON p.a = x AND p.b = y JOIN t AS q ON q.a = x AND q.b = z JOIN t AS r ON r.a = y AND r.b = z), 0)"
        " - 3 * coalesce((SELECT sum(c) FROM k), 0) AS BIGINT) AS matches",
    ),
    "q6": (f"{_TRIANGLES}, {_AROUND}", "SELECT CAST(coalesce(sum(c * (c - 1) / 2), 0) AS BIGINT) AS matches FROM k"),
}


def closed_count(graph: str, pattern: str) -> str | None:
    """The count of an unlabelled pattern by a formula, where one is known."""
    if pattern not in _CLOSED:
        return None
    more, body = _CLOSED[pattern]
    return f"WITH {graph_ctes(graph)}{', ' + more if more else ''} {body}"
