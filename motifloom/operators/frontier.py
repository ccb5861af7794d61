"""Frontier expansion: in each superstep one bound vertex is expanded as a star to its unbound neighbours.

White vertices are unbound, gray ones bound, black ones bound and expanded. Expanding a vertex checks
its edges to gray neighbours and binds its white ones. With per_row every row chooses its own next
vertex; rows that have the same colours travel together.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifloom.operators import compress as packed
from motifloom.operators.graph import DataGraph
from motifloom.operators.units import _edge_args
from motifloom.plans.ir import relation, use_symmetry
from motifloom.plans.pattern import QueryGraph
from motifloom.storage import durable


def expand(rows: DataFrame, g: DataGraph, q: QueryGraph, v: int, bound: frozenset[int], black: frozenset[int], symmetry: bool) -> DataFrame:
    """Expands v: verifies its edges to gray neighbours and binds its white neighbours."""
    gray = sorted(y for y in q.adjacency[v] if y in bound and y not in black)
    white = sorted(y for y in q.adjacency[v] if y not in bound)
    for y in gray:
        pairs = g.pairs(**_edge_args(q, v, y)).select(F.col("u").alias(f"v{v}"), F.col("v").alias(f"v{y}"))
        rows = rows.join(pairs, [f"v{v}", f"v{y}"], "left_semi")
    sources: dict[tuple, str] = {}
    for x in white:
        args = tuple(_edge_args(q, v, x).items())
        if args not in sources:
            sources[args] = f"_n{len(sources)}"
            near = g.adjacency(**dict(args)).select(F.col("u").alias(f"v{v}"), F.col("nbrs").alias(sources[args]))
            rows = rows.join(near, f"v{v}")
    placed = sorted(bound)
    for x in white:
        values = F.col(sources[tuple(_edge_args(q, v, x).items())])
        tests = [(y, how) for y in placed if (how := relation(q, x, y, symmetry))]
        if tests:
            values = F.filter(values, packed.checker(tests))
        rows = rows.select(*rows.columns, F.explode(values).alias(f"v{x}"))
        placed.append(x)
    return rows.drop(*sources.values())


def _unverified(q: QueryGraph, bound: frozenset[int], black: frozenset[int]) -> list[int]:
    """Gray vertices with an edge that no black vertex has settled."""
    return [v for v in sorted(bound - black) if any(y not in black for y in q.adjacency[v])]


def _load(rows: DataFrame, g: DataGraph, q: QueryGraph, v: int, bound: frozenset[int]) -> float:
    """Rows that expanding v would make: the choices of its white neighbours out of each image's degree."""
    white = sum(y not in bound for y in q.adjacency[v])
    degrees = g.vertices.select(F.col("id").alias(f"v{v}"), "degree")
    choices = reduce(lambda a, b: a * b, [F.greatest(F.col("degree") - i, F.lit(0)).cast("double") for i in range(white)], F.lit(1.0))
    return rows.join(degrees, f"v{v}").agg(F.coalesce(F.sum(choices), F.lit(0.0))).first()[0]


def run(g: DataGraph, q: QueryGraph, *, heuristic: str = "min_comm", per_row: bool = False, symmetry: str = "auto", keep: bool = True, start: int | None = None) -> DataFrame:
    """Matches v1..vn. heuristic: min_comm (at run time), fixed (smallest vertex) or random (by a fixed hash)."""
    ordered = use_symmetry(q, symmetry)
    first = start or max(q.vertices, key=lambda v: (q.degree(v), -v))
    rows = g.vertices.where(F.col("label") == q.label(first)) if q.label(first) is not None else g.vertices
    rows = rows.select(F.col("id").alias(f"v{first}"))
    if per_row:
        return _by_row(rows, g, q, first, ordered)
    bound, black = frozenset({first}), frozenset()
    while gray := _unverified(q, bound, black):
        if heuristic == "min_comm" and len(gray) > 1:
            v = min(gray, key=lambda x: (_load(rows, g, q, x, bound), x))
        elif heuristic == "random":
            v = min(gray, key=lambda x: (x * 2654435761 + len(black) * 40503) % 1_000_003)
        else:
            v = gray[0]
        rows = expand(rows, g, q, v, bound, black, ordered)
        if keep and _unverified(q, bound | q.adjacency[v], black | {v}):
            rows = durable(rows)
        bound, black = bound | q.adjacency[v], black | {v}
    return rows.select(*[f"v{v}" for v in q.vertices])


def _by_row(rows: DataFrame, g: DataGraph, q: QueryGraph, first: int, ordered: bool) -> DataFrame:
    """Every row expands the gray vertex with the fewest expected children; ids rank degrees, so no probe is needed."""
    states = {(frozenset({first}), frozenset()): rows}
    done: list[DataFrame] = []
    while states:
        after: dict[tuple, list[DataFrame]] = {}
        for (bound, black), part in states.items():
            gray = _unverified(q, bound, black)
            if not gray:
                done.append(part.select(*[f"v{v}" for v in q.vertices]))
                continue
            whites = {v: sum(y not in bound for y in q.adjacency[v]) for v in gray}
            fewest = [v for v in gray if whites[v] == min(whites.values())]
            for v in fewest:
                mine = part
                for w in fewest:
                    if w != v:
                        mine = mine.where((F.col(f"v{v}") < F.col(f"v{w}")) if w > v else (F.col(f"v{v}") <= F.col(f"v{w}")))
                key = (bound | q.adjacency[v], black | {v})
                out = expand(mine, g, q, v, bound, black, ordered)
                after.setdefault(key, []).append(out.select(*[f"v{x}" for x in sorted(key[0])]))
        states = {k: durable(reduce(DataFrame.unionByName, parts)) for k, parts in after.items()}
    return reduce(DataFrame.unionByName, done)
