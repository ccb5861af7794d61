"""Core and bud units: the core of a pattern first, then every other vertex as an array, in one assembly.

A bud unit maps each data clique to the vertices adjacent to all of it. Core matches meet it on the
images of the unit's clique vertices.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifloom.operators import compress as packed
from motifloom.operators import growth
from motifloom.operators.graph import DataGraph
from motifloom.operators.units import bud
from motifloom.plans.ir import GrowthPlan, Round, relation, use_symmetry
from motifloom.plans.optimize import cover_first
from motifloom.plans.pattern import QueryGraph


def subset_plan(q: QueryGraph, order: tuple[int, ...]) -> GrowthPlan:
    """A growth plan over some vertices of q only."""
    rounds = tuple(Round(x, tuple(sorted(q.adjacency[x] & set(order[:i]))), False) for i, x in enumerate(order) if i)
    return GrowthPlan(tuple(order), rounds)


def run(g: DataGraph, q: QueryGraph, *, max_clique: int = 3, symmetry: str = "auto", allow_product: bool = False) -> DataFrame:
    """Compressed matches: single vertices for the core, arrays for the buds. Unlabelled patterns."""
    if q.labelled or q.directed:
        raise ValueError("bud units are for unlabelled, undirected patterns")
    ordered = use_symmetry(q, symmetry)
    if allow_product and not q.connected(q.min_cover):
        return _product(g, q, ordered)
    core, units = q.clique_buds
    order = tuple(v for v in cover_first(q) if v in core)
    rows = growth.run(g, q, subset_plan(q, order), symmetry=symmetry) if len(order) > 1 else g.vertices.select(F.col("id").alias(f"v{order[0]}"))
    return _assemble(rows, g, q, units, sorted(core), ordered, max_clique)


def _assemble(rows: DataFrame, g: DataGraph, q: QueryGraph, units, core: list[int], ordered: bool, max_clique: int) -> DataFrame:
    found: dict[int, list[str]] = {}
    for k, (clique, buds) in enumerate(units):
        pieces = [clique] if len(clique) + 1 <= max_clique else [(v,) for v in clique]
        for j, piece in enumerate(pieces):
            name = f"_b{k}_{j}"
            table = bud(g, len(piece)).select(*[F.col(f"v{i + 1}").alias(f"_k{i}") for i in range(len(piece))], F.col("buds").alias(name))
            rows = rows.withColumn("_s", F.array_sort(F.array(*[F.col(f"v{v}") for v in piece])))
            for i in range(len(piece)):
                rows = rows.withColumn(f"_k{i}", F.get("_s", F.lit(i)))
            rows = rows.join(table, [f"_k{i}" for i in range(len(piece))]).drop("_s", *[f"_k{i}" for i in range(len(piece))])
            for x in buds:
                found.setdefault(x, []).append(name)
    for x in sorted(found):
        values = F.col(found[x][0])
        for other in found[x][1:]:
            values = F.array_intersect(values, F.col(other))
        tests = [(y, how) for y in core if (how := relation(q, x, y, ordered))]
        rows = rows.withColumn(f"c{x}", F.filter(values, packed.checker(tests)) if tests else values).where(F.size(f"c{x}") > 0)
    return rows.select(*[f"v{v}" for v in core], *[f"c{x}" for x in sorted(found)])


def _product(g: DataGraph, q: QueryGraph, ordered: bool) -> DataFrame:
    """A disconnected minimum cover: its parts are matched apart and multiplied, which can be huge."""
    core, parts = set(q.min_cover), []
    while core:
        piece, stack = set(), [min(core)]
        while stack:
            v = stack.pop()
            if v not in piece:
                piece.add(v)
                stack.extend(q.adjacency[v] & core)
        parts.append(sorted(piece))
        core -= piece
    rows, placed = None, []
    for piece in parts:
        order = [piece[0]]
        while len(order) < len(piece):
            order.append(min(v for v in piece if v not in order and q.adjacency[v] & set(order)))
        mine = growth.run(g, q, subset_plan(q, tuple(order)), symmetry="on" if ordered else "off") if len(order) > 1 else g.vertices.select(F.col("id").alias(f"v{order[0]}"))
        rows = mine if rows is None else rows.crossJoin(mine)
        for x in piece:
            for y in placed:
                if how := relation(q, x, y, ordered):
                    rows = rows.where(packed.compare(F.col(f"v{x}"), how, F.col(f"v{y}")))
        placed += piece
    units = tuple(((v,), (x,)) for x in q.vertices if x not in q.min_cover for v in sorted(q.adjacency[x]))
    return _assemble(rows, g, q, units, sorted(placed), ordered, 2)
