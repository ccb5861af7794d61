"""Join units: edges, stars, wedges, cliques and bud units as relations."""

from __future__ import annotations

from functools import reduce
from itertools import permutations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifloom.operators import compress as packed
from motifloom.operators.graph import DataGraph
from motifloom.operators.partition import clique_buds, clique_table
from motifloom.plans.ir import UnitNode, relation
from motifloom.plans.pattern import QueryGraph


def _edge_args(q: QueryGraph, y: int, x: int) -> dict:
    """How to look up neighbours of an image of y that can be images of x."""
    forward = (y, x) in q.edges
    e = ((y, x) if forward else (x, y)) if q.directed else (min(x, y), max(x, y))
    return {"ulabel": q.label(y), "vlabel": q.label(x), "elabel": q.elabel(e), "inward": q.directed and not forward}


def _checks(q: QueryGraph, x: int, placed, symmetry: bool):
    tests = [(y, how) for y in placed if (how := relation(q, x, y, symmetry))]
    return tests


def edge(g: DataGraph, q: QueryGraph, u: UnitNode, symmetry: bool) -> DataFrame:
    a, b = u.edges[0]
    rows = g.pairs(**_edge_args(q, a, b)).select(F.col("u").alias(f"v{a}"), F.col("v").alias(f"v{b}"))
    how = relation(q, a, b, symmetry)
    return rows.where(packed.compare(F.col(f"v{a}"), how, F.col(f"v{b}"))) if how else rows


def star(g: DataGraph, q: QueryGraph, u: UnitNode, symmetry: bool) -> DataFrame:
    """All leaves of a root come out of its own neighbour list: no data moves once lists are in place.

    Each leaf is filtered by order and injectivity as its column appears; leaves in u.arrays stay arrays.
    """
    root = u.root
    leaves = [v for v in u.vertices if v != root and v not in u.arrays] + [v for v in u.vertices if v in u.arrays]
    sources = {}
    for x in leaves:
        sources.setdefault(tuple(_edge_args(q, root, x).items()), []).append(x)
    rows, lists = None, {}
    for k, (args, xs) in enumerate(sources.items()):
        near = g.adjacency(**dict(args)).select(F.col("u").alias(f"v{root}"), F.col("nbrs").alias(f"_n{k}"))
        rows = near if rows is None else rows.join(near, f"v{root}")
        lists |= {x: f"_n{k}" for x in xs}
    placed = [root]
    held = list(dict.fromkeys(lists.values()))
    for x in leaves:
        tests = _checks(q, x, placed, symmetry)
        values = F.col(lists[x])
        if tests:
            values = F.filter(values, packed.checker(tests))
        kept = [c for c in rows.columns if c.startswith(("v", "c"))]
        if x in u.arrays:
            rows = rows.select(*kept, *held, values.alias(f"c{x}")).where(F.size(f"c{x}") > 0)
        else:
            rows = rows.select(*kept, *held, F.explode(values).alias(f"v{x}"))
            placed.append(x)
    return rows.drop(*held)


def _assignments(q: QueryGraph, vertices: tuple[int, ...], symmetry: bool) -> list[tuple[int, ...]]:
    """Which member of a clique, in ascending order, each vertex may take: vertices[i] the p[i]-th smallest."""
    good = []
    for p in permutations(range(len(vertices))):
        hows = [(p[i], relation(q, vertices[i], vertices[j], symmetry), p[j]) for i in range(len(p)) for j in range(i + 1, len(p))]
        if not any((how == "<" and a > b) or (how == ">" and a < b) for a, how, b in hows):
            good.append(p)
    return good


def clique(g: DataGraph, q: QueryGraph, u: UnitNode, symmetry: bool, triangle_index: str | None = None) -> DataFrame:
    """Each clique is found once, then put into every assignment that order and labels allow.

    With a triangle index cliques are read off the lists of their smallest vertex, and the vertex in
    u.arrays, if any, stays an array: the common neighbours of all others. Without it they are grown.
    """
    single = tuple(v for v in u.vertices if v not in u.arrays)
    k, held = len(single), []
    if u.arrays:
        sets, held = clique_buds(g, k, triangle_index == "ordered"), ["buds"]
    else:
        sets = clique_from_index(g, k, triangle_index == "ordered") if triangle_index and k > 2 else clique_table(g, k)
    sets = sets.toDF(*[f"_s{i}" for i in range(k)], *held)
    choices = [F.struct(*[F.col(f"_s{p[i]}").alias(f"v{v}") for i, v in enumerate(single)]) for p in _assignments(q, single, symmetry)]
    rows = sets.select(F.explode(F.array(*choices)).alias("m") if len(choices) > 1 else choices[0].alias("m"), *held).select("m.*", *held)
    if q.labelled:
        for v in single:
            if q.label(v) is not None:
                rows = rows.join(g.vertices.where(F.col("label") == q.label(v)).select(F.col("id").alias(f"v{v}")), f"v{v}", "left_semi")
    if u.arrays:
        (x,) = u.arrays
        values = F.col("buds")
        if q.label(x) is not None:  # the list of one member, cut by label
            near = g.adjacency(**_edge_args(q, single[0], x)).select(F.col("u").alias(f"v{single[0]}"), F.col("nbrs").alias("_n"))
            rows = rows.join(near, f"v{single[0]}")
            values = F.array_intersect("buds", "_n")
        tests = _checks(q, x, single, symmetry)
        kept = F.filter(values, packed.checker(tests)) if tests else values
        rows = rows.select(*[f"v{v}" for v in single], kept.alias(f"c{x}")).where(F.size(f"c{x}") > 0)
    return rows


def clique_from_index(g: DataGraph, k: int, ordered: bool = True) -> DataFrame:
    """v1 < … < vk from the triangle index: every pair of the last k - 1 is a local edge of v1."""
    names = [f"v{i}" for i in range(1, k)]
    last = F.col(names[-1])
    above = F.filter("buds", lambda e: e > last)
    return clique_buds(g, k - 1, ordered).select(*names, F.explode(above).alias(f"v{k}"))


def bud(g: DataGraph, x: int) -> DataFrame:
    """v1 < … < vx for every x-clique, with the array of all vertices adjacent to all of them."""
    rows = clique_table(g, x) if x > 1 else g.vertices.select(F.col("id").alias("v1"))
    near = g.adjacency()
    for i in range(1, x + 1):
        rows = rows.join(near.select(F.col("u").alias(f"v{i}"), F.col("nbrs").alias(f"_n{i}")), f"v{i}")
    found = reduce(F.array_intersect, [F.col(f"_n{i}") for i in range(1, x + 1)])
    return rows.select(*[f"v{i}" for i in range(1, x + 1)], found.alias("buds")).where(F.size("buds") > 0)


def unit(g: DataGraph, q: QueryGraph, u: UnitNode, symmetry: bool, triangle_index: str | None = None) -> DataFrame:
    if u.kind == "edge":
        return edge(g, q, u, symmetry)
    if u.kind == "clique":
        return clique(g, q, u, symmetry, triangle_index)
    return star(g, q, u, symmetry)
