"""The general worst-case-optimal join, one group of attributes at a time.

For every group of attributes the relations that speak of it are reduced by semi-joins with the partial
results, joined among themselves, and joined with the partial results. Groups of one attribute give
vertex growth; the vertices of a star or a clique at once give the overlapping binary join.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifloom.operators import compress as packed
from motifloom.operators.graph import DataGraph
from motifloom.operators.units import _edge_args
from motifloom.plans.ir import relation, use_symmetry
from motifloom.plans.optimize import greedy, star_cover_plan
from motifloom.plans.pattern import QueryGraph

SPLITS = ("vertex", "star", "clique")


def join(relations: list[DataFrame], order: list[str] | list[tuple[str, ...]] | None = None) -> DataFrame:
    """The natural join of relations of any arity, group by group of attributes (or one by one)."""
    given = order or list(dict.fromkeys(c for r in relations for c in r.columns))
    groups = [(a,) if isinstance(a, str) else tuple(a) for a in given]
    rows: DataFrame | None = None
    bound: list[str] = []
    for group in groups:
        views = [r.select(*[c for c in r.columns if c in bound], *[c for c in r.columns if c in group]).distinct() for r in relations if set(group) & set(r.columns)]
        if len(group) == 1:
            rows = _single(rows, views, group[0], bound)
        else:
            part = _among(_reduced(views, rows, bound))
            shared = [c for c in part.columns if c in bound]
            rows = part if rows is None else rows.join(part, shared) if shared else rows.crossJoin(part)
        bound += group
    return rows.select(*[a for group in groups for a in group])


def _single(rows: DataFrame | None, views: list[DataFrame], a: str, bound: list[str]) -> DataFrame:
    """One attribute: the view with most bound attributes brings it, the others reduce it."""
    views = sorted(views, key=lambda v: -len(v.columns))
    if rows is None:
        rows = views[0].select(a)
        for v in views[1:]:
            rows = rows.intersect(v.select(a))
        return rows
    shared = [c for c in views[0].columns if c in bound]
    rows = rows.join(views[0], shared) if shared else rows.crossJoin(views[0])
    for v in views[1:]:
        rows = rows.join(v, [c for c in v.columns if c in rows.columns], "left_semi")
    return rows


def _reduced(views: list[DataFrame], rows: DataFrame | None, bound: list[str]) -> list[DataFrame]:
    """Views without what the partial results rule out."""
    out = []
    for v in views:
        known = [c for c in v.columns if c in bound]
        out.append(v.join(rows.select(*known).distinct(), known, "left_semi") if known else v)
    return out


def _among(views: list[DataFrame]) -> DataFrame:
    """The natural join of a group's views, each next one sharing most columns with those before."""
    left = sorted(views, key=lambda v: -len(v.columns))
    rows = left.pop(0)
    while left:
        v = max(left, key=lambda v: len(set(v.columns) & set(rows.columns)))
        left.remove(v)
        shared = [c for c in v.columns if c in rows.columns]
        rows = rows.join(v, shared) if shared else rows.crossJoin(v)
    return rows


def groups_of(q: QueryGraph, split: str = "vertex", order: tuple[int, ...] | None = None) -> list[tuple[int, ...]]:
    """Query vertices in the groups that are popped at once: single ones, stars of a cover, or largest cliques first."""
    if split not in SPLITS:
        raise ValueError(f"split is one of {', '.join(SPLITS)}, not {split}")
    if split == "vertex":
        return [(v,) for v in order or greedy(q)]
    if split == "star":
        pieces = [tuple(u.vertices) for u in star_cover_plan(q).leaves]
    else:
        pieces = sorted([*q.cliques(3), *q.edges], key=lambda c: (-len(c), c))
    out, placed = [], set()
    while set(q.vertices) - placed:
        new = [p for p in pieces if set(p) - placed and (not placed or set(p) & placed)]
        best = max(new, key=lambda p: (len(p), len(set(p) & placed), [-v for v in p]))
        out.append(tuple(v for v in best if v not in placed))
        placed |= set(best)
    return out


def run(g: DataGraph, q: QueryGraph, *, symmetry: str = "auto", order: tuple[int, ...] | None = None, split: str = "vertex") -> DataFrame:
    """Matches as the natural join of one edge relation per query edge, with order and injectivity on top."""
    ordered = use_symmetry(q, symmetry)
    relations = []
    for a, b in q.edges:
        rows = g.pairs(**_edge_args(q, a, b)).select(F.col("u").alias(f"v{a}"), F.col("v").alias(f"v{b}"))
        how = relation(q, a, b, ordered)
        relations.append(rows.where(packed.compare(F.col(f"v{a}"), how, F.col(f"v{b}"))) if how else rows)
    rows = join(relations, [tuple(f"v{v}" for v in group) for group in groups_of(q, split, order)])
    for a in q.vertices:
        for b in range(a + 1, q.n + 1):
            how = relation(q, a, b, ordered)
            if how and not q.has_edge(a, b):
                rows = rows.where(packed.compare(F.col(f"v{a}"), how, F.col(f"v{b}")))
    return rows.select(*[f"v{v}" for v in q.vertices])
