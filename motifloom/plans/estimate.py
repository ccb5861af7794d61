"""Size estimates and worst-case bounds of patterns."""

from __future__ import annotations

import math

from motifloom.plans.pattern import QueryGraph


def sub_pattern(q: QueryGraph, edges) -> QueryGraph:
    """The pattern of some edges of q, renumbered, with labels."""
    used = sorted({v for e in edges for v in e})
    new = {v: i + 1 for i, v in enumerate(used)}
    labels = [q.label(v) for v in used] if q.labels else None
    return QueryGraph.from_edges([(new[a], new[b]) for a, b in edges], labels, n=len(used))


def _images(q: QueryGraph) -> int:
    return len(q.automorphisms) if not q.labelled else 1


def uniform(q: QueryGraph, stats: dict) -> float:
    """Every pair of vertices is an edge with the same probability."""
    n, m = stats["n"], stats["m"]
    return n**q.n * (2.0 * m / n**2) ** len(q.edges) / _images(q) if n else 0.0


def power_law(q: QueryGraph, stats: dict) -> float:
    """Edges fall between vertices in proportion to their expected degrees."""
    s, m = stats["s"], stats["m"]
    return math.prod(s[q.degree(v)] for v in q.vertices) / (2.0 * m) ** len(q.edges) / _images(q) if m else 0.0


def label(q: QueryGraph, stats: dict, label_pairs: dict, label_counts: dict) -> float:
    """Every pair of vertices with given labels is an edge with the probability seen between those labels."""
    size = 1.0
    for v in q.vertices:
        size *= label_counts.get(q.label(v), 0) if q.label(v) is not None else stats["n"]
    for a, b in q.edges:
        la, lb = q.label(a), q.label(b)
        pairs = sum(c for (x, y), c in label_pairs.items() if la in (None, x) and lb in (None, y))
        na = label_counts.get(la, 0) if la is not None else stats["n"]
        nb = label_counts.get(lb, 0) if lb is not None else stats["n"]
        size *= pairs / (na * nb) if na and nb else 0.0
    return size


def bound(q: QueryGraph, m: int) -> float:
    """The largest possible number of results: edges to the power of the fractional edge cover number."""
    return float(m) ** q.fractional_cover


def q_error(estimate: float, true: float) -> float:
    estimate, true = max(estimate, 1.0), max(true, 1.0)
    return max(estimate / true, true / estimate)


class Sizer:
    """Estimated sizes of the sub-patterns of one query, by model name."""

    def __init__(self, q: QueryGraph, stats: dict, model: str = "power_law", label_pairs: dict | None = None, label_counts: dict | None = None, exact=None):
        self.q, self.stats, self.model, self.exact = q, stats, model, exact
        self.label_pairs, self.label_counts = label_pairs or {}, label_counts or {}
        self._known: dict = {}

    def __call__(self, edges) -> float:
        edges = tuple(sorted(edges))
        if edges not in self._known:
            p = sub_pattern(self.q, edges)
            if self.model == "bound":
                size = bound(p, self.stats["m"])
            elif self.model == "uniform":
                size = uniform(p, self.stats)
            elif self.model == "exact":
                size = float(self.exact(p))
            elif p.labelled and self.label_pairs:
                size = label(p, self.stats, self.label_pairs, self.label_counts)
            else:
                size = power_law(p, self.stats)
            self._known[edges] = size
        return self._known[edges]
