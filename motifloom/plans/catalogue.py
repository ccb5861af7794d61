"""The query workloads: unlabelled q1 to q9, labelled l1 to l9, and generic shapes."""

from __future__ import annotations

from itertools import combinations

from motifloom.plans.pattern import QueryGraph


def _edges(text: str) -> list[tuple[int, int]]:
    return [(int(e[0]), int(e[1])) for e in text.split()]


# fixed values: the shapes of the unlabelled workload
UNLABELLED = {
    "q1": "12 24 34 13",
    "q2": "12 13 23 14 24",
    "q3": "12 13 14 23 24 34",
    "q4": "12 23 34 14 15 25",
    "q5": "12 13 15 23 24 25 34",
    "q6": "12 13 14 15 23 24 25 34 35",
    "q7": "12 23 34 45",
    "q8": "12 23 34 14 15 25 36 46",
    "q9": "13 35 12 23 34 45 16 56",
}

#: Vertex labels of the typed graph.
LABELS = ("customer", "order", "part", "supplier", "nation", "region", "brand", "type", "segment", "priority")
CODE = {name: i + 1 for i, name in enumerate(LABELS)}

# fixed values: the labelled workload over the typed graph, as vertex labels and edges
_TYPED = {
    "l1": ("customer customer nation", "12 13 23"),
    "l2": ("customer customer order part order", "12 23 34 45 15"),
    "l3": ("order customer part supplier", "12 13 14"),
    "l4": ("part supplier part supplier", "12 23 34 14"),
    "l5": ("part brand type supplier", "12 13 14"),
    "l6": ("order part supplier nation customer", "12 13 23 34 45 15"),
    "l7": ("customer order part brand", "12 23 34"),
    "l8": ("customer nation region nation customer segment", "12 23 34 45 56 16"),
    "l9": ("customer customer customer nation nation nation region", "12 13 23 14 25 36 47 57 67"),
}


def unlabelled(name: str) -> QueryGraph:
    return QueryGraph.from_edges(_edges(UNLABELLED[name]), name=name)


def labelled(name: str) -> QueryGraph:
    kinds, edges = _TYPED[name]
    return QueryGraph.from_edges(_edges(edges), labels=[CODE[k] for k in kinds.split()], name=name)


def example() -> QueryGraph:
    """The running example: a 4-cycle with the chord 2-4."""
    return QueryGraph.from_edges(_edges("12 23 34 14 24"), name="example")


EXAMPLE_EDGES = _edges("12 26 56 15 25 35 36 34 45")
EXAMPLE_LABELS = {1: 1, 4: 1, 2: 2, 3: 2, 6: 3, 5: 4}


def clique(k: int) -> QueryGraph:
    return QueryGraph.from_edges(combinations(range(1, k + 1), 2), name=f"clique{k}", n=k)


def star(k: int) -> QueryGraph:
    return QueryGraph.from_edges([(1, i) for i in range(2, k + 2)], name=f"star{k}")


def cycle(k: int) -> QueryGraph:
    return QueryGraph.from_edges([(i, i % k + 1) for i in range(1, k + 1)], name=f"cycle{k}")


def path(k: int) -> QueryGraph:
    """A path of k vertices."""
    return QueryGraph.from_edges([(i, i + 1) for i in range(1, k)], name=f"path{k}")


def book(k: int) -> QueryGraph:
    """k triangles on one common edge."""
    return QueryGraph.from_edges([(1, 2), *[(i, j) for j in range(3, k + 3) for i in (1, 2)]], name=f"book{k}")


def wheel(k: int) -> QueryGraph:
    """A hub and a rim of k vertices."""
    return QueryGraph.from_edges([*[(1, i) for i in range(2, k + 2)], *[(i, i + 1 if i < k + 1 else 2) for i in range(2, k + 2)]], name=f"wheel{k}")


def tailed_triangle() -> QueryGraph:
    return QueryGraph.from_edges(_edges("12 13 23 14"), name="tailed_triangle")


def by_name(name: str) -> QueryGraph:
    if name in UNLABELLED:
        return unlabelled(name)
    if name in _TYPED:
        return labelled(name)
    fixed = {"edge": path(2), "wedge": path(3), "triangle": clique(3), "tailed_triangle": tailed_triangle(), "example": example()}
    if name in fixed:
        return fixed[name]
    for prefix, make in (("clique", clique), ("star", star), ("cycle", cycle), ("path", path), ("book", book), ("wheel", wheel)):
        if name.startswith(prefix) and name[len(prefix) :].isdigit():
            return make(int(name[len(prefix) :]))
    raise KeyError(name)
