"""Query graphs: small, immutable, driver-side, with exact structure functions (n up to about 10)."""

from __future__ import annotations

import re
from dataclasses import dataclass, field
from functools import cached_property
from itertools import combinations, permutations

Edge = tuple[int, int]


@dataclass(frozen=True)
class QueryGraph:
    """Vertices are 1..n. An undirected edge is (i, j) with i < j; a directed one is (from, to)."""

    n: int
    edges: tuple[Edge, ...]
    labels: tuple[object, ...] | None = None
    elabels: tuple[tuple[Edge, object], ...] = ()
    directed: bool = False
    name: str = field(default="", compare=False)

    # ------------------------------------------------------------ building

    @staticmethod
    def from_edges(edges, labels=None, elabels=None, directed: bool = False, name: str = "", n: int | None = None) -> QueryGraph:
        fixed = []
        for a, b in edges:
            if a == b:
                raise ValueError("a query graph has no loops")
            fixed.append((a, b) if directed or a < b else (b, a))
        size = n or max((v for e in fixed for v in e), default=0)
        if labels is not None:
            labels = tuple(labels[v] for v in range(1, size + 1)) if isinstance(labels, dict) else tuple(labels)
            if len(labels) != size:
                raise ValueError("there must be a label for every vertex")
        named = tuple(sorted(((e if directed or e[0] < e[1] else e[::-1]), x) for e, x in (elabels or {}).items()))
        return QueryGraph(size, tuple(sorted(set(fixed))), labels, named, directed, name)

    @staticmethod
    def parse(text: str, name: str = "") -> QueryGraph:
        """`a-b, b-c; a:Customer, c:7` (undirected) or `a>b` (directed); `a-[x]-b` labels an edge.

        Vertices are numbered in the order in which they first occur.
        """
        pattern, _, marks = text.partition(";")
        ids: dict[str, int] = {}
        edges, elabels, directed = [], {}, False
        for part in filter(None, (p.strip() for p in pattern.split(","))):
            m = re.fullmatch(r"(\w+)\s*(?:-\s*\[(\w+)\]\s*)?(->|>|-)\s*(\w+)", part)
            if not m:
                raise ValueError(f"not an edge: {part}")
            a, b, arrow = m[1], m[4], m[3]
            directed |= ">" in arrow
            e = tuple(ids.setdefault(x, len(ids) + 1) for x in (a, b))
            edges.append(e)
            if m[2]:
                elabels[e] = int(m[2]) if m[2].isdigit() else m[2]
        labels = None
        if marks.strip():
            labels = {v: None for v in ids.values()}
            for part in marks.split(","):
                v, _, x = part.strip().partition(":")
                labels[ids[v]] = int(x) if x.isdigit() else x
        return QueryGraph.from_edges(edges, labels, elabels, directed, name or text)

    # ------------------------------------------------------------ plain structure

    @cached_property
    def vertices(self) -> tuple[int, ...]:
        return tuple(range(1, self.n + 1))

    @cached_property
    def adjacency(self) -> dict[int, frozenset[int]]:
        near: dict[int, set[int]] = {v: set() for v in self.vertices}
        for a, b in self.edges:
            near[a].add(b)
            near[b].add(a)
        return {v: frozenset(x) for v, x in near.items()}

    def degree(self, v: int) -> int:
        return len(self.adjacency[v])

    def has_edge(self, a: int, b: int) -> bool:
        return b in self.adjacency[a]

    def label(self, v: int):
        return self.labels[v - 1] if self.labels else None

    def elabel(self, e: Edge):
        return dict(self.elabels).get(e)

    @property
    def labelled(self) -> bool:
        return self.labels is not None and any(x is not None for x in self.labels)

    def induced_edges(self, chosen) -> tuple[Edge, ...]:
        chosen = set(chosen)
        return tuple(e for e in self.edges if e[0] in chosen and e[1] in chosen)

    def connected(self, chosen=None) -> bool:
        chosen = set(self.vertices if chosen is None else chosen)
        if not chosen:
            return True
        seen, stack = set(), [min(chosen)]
        while stack:
            v = stack.pop()
            if v not in seen:
                seen.add(v)
                stack.extend(self.adjacency[v] & chosen)
        return seen == chosen

    # ------------------------------------------------------------ symmetry

    @cached_property
    def automorphisms(self) -> tuple[tuple[int, ...], ...]:
        """All label-preserving self-isomorphisms, as the images of 1..n."""
        edges, elabels, out = set(self.edges), dict(self.elabels), []

        def fits(image: list[int], v: int, w: int) -> bool:
            if self.degree(v) != self.degree(w) or self.label(v) != self.label(w):
                return False
            for u in range(1, v):
                x = image[u - 1]
                for a, b, c, d in ((u, v, x, w), (v, u, w, x)):
                    one = (a, b) if self.directed or a < b else (b, a)
                    two = (c, d) if self.directed or c < d else (d, c)
                    if (one in edges) != (two in edges) or elabels.get(one) != elabels.get(two):
                        return False
            return True

        def extend(image: list[int]) -> None:
            v = len(image) + 1
            if v > self.n:
                out.append(tuple(image))
                return
            for w in self.vertices:
                if w not in image and fits(image, v, w):
                    extend([*image, w])

        extend([])
        return tuple(out)

    @cached_property
    def symmetry_order(self) -> tuple[Edge, ...]:
        """Pairs (i, j), meaning f(v_i) < f(v_j), that leave one match of each automorphism class.

        The smallest vertex of the largest orbit goes below its orbit and is then fixed; the group
        that remains is treated alike until only the identity is left.
        """
        group, order = list(self.automorphisms), []
        while len(group) > 1:
            orbits = {v: frozenset(g[v - 1] for g in group) for v in self.vertices}
            low = min(self.vertices, key=lambda v: (-len(orbits[v]), v))
            order += [(low, w) for w in sorted(orbits[low]) if w != low]
            group = [g for g in group if g[low - 1] == low]
        return tuple(sorted(order))

    # ------------------------------------------------------------ covers and pieces

    def covers(self, chosen) -> bool:
        return all(a in chosen or b in chosen for a, b in self.edges)

    @cached_property
    def vertex_covers(self) -> tuple[frozenset[int], ...]:
        return tuple(frozenset(c) for k in range(self.n + 1) for c in combinations(self.vertices, k) if self.covers(set(c)))

    @cached_property
    def min_cover(self) -> frozenset[int]:
        return self.vertex_covers[0]

    @cached_property
    def min_connected_covers(self) -> tuple[frozenset[int], ...]:
        good = [c for c in self.vertex_covers if self.connected(c)]
        return tuple(c for c in good if len(c) == len(good[0]))

    def cliques(self, low: int = 3) -> list[tuple[int, ...]]:
        return [c for k in range(low, self.n + 1) for c in combinations(self.vertices, k) if all(self.has_edge(a, b) for a, b in combinations(c, 2))]

    @cached_property
    def fractional_cover(self) -> float:
        """Minimum fractional edge cover number; an optimum with weights 0, 1/2 and 1 exists.

        Half-integral covers are those of the bipartite double cover: n minus half its maximum matching.
        """
        match: dict[int, int] = {}

        def augment(v: int, seen: set[int]) -> bool:
            for w in self.adjacency[v]:
                if w not in seen:
                    seen.add(w)
                    if w not in match or augment(match[w], seen):
                        match[w] = v
                        return True
            return False

        if any(not self.adjacency[v] for v in self.vertices):
            return float("inf")
        size = sum(augment(v, set()) for v in self.vertices)
        return self.n - size / 2

    @cached_property
    def clique_buds(self) -> tuple[frozenset[int], tuple[tuple[tuple[int, ...], tuple[int, ...]], ...]]:
        """A core (minimum connected cover) and bud units: (clique vertices, buds), buds adjacent to all of them.

        Every vertex outside the core has all its neighbours in it; vertices with the same neighbours
        share a unit. Neighbours that are no clique give one unit per maximal clique among them.
        """
        core = self.min_connected_covers[0]
        units: dict[tuple[int, ...], list[int]] = {}
        for v in self.vertices:
            if v in core:
                continue
            near = sorted(self.adjacency[v])
            parts = [c for k in range(len(near), 0, -1) for c in combinations(near, k) if all(self.has_edge(a, b) for a, b in combinations(c, 2))]
            chosen, left = [], set(near)
            for c in parts:
                if left & set(c) and set(c) <= set(near):
                    chosen.append(c)
                    left -= set(c)
                if not left:
                    break
            for c in chosen:
                units.setdefault(c, []).append(v)
        return core, tuple((c, tuple(vs)) for c, vs in sorted(units.items()))

    # ------------------------------------------------------------ brute force, for tests

    def brute_force(self, edges, labels: dict | None = None, order: bool | None = None) -> set[tuple[int, ...]]:
        """All matches by trying every injective mapping."""
        order = (not self.labelled) if order is None else order
        have = set(edges) if self.directed else {e for a, b in edges for e in ((a, b), (b, a))}
        nodes = sorted({v for e in edges for v in e})
        out = set()
        for f in permutations(nodes, self.n):
            if all((f[a - 1], f[b - 1]) in have for a, b in self.edges) and (not self.labelled or all(self.label(v) is None or labels[f[v - 1]] == self.label(v) for v in self.vertices)):
                if not order or all(f[a - 1] < f[b - 1] for a, b in self.symmetry_order):
                    out.add(f)
        return out
