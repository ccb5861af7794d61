"""Plan search: growth orders, join trees, hypercube shares."""

from __future__ import annotations

import math
from itertools import combinations, product

from motifloom.plans.estimate import Sizer
from motifloom.plans.ir import GrowthPlan, JoinNode, Round, UnitNode, joins_of, use_symmetry
from motifloom.plans.pattern import QueryGraph

# ---------------------------------------------------------------- growth


def _extend(q: QueryGraph, order: list[int], allowed: set[int], freq: dict | None) -> list[int]:
    """Goes on with the vertex that has most edges to those chosen; rarer labels, then smaller ids first."""
    while allowed - set(order):
        rest = [v for v in sorted(allowed - set(order)) if not order or q.adjacency[v] & set(order)] or sorted(allowed - set(order))
        rare = lambda v: (freq or {}).get(q.label(v), 0)
        if order:
            order.append(min(rest, key=lambda v: (-len(q.adjacency[v] & set(order)), rare(v), v)))
        else:
            order.append(min(rest, key=lambda v: (-q.degree(v), rare(v), v)))
    return order


def greedy(q: QueryGraph, label_freq: dict | None = None) -> tuple[int, ...]:
    return tuple(_extend(q, [], set(q.vertices), label_freq))


def cover_first(q: QueryGraph, label_freq: dict | None = None) -> tuple[int, ...]:
    """The greedy order inside a minimum connected vertex cover, then outside."""
    core = q.min_connected_covers[0]
    order: list[int] = []
    while core - set(order):
        near = [v for v in sorted(core - set(order)) if not order or q.adjacency[v] & set(order)]
        order.append(min(near, key=lambda v: (-len(q.adjacency[v] & set(order)), -q.degree(v) if not order else 0, (label_freq or {}).get(q.label(v), 0), v)))
    return tuple(_extend(q, order, set(q.vertices), label_freq))


def compressible(q: QueryGraph, order: tuple[int, ...]) -> tuple[int, ...]:
    """Vertices of an order without later neighbours; the first is needed to start from."""
    return tuple(v for i, v in enumerate(order) if i and not q.adjacency[v] & set(order[i + 1 :]))


def _groups(q: QueryGraph, x: int, back: tuple[int, ...], ordered_index: bool, symmetry: bool) -> tuple[tuple[int, tuple[int, ...]], ...]:
    """Triangle-index groups for target x, greedily the largest first.

    A visit to y resolves those y' in back that are query-neighbours of y. With the ordered index an
    edge is stored only if both its ends exceed the anchor, so O_Q must prove that for y' and for x.
    """
    left, out = set(back), []
    above = lambda low, high: symmetry and (low, high) in q.symmetry_order

    def inside(y: int) -> list[int]:
        return [z for z in sorted(left) if z != y and q.has_edge(y, z) and (not ordered_index or (above(y, z) and above(y, x)))]

    while left:
        y = min(left, key=lambda v: (-len(inside(v)), v))
        got = tuple(inside(y))
        out.append((y, got))
        left -= {y, *got}
    return tuple(out)


def growth_plan(q: QueryGraph, order="greedy", compression: bool = False, triangle_index: str | None = None, label_freq: dict | None = None, symmetry: str = "auto") -> GrowthPlan:
    if isinstance(order, str):
        order = {"greedy": greedy, "cover_first": cover_first}[order](q, label_freq)
    order = tuple(order)
    if sorted(order) != list(q.vertices):
        raise ValueError("an order must hold every query vertex once")
    if q.n > 1 and not q.connected():
        raise ValueError("the pattern must be connected")
    arrays = set(compressible(q, order)) if compression else set()
    rounds = []
    for i, x in enumerate(order[1:], 1):
        back = tuple(sorted(q.adjacency[x] & set(order[:i])))
        if not back:
            raise ValueError(f"vertex {x} has no neighbour among those placed before it")
        groups = _groups(q, x, back, triangle_index == "ordered", use_symmetry(q, symmetry)) if triangle_index and len(back) > 1 else ()
        rounds.append(Round(x, back, x in arrays, groups))
    return GrowthPlan(order, tuple(rounds))


# ---------------------------------------------------------------- join trees


def _star(q: QueryGraph, root: int, leaves, kind: str = "star") -> UnitNode:
    edges = tuple(sorted((root, v) if (root, v) in q.edges else (v, root) for v in leaves))
    return UnitNode(kind, tuple(sorted({root, *leaves})), edges, root)


def unit_of(q: QueryGraph, kind: str, vertices, root: int = 0) -> UnitNode:
    """A join unit for trees of one's own: a clique of vertices, or a star of leaves around root."""
    return _star(q, root, vertices, kind) if root else UnitNode(kind, tuple(sorted(vertices)), q.induced_edges(vertices))


def edge_plan(q: QueryGraph) -> JoinNode | UnitNode:
    """One query edge at a time, each next one touching those before."""
    left = sorted(q.edges)
    first = min(left)
    node: JoinNode | UnitNode = UnitNode("edge", tuple(sorted(first)), (first,))
    left.remove(first)
    while left:
        e = min((x for x in left if set(x) & set(node.vertices)), key=lambda x: (-len(set(x) & set(node.vertices)), x))
        node = JoinNode(node, UnitNode("edge", tuple(sorted(e)), (e,)))
        left.remove(e)
    return node


def star_cover_plan(q: QueryGraph, label_freq: dict | None = None) -> JoinNode | UnitNode:
    """Left-deep over stars: each vertex of a cover with its edges that are not used yet."""
    cover = min((c for c in q.vertex_covers if len(c) == len(q.min_cover)), key=lambda c: (-sum(q.degree(v) for v in c), sorted(c)))
    used: set = set()
    units: list[UnitNode] = []
    rest = set(cover)
    while rest:
        placed = {v for u in units for v in u.vertices}
        near = [v for v in rest if not units or v in placed or q.adjacency[v] & placed] or list(rest)
        root = min(near, key=lambda v: (-q.degree(v), (label_freq or {}).get(q.label(v), 0), v))
        rest.discard(root)
        leaves = [v for v in sorted(q.adjacency[root]) if frozenset((root, v)) not in used]
        used |= {frozenset((root, v)) for v in leaves}
        if leaves:
            units.append(_star(q, root, leaves))
    return _left_deep(units)


def _left_deep(units: list[UnitNode]) -> JoinNode | UnitNode:
    node: JoinNode | UnitNode = units[0]
    left = units[1:]
    while left:
        nxt = max(left, key=lambda u: (len(set(u.vertices) & set(node.vertices)), -left.index(u)))
        node = JoinNode(node, nxt)
        left.remove(nxt)
    return node


def cover_first_tree(q: QueryGraph) -> JoinNode | UnitNode:
    """Left-deep: the edges of a minimum connected cover one by one, then for each other vertex its star into the cover."""
    core = q.min_connected_covers[0]
    inside = q.induced_edges(core)
    units = [_star(q, v, sorted(q.adjacency[v])) for v in q.vertices if v not in core]
    if not inside:  # a star's centre covers it alone
        (centre,) = core
        return _star(q, centre, sorted(q.adjacency[centre]))
    left = sorted(inside)
    node: JoinNode | UnitNode = UnitNode("edge", tuple(sorted(left[0])), (left.pop(0),))
    while left:
        e = min((x for x in left if set(x) & set(node.vertices)), key=lambda x: (-len(set(x) & set(node.vertices)), x))
        node = JoinNode(node, UnitNode("edge", tuple(sorted(e)), (e,)))
        left.remove(e)
    for u in units:
        node = JoinNode(node, u)
    return node


def wedge_plan(q: QueryGraph) -> JoinNode | UnitNode:
    """Left-deep over stars of at most two edges; every edge used once.

    Each step takes two unused edges at the vertex that touches most of what is placed.
    """
    left = {frozenset(e) for e in q.edges}
    units: list[UnitNode] = []
    while left:
        placed = {v for u in units for v in u.vertices}
        options = []
        for root in q.vertices:
            mine = sorted(v for v in q.adjacency[root] if frozenset((root, v)) in left)
            options += [(root, pair) for k in (2, 1) for pair in combinations(mine, k)]
        if placed:
            options = [o for o in options if {o[0], *o[1]} & placed]
        root, leaves = max(options, key=lambda o: (len(o[1]), len({o[0], *o[1]} & placed), -o[0], [-v for v in o[1]]))
        left -= {frozenset((root, v)) for v in leaves}
        units.append(_star(q, root, leaves, "wedge"))
    return _left_deep(units)


def star_to_wedge(plan: JoinNode | UnitNode, q: QueryGraph) -> JoinNode | UnitNode:
    """Splits every star of a left-deep plan into stars of at most two edges, in place."""
    out: JoinNode | UnitNode | None = None
    for unit in plan.leaves:
        leaves = [v for v in unit.vertices if v != unit.root]
        shared = [v for v in leaves if out is not None and v in out.vertices]
        leaves = shared + [v for v in leaves if v not in shared]
        for i in range(0, len(leaves), 2):
            piece = _star(q, unit.root, leaves[i : i + 2], "wedge")
            out = piece if out is None else JoinNode(out, piece)
    return out


def _all_units(q: QueryGraph, kind: str) -> list[UnitNode]:
    units = [UnitNode("edge", tuple(sorted(e)), (e,)) for e in q.edges] if kind == "edge" else []
    if kind in ("star", "wedge", "clique"):
        for root in q.vertices:
            near = sorted(q.adjacency[root])
            most = 2 if kind == "wedge" else len(near)
            units += [_star(q, root, leaves, "wedge" if kind == "wedge" else "star") for k in range(1, most + 1) for leaves in combinations(near, k)]
    if kind == "clique":
        units += [UnitNode("clique", c, q.induced_edges(c)) for c in q.cliques(3)]
    return units


def bushy(q: QueryGraph, sizer: Sizer, unit: str = "clique", overlap: bool = True, left_deep: bool = False, label_freq: dict | None = None) -> JoinNode | UnitNode:
    """The cheapest join tree by dynamic programming over connected sets of covered edges.

    A tree costs the sizes of its units and intermediate results. With overlap the two sides of a
    join may share query edges, which then act as a semi-join.
    """
    rare = lambda vs: sum((label_freq or {}).get(q.label(v), 0) for v in vs)
    best: dict[frozenset, tuple[tuple, JoinNode | UnitNode]] = {}
    units = _all_units(q, unit)
    for u in sorted(units, key=lambda u: (u.kind != "clique", len(u.edges), u.vertices, u.root)):
        state, cost = frozenset(u.edges), (sizer(u.edges), 0, rare(u.vertices))
        if state not in best or cost < best[state][0]:
            best[state] = (cost, u)
    leaves = dict(best)
    full = frozenset(q.edges)
    changed = True
    while changed:
        changed = False
        now = list(best.items())
        for (s1, (c1, n1)), (s2, (c2, n2)) in product(now, leaves.items() if left_deep else now):
            both = s1 | s2
            if both == s1 or both == s2 or (not overlap and s1 & s2) or not set(n1.vertices) & set(n2.vertices):
                continue
            out = sizer(both) if both != full else 0.0
            cost = (c1[0] + c2[0] + out, c1[1] + c2[1] + 1, c1[2] + c2[2])
            if both not in best or _less(cost, best[both][0]):
                best[both] = (cost, JoinNode(n1, n2))
                changed = True
    return best[full][1]


def _less(a: tuple, b: tuple) -> bool:
    """Clearly cheaper, or equally cheap with fewer joins or rarer labels."""
    if not math.isclose(a[0], b[0], rel_tol=1e-9):
        return a[0] < b[0]
    return a[1:] < b[1:]


def plan_cost(plan: JoinNode | UnitNode, sizer: Sizer) -> float:
    """Sizes of all units and of all results but the last."""
    nodes = joins_of(plan)
    return sum(sizer(u.edges) for u in plan.leaves) + sum(sizer(n.edges) for n in nodes[:-1])


def growth_cost(q: QueryGraph, plan: GrowthPlan, sizer: Sizer) -> float:
    """Sizes of the partial results of every round but the last."""
    return sum(sizer(q.induced_edges(plan.order[:k])) for k in range(2, q.n))


def batch_vertex(plan: JoinNode | UnitNode) -> int:
    """The join-key vertex that occurs in most units; smaller ids first. Without a join any vertex that is no array."""
    keys = {v for n in joins_of(plan) for v in n.key} or set(plan.vertices) - {v for u in plan.leaves for v in u.arrays}
    return min(keys, key=lambda v: (-sum(v in u.vertices for u in plan.leaves), v))


# ---------------------------------------------------------------- hypercube shares


def routed_edges(q: QueryGraph, shares: tuple[int, ...], m: int | dict[tuple[int, int], int], ordered: bool) -> float:
    """Edge copies sent: for each query edge, one per choice of the other coordinates.

    m is the number of data edges, or tells for each query edge how many arcs have its labels.
    """
    total = math.prod(shares)
    one_way = lambda a, b: ordered and ((a, b) in q.symmetry_order or (b, a) in q.symmetry_order)
    arcs = lambda e: (m[e] if isinstance(m, dict) else 2 * m) / (2 if one_way(*e) else 1)
    return sum(arcs((a, b)) * total / (shares[a - 1] * shares[b - 1]) for a, b in q.edges)


def doubled_shares(q: QueryGraph, cells: int, m: int | dict[tuple[int, int], int], ordered: bool) -> tuple[int, ...]:
    """Shares that are powers of two: as long as there is room, the one that takes most from a cell's load is doubled."""
    s = [1] * q.n
    load = lambda s: routed_edges(q, tuple(s), m, ordered) / math.prod(s)
    while 2 * math.prod(s) <= cells:
        s = min(([*s[:i], 2 * s[i], *s[i + 1 :]] for i in range(q.n)), key=load)
    return tuple(s)


def fractional_shares(q: QueryGraph, cells: int, steps: int = 420) -> tuple[float, ...]:
    """Share exponents that minimise the largest load exponent, by descent on a lattice of exponents.

    The load of an edge is M / (b_i b_j), so the smallest sum of two exponents over the query edges
    is to be as large as possible while all exponents sum to 1. steps is a multiple of 2 to 7, so that
    equal exponents of up to seven vertices lie on the lattice.
    """
    x = {v: steps // q.n for v in q.vertices}
    for v in list(q.vertices)[: steps - sum(x.values())]:
        x[v] += 1

    def worth(x):
        sums = sorted(x[a] + x[b] for a, b in q.edges)
        return sums

    improved = True
    while improved:
        improved = False
        for a, b in product(q.vertices, q.vertices):
            if a != b and x[a] > 0:
                y = x | {a: x[a] - 1, b: x[b] + 1}
                if worth(y) > worth(x):
                    x, improved = y, True
    return tuple(cells ** (x[v] / steps) for v in q.vertices)


def shares(q: QueryGraph, cells: int, method="optimize", m: int | dict[tuple[int, int], int] = 1, ordered: bool = True) -> tuple[int, ...]:
    """Bucket numbers per query vertex whose product is at most cells."""
    if not isinstance(method, str):
        if len(method) != q.n or math.prod(method) > cells:
            raise ValueError("there must be a share for every vertex and at most `cells` cells")
        return tuple(method)
    if method == "uniform":
        b = int(round(cells ** (1 / q.n)))
        b -= b**q.n > cells
        return (max(b, 1),) * q.n
    if method == "round_down":
        return tuple(max(1, math.floor(b + 1e-9)) for b in fractional_shares(q, cells))
    if q.n <= 6 and cells <= 4096:
        found: list[tuple[int, ...]] = []

        def choose(prefix: tuple[int, ...], room: int) -> None:
            if len(prefix) == q.n:
                if room == 1 or math.prod(prefix) * 2 > cells:  # others leave half of the cells idle
                    found.append(prefix)
                return
            for b in range(1, room + 1):
                choose((*prefix, b), room // b)

        choose((), cells)
    else:
        near = [sorted({max(1, math.floor(b) + d) for d in (-1, 0, 1, 2)}) for b in fractional_shares(q, cells)]
        found = [s for s in product(*near) if math.prod(s) <= cells]
        if isinstance(m, dict):  # the fractions know no sizes
            found.append(doubled_shares(q, cells, m, ordered))
    return min(found, key=lambda s: (cells - math.prod(s), routed_edges(q, s, m, ordered), s))
