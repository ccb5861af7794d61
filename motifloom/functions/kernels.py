"""Local matching kernels over a graph in compressed sparse rows, vectorised in NumPy.

All kernels give an array of matches (rows) by query vertex (columns), as original ids.
"""

from __future__ import annotations

import os
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa

from motifloom.plans.ir import relation
from motifloom.plans.optimize import cover_first
from motifloom.plans.pattern import QueryGraph

#: Candidate rows that one expansion step makes at most.
STEP = 1 << 18
#: Numbers of candidates that a worker remembers at most by the images that they hang on, from so many of a block.
KNOWN, KNOWN_OF_BLOCK = 1 << 16, 1 << 12


class Csr:
    """Arcs u -> v (both directions of an undirected edge) with positions for ids."""

    def __init__(self, u: np.ndarray, v: np.ndarray, labels: dict[int, int] | tuple[np.ndarray, np.ndarray] | None = None):
        """labels: a dict, or sorted ids and their labels."""
        self.ids = np.unique(np.concatenate([u, v])) if len(u) else np.empty(0, np.int64)
        n = self.n = len(self.ids)
        a, b = np.searchsorted(self.ids, u), np.searchsorted(self.ids, v)
        self.keys = np.unique(a * n + b) if n else np.empty(0, np.int64)
        self.indices = self.keys % max(n, 1)
        self.indptr = np.searchsorted(self.keys, np.arange(n + 1) * n)
        self.degree = np.diff(self.indptr)
        self.labels = None
        if labels is not None:
            known = labels if isinstance(labels, tuple) else tuple(np.array(x, np.int64) for x in zip(*sorted(labels.items())))
            self.labels = np.full(n, -1, np.int64)
            if len(known) and len(known[0]):
                at = np.searchsorted(known[0], self.ids).clip(max=len(known[0]) - 1)
                here = known[0][at] == self.ids
                self.labels[here] = known[1][at][here]

    @property
    def nbytes(self) -> int:
        return sum(x.nbytes for x in (self.ids, self.keys, self.indices, self.indptr, self.degree, self.labels) if x is not None)

    def has(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        key = a * self.n + b
        at = np.searchsorted(self.keys, key)
        at[at == len(self.keys)] = 0
        return self.keys[at] == key if len(self.keys) else np.zeros(len(key), bool)


def cell_csr(columns: list[np.ndarray]) -> MappedCsr:
    """The graph of different undirected edges u, v (and the labels of u and v, if given), with positions of four bytes.

    columns is emptied: beside the arrays that stay, only one side's arcs are held in full length.
    """
    ids = np.unique(np.concatenate([np.unique(x) for x in columns[:2]]))
    n = len(ids)
    kind = np.int32 if n < 1 << 31 else np.int64
    csr = MappedCsr.__new__(MappedCsr)
    csr.ids, csr.n, csr.labels, csr.kept = ids.astype(np.int64), n, None, {}
    a, b = (np.searchsorted(ids, x).astype(kind) for x in columns[:2])
    if len(columns) > 2:
        csr.labels = np.full(n, -1, np.int64)
        csr.labels[a], csr.labels[b] = columns[2:]
    columns.clear()
    csr.indptr = np.concatenate([[0], np.cumsum(np.bincount(a, minlength=n) + np.bincount(b, minlength=n))]).astype(np.int64)
    keys = np.empty(2 * len(a), np.int64)
    for part, x, y in ((keys[: len(a)], a, b), (keys[len(a) :], b, a)):
        np.multiply(x, n, out=part, dtype=np.int64)
        part += y
    del a, b
    keys.sort()
    keys %= max(n, 1)
    csr.indices = keys.astype(kind)
    csr.degree = _Degrees(csr.indptr)
    return csr


class _Degrees:
    """Degrees of positions, from the offsets."""

    def __init__(self, indptr: np.ndarray):
        self.indptr = indptr

    def __getitem__(self, at: np.ndarray) -> np.ndarray:
        return self.indptr[at + 1].astype(np.int64) - self.indptr[at]

    def __array__(self, dtype=None, copy=None) -> np.ndarray:
        return np.diff(self.indptr).astype(dtype or np.int64)


class MappedCsr(Csr):
    """The same over arrays in a folder, which are mapped and not loaded."""

    def __init__(self, folder: str):
        part = lambda name: np.load(f"{folder}/{name}.npy", mmap_mode="r") if os.path.exists(f"{folder}/{name}.npy") else None
        self.ids, self.indptr, self.labels = part("ids"), part("indptr"), part("labels")
        self.n = len(self.ids)
        kind = np.int32 if self.n < 1 << 31 else np.int64
        path = f"{folder}/indices.bin"
        self.indices = np.memmap(path, kind, "r") if os.path.getsize(path) else np.empty(0, kind)
        self.degree = _Degrees(self.indptr)
        #: Candidate sets by pattern.
        self.kept: dict = {}

    @property
    def nbytes(self) -> int:
        return sum(x.nbytes for x in (self.ids, self.indices, self.indptr, self.labels) if x is not None)

    def has(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """By halving each row's own part of the indices."""
        low, end = self.indptr[a].astype(np.int64), self.indptr[a + 1].astype(np.int64)
        high = end.copy()
        while len(low) and (open_ := low < high).any():
            middle = (low + high) >> 1
            less = open_ & (self.indices[np.minimum(middle, len(self.indices) - 1)] < b)
            low = np.where(less, middle + 1, low)
            high = np.where(open_ & ~less, middle, high)
        found = low < end
        found[found] = self.indices[low[found]] == b[found]
        return found


def _rows(csr: Csr, good: np.ndarray) -> np.ndarray:
    """How many neighbours of each position are good, by blocks of arcs."""
    out = np.zeros(csr.n, np.int64)
    at = 0
    while at < csr.n:
        stop = min(csr.n, max(at + 1, int(np.searchsorted(csr.indptr, csr.indptr.dtype.type(int(csr.indptr[at]) + STEP), "right")) - 1))
        sums = np.concatenate([[0], np.cumsum(good[csr.indices[csr.indptr[at] : csr.indptr[stop]]])])
        out[at:stop] = np.diff(sums[csr.indptr[at : stop + 1] - csr.indptr[at]])
        at = stop
    return out


def _compare(left: np.ndarray, how: str, right: np.ndarray) -> np.ndarray:
    return left < right if how == "<" else left > right if how == ">" else left != right


def _allowed(csr: Csr, q: QueryGraph) -> dict[int, np.ndarray | None]:
    """Positions that a query vertex may take, by label."""
    return {v: None if q.label(v) is None or csr.labels is None else csr.labels == q.label(v) for v in q.vertices}


def _candidates(csr: Csr, q: QueryGraph, rows: np.ndarray, placed: list[int], x: int, allowed, symmetry: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Row numbers and images of x: candidates of the neighbour of least degree, checked against the others."""
    back = [i for i, y in enumerate(placed) if q.has_edge(x, y)]
    near = rows[:, back]
    pivot = near[np.arange(len(rows)), csr.degree[near].argmin(1)]
    sizes = csr.degree[pivot]
    ends = np.cumsum(sizes)
    at = 0
    while at < len(rows):
        stop = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + STEP, "right")))
        part = sizes[at:stop]
        who = np.repeat(np.arange(at, stop), part)
        offset = np.arange(part.sum()) - np.repeat(np.cumsum(part) - part, part)
        cand = csr.indices[csr.indptr[pivot[who]] + offset]
        keep = np.ones(len(cand), bool) if allowed[x] is None else allowed[x][cand].copy()
        for i, y in enumerate(placed):
            how = relation(q, x, y, symmetry)
            if how:  # positions are in the order of ids
                keep &= _compare(cand, how, rows[who, i])
        who, cand = who[keep], cand[keep]
        for i in back:
            if len(back) > 1:
                good = csr.has(rows[who, i], cand)
                who, cand = who[good], cand[good]
        if len(who):
            yield who, cand
        at = stop


def _expand(csr: Csr, q: QueryGraph, rows: np.ndarray, placed: list[int], x: int, allowed, symmetry: bool) -> Iterator[np.ndarray]:
    """rows with a column for x."""
    for who, cand in _candidates(csr, q, rows, placed, x, allowed, symmetry):
        yield np.concatenate([rows[who], cand[:, None]], 1)


def _last(csr: Csr, q: QueryGraph, rows: np.ndarray, placed: list[int], x: int, allowed, symmetry: bool, known: dict | None = None) -> int:
    """How many rows a column for x would make.

    Without an order to keep, rows whose neighbours of x have the same images share its candidates: these
    are listed once, and images that other vertices took already are subtracted. known: how many candidates hang
    on some images, from earlier blocks.
    """
    hows = [relation(q, x, y, symmetry) for y in placed]
    if "<" in hows or ">" in hows:
        return sum(len(who) for who, _ in _candidates(csr, q, rows, placed, x, allowed, symmetry))
    back = [i for i, y in enumerate(placed) if q.has_edge(x, y)]
    key = rows[:, back[0]].astype(np.int64)
    for i in back[1:]:
        key = np.unique(key, return_inverse=True)[1].reshape(-1) * csr.n + rows[:, i]
    _, at, same = np.unique(key, return_index=True, return_inverse=True)
    images, sizes = rows[at][:, back], np.zeros(len(at), np.int64)
    names = [tuple(r) for r in images.tolist()] if known is not None and len(at) <= KNOWN_OF_BLOCK else None
    new = np.array([i for i, name in enumerate(names) if name not in known], np.int64) if names else np.arange(len(at))
    if names:
        sizes[:] = [known.get(name, 0) for name in names]
    for who, _ in _candidates(csr, q, images[new], [placed[i] for i in back], x, allowed, symmetry) if len(new) else ():
        sizes[new] += np.bincount(who, minlength=len(new))
    if names:
        known.update((names[i], int(sizes[i])) for i in new[: max(0, KNOWN - len(known))].tolist())
    total = int(sizes[same.reshape(-1)].sum())
    for i, how in enumerate(hows):
        if how:  # images of different vertices differ, so none is subtracted twice
            taken = np.ones(len(rows), bool) if allowed[x] is None else allowed[x][rows[:, i]].copy()
            for j in back:
                taken[taken] = csr.has(rows[taken, j], rows[taken, i])
            total -= int(taken.sum())
    return total


def _grow(csr: Csr, q: QueryGraph, order: tuple[int, ...], symmetry: bool, seeds: np.ndarray | None, allowed) -> Iterator[np.ndarray]:
    """Matches of the vertices in order, as positions, columns in that order; depth first by blocks."""
    if seeds is not None:  # compared in the width of the ids, or all of these would be widened
        seeds = seeds[seeds <= np.iinfo(csr.ids.dtype).max].astype(csr.ids.dtype)
    first = np.arange(csr.n) if seeds is None else np.searchsorted(csr.ids, seeds)
    if seeds is not None:
        inside = first < csr.n
        first, seeds = first[inside], seeds[inside]
        first = first[csr.ids[first] == seeds]
    if allowed[order[0]] is not None:
        first = first[allowed[order[0]][first]]

    def go(rows: np.ndarray, depth: int):
        if depth == len(order):
            yield rows
            return
        for block in _expand(csr, q, rows, list(order[:depth]), order[depth], allowed, symmetry):
            yield from go(block, depth + 1)

    if len(first):
        yield from go(first[:, None], 1)


def _named(csr: Csr, rows: np.ndarray, order, q: QueryGraph) -> np.ndarray:
    return csr.ids[rows[:, [order.index(v) for v in q.vertices]]].astype(np.int64)


def cover(csr: Csr, q: QueryGraph, symmetry: bool, seeds: np.ndarray | None = None) -> Iterator[np.ndarray]:
    """A connected vertex cover first, then each other vertex by intersecting its neighbours' lists."""
    order = cover_first(q)
    for rows in _grow(csr, q, order, symmetry, seeds, _allowed(csr, q)):
        yield _named(csr, rows, order, q)


def pieces(q: QueryGraph) -> tuple[tuple[int, ...], tuple[int, ...]] | None:
    """Two overlapping connected vertex sets that hold every edge, the larger as small as can be."""
    best = None
    for k in range(2, q.n):
        for a in combinations(q.vertices, k):
            for extra in range(1, k + 1):
                for shared in combinations(a, extra):
                    b = tuple(sorted(set(q.vertices) - set(a) | set(shared)))
                    if len(b) < 2 or len(b) > k or not q.connected(a) or not q.connected(b):
                        continue
                    if all(set(e) <= set(a) or set(e) <= set(b) for e in q.edges):
                        rank = (k, len(shared), a, b)
                        best = min(best or rank, rank)
        if best:
            return best[2], best[3]
    return None


def _subset_order(q: QueryGraph, chosen: tuple[int, ...], lead: int | None = None) -> tuple[int, ...]:
    order = [lead or max(chosen, key=lambda v: (len(q.adjacency[v] & set(chosen)), -v))]
    while len(order) < len(chosen):
        rest = [v for v in chosen if v not in order and q.adjacency[v] & set(order)]
        order.append(min(rest, key=lambda v: (-len(q.adjacency[v] & set(order)), v)))
    return tuple(order)


def decompose(csr: Csr, q: QueryGraph, symmetry: bool, seeds: np.ndarray | None = None) -> Iterator[np.ndarray]:
    """Two pieces by expansion, glued by a merge join on the vertices they share.

    Seeds are images of the first vertex of the cover order: each piece that holds it starts from them.
    """
    parts = pieces(q)
    if parts is None:
        yield from cover(csr, q, symmetry, seeds)
        return
    tables, lead = [], cover_first(q)[0]
    for chosen in parts:
        order = _subset_order(q, chosen, lead if seeds is not None and lead in chosen else None)
        blocks = list(_grow(csr, q, order, symmetry, seeds if order[0] == lead else None, _allowed(csr, q)))
        tables.append((order, np.concatenate(blocks) if blocks else np.empty((0, len(order)), np.int64)))
    (oa, a), (ob, b) = tables
    shared = [v for v in oa if v in ob]
    if not len(a) or not len(b):
        return
    ka, kb = a[:, [oa.index(v) for v in shared]], b[:, [ob.index(v) for v in shared]]
    _, code = np.unique(np.concatenate([ka, kb]), axis=0, return_inverse=True)
    code = code.reshape(-1)
    ca, cb = code[: len(a)], code[len(a) :]
    by = np.argsort(cb, kind="stable")
    low, high = np.searchsorted(cb[by], ca, "left"), np.searchsorted(cb[by], ca, "right")
    only = [v for v in ob if v not in oa]
    order = (*oa, *only)
    ends = np.cumsum(high - low)
    at = 0
    while at < len(a):
        stop = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + STEP, "right")))
        part = (high - low)[at:stop]
        left = np.repeat(np.arange(at, stop), part)
        right = by[np.repeat(low[at:stop], part) + np.arange(part.sum()) - np.repeat(np.cumsum(part) - part, part)]
        rows = np.concatenate([a[left], b[right][:, [ob.index(v) for v in only]]], 1)
        keep = np.ones(len(rows), bool)
        for x in only:
            for y in oa:
                how = relation(q, x, y, symmetry) if y not in shared else None
                if how:
                    keep &= _compare(rows[:, order.index(x)], how, rows[:, order.index(y)])
        if keep.any():
            yield _named(csr, rows[keep], order, q)
        at = stop


def core_order(q: QueryGraph) -> tuple[int, ...]:
    """Vertices of the 2-core first, then the forest that hangs on it, leaves last."""
    core = set(q.vertices)
    while True:
        thin = {v for v in core if len(q.adjacency[v] & core) < 2}
        if not thin:
            break
        core -= thin
    rank = lambda v: 0 if v in core else 2 if q.degree(v) == 1 else 1
    order = [min(q.vertices, key=lambda v: (rank(v), -q.degree(v), v))]
    while len(order) < q.n:
        near = [v for v in q.vertices if v not in order and q.adjacency[v] & set(order)]
        order.append(min(near, key=lambda v: (rank(v), -len(q.adjacency[v] & set(order)), v)))
    return tuple(order)


def candidate_sets(csr: Csr, q: QueryGraph) -> dict[int, np.ndarray]:
    """Positions per query vertex that pass label, degree and neighbour-label filters, narrowed along the edges."""
    if (kept := getattr(csr, "kept", {}).get(q)) is not None:
        return kept
    out = {}
    for v in q.vertices:
        ok = np.asarray(csr.degree) >= q.degree(v)
        if csr.labels is not None and q.label(v) is not None:
            ok &= csr.labels == q.label(v)
        if csr.labels is not None:
            for label in {q.label(w) for w in q.adjacency[v]} - {None}:
                need = sum(q.label(w) == label for w in q.adjacency[v])
                ok &= _rows(csr, np.asarray(csr.labels) == label) >= need
        out[v] = ok
    order = core_order(q)
    for sweep in (order, order[::-1]):
        for v in sweep:
            for w in q.adjacency[v]:
                out[v] = out[v] & (_rows(csr, out[w]) > 0)
    if isinstance(csr, MappedCsr):
        csr.kept[q] = out
    return out


def candidate(csr: Csr, q: QueryGraph, symmetry: bool, seeds: np.ndarray | None = None) -> Iterator[np.ndarray]:
    """An index of candidates before enumeration in the order core, forest, leaves.

    Where seeds are given they are images of the first vertex of the cover order, which then leads.
    """
    if not csr.n:
        return
    allowed = candidate_sets(csr, q)
    order = core_order(q)
    if seeds is not None:
        lead = cover_first(q)[0]
        rest = [lead]
        while len(rest) < q.n:
            rest.append(min((v for v in q.vertices if v not in rest and q.adjacency[v] & set(rest)), key=order.index))
        order = tuple(rest)
    for rows in _grow(csr, q, order, symmetry, seeds, allowed):
        yield _named(csr, rows, order, q)


def backtrack(csr: Csr, q: QueryGraph, symmetry: bool, seeds: np.ndarray | None = None) -> Iterator[np.ndarray]:
    """Plain backtracking, one vertex after the other: a baseline for tests."""
    order, allowed, out = cover_first(q), _allowed(csr, q), []
    start = range(csr.n) if seeds is None else np.searchsorted(csr.ids, seeds[np.isin(seeds, csr.ids)])

    def go(image: dict[int, int]) -> None:
        if len(image) == q.n:
            out.append([int(csr.ids[image[v]]) for v in q.vertices])
            return
        x = order[len(image)]
        back = [image[y] for y in q.adjacency[x] if y in image]
        pool = start if not image else csr.indices[csr.indptr[back[0]] : csr.indptr[back[0] + 1]]
        for c in pool:
            c = int(c)
            if allowed[x] is not None and not allowed[x][c]:
                continue
            if all(csr.has(np.array([b]), np.array([c]))[0] for b in back) and all(not (how := relation(q, x, y, symmetry)) or bool(_compare(np.array(c), how, np.array(image[y]))) for y in image):
                go(image | {x: c})

    go({})
    if out:
        yield np.array(out, np.int64)


def _light_order(csr: Csr, q: QueryGraph, allowed, lead: int) -> tuple[int, ...]:
    """From lead on, always the vertex of which a placed one has the fewest candidates among its neighbours."""
    kept = getattr(csr, "kept", {})
    if (q, lead) not in kept:
        near = {x: csr.degree if allowed[x] is None else _rows(csr, allowed[x]) for x in q.vertices}
        spread = lambda y, x: float(n.mean()) if len(n := np.asarray(near[x]) if allowed[y] is None else np.asarray(near[x])[allowed[y]]) else 0.0
        fan = {(y, x): spread(y, x) for x in q.vertices for y in q.adjacency[x]}
        order = [lead]
        while len(order) < q.n:
            rest = {v: min(fan[y, v] for y in order if y in q.adjacency[v]) for v in q.vertices if v not in order and q.adjacency[v] & set(order)}
            order.append(min(rest, key=lambda v: (rest[v], v)))
        kept[q, lead] = tuple(order)
    return kept[q, lead]


def count(csr: Csr, q: QueryGraph, kernel: str, symmetry: bool, seeds: np.ndarray | None = None) -> int:
    """How many matches the kernel finds. cover and candidate never list the images of the last vertex per match."""
    if kernel not in ("cover", "candidate") or q.n < 2:
        return sum(len(rows) for rows in KERNELS[kernel](csr, q, symmetry, seeds))
    if not csr.n:
        return 0
    order = cover_first(q)
    allowed = candidate_sets(csr, q) if kernel == "candidate" else _allowed(csr, q)
    if kernel == "candidate":
        order = _light_order(csr, q, allowed, order[0])
    placed = list(order[:-1])
    known = csr.kept.setdefault(("sizes", q, kernel, symmetry), {}) if isinstance(csr, MappedCsr) else None
    return sum(_last(csr, q, rows, placed, order[-1], allowed, symmetry, known) for rows in _grow(csr, q, order[:-1], symmetry, seeds, allowed))


def _falls(x: np.ndarray, parts: int, part: int) -> np.ndarray:
    """Which of x are part modulo parts, block by block."""
    out = np.empty(len(x), bool)
    for i in range(0, len(x), STEP):
        out[i : i + STEP] = x[i : i + STEP] % parts == part
    return out


def _different(x: np.ndarray) -> np.ndarray:
    """The different values, ascending, block by block: memory follows them and not their repeats."""
    found, parts = x[:0], []
    for i in range(0, len(x), STEP):
        parts.append(np.unique(x[i : i + STEP]))
        if sum(map(len, parts)) > max(4 * STEP, len(found)):
            found, parts = np.unique(np.concatenate([found, *parts])), []
    return np.unique(np.concatenate([found, *parts]))


def squares(cell: int, blocks: tuple[int, int], roots: np.ndarray, lists: pa.ListArray) -> int:
    """Pairs of stars over the same leaves x < y, one root below x, y and the other root, for the pairs of one block.

    x falls on cell // s modulo p and y on cell % s modulo s, for blocks (p, s). lists: each root's leaves, ascending.
    Of the k roots of a pair, j lie below x; the i-th of these has k - i roots above it.
    """
    p, s = blocks
    by = np.argsort(roots)
    roots, lists = roots[by], lists.take(pa.array(by))
    leaves, sizes = lists.flatten().to_numpy(), np.diff(lists.offsets.to_numpy())
    root = np.repeat(np.arange(len(roots), dtype=np.int32), sizes)
    del lists, sizes, by
    mine = _falls(leaves, p, cell // s)
    xs, at = leaves[mine], root[mine]
    order = np.argsort(xs, kind="stable")  # roots ascend within an x
    xs, at = xs[order], at[order]
    del mine, order
    if s > 1:
        mine = _falls(leaves, s, cell % s)
        leaves, root = leaves[mine], root[mine]
        del mine
    names = _different(leaves)
    ys = np.empty(len(leaves), np.int32)
    for i in range(0, len(leaves), STEP):
        ys[i : i + STEP] = np.searchsorted(names, leaves[i : i + STEP])
    del leaves
    ends = np.searchsorted(root, np.arange(len(roots), dtype=root.dtype), "right")
    key = root.astype(np.int64)
    del root
    key *= len(names) + 1
    key += ys
    total = 0
    cuts = np.flatnonzero(np.r_[True, xs[1:] != xs[:-1], True]) if len(xs) else []
    for a, b in zip(cuts[:-1], cuts[1:]):
        x, rows = xs[a], at[a:b]
        start = np.searchsorted(key, rows.astype(np.int64) * (len(names) + 1) + np.searchsorted(names, x, "right"))
        parts = [ys[i:j] for i, j in zip(start.tolist(), ends[rows].tolist())]
        cut = int(np.searchsorted(roots[rows], x))
        if not cut:
            continue
        low, all_ = np.concatenate(parts[:cut]), sum(map(len, parts))
        if 8 * all_ < len(names):  # few of many leaves
            _, code = np.unique(np.concatenate(parts), return_inverse=True)
            j, k = np.bincount(code[: len(low)], minlength=len(code)), np.bincount(code, minlength=len(code))
        else:
            j = np.bincount(low, minlength=len(names))
            k = j + np.bincount(np.concatenate(parts[cut:]), minlength=len(names)) if cut < len(parts) else j
        total += int((j * (k - 1) - j * (j - 1) // 2).sum())
    return total


def pairs(how: str | None, f: np.ndarray, at: np.ndarray, y: np.ndarray, z: np.ndarray) -> int:
    """Sum of n * (n - 1) over the pairs (f, z) whose images of y, n of them, have both f and z as neighbours.

    (f, at) and (y, z) are arcs in any order, at and y the same kind of vertex; how: what z has to be to f.
    """
    by = np.argsort(y, kind="stable")
    y, z = y[by], z[by]
    del by
    names = np.unique(z)
    z = np.searchsorted(names, z).astype(z.dtype)
    by = np.argsort(f, kind="stable")
    f, at = f[by], at[by]
    del by
    low = np.searchsorted(y, at)
    sizes = np.searchsorted(y, at, "right") - low
    some = sizes > 0
    f, low, sizes = f[some], low[some], sizes[some]
    del at, y, some
    cuts = np.flatnonzero(np.r_[True, f[1:] != f[:-1], True]) if len(f) else np.zeros(1, np.int64)
    ends = np.concatenate([[0], np.cumsum(sizes)])
    listed = lambda a, b: z[np.repeat(low[a:b] - (ends[a:b] - ends[a]), sizes[a:b]) + np.arange(ends[b] - ends[a])]
    total, i = 0, 0
    while i < len(cuts) - 1:
        j = max(i + 1, int(np.searchsorted(ends[cuts], ends[cuts[i]] + 4 * STEP, "right")) - 1)
        a, b = cuts[i], cuts[j]
        if ends[b] - ends[a] > 4 * STEP:  # one vertex with long lists: its images are counted piece by piece
            n = np.zeros(len(names), np.int64)
            while a < b:
                stop = min(b, max(a + 1, int(np.searchsorted(ends, ends[a] + 4 * STEP, "right")) - 1))
                n += np.bincount(listed(a, stop), minlength=len(names))
                a = stop
            if how:
                n = n[_compare(names, how, f[cuts[i]])]
        else:
            cand, lead = listed(a, b), np.repeat(f[a:b], sizes[a:b])
            if how:
                keep = _compare(names[cand], how, lead)
                cand, lead = cand[keep], lead[keep]
            key = np.searchsorted(f[cuts[i:j]], lead) * len(names) + cand
            key.sort()
            n = np.diff(np.flatnonzero(np.r_[True, key[1:] != key[:-1], True])) if len(key) else np.empty(0, np.int64)
        total += int((n * (n - 1)).sum())
        i = j
    return total


def cliques4(seeds: pa.ListArray, ids: np.ndarray, lists: pa.ListArray) -> int:
    """4-cliques by their smallest vertex: seeds has each one's larger neighbours, lists those of ids, the neighbours' own, all ascending.

    The third and fourth vertex are found in the graph between a seed's neighbours, as rows of bits.
    """
    by = np.argsort(ids)
    ids, lists = ids[by], lists.take(pa.array(by))
    offsets, near = lists.offsets.to_numpy().astype(np.int64), lists.flatten().to_numpy()
    names = np.unique(near)
    near = np.searchsorted(names, near).astype(np.int32)
    place = np.full(len(names) + 1, -1, np.int32)  # the last one is for those that are in no list
    ends, tops, total = seeds.offsets.to_numpy(), seeds.flatten().to_numpy(), 0
    for a, b in zip(ends[:-1].tolist(), ends[1:].tolist()):
        members = tops[a:b]
        code = np.searchsorted(names, members)
        code[(code == len(names)) | (names[np.minimum(code, len(names) - 1)] != members) if len(names) else slice(None)] = len(names)
        at = np.searchsorted(ids, members)
        rows = np.flatnonzero((at < len(ids)) & (ids[np.minimum(at, len(ids) - 1)] == members)) if len(ids) else np.empty(0, np.int64)
        place[code] = np.arange(len(members))
        place[-1] = -1
        width = -(-len(members) // 64) * 64
        bits = np.zeros((len(members), width), np.uint8)
        who, other = [], []
        low, high = offsets[at[rows]], offsets[at[rows] + 1]
        i = 0
        while i < len(rows):
            j = max(i + 1, int(np.searchsorted(np.cumsum(high[i:] - low[i:]), 4 * STEP, "right")) + i)
            sizes = high[i:j] - low[i:j]
            found = place[near[np.repeat(low[i:j] - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())]]
            inside = found >= 0
            who.append(np.repeat(rows[i:j], sizes)[inside])
            other.append(found[inside])
            bits[who[-1], other[-1]] = 1
            i = j
        place[code] = -1
        if not who:
            continue
        words = np.packbits(bits, axis=1, bitorder="little").view(np.uint64)
        x, y = np.concatenate(who), np.concatenate(other)
        step = max(1, 4 * STEP // max(1, words.shape[1]))
        for i in range(0, len(x), step):
            total += int(np.bitwise_count(words[x[i : i + step]] & words[y[i : i + step]]).sum(dtype=np.int64))
    return total


KERNELS = {"cover": cover, "decompose": decompose, "candidate": candidate, "backtrack": backtrack}
