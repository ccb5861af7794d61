"""Hypercube shares: one shuffle that replicates edges to a grid of cells, then local matching."""

from __future__ import annotations

import gc
import math
from collections.abc import Callable
from functools import reduce
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifloom.functions.kernels import KERNELS, cell_csr
from motifloom.operators import compress as packed
from motifloom.operators.batching import in_turn, meet, total
from motifloom.operators.graph import DataGraph
from motifloom.operators.units import _edge_args
from motifloom.plans import optimize
from motifloom.plans.ir import relation, use_symmetry
from motifloom.plans.pattern import QueryGraph
from motifloom.storage import release, ship

#: Copies of edges that one round of cells sends at most, by the model; each takes some 15 bytes of shuffle files.
ROUND_COPIES = 150_000_000
#: Integers of edges that one cell's task should hold at most when the number of cells is chosen.
CELL_INTEGERS = 8_000_000
#: What an edge counts for there: its ends; with labels also these, and what the candidate kernel keeps beside them.
EDGE_INTEGERS, LABELLED_INTEGERS = 2, 8


def _weights(shares: tuple[int, ...]) -> list[int]:
    """The place value of each coordinate in a cell's number."""
    return [math.prod(shares[i + 1 :]) for i in range(len(shares))]


def home_cell(q: QueryGraph, shares: tuple[int, ...]) -> Column:
    """The only cell that owns a match."""
    return reduce(lambda a, b: a + b, [F.pmod(f"v{v}", F.lit(b)) * w for v, b, w in zip(q.vertices, shares, _weights(shares))])


def usable(g: DataGraph, q: QueryGraph) -> int | dict[tuple[int, int], int]:
    """What the model of loads counts: how many arcs have the labels of each query edge; without labels, the edges."""
    if not (q.labelled and g.has_labels):
        return g.stats["m"]
    fits = lambda want, kind: want is None or want == kind
    return {(a, b): sum(n for (x, y), n in g.label_pairs().items() if fits(q.label(a), x) and fits(q.label(b), y)) for a, b in q.edges}


def choose_cells(g: DataGraph, q: QueryGraph, task_integers: int = CELL_INTEGERS, most: int = 1 << 16) -> int:
    """The smallest power of two whose modelled load per cell fits a task."""
    cells, m, each = 1, usable(g, q), LABELLED_INTEGERS if q.labelled else EDGE_INTEGERS
    while cells < most:
        s = optimize.doubled_shares(q, cells, m, use_symmetry(q)) if isinstance(m, dict) else optimize.shares(q, cells, "round_down", m)
        if each * optimize.routed_edges(q, s, m, use_symmetry(q)) / math.prod(s) <= task_integers:
            break
        cells *= 2
    return cells


def route(g: DataGraph, q: QueryGraph, shares: tuple[int, ...], use_order: bool = True) -> DataFrame:
    """cell, tag, u, v: each arc that can match query edge number tag, once per choice of the other coordinates.

    Where the order of the two query vertices is fixed only the rising orientation travels.
    """
    weight = _weights(shares)
    parts = []
    for tag, (i, j) in enumerate(q.edges):
        rows = g.pairs(**_edge_args(q, i, j))
        how = relation(q, i, j, use_order)
        if how in ("<", ">"):
            rows = rows.where(packed.compare(F.col("u"), how, F.col("v")))
        others = [k for k in range(q.n) if k + 1 not in (i, j)]
        offsets = [sum(z * weight[k] for z, k in zip(zs, others)) for zs in product(*[range(shares[k]) for k in others])]
        base = F.pmod("u", F.lit(shares[i - 1])) * weight[i - 1] + F.pmod("v", F.lit(shares[j - 1])) * weight[j - 1]
        parts.append(rows.select(F.explode(_shifted(base, offsets)).alias("cell"), F.lit(tag).alias("tag"), "u", "v"))
    return reduce(DataFrame.unionByName, parts)


def _shifted(base: Column, offsets: list[int]) -> Column:
    return F.transform(F.array(*[F.lit(o) for o in offsets]), lambda o: base + o)


def local_edges(routed: DataFrame) -> DataFrame:
    """cell, u, v with every undirected edge once per cell."""
    return routed.select("cell", F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct()


def dealt_edges(g: DataGraph, q: QueryGraph, shares: tuple[int, ...], use_order: bool = True) -> DataFrame:
    """cell, u, v (u < v; with the labels ul, vl if q has any): every undirected edge once per cell that has a use for it.

    An edge's cells are told apart before it is multiplied, so copies for several query edges neither travel nor meet.
    """
    weight = _weights(shares)
    e = g.labelled if g.has_labels else g.edges.withColumns({"slabel": F.lit(None).cast("int"), "dlabel": F.lit(None).cast("int")})
    none, cells, uses = F.array().cast("array<bigint>"), [], []
    for i, j in q.edges:
        others = [k for k in range(q.n) if k + 1 not in (i, j)]
        offsets = [sum(z * weight[k] for z, k in zip(zs, others)) for zs in product(*[range(shares[k]) for k in others])]
        how = relation(q, i, j, use_order)
        for u, ulabel, v, vlabel in (("src", "slabel", "dst", "dlabel"), ("dst", "dlabel", "src", "slabel")):
            fits = [F.col(kind) == q.label(x) for x, kind in ((i, ulabel), (j, vlabel)) if q.label(x) is not None]
            uses.append(reduce(lambda a, b: a & b, fits, F.lit(True)))
            if how in ("<", ">"):
                fits.append(packed.compare(F.col(u), how, F.col(v)))
            base = F.pmod(u, F.lit(shares[i - 1])) * weight[i - 1] + F.pmod(v, F.lit(shares[j - 1])) * weight[j - 1]
            into = _shifted(base, offsets).cast("array<bigint>")
            cells.append(F.when(reduce(lambda a, b: a & b, fits), into).otherwise(none) if fits else into)
    if q.labelled:
        e = e.where(reduce(lambda a, b: a | b, uses))
    kinds = [F.coalesce(c, F.lit(-1)).alias(n) for c, n in (("slabel", "ul"), ("dlabel", "vl"))] if q.labelled else []
    small = "int" if g.ranked and g.stats["n"] < 1 << 31 else "bigint"
    return e.select(F.explode(F.array_distinct(F.concat(*cells))).alias("cell"), F.col("src").cast(small).alias("u"), F.col("dst").cast(small).alias("v"), *kinds)


def _cells(batches):
    """(cell, columns) of a partition sorted by cell, one cell at a time; the caller holds the only copy."""
    held: list[pa.RecordBatch] = []

    def whole():
        t = pa.Table.from_batches(held)
        held.clear()
        return t.column(0)[0].as_py(), [t.column(i).to_numpy() for i in range(1, t.num_columns)]

    for batch in batches:
        cells = batch.column(0).to_numpy()
        cuts = [0, *(np.flatnonzero(cells[1:] != cells[:-1]) + 1).tolist(), len(cells)]
        for a, b in zip(cuts, cuts[1:]):
            if a == b:
                continue
            if held and held[0].column(0)[0].as_py() != cells[a]:
                yield whole()
            held.append(batch.slice(a, b - a))
    if held:
        yield whole()


def _owned(q: QueryGraph, kernel: str, symmetry: bool, shares: tuple[int, ...], batches):
    """Matches of each cell that the cell owns, block by block: only a cell's edges are ever held."""
    find, weight = KERNELS[kernel], _weights(shares)
    for cell, columns in _cells(batches):
        csr = cell_csr(columns)
        rows = None
        for rows in find(csr, q, symmetry):
            owner = sum((rows[:, i] % shares[i]) * weight[i] for i in range(q.n))
            yield rows[owner == cell]
        del csr, rows
        gc.collect()  # the kernels' recursive generators hold a cell's arrays in cycles


def _solver(q: QueryGraph, kernel: str, symmetry: bool, shares: tuple[int, ...]):
    names = [f"v{i}" for i in q.vertices]

    def run(batches):
        for rows in _owned(q, kernel, symmetry, shares, batches):
            if len(rows):
                yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(rows[:, i])) for i in range(q.n)], names=names)

    return run


def rounds(g: DataGraph, q: QueryGraph, shares: tuple[int, ...], ordered: bool) -> int:
    """In how many rounds the cells are worked off, so that only one round's copies are on disk."""
    copies = min(optimize.routed_edges(q, shares, usable(g, q), ordered), g.stats["m"] * math.prod(shares))
    return max(1, min(math.prod(shares), math.ceil(copies / ROUND_COPIES)))


def _number(q: QueryGraph, kernel: str, symmetry: bool, shares: tuple[int, ...]):
    def run(batches):
        n = sum(len(rows) for rows in _owned(q, kernel, symmetry, shares, batches))
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], names=["n"])

    return run


def _dealt(g: DataGraph, q: QueryGraph, cells: int | None, shares, ordered: bool) -> tuple[Callable[[int, int], DataFrame], tuple[int, ...]]:
    """make(k, b): edges sorted by cell inside each task, for the k-th of b rounds of cells; and the shares."""
    s = optimize.shares(q, max(cells or 1, choose_cells(g, q)), shares, usable(g, q), ordered)
    ship(g.spark)

    def make(k: int, b: int) -> DataFrame:
        release(g.spark) if b > 1 else None
        edges = dealt_edges(g, q, s, ordered)
        edges = edges.where(F.pmod("cell", F.lit(b)) == k) if b > 1 else edges
        return edges.repartition("cell").sortWithinPartitions("cell")

    return make, s


def run(g: DataGraph, q: QueryGraph, cells: int | None = None, *, shares="optimize", dedupe: str = "owner", kernel: str = "cover", use_order: bool = True, symmetry: str = "auto", **refused) -> DataFrame:
    """Matches v1..vn. cells: at least so many, more where a cell's edges would not fit a task. dedupe: owner (edges merged per cell, owner test) or tagged (a copy per query edge)."""
    if refused:
        raise ValueError(f"not useful for hypercube shares: {', '.join(refused)}")
    ordered = use_symmetry(q, symmetry)
    if dedupe == "tagged" or q.directed or q.elabels:  # merged edges forget which query edge they are for
        s = optimize.shares(q, max(cells or 1, choose_cells(g, q)), shares, usable(g, q), ordered and use_order)
        return _tagged(route(g, q, s, ordered and use_order), q, ordered)
    make, s = _dealt(g, q, cells, shares, ordered and use_order)
    found = lambda k, b: make(k, b).mapInArrow(_solver(q, kernel, ordered, s), ", ".join(f"v{v} long" for v in q.vertices))
    b = rounds(g, q, s, ordered and use_order)
    return found(0, 1) if b == 1 else in_turn(found, b)


def count(g: DataGraph, q: QueryGraph, cells: int | None = None, *, shares="optimize", dedupe: str = "owner", kernel: str = "cover", symmetry: str = "auto") -> DataFrame:
    """One row, column matches: tasks count what their cells own and send a number."""
    if dedupe == "tagged" or q.directed or q.elabels:
        return run(g, q, cells, shares=shares, dedupe=dedupe, symmetry=symmetry).agg(F.count(F.lit(1)).alias("matches"))
    ordered = use_symmetry(q, symmetry)
    make, s = _dealt(g, q, cells, shares, ordered)
    counted = lambda k, b: make(k, b).mapInArrow(_number(q, kernel, ordered, s), "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("bigint").alias("matches"))
    b = rounds(g, q, s, ordered)
    return counted(0, 1) if b == 1 else g.spark.createDataFrame([(total(counted, b),)], "matches bigint")


def _tagged(routed: DataFrame, q: QueryGraph, ordered: bool) -> DataFrame:
    """Joins of the tagged copies inside each cell: every match comes up in exactly one cell."""
    left = list(enumerate(q.edges))
    rows, placed = None, []
    while left:
        tag, (i, j) = min((t for t in left if rows is None or set(t[1]) & set(placed)), key=lambda t: (-len(set(t[1]) & set(placed)), t[0]))
        left.remove((tag, (i, j)))
        part = routed.where(F.col("tag") == tag).select("cell", F.col("u").alias(f"v{i}"), F.col("v").alias(f"v{j}"))
        key = ["cell", *[f"v{x}" for x in (i, j) if x in placed]]
        rows = part if rows is None else meet(rows, part, key)
        for x in (i, j):
            if x not in placed:
                for y in placed:
                    how = relation(q, x, y, ordered)
                    if how:
                        rows = rows.where(packed.compare(F.col(f"v{x}"), how, F.col(f"v{y}")))
                placed.append(x)
        if how := relation(q, i, j, ordered):
            rows = rows.where(packed.compare(F.col(f"v{i}"), how, F.col(f"v{j}")))
    return rows.select(*[f"v{v}" for v in q.vertices])


def load(g: DataGraph, q: QueryGraph, shares: tuple[int, ...], use_order: bool = True) -> DataFrame:
    """One row: routed copies, and the largest and smallest cell before and after duplicates merge."""
    routed = route(g, q, shares, use_order)
    raw = routed.groupBy("cell").agg(F.count(F.lit(1)).alias("raw"))
    merged = local_edges(routed).groupBy("cell").agg(F.count(F.lit(1)).alias("merged"))
    return raw.join(merged, "cell").agg(F.sum("raw").cast("bigint").alias("copies"), F.max("raw").alias("max_raw"), F.max("merged").alias("max_merged"), F.min("raw").alias("min_raw"))
