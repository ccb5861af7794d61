"""Binary joins: join units first, then a tree of joins on shared vertices."""

from __future__ import annotations

import math
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifloom.functions.kernels import squares
from motifloom.operators import compress as packed
from motifloom.operators.batching import hash_range_join, meet
from motifloom.operators.graph import DataGraph
from motifloom.operators.units import unit
from motifloom.plans import optimize
from motifloom.plans.estimate import Sizer
from motifloom.plans.ir import JoinNode, UnitNode, relation, use_symmetry
from motifloom.plans.pattern import QueryGraph
from motifloom.storage import release, ship

#: Neighbours that one block of a join of grouped stars holds at most, on either side.
BLOCK_ARCS = 8_000_000
#: A broadcast hint holds up to so many estimated bytes of the table that is sent; driver and executors hold what is broadcast. Beyond, the join is shuffled.
BROADCAST_BYTES = 128 << 20


def sizer(g: DataGraph, q: QueryGraph, model: str = "power_law", exact=None) -> Sizer:
    named = q.labelled and model == "power_law"
    return Sizer(q, g.stats, model, g.label_pairs() if named else None, g.label_counts() if named else None, exact)


def plan(g: DataGraph, q: QueryGraph, kind: str = "clique", shape: str = "bushy", overlap: bool = True, cost: str = "power_law", triangle_index: str | None = None, order: str | None = None) -> JoinNode | UnitNode:
    """kind: edge, star, wedge or clique units; shape: left_deep or bushy.

    Clique units lie in one partition only with a triangle index, so without one the search has stars.
    order="cover_first" joins the edges of a connected cover first, then a star for each other vertex.
    """
    freq = g.label_counts() if q.labelled else None
    if order == "cover_first":
        return optimize.cover_first_tree(q)
    if kind == "edge":
        return optimize.edge_plan(q)
    if shape == "left_deep" and kind == "star":
        return optimize.star_cover_plan(q, freq)
    if shape == "left_deep" and kind == "wedge":
        return optimize.wedge_plan(q)
    if kind == "clique" and (not triangle_index or q.directed or q.elabels):
        kind = "star"
    return optimize.bushy(q, sizer(g, q, cost), kind, overlap, shape == "left_deep", freq)


def _clique_array(q: QueryGraph, u: UnitNode, free: list[int], triangle_index: str | None, symmetry: bool) -> tuple[int, ...]:
    """The vertex of a clique unit that stays an array: one that no other unit has.

    With the ordered index the order must prove another vertex the smallest, or lists below it are missing.
    """
    if not triangle_index or len(u.vertices) < 3:
        return ()
    above = lambda low, x: all(v == low or relation(q, low, v, symmetry) == "<" for v in u.vertices) and low != x
    good = [x for x in free if triangle_index == "full" or any(above(low, x) for low in u.vertices)]
    return (max(good),) if good else ()


def with_arrays(tree: JoinNode | UnitNode, q: QueryGraph, triangle_index: str | None = None, symmetry: bool = True) -> JoinNode | UnitNode:
    """Keeps as arrays what no other unit needs: the leaves of stars and one vertex of a clique."""
    uses: dict[int, int] = {}
    for u in tree.leaves:
        for v in u.vertices:
            uses[v] = uses.get(v, 0) + 1

    def mark(node):
        if isinstance(node, JoinNode):
            return JoinNode(mark(node.left), mark(node.right))
        free = [v for v in node.vertices if v != node.root and uses[v] == 1]
        if node.kind in ("star", "wedge"):
            return replace(node, arrays=tuple(free))
        if node.kind == "clique":
            return replace(node, arrays=_clique_array(q, node, free, triangle_index, symmetry))
        return node

    return mark(tree)


def broadcast_bytes(columns: int, keys: int) -> int:
    """What a broadcast row takes in the driver: the row and its key with a word each for nulls, its size and next row, two slots of the
    half-filled table of keys; and all of it again as the blocks that are sent."""
    return 2 * (8 * (1 + columns) + 8 * (1 + keys) + 16 + 32)


def lower(g: DataGraph, q: QueryGraph, node: JoinNode | UnitNode, symmetry: bool, triangle_index: str | None = None, batch: tuple[int, int, int] | None = None, hint: str | None = None, cache: dict | None = None, ranges: int = 1) -> DataFrame:
    """The relation of a plan node. batch = (vertex, k, b) restricts every unit that holds the vertex.

    ranges > 1 runs every join in so many ranges of its key's hash, one after the other.
    """
    if isinstance(node, UnitNode):
        if cache is not None and batch and batch[0] not in node.vertices:
            if node not in cache:
                cache[node] = unit(g, q, node, symmetry, triangle_index).persist()
            return cache[node]
        rows = unit(g, q, node, symmetry, triangle_index)
        if batch and f"v{batch[0]}" in rows.columns:
            rows = rows.where(F.pmod(f"v{batch[0]}", F.lit(batch[2])) == batch[1])
        return rows
    left = lower(g, q, node.left, symmetry, triangle_index, batch, hint, cache, ranges)
    right = lower(g, q, node.right, symmetry, triangle_index, batch, hint, cache, ranges)
    key = [c for c in left.columns if c in right.columns]
    if hint == "broadcast" and broadcast_bytes(len(right.columns), len(key)) * sizer(g, q)(node.right.edges) > BROADCAST_BYTES:
        hint = None
    rows = hash_range_join(left, right, key, ranges, hint, in_order=True) if ranges > 1 else meet(left, right, key, hint)
    only_left = [c for c in left.columns if c not in key]
    only_right = [c for c in right.columns if c not in key]
    for a in only_left:
        for b in only_right:
            how = relation(q, int(a[1:]), int(b[1:]), symmetry)
            if not how:
                continue
            if a[0] == "v" and b[0] == "v":
                rows = rows.where(packed.compare(F.col(a), how, F.col(b)))
            elif a[0] == "v":
                back = relation(q, int(b[1:]), int(a[1:]), symmetry)
                rows = rows.withColumn(b, F.filter(b, packed.against(back, a))).where(F.size(b) > 0)
            elif b[0] == "v":
                rows = rows.withColumn(a, F.filter(a, packed.against(how, b))).where(F.size(a) > 0)
    return rows


def run(
    g: DataGraph,
    q: QueryGraph,
    tree: JoinNode | UnitNode | None = None,
    *,
    kind: str = "clique",
    shape: str = "bushy",
    overlap: bool = True,
    cost: str = "power_law",
    compression: bool = False,
    triangle_index: str | None = None,
    symmetry: str = "auto",
    batch: tuple[int, int, int] | None = None,
    hint: str | None = None,
    cache: dict | None = None,
    ranges: int = 1,
) -> DataFrame:
    """Matches; compressed where star leaves or clique vertices are kept as arrays."""
    if q.n > 1 and not q.connected():
        raise ValueError("the pattern must be connected")
    tree = tree or plan(g, q, kind, shape, overlap, cost, triangle_index)
    if compression:
        tree = with_arrays(tree, q, triangle_index, use_symmetry(q, symmetry))
        if batch and any(batch[0] in u.arrays for u in tree.leaves):
            raise ValueError("the batch vertex must not be kept as an array")
    rows = lower(g, q, tree, use_symmetry(q, symmetry), triangle_index, batch, hint, cache, ranges)
    order = [f"v{v}" for v in q.vertices if f"v{v}" in rows.columns] + [f"c{v}" for v in q.vertices if f"c{v}" in rows.columns]
    return rows.select(*order)


def grouped(g: DataGraph, q: QueryGraph, tree: JoinNode | UnitNode, symmetry: bool) -> tuple[int, int] | None:
    """In how many blocks of either leaf two stars over the same two leaves meet grouped by these; None where they join as rows.

    That takes an order that puts one root below all others and the leaves in order, and pays where copies of the lists
    are fewer than the stars.
    """
    if not isinstance(tree, JoinNode) or len(tree.leaves) != 2 or q.n != 4 or q.labelled or q.directed or q.elabels or not g.whole_lists:
        return None
    (low, high), m = sorted(tree.leaves, key=lambda u: u.root), g.stats["m"]
    if {low.kind, high.kind} - {"star", "wedge"} or len(tree.key) != 2 or not {low.root, high.root}.isdisjoint(tree.key) or len(q.edges) != 4:
        return None
    x, y = tree.key
    if any(relation(q, low.root, v, symmetry) != "<" for v in (x, y, high.root)) or any(relation(q, high.root, v, symmetry) for v in (x, y)) or relation(q, x, y, symmetry) != "<":
        return None
    parts = math.ceil(2 * m / BLOCK_ARCS)
    blocks = (max(parts, g.spark.sparkContext.defaultParallelism), max(1, parts))
    return blocks if 2 * m * sum(blocks) < g.stats["s"][2] / 2 else None


def _squares(blocks: tuple[int, int]):
    def run(batches):
        held = [batch for batch in batches if batch.num_rows]
        n = 0
        if held:
            cell, roots = held[0].column(0), np.concatenate([batch.column(1).to_numpy() for batch in held])
            lists = pa.concat_arrays([held.pop(0).column(2) for _ in range(len(held))])
            n = squares(cell[0].as_py(), blocks, roots, lists)
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], names=["n"])

    return run


def grouped_count(g: DataGraph, blocks: tuple[int, int]) -> DataFrame:
    """One row, column matches: the join of two stars on both leaves, with the roots of a pair of leaves counted and not listed.

    A block of pairs gets every star with the leaves that are in it; a task groups its stars pair by pair.
    """
    ship(g.spark)
    p, s = blocks
    near = g.adjacency()
    near.count()
    release(g.spark)
    small = "array<int>" if g.ranked and g.stats["n"] < 1 << 31 else "array<bigint>"
    rows = near.select(F.explode(F.sequence(F.lit(0), F.lit(p * s - 1))).alias("cell"), "u", F.col("nbrs").cast(small).alias("nbrs"))
    if s > 1:
        rows = rows.withColumn("nbrs", F.filter("nbrs", lambda e: (F.pmod(e, F.lit(p)) == F.floor(F.col("cell") / s)) | (F.pmod(e, F.lit(s)) == F.pmod("cell", F.lit(s)))))
    rows = rows.where(F.size("nbrs") > 1).repartitionById(p * s, F.col("cell").cast("int"))
    return rows.mapInArrow(_squares(blocks), "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("bigint").alias("matches"))


__all__ = ["grouped", "grouped_count", "lower", "plan", "run", "sizer", "with_arrays"]
