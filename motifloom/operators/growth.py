"""Vertex growth: one query vertex per round, its candidates by intersecting neighbour lists.

Candidates are proposed by the placed neighbour with the shortest list and intersected with the lists
of the others, shortest first, row by row (the size probe). With ids ranked by degree and no labels the
least id has the shortest list, so the probe costs nothing; otherwise the lengths of the lists are looked
up, a narrow join per placed neighbour.
"""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifloom.functions import kernels
from motifloom.operators import compress as packed
from motifloom.operators.graph import DataGraph
from motifloom.operators.partition import triangle_index as index_of
from motifloom.plans.ir import GrowthPlan, Round, relation, use_symmetry
from motifloom.plans.optimize import growth_plan
from motifloom.plans.pattern import QueryGraph
from motifloom.storage import meet, release, ship, stored

#: Bytes of neighbour lists that a batch of a count may carry, before compression; more on graphs whose own lists take a third of it.
LIST_BYTES = 1 << 30
MOST_BATCHES = 256
#: Edges of a graph whose cliques' later rounds run inside a task, as its cell may need them all.
CELL_EDGES = 32_000_000
#: Arcs that a block of pairs holds at most, on either side.
BLOCK_ARCS = 8_000_000


def _kind(q: QueryGraph, y: int, x: int) -> tuple:
    """Labels and direction of the arcs from an image of y to one of x."""
    a, b = (y, x) if (y, x) in q.edges or not q.directed else (x, y)
    e = (a, b) if q.directed else (min(x, y), max(x, y))
    return q.label(y), q.label(x), q.elabel(e), q.directed and (y, x) not in q.edges


def _lists(g: DataGraph, q: QueryGraph, y: int, x: int) -> DataFrame:
    """u, nbrs: the neighbours of an image of y that can be images of x."""
    return g.adjacency(*_kind(q, y, x))


def _checks(q: QueryGraph, x: int, placed: list[int], symmetry: bool, known: tuple[int, ...] = ()):
    """A predicate on candidates of x against placed single vertices."""
    tests = [(y, how) for y in placed if y not in known and (how := relation(q, x, y, symmetry))]
    return packed.checker(tests) if tests else None


def _intersected(rows: DataFrame, g: DataGraph, q: QueryGraph, x: int, back: tuple[int, ...], proposer: str, hint: str | None) -> tuple[DataFrame, Column]:
    """rows with list columns joined, and the expression that intersects them."""
    hinted = lambda df: df.hint(hint) if hint else df
    if len(back) == 1 or proposer == "first":
        lists = []
        for k, y in enumerate(back):
            near = _lists(g, q, y, x).select(F.col("u").alias(f"_u{k}"), F.col("nbrs").alias(f"_n{k}"))
            rows = rows.join(hinted(near), F.col(f"v{y}") == F.col(f"_u{k}")).drop(f"_u{k}")
            lists.append(F.col(f"_n{k}"))
        return rows, reduce(F.array_intersect, lists)
    if g.ranked and not (q.labelled or q.elabels or q.directed):
        # ids say which list is the shortest
        rows = rows.withColumn("_by", F.array_sort(F.array(*[F.struct(F.col(f"v{y}").alias("u")) for y in back])))
        near = _lists(g, q, back[0], x).select("u", F.col("nbrs").alias("_m"))
    else:
        rows, near = _probed(rows, g, q, x, back)
    keys = [c for c in near.columns if c != "_m"]
    near = near.select(*[F.col(c).alias(f"_{c}") for c in keys], "_m")
    current = None
    for k in range(len(back)):
        rows = rows.withColumns({f"_at_{c}": F.get("_by", F.lit(k))[c] for c in keys})
        same = reduce(lambda a, b: a & b, [F.col(f"_at_{c}") == F.col(f"_{c}") for c in keys])
        rows = rows.join(hinted(near), same).drop(*[f"_at_{c}" for c in keys], *[f"_{c}" for c in keys])
        if k == 0:
            rows = rows.withColumnRenamed("_m", "_n0")
            current = F.col("_n0")
        elif k < len(back) - 1:
            rows = rows.withColumn("_n0", F.array_intersect("_n0", "_m")).drop("_m").where(F.size("_n0") > 0)
        else:
            current = F.array_intersect("_n0", "_m")
    return rows, current


def _probed(rows: DataFrame, g: DataGraph, q: QueryGraph, x: int, back: tuple[int, ...]) -> tuple[DataFrame, DataFrame]:
    """rows with _by: (size, kind, u) of the placed neighbours, shortest list first; and the lists of all kinds."""
    kinds: list = []
    for y in back:
        lists = _lists(g, q, y, x)
        if not any(lists is other for other in kinds):
            kinds.append(lists)
    probes = []
    for y in back:
        kind = next(i for i, other in enumerate(kinds) if other is _lists(g, q, y, x))
        sizes = kinds[kind].select(F.col("u").alias("_u"), F.size("nbrs").cast("bigint").alias("_size"))
        if not g.whole_lists:
            sizes = sizes.groupBy("_u").agg(F.sum("_size").alias("_size"))
        rows = rows.join(sizes, F.col(f"v{y}") == F.col("_u")).drop("_u").withColumnRenamed("_size", f"_size{y}")
        probes.append(F.struct(F.col(f"_size{y}").alias("size"), F.lit(kind).alias("kind"), F.col(f"v{y}").alias("u")))
    rows = rows.withColumn("_by", F.array_sort(F.array(*probes))).drop(*[f"_size{y}" for y in back])
    near = reduce(DataFrame.unionByName, [lists.select(F.lit(i).alias("kind"), "u", F.col("nbrs").alias("_m")) for i, lists in enumerate(kinds)])
    return rows, near


def _semi(rows: DataFrame, g: DataGraph, q: QueryGraph, r: Round, placed: list[int], symmetry: bool) -> DataFrame:
    """Candidates as rows: exploded from one list, then reduced by semi-joins with the edges."""
    x, first = r.target, r.back[0]
    near = _lists(g, q, first, x).select(F.col("u").alias("_u"), "nbrs")
    check = _checks(q, x, placed, symmetry)
    values = F.filter("nbrs", check) if check else F.col("nbrs")
    rows = rows.join(near, F.col(f"v{first}") == F.col("_u"))
    rows = rows.select(*[c for c in rows.columns if c not in ("_u", "nbrs")], F.explode(values).alias(f"v{x}"))
    for y in r.back[1:]:
        pairs = g.pairs(q.label(y), q.label(x), q.elabel((min(x, y), max(x, y))), inward=q.directed and (y, x) not in q.edges)
        rows = rows.join(pairs, (F.col(f"v{y}") == F.col("u")) & (F.col(f"v{x}") == F.col("v")), "left_semi")
    return rows


def _grouped(rows: DataFrame, g: DataGraph, q: QueryGraph, r: Round, tri: DataFrame) -> tuple[DataFrame, Column]:
    """One visit per group: the anchor's index tells which neighbours its matched neighbours have."""
    current = None
    for k, (anchor, inside) in enumerate(r.groups):
        parts = []
        if not inside or q.label(r.target) is not None:
            near = _lists(g, q, anchor, r.target).select(F.col("u").alias("_u"), F.col("nbrs").alias(f"_g{k}"))
            rows = rows.join(near, F.col(f"v{anchor}") == F.col("_u")).drop("_u")
            parts.append(F.col(f"_g{k}"))
        for y in inside:
            ends = tri.select(F.col("u").alias("_u"), F.col("a").alias("_a"), F.col("ends").alias(f"_t{k}_{y}"))
            rows = rows.join(ends, (F.col(f"v{anchor}") == F.col("_u")) & (F.col(f"v{y}") == F.col("_a"))).drop("_u", "_a")
            parts.append(F.col(f"_t{k}_{y}"))
        for found in parts:
            current = found if current is None else F.array_intersect(current, found)
    return rows, current


def run(
    g: DataGraph,
    q: QueryGraph,
    plan: GrowthPlan | None = None,
    *,
    compression: bool = False,
    triangle_index: str | None = None,
    proposer: str = "min_degree",
    execution: str = "array",
    symmetry: str = "auto",
    batch: tuple[int, int] | None = None,
    hint: str | None = None,
    rounds_only: int | None = None,
) -> DataFrame:
    """Matches, compressed where the plan keeps arrays. batch = (k, b) takes the k-th of b parts of the seeds."""
    if execution not in ("array", "edge_semi"):
        raise ValueError(f"execution is array or edge_semi, not {execution}")
    if proposer not in ("min_degree", "first"):
        raise ValueError(f"proposer is min_degree or first, not {proposer}")
    plan = plan or growth_plan(q, "greedy", compression=compression, triangle_index=triangle_index)
    ordered = use_symmetry(q, symmetry)
    first = plan.order[0]
    if q.n == 1:
        rows = g.vertices.select(F.col("id").alias("v1"), "label")
        return (rows.where(F.col("label") == q.label(1)) if q.labelled else rows).select("v1")
    single, arrays = [first], []
    alike = {x: min(s) for s in same_arrays(q, plan, ordered) for x in s} if g.whole_lists and execution == "array" else {}
    usable = not (q.directed or q.elabels)  # the index knows neither directions nor edge labels
    tri = index_of(g, triangle_index == "ordered") if usable and any(inside for r in plan.rounds for _, inside in r.groups) else None
    rows = None
    for r in plan.rounds[:rounds_only]:
        x = r.target
        if alike.get(x) in arrays:
            # the array of an earlier vertex, which respects all that this one has to: no list is looked up again
            rows = rows.withColumn(f"c{x}", F.col(f"c{alike[x]}"))
            arrays.append(x)
            continue
        if rows is None:
            near = _lists(g, q, first, x).select(F.col("u").alias(f"v{first}"), F.col("nbrs").alias("_n0"))
            rows = near if batch is None else near.where(F.pmod(f"v{first}", F.lit(batch[1])) == batch[0])
            found: Column = F.col("_n0")
        elif execution == "edge_semi":
            rows = _semi(rows, g, q, r, single, ordered)
            single.append(x)
            continue
        elif tri is not None and any(inside for _, inside in r.groups):
            rows, found = _grouped(rows, g, q, r, tri)
        else:
            rows, found = _intersected(rows, g, q, x, r.back, proposer, hint)
        check = _checks(q, x, single, ordered)
        found = F.filter(found, check) if check else found
        keep = [f"v{y}" for y in single] + [f"c{y}" for y in arrays]
        if r.keep_array and execution == "array":
            rows = rows.select(*keep, found.alias(f"c{x}")).where(F.size(f"c{x}") > 0)
            arrays.append(x)
            continue
        # exploding the expression itself keeps the optimiser from evaluating the intersection twice
        rows = rows.select(*keep, F.explode(found).alias(f"v{x}"))
        single.append(x)
        for y in arrays:  # an array of an earlier round must respect the new vertex
            if how := relation(q, y, x, ordered):
                rows = rows.withColumn(f"c{y}", F.filter(f"c{y}", packed.against(how, f"v{x}"))).where(F.size(f"c{y}") > 0)
    return rows


def same_arrays(q: QueryGraph, plan: GrowthPlan, symmetry: bool) -> tuple[frozenset[int], ...]:
    """Sets of array vertices whose arrays are equal by plan: same neighbours, same checks against all single vertices."""
    single = [v for v in plan.order if v not in plan.arrays]
    groups: dict[tuple, set[int]] = {}
    for r in plan.rounds:
        if r.keep_array:
            key = (r.back, q.label(r.target), tuple(relation(q, r.target, y, symmetry) for y in single))
            groups.setdefault(key, set()).add(r.target)
    return tuple(frozenset(s) for s in groups.values() if len(s) > 1)


def list_batches(g: DataGraph, q: QueryGraph, plan: GrowthPlan, rows_of) -> int:
    """How many batches keep the neighbour lists that one batch's rows carry through a shuffle within LIST_BYTES.

    rows_of estimates matches of some query edges; a row carries the shorter list of an edge, half the sum of both at most.
    """
    m = g.stats["m"]
    if q.labelled or q.directed or not m:
        return 1
    most = 0.0
    for k, r in enumerate(plan.rounds):
        if len(r.back) > 1:
            placed = [v for v in plan.order[: k + 1] if v not in plan.arrays]
            most = max(most, 8 * rows_of(q.induced_edges(placed)) * g.stats["s"][2] / (2 * m))
    return min(MOST_BATCHES, max(1, math.ceil(most / max(LIST_BYTES, 48 * m))))


def twin(q: QueryGraph, plan: GrowthPlan, symmetry: bool) -> int | None:
    """A vertex between the first and the last that can trade places with the last: same neighbours, label and checks."""
    x = plan.order[-1]
    if q.directed or q.elabels or plan.arrays != (x,):
        return None
    for y in plan.order[1:-1]:
        others = [z for z in plan.order if z not in (x, y)]
        if q.adjacency[x] == q.adjacency[y] and q.label(x) == q.label(y) and all(relation(q, x, z, symmetry) == relation(q, y, z, symmetry) for z in others):
            return y
    return None


def paired(g: DataGraph, q: QueryGraph, plan: GrowthPlan, y: int, **options) -> DataFrame:
    """One row, column matches: the last round counted without lists, as its candidates are the images of its twin y."""
    x = plan.order[-1]
    rows = run(g, q, plan, rounds_only=len(plan.rounds) - 1, **options)
    images = rows.groupBy(*[f"v{z}" for z in plan.order if z not in (x, y)]).agg(F.count(F.lit(1)).alias("n"))
    each = F.col("n") * (F.col("n") - 1)
    if relation(q, x, y, use_symmetry(q, options.get("symmetry", "auto"))) != "!=":
        each = F.shiftright(each, 1)
    return images.agg(F.coalesce(F.sum(each), F.lit(0)).cast("bigint").alias("matches"))


def pair_blocks(g: DataGraph, q: QueryGraph, plan: GrowthPlan, y: int, rows: float) -> tuple[int, int] | None:
    """In how many blocks of either side the images of a square's twins are counted by the other two vertices.

    None where the pattern is no square, or where copies of the lists are no fewer than the rows (by estimate) that would be grouped.
    """
    f, z = plan.order[0], plan.order[2]
    if q.n != 4 or len(q.edges) != 4 or plan.order[1] != y or q.adjacency[y] != {f, z}:
        return None
    arcs = [g.label_pairs().get((q.label(y), q.label(v)), 0) if q.labelled and q.label(y) is not None and q.label(v) is not None else 2 * g.stats["m"] for v in (f, z)]
    p, s = (max(1, math.ceil(n / BLOCK_ARCS)) for n in arcs)
    p = max(p, g.spark.sparkContext.defaultParallelism)
    return (p, s) if arcs[0] * s + arcs[1] * p < rows else None


def _pairs(how: str | None):
    def run(batches):
        ends: dict[bool, list] = {False: [], True: []}
        near: dict[bool, list] = {False: [], True: []}
        for batch in batches:
            lists, side = batch.column(2), batch.column(1).to_numpy(zero_copy_only=False)
            for second in (False, True):
                some = lists.filter(pa.array(side == second))
                ends[second].append(np.repeat(batch.column(0).to_numpy()[side == second], np.diff(some.offsets.to_numpy())))
                near[second].append(some.flatten().to_numpy())
        n = 0
        if near[False] and near[True]:
            (at, y), (f, z) = ([np.concatenate(x.pop(k)) for k in (False, True)] for x in (ends, near))
            n = kernels.pairs(how, f, at, y, z)
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], names=["n"])

    return run


def _in_part(parts: int, how: str | None):
    """Tells the neighbours of u that fall on part."""
    return lambda e: (F.pmod(e, F.lit(parts)) == F.col("part")) & (packed.compare(e, how, F.col("u")) if how else F.lit(True))


def pair_count(g: DataGraph, q: QueryGraph, plan: GrowthPlan, y: int, blocks: tuple[int, int], symmetry: str = "auto", list_bytes: int = LIST_BYTES) -> DataFrame:
    """What paired counts for a square, without a row per image of the first three vertices.

    The lists of the images of y go to blocks of pairs of the other two vertices, and a task counts the images of each pair.
    Blocks run in rounds, so that only one round's lists, about list_bytes, are on disk.
    """
    ship(g.spark)
    (p, s), (f, _, z, x) = blocks, plan.order
    ordered = use_symmetry(q, symmetry)
    small = "int" if g.ranked and g.stats["n"] < 1 << 31 else "bigint"
    copies = 0
    sides = []
    kinds = {_kind(q, y, v) for v in (f, z)}  # stored, as lists that executors keep hold on to the shuffle files that they came from
    near = {kind: stored(g.lists(*kind), "lists") for kind in kinds}
    for v, parts, other in ((f, p, s), (z, s, p)):
        lists = near[_kind(q, y, v)]
        rows = lists.select(F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"), "u", "nbrs")
        rows = rows.select("part", F.col("u").cast(small).alias("u"), F.filter("nbrs", _in_part(parts, relation(q, v, y, ordered))).cast(f"array<{small}>").alias("nbrs")).where(F.size("nbrs") > 0)
        rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(other - 1))))
        cell = F.col("part") * s + F.col("other") if v == f else F.col("other") * s + F.col("part")
        sides.append(rows.select(cell.alias("cell"), "u", F.lit(v == z).alias("second"), "nbrs"))
        copies += other * (lists.agg(F.sum(F.size("nbrs"))).first()[0] or 0)
    release(g.spark)
    both = sides[0].unionByName(sides[1])
    rounds = min(p * s, max(1, math.ceil(4 * copies / list_bytes)))
    n = 0
    for k in range(rounds):
        dealt = both.where(F.pmod("cell", F.lit(rounds)) == k).repartitionById(math.ceil(p * s / rounds), F.floor(F.col("cell") / rounds).cast("int"))
        n += dealt.select("u", "second", "nbrs").mapInArrow(_pairs(relation(q, z, f, ordered)), "n long").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        release(g.spark)
    if relation(q, x, y, ordered) != "!=":
        n >>= 1
    return g.spark.createDataFrame([(n,)], "matches bigint")


def clique_cells(g: DataGraph, q: QueryGraph, plan: GrowthPlan, symmetry: bool, batches: int) -> int | None:
    """In how many cells the seeds of a 4-clique grow within tasks; None where rows that carry lists fit one batch, or a cell would not fit a task."""
    total_order = all(relation(q, x, y, symmetry) == "<" for x in q.vertices for y in q.vertices if x < y)
    if q.n != 4 or len(q.edges) != 6 or q.labelled or q.directed or q.elabels or not total_order or plan.order != (1, 2, 3, 4):
        return None
    if batches == 1 or not g.ranked or not g.whole_lists or g.stats["m"] > CELL_EDGES:
        return None
    return 2 * g.spark.sparkContext.defaultParallelism


def _cliques(batches):
    held = list(batches)
    n = 0
    if held:
        t = pa.Table.from_batches(held)
        held.clear()
        first, rest = (t.filter(pa.compute.equal(t.column(1), pa.scalar(k))) for k in (True, False))
        if first.num_rows and rest.num_rows:
            n = kernels.cliques4(first.column(2).combine_chunks(), rest.column(0).to_numpy(), rest.column(2).combine_chunks())
    yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], names=["n"])


def clique_count(g: DataGraph, q: QueryGraph, cells: int) -> DataFrame:
    """One row, column matches: 4-cliques by growth from their smallest vertex, whose neighbours' lists go to a cell of seeds once and not once per row."""
    ship(g.spark)
    small = "int" if g.stats["n"] < 1 << 31 else "bigint"
    up = g.lists().select(F.col("u").cast(small).alias("u"), F.filter("nbrs", lambda e: e > F.col("u")).cast(f"array<{small}>").alias("nbrs")).where(F.size("nbrs") > 0)
    up = stored(up, "lists")
    release(g.spark)
    seeds = up.select(F.pmod("u", F.lit(cells)).alias("cell"), "u", F.lit(True).alias("first"), "nbrs")
    used = up.select(F.pmod("u", F.lit(cells)).alias("cell"), F.explode("nbrs").alias("u")).distinct()
    lists = meet(used, up, ["u"]).select("cell", "u", F.lit(False).alias("first"), "nbrs")
    dealt = seeds.unionByName(lists).repartitionById(cells, F.col("cell").cast("int")).select("u", "first", "nbrs")
    return dealt.mapInArrow(_cliques, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("bigint").alias("matches"))
