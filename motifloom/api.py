"""One entry for every strategy, preset and switch."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from motifloom.operators import batching as batches_
from motifloom.operators import binary, cliquebud, compress, frontier, growth, hybrid, hypercube, replicate, wco
from motifloom.operators.batching import BatchSpec
from motifloom.operators.graph import DataGraph
from motifloom.plans import optimize
from motifloom.plans.advisor import advise
from motifloom.plans.ir import JoinNode, UnitNode, use_symmetry
from motifloom.plans.pattern import QueryGraph
from motifloom.storage import release

#: The surveyed algorithms as fixed settings: `published` as first described, `full` with all optimizations.
PRESETS: dict[str, dict] = {
    "star_left_deep": {"published": {"strategy": "binary", "unit": "star", "shape": "left_deep"}, "full": {"compression": True, "batching": 4}},
    "hypercube_single_round": {"published": {"strategy": "hypercube"}, "full": {}},
    "frontier_supersteps": {"published": {"strategy": "frontier"}, "full": {}},
    "wedge_left_deep": {"published": {"strategy": "binary", "unit": "wedge", "shape": "left_deep", "compression": True}, "full": {"batching": 4}},
    "clique_bushy": {"published": {"strategy": "binary", "unit": "clique", "shape": "bushy", "triangle_index": "ordered", "compression": True}, "full": {"batching": 4}},
    "clique_buds": {"published": {"strategy": "cliquebud"}, "full": {}},
    "prefix_growth": {"published": {"strategy": "growth", "batching": 4}, "full": {"triangle_index": "full", "compression": True}},
    "replicated": {"published": {"strategy": "replicated"}, "full": {}},
}

#: Rows that are counted per pair of twins at a time, when no batching is asked for; more of a square's are not made but counted in blocks.
TWIN_ROWS = 16_000_000

STRATEGIES = ("binary", "growth", "hypercube", "replicated", "frontier", "cliquebud", "wco", "hybrid")


def match(
    g: DataGraph,
    q: QueryGraph,
    strategy: str = "auto",
    *,
    preset: str | None = None,
    form: str = "published",
    unit: str = "clique",
    shape: str = "bushy",
    overlap: bool = True,
    cost: str = "power_law",
    order="greedy",
    proposer: str = "min_degree",
    execution: str = "array",
    batching: int | BatchSpec | None = None,
    triangle_index: str | None = None,
    compression: bool = False,
    symmetry: str = "auto",
    output: str = "rows",
    limit: int | None = None,
    cells: int | None = None,
    shares="optimize",
    dedupe: str = "owner",
    kernel: str | None = None,
    heuristic: str = "min_comm",
    hint: str | None = None,
    tree: JoinNode | UnitNode | None = None,
    ranges: int = 1,
    split: str = "vertex",
) -> DataFrame:
    """All matches of q in g.

    output: rows (v1..vn), count (one row, matches) or compressed (v and c columns). batching is a
    number of batches, or a BatchSpec that derives it from the estimated size; batches run one after the
    other, when match is called, and rows come back from the shared folder. tree gives a join tree of
    one's own, ranges runs each of its joins in so many parts. Strategies other than growth and binary
    take no optimizations and say so.
    """
    if preset:
        chosen = PRESETS[preset]["published"] | (PRESETS[preset]["full"] if form == "full" else {})
        return match(g, q, **({"symmetry": symmetry, "output": output, "limit": limit} | chosen))
    if strategy == "auto":
        advice = advise(g, q)
        strategy = advice.strategy
        if strategy in ("growth", "binary"):
            compression = compression or advice.compression
            triangle_index = triangle_index or ("full" if advice.triangle_index else None)
            batching = batching or BatchSpec()
            order = advice.order if strategy == "growth" and order == "greedy" else order
    if strategy not in STRATEGIES:
        raise ValueError(f"no such strategy: {strategy}")
    if strategy not in ("growth", "binary") and (batching or triangle_index or compression):
        raise ValueError(f"batching, triangle index and compression are not for the strategy {strategy}")
    ordered = use_symmetry(q, symmetry)
    same: tuple = ()
    spec = batching if isinstance(batching, BatchSpec) else BatchSpec()
    if strategy == "growth":
        plan = optimize.growth_plan(q, order, compression, triangle_index, g.label_counts() if q.labelled else None, symmetry)
        same = growth.same_arrays(q, plan, ordered) if g.whole_lists else ()  # chunks of a list are not the same array
        options = {"triangle_index": triangle_index, "proposer": proposer, "execution": execution, "symmetry": symmetry, "hint": hint}
        make = lambda k, b: growth.run(g, q, plan, batch=(k, b) if b > 1 else None, **options)
        if output == "count" and (y := growth.twin(q, plan, ordered)):
            prefix = binary.sizer(g, q)(q.induced_edges([v for v in q.vertices if v != plan.order[-1]]))
            if prefix > TWIN_ROWS and not batching and not hint and execution == "array" and proposer == "min_degree" and (blocks := growth.pair_blocks(g, q, plan, y, prefix)):
                return growth.pair_count(g, q, plan, y, blocks, symmetry)
            b = spec.batches(prefix) if isinstance(batching, BatchSpec) else batching or BatchSpec(TWIN_ROWS).batches(prefix)
            return _in_batches(g, lambda k, n: growth.paired(g, q, plan, y, batch=(k, n) if n > 1 else None, **options), b, spec)
    elif strategy == "binary":
        tree = tree or binary.plan(g, q, unit, shape, overlap, cost, triangle_index, order if order == "cover_first" else None)
        tree = binary.with_arrays(tree, q, triangle_index, ordered) if compression else tree
        if output == "count" and compression and not batching and ranges == 1 and not hint and (blocks := binary.grouped(g, q, tree, ordered)):
            return binary.grouped_count(g, blocks)
        vertex = batches_.pick_binary(tree)
        cache: dict | None = {} if spec.miss == "cache" else None
        make = lambda k, b: binary.run(g, q, tree, triangle_index=triangle_index, symmetry=symmetry, batch=(vertex, k, b) if b > 1 else None, hint=hint, cache=cache if b > 1 else None, ranges=ranges)
    elif strategy == "hypercube":
        make = lambda k, b: hypercube.run(g, q, cells, shares=shares, dedupe=dedupe, kernel=kernel or ("candidate" if q.labelled else "cover"), symmetry=symmetry)
    elif strategy == "replicated":
        make = lambda k, b: replicate.run(g, q, kernel=kernel or ("candidate" if q.labelled else "cover"), execution="broadcast_join" if execution == "broadcast_join" else "kernel", symmetry=symmetry)
    elif strategy == "frontier":
        make = lambda k, b: frontier.run(g, q, heuristic="min_comm" if heuristic == "per_row" else heuristic, per_row=heuristic == "per_row", symmetry=symmetry)
    elif strategy == "cliquebud":
        make = lambda k, b: cliquebud.run(g, q, symmetry=symmetry)
    elif strategy == "wco":
        make = lambda k, b: wco.run(g, q, symmetry=symmetry, split=split)
    else:
        make = lambda k, b: hybrid.run(g, q, symmetry=symmetry)
    if strategy == "replicated" and output == "count" and execution != "broadcast_join":
        return replicate.count(g, q, kernel=kernel or ("candidate" if q.labelled else "cover"), symmetry=symmetry)
    if strategy == "hypercube" and output == "count":
        return hypercube.count(g, q, cells, shares=shares, dedupe=dedupe, kernel=kernel or ("candidate" if q.labelled else "cover"), symmetry=symmetry)
    if strategy == "growth" and output == "count" and execution == "array" and not batching:
        batching = growth.list_batches(g, q, plan, binary.sizer(g, q))
        if not hint and proposer == "min_degree" and not triangle_index and (cells := growth.clique_cells(g, q, plan, ordered, batching)):
            return growth.clique_count(g, q, cells)
    b = spec.batches(binary.sizer(g, q)(q.edges)) if isinstance(batching, BatchSpec) else batching or 1
    if output == "count":
        counted = lambda k, n: compress.count(make(k, n), q, ordered, same)
        return _in_batches(g, counted, b, spec)
    shown = make if output == "compressed" else lambda k, n: compress.expand(make(k, n), q, ordered)
    rows = shown(0, 1) if b == 1 else batches_.in_turn(shown, b, spec)
    return rows if output == "compressed" or limit is None else rows.limit(limit)


def _in_batches(g: DataGraph, counted, b: int, spec: BatchSpec) -> DataFrame:
    """Counts of all batches as one: one job after the other, so that only one batch is in memory and on disk."""
    if b == 1:
        return counted(0, 1)

    def one(k: int, n: int) -> DataFrame:
        release(g.spark)
        return counted(k, n)

    return g.spark.createDataFrame([(batches_.total(one, b, spec),)], "matches bigint")


def sql_match(spark: SparkSession, pattern: str, g: DataGraph, view: str = "matches", **options) -> DataFrame:
    """Matches of a pattern text, also as a temporary view."""
    rows = match(g, QueryGraph.parse(pattern), **options)
    rows.createOrReplaceTempView(view)
    return rows


def register_views(g: DataGraph, prefix: str = "g") -> None:
    """Temporary views of a graph's edges, vertices and adjacency, for SQL."""
    g.edges.createOrReplaceTempView(f"{prefix}_edges")
    g.vertices.createOrReplaceTempView(f"{prefix}_vertices")
    g.adjacency().createOrReplaceTempView(f"{prefix}_adj")
