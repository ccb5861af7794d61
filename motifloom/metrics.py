"""Analytic cost measures over logical workers, and timed runs.

Logical ownership is arithmetic (vertex id mod w), so that SQL can recompute every figure.
"""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifloom.operators import binary, frontier, growth, hypercube, partition
from motifloom.operators.batching import out_of_memory
from motifloom.operators.graph import DataGraph
from motifloom.plans import estimate, optimize
from motifloom.plans.ir import JoinNode, UnitNode, joins_of, use_symmetry
from motifloom.plans.pattern import QueryGraph

#: Times are capped at three hours, as in the published experiments.
CAP = 10_800.0


def intermediates(g: DataGraph, q: QueryGraph, order="greedy") -> DataFrame:
    """step (vertices bound), rows: partial results of every growth round, without arrays."""
    plan = optimize.growth_plan(q, order)
    parts = []
    for k in range(1, len(plan.rounds) + 1):
        rows = growth.run(g, q, plan, rounds_only=k)
        parts.append(rows.agg(F.lit(k + 1).cast("bigint").alias("step"), F.count(F.lit(1)).alias("rows")))
    return reduce(DataFrame.unionByName, parts)


def growth_comm(g: DataGraph, q: QueryGraph, w: int, order="greedy") -> DataFrame:
    """total, worst: integers that prefixes and their candidates take to the owners of the vertices they visit.

    In each round a prefix visits its placed neighbours in ascending order, so by ascending degree. A
    visit costs the ids placed and the candidates carried so far (none at the first), and nothing where
    the prefix is already. A prefix stays where its last visit was.
    """
    plan = optimize.growth_plan(q, order)
    near = g.adjacency()
    parts, last = [], F.col(f"v{plan.order[0]}")
    for k, r in enumerate(plan.rounds):
        if k:
            rows = growth.run(g, q, plan, rounds_only=k).withColumn("_from", last)
            stops = F.array_sort(F.array(*[F.col(f"v{y}") for y in r.back]))
            rows = rows.withColumn("_stops", stops).withColumn("_carried", F.lit(0).cast("bigint"))
            for j in range(len(r.back)):
                owner = F.pmod(F.get("_stops", F.lit(j)), F.lit(w))
                parts.append(rows.where(F.pmod("_from", F.lit(w)) != owner).select(owner.alias("owner"), (F.lit(k + 1) + F.col("_carried")).cast("bigint").alias("ints")))
                if j + 1 < len(r.back):
                    rows = rows.withColumn("_at", F.get("_stops", F.lit(j)))
                    rows = rows.join(near.select(F.col("u").alias("_u"), F.col("nbrs").alias("_m")), F.col("_at") == F.col("_u"))
                    held = F.col("_m") if j == 0 else F.array_intersect("_held", "_m")
                    rows = rows.withColumn("_held", held).withColumn("_carried", F.size("_held").cast("bigint")).withColumn("_from", F.col("_at")).drop("_m", "_u", "_at")
        last = F.greatest(*[F.col(f"v{y}") for y in r.back]) if len(r.back) > 1 else F.col(f"v{r.back[0]}")
    return _spread(reduce(DataFrame.unionByName, parts), w)


def frontier_comm(g: DataGraph, q: QueryGraph, w: int) -> DataFrame:
    """total, worst: ids of the rows that each superstep of frontier expansion (fixed choice) takes to the next vertex's owner."""
    ordered, first = use_symmetry(q), max(q.vertices, key=lambda v: (q.degree(v), -v))
    rows = g.vertices.select(F.col("id").alias(f"v{first}"))
    bound, black, at, parts = frozenset({first}), frozenset(), first, []
    while gray := frontier._unverified(q, bound, black):
        v = gray[0]
        owner = F.pmod(f"v{v}", F.lit(w))
        parts.append(rows.where(owner != F.pmod(f"v{at}", F.lit(w))).select(owner.alias("owner"), F.lit(len(bound)).cast("bigint").alias("ints")))
        rows = frontier.expand(rows, g, q, v, bound, black, ordered)
        bound, black, at = bound | q.adjacency[v], black | {v}, v
    return _spread(reduce(DataFrame.unionByName, parts), w)


def replication_comm(g: DataGraph, machines: int) -> DataFrame:
    """total, worst: two integers per edge to every machine when the graph is loaded; matching moves nothing."""
    return g.edges.agg((F.count(F.lit(1)) * 2 * machines).alias("total"), (F.count(F.lit(1)) * 2).alias("worst"))


def rounds(g: DataGraph, q: QueryGraph) -> DataFrame:
    """strategy, rounds (how often partial results are exchanged) and edge_rounds (edges that travel if each round moves the graph once)."""
    steps, bound, black = 0, frozenset({max(q.vertices, key=lambda v: (q.degree(v), -v))}), frozenset()
    while gray := frontier._unverified(q, bound, black):
        bound, black, steps = bound | q.adjacency[gray[0]], black | {gray[0]}, steps + 1
    depth = lambda n: 0 if isinstance(n, UnitNode) else 1 + max(depth(n.left), depth(n.right))
    rows = [("growth", q.n - 1), ("binary_edge", depth(binary.plan(g, q, "edge"))), ("binary_wedge", depth(binary.plan(g, q, "wedge", "left_deep"))), ("binary_clique", depth(binary.plan(g, q, triangle_index="full"))), ("hypercube", 1), ("frontier", steps), ("replicated", 0)]
    m = g.edges.where("src < dst").agg(F.count(F.lit(1)).alias("m"))
    return g.spark.createDataFrame(rows, "strategy string, rounds bigint").crossJoin(m).select("strategy", "rounds", (F.col("rounds") * F.col("m")).alias("edge_rounds"))


def sampled_count(g: DataGraph, q: QueryGraph, parts: int = 10, part: int = 0) -> DataFrame:
    """matches: those whose first placed vertex lies in one of `parts` hash parts, times their number."""
    from motifloom.operators import compress

    plan = optimize.growth_plan(q, compression=True)
    rows = growth.run(g, q, plan, batch=(part, parts))
    return compress.count(rows, q, use_symmetry(q)).select((F.col("matches") * parts).alias("matches"))


def q_errors(g: DataGraph, patterns: dict[str, QueryGraph]) -> DataFrame:
    """pattern, true, power_law, uniform (q-errors) and bound_log (log10 of the worst-case bound)."""
    import math

    from motifloom import api

    out = []
    for name, q in patterns.items():
        true = api.match(g, q, "growth", output="count", compression=True).first()[0]
        out.append((name, true, *[round(estimate.q_error(f(q, g.stats), true), 4) for f in (estimate.power_law, estimate.uniform)], round(math.log10(max(estimate.bound(q, g.stats["m"]), 1)), 4)))
    return g.spark.createDataFrame(out, "pattern string, true bigint, power_law double, uniform double, bound_log double")


def partition_cost(g: DataGraph, w: int) -> DataFrame:
    """kind, seconds to build, avg_edges, max_edges of the hash partition and both triangle partitions."""
    out = []
    for kind, build in (("hash", lambda: g.adjacency().count()), ("triangle_ordered", lambda: partition.triangle_index(g, True).count()), ("triangle", lambda: partition.triangle_index(g).count())):
        began = time.perf_counter()
        build()
        took = time.perf_counter() - began
        sizes = (partition.hash_stats(g, w) if kind == "hash" else partition.triangle_stats(g, w, kind == "triangle_ordered")).first()
        out.append((kind, took, float(sizes["avg_edges"]), sizes["max_edges"]))
    return g.spark.createDataFrame(out, "kind string, seconds double, avg_edges double, max_edges bigint")


def binary_comm(g: DataGraph, q: QueryGraph, w: int, tree: JoinNode | UnitNode | None = None) -> DataFrame:
    """total, worst: integers that the inputs of all joins take to the owner of their key (sum of its ids mod w)."""
    tree = tree or binary.plan(g, q)
    ordered = use_symmetry(q)
    parts = []
    for node in joins_of(tree):
        for side in (node.left, node.right):
            rows = binary.lower(g, q, side, ordered)
            owner = F.pmod(reduce(lambda a, b: a + b, [F.col(f"v{v}") for v in node.key]), F.lit(w))
            parts.append(rows.select(owner.alias("owner"), F.lit(len(side.vertices)).cast("bigint").alias("ints")))
    if not parts:
        return g.spark.createDataFrame([(0, 0)], "total bigint, worst bigint")
    return _spread(reduce(DataFrame.unionByName, parts), w)


def hypercube_comm(g: DataGraph, q: QueryGraph, shares: tuple[int, ...], tagged: bool = False) -> DataFrame:
    """total, worst: two integers (three with a tag) per edge copy, by cell."""
    routed = hypercube.route(g, q, shares, use_symmetry(q))
    return _spread(routed.select(F.col("cell").alias("owner"), F.lit(3 if tagged else 2).cast("bigint").alias("ints")), 0)


def _spread(sent: DataFrame, w: int) -> DataFrame:
    each = sent.groupBy("owner").agg(F.sum("ints").alias("ints"))
    return each.agg(F.coalesce(F.sum("ints"), F.lit(0)).cast("bigint").alias("total"), F.coalesce(F.max("ints"), F.lit(0)).cast("bigint").alias("worst"))


def load_balance(matches: DataFrame, vertex: int, w: int) -> DataFrame:
    """workers, worst, mean: matches per owner of one query vertex."""
    each = matches.groupBy(F.pmod(f"v{vertex}", F.lit(w)).alias("owner")).agg(F.count(F.lit(1)).alias("n"))
    return each.agg(F.lit(w).cast("bigint").alias("workers"), F.max("n").alias("worst"), F.round(F.sum("n") / w, 6).alias("mean"))


def compression_ratio(g: DataGraph, q: QueryGraph, order="greedy") -> DataFrame:
    """plain, stored: integers of all matches as rows, and of the compressed rows."""
    from motifloom.operators import compress

    plan = optimize.growth_plan(q, order, True)
    rows = growth.run(g, q, plan)
    arrays = compress.array_vertices(rows)
    stored = reduce(lambda a, b: a + b, [F.size(f"c{x}") for x in arrays], F.lit(q.n - len(arrays)))
    kept = rows.agg(F.coalesce(F.sum(stored), F.lit(0)).cast("bigint").alias("stored"))
    plain = compress.count(rows, q, use_symmetry(q), growth.same_arrays(q, plan, use_symmetry(q)) if g.whole_lists else ()).select((F.col("matches") * q.n).alias("plain"))
    return plain.crossJoin(kept)  # two one-row frames


def timed(make: Callable[[], DataFrame], repeat: int = 3, cap: float = CAP) -> dict:
    """Wall clock of an action: median and mean of some runs, and how it ended.

    A run beyond the cap is cancelled with all its jobs.
    """
    seconds, status, value = [], "finished", None
    for _ in range(repeat):
        group, late, over = f"timed-{uuid.uuid4().hex}", threading.Event(), threading.Event()
        context = SparkSession.getActiveSession().sparkContext

        def watch():
            if not over.wait(cap):
                late.set()
                while not over.wait(0.5):  # again and again, as a run may still be planning or start more jobs
                    context.cancelJobGroup(group)

        timer = threading.Thread(target=watch, daemon=True)
        context.setJobGroup(group, "timed run", interruptOnCancel=True)
        began = time.perf_counter()
        timer.start()
        try:
            value = make().first()[0]
            if late.is_set():
                status = "over time"
        except Exception as e:  # noqa: BLE001 - an experiment records how a run ends
            status = "over time" if late.is_set() else "out of memory" if out_of_memory(e) else "failed"
        finally:
            over.set()
            context.setLocalProperty("spark.jobGroup.id", None)
        if status != "finished":
            break
        seconds.append(time.perf_counter() - began)
    seconds.sort()
    return {"status": status, "value": value, "median_s": seconds[len(seconds) // 2] if seconds else None, "mean_s": sum(seconds) / len(seconds) if seconds else None}


def completion_rate(runs: list[dict]) -> float:
    return sum(r["status"] == "finished" for r in runs) / len(runs) if runs else 0.0


def event_log_times(spark: SparkSession, path: str) -> DataFrame:
    """executor, compute_s, wait_s from an event log: run time without and of shuffle-fetch waiting.

    T_comp is the largest compute_s, T_comm what wall clock has beyond it.
    """
    raw = spark.read.text(path).where(F.col("value").startswith('{"Event":"SparkListenerTaskEnd"'))
    get = lambda p: F.get_json_object("value", f"$.{p}")
    rows = raw.select(
        get("['Task Info']['Executor ID']").alias("executor"),
        (get("['Task Metrics']['Executor Run Time']").cast("double") / 1000).alias("run_s"),
        (get("['Task Metrics']['Shuffle Read Metrics']['Fetch Wait Time']").cast("double") / 1000).alias("wait_s"),
        get("['Task Metrics']['Peak Execution Memory']").cast("bigint").alias("peak_bytes"),
    )
    return rows.groupBy("executor").agg(F.sum(F.col("run_s") - F.col("wait_s")).alias("compute_s"), F.sum("wait_s").alias("wait_s"), F.max("peak_bytes").alias("peak_bytes"))
