"""The published experiments on the given tables: a table of runs with time, outcome and completion rate.

    python -m motifloom.experiments [folder of tables] [cap in seconds] [repeats]

Each run counts the matches of one pattern on one prepared graph by one strategy. A run beyond the cap
is cancelled and counts as not completed, as does one that ends out of memory.
"""

from __future__ import annotations

import sys

from pyspark.sql import SparkSession

from motifloom import api, metrics
from motifloom.operators import partition
from motifloom.operators.graph import DataGraph, build
from motifloom.plans import catalogue
from motifloom.plans.ir import JoinNode
from motifloom.plans.pattern import QueryGraph
from motifloom.session import session

_ALL = {"triangle_index": "full", "compression": True}
STRATEGIES: dict[str, dict] = {
    "binary": {"strategy": "binary"} | _ALL,
    "growth": {"strategy": "growth"} | _ALL,
    "hypercube": {"strategy": "hypercube", "cells": 64},
    "replicated": {"strategy": "replicated"},
}
#: Switched off one by one, for both strategies that have the switches.
ABLATIONS: dict[str, dict] = {"all": {"batching": 4}, "no batching": {}, "no triangle index": {"batching": 4, "triangle_index": None}, "no compression": {"batching": 4, "compression": False}}


def plan_of_runs(trees: dict[str, JoinNode] | None = None) -> list[tuple[str, str, str, str, dict]]:
    """(experiment, pattern, graph, method, options) of every run."""
    runs = []
    for q in ("q2", "q5"):
        for g in ("lattice", "cobuy"):
            for s in ("binary", "growth"):
                runs += [("switches", q, g, f"{s}, {name}", STRATEGIES[s] | off) for name, off in ABLATIONS.items()]
    for q in ("q7", "q8", "q9"):
        for g in ("lattice", "cobuy"):
            runs += [("complex patterns", q, g, s, o) for s, o in STRATEGIES.items()]
            runs.append(("complex patterns", q, g, "growth, cover first", STRATEGIES["growth"] | {"order": "cover_first"}))
    for name, tree in (trees or {}).items():
        runs.append(("complex patterns", "q8", "cobuy", f"binary, {name} tree", STRATEGIES["binary"] | {"tree": tree}))
    for q in ("q1", "q2", "q3", "q4", "q5", "q6"):
        for g in ("cobuy", "lattice", "sharedline"):
            runs += [("simple patterns", q, g, s, o) for s, o in STRATEGIES.items()]
    for q in ("q2", "q3"):
        runs += [("large synthetic graph", q, "scalefree", s, o) for s, o in STRATEGIES.items()]
    for q in ("l1", "l2", "l3", "l5", "l6", "l7", "l8", "l9"):
        runs += [("labelled patterns", q, "typed", s, o) for s, o in STRATEGIES.items()]
    runs.append(("labelled patterns", "l8", "typed", "growth, cover first", STRATEGIES["growth"] | {"order": "cover_first"}))
    return runs


def prepare(g: DataGraph, q: QueryGraph, options: dict) -> None:
    """Computes what a run reads of the graph beforehand: the neighbour lists and, where it is asked for, the triangle index."""
    g.adjacency().count()
    if options.get("triangle_index") and not q.labelled:
        partition.triangle_index(g, options["triangle_index"] == "ordered").count()


def _seconds(x: float | None) -> float | None:
    return None if x is None else round(x, 2)


def run(spark: SparkSession, sf_dir: str, cap: float, repeat: int = 1, only: str | None = None) -> list[dict]:
    """Runs in order; the graph's preparation is no part of a run's time."""
    from motifloom.registry import Q8_TREES

    out = []
    for experiment, pattern, graph, method, options in plan_of_runs(Q8_TREES):
        if only and experiment != only:
            continue
        g, q = build(spark, sf_dir, graph), catalogue.by_name(pattern)
        prepare(g, q, options)
        row = metrics.timed(lambda: api.match(g, q, output="count", **options), repeat, cap)
        out.append({"experiment": experiment, "pattern": pattern, "graph": graph, "method": method} | row)
        print("| " + " | ".join(str(x) for x in (experiment, pattern, graph, method, row["status"], row["value"], _seconds(row["mean_s"]), _seconds(row["median_s"]))) + " |", flush=True)
    return out


def completion(rows: list[dict]) -> dict[str, float]:
    """Share of finished runs per strategy over the simple patterns; strategies without a run are left out."""
    mine = {s: [r for r in rows if r["experiment"] == "simple patterns" and r["method"] == s] for s in STRATEGIES}
    return {s: metrics.completion_rate(r) for s, r in mine.items() if r}


def main() -> None:
    folder = sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01"
    cap = float(sys.argv[2]) if len(sys.argv) > 2 else metrics.CAP
    repeat = int(sys.argv[3]) if len(sys.argv) > 3 else 3
    spark = session("experiments", memory="12g")
    print("| experiment | pattern | graph | method | outcome | matches | mean s | median s |\n| --- | --- | --- | --- | --- | --- | --- | --- |")
    rows = run(spark, folder, cap, repeat, sys.argv[4] if len(sys.argv) > 4 else None)
    print(completion(rows))
    spark.stop()


if __name__ == "__main__":
    main()
