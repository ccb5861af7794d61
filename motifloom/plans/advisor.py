"""A decision guide: which strategy and which switches for a pattern on a graph."""

from __future__ import annotations

from dataclasses import dataclass, field

from motifloom.plans import optimize
from motifloom.plans.estimate import Sizer
from motifloom.plans.ir import UnitNode
from motifloom.plans.pattern import QueryGraph

#: Below this average degree arrays cost more than they save.
DENSE_ENOUGH = 5.0
#: The triangle index wants this share of the edges as memory per machine.
INDEX_SHARE = 0.6
#: From this average degree on a triangle partition comes close to the whole graph.
TOO_DENSE = 150.0


@dataclass(frozen=True)
class Cluster:
    machine_bytes: int = 1 << 30
    machines: int = 8


@dataclass(frozen=True)
class Advice:
    strategy: str
    batching: bool
    triangle_index: bool
    compression: bool
    order: str
    reasons: tuple[str, ...] = field(default_factory=tuple)


def decide(q: QueryGraph, stats: dict, cluster: Cluster, label_pairs: dict | None = None, label_counts: dict | None = None) -> Advice:
    """A pure function of the statistics."""
    reasons = []
    sizer = Sizer(q, stats, "power_law", label_pairs, label_counts)
    graph_bytes = 16 * stats["m"] + 8 * stats["n"]
    tree = optimize.bushy(q, sizer, "clique")
    if graph_bytes <= cluster.machine_bytes // 2:
        strategy = "replicated"
        reasons.append("the graph fits one machine")
    elif isinstance(tree, UnitNode):
        strategy = "binary"
        reasons.append("the pattern is a join unit")
    else:
        plan = optimize.growth_plan(q)
        grown, joined = optimize.growth_cost(q, plan, sizer), optimize.plan_cost(tree, sizer)
        strategy = "binary" if joined < grown else "growth"
        reasons.append(f"estimated cost: growth {grown:.3g}, binary {joined:.3g}")
    compression = stats["avg_degree"] >= DENSE_ENOUGH
    reasons.append("arrays pay off" if compression else "the graph is too sparse for arrays")
    index = cluster.machine_bytes >= INDEX_SHARE * 16 * stats["m"] and stats["avg_degree"] < TOO_DENSE
    reasons.append("memory suffices for the triangle index" if index else "no triangle index")
    greedy, cover = optimize.greedy(q), optimize.cover_first(q)
    more = len(optimize.compressible(q, cover)) > len(optimize.compressible(q, greedy))
    reasons.append("the cover-first order keeps more arrays" if more else "the cover-first order keeps no more arrays")
    return Advice(strategy, True, index, compression, "cover_first" if more else "greedy", tuple(reasons))


def advise(g, q: QueryGraph, cluster: Cluster | None = None) -> Advice:
    named = q.labelled
    return decide(q, g.stats, cluster or Cluster(), g.label_pairs() if named else None, g.label_counts() if named else None)
