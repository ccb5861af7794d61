"""Growth and joins together: two overlapping pieces are grown, then joined on what they share."""

from __future__ import annotations

from pyspark.sql import DataFrame

from motifloom.functions.kernels import _subset_order, pieces
from motifloom.operators import compress as packed
from motifloom.operators import growth
from motifloom.operators.cliquebud import subset_plan
from motifloom.operators.graph import DataGraph
from motifloom.plans.ir import relation, use_symmetry
from motifloom.plans.pattern import QueryGraph
from pyspark.sql import functions as F


def run(g: DataGraph, q: QueryGraph, *, symmetry: str = "auto") -> DataFrame:
    """Matches v1..vn; a pattern that does not part is grown whole."""
    parts = pieces(q)
    if parts is None:
        return growth.run(g, q, symmetry=symmetry)
    ordered = use_symmetry(q, symmetry)
    left, right = (growth.run(g, q, subset_plan(q, _subset_order(q, p)), symmetry=symmetry) for p in parts)
    shared = sorted(set(parts[0]) & set(parts[1]))
    rows = left.join(right, [f"v{v}" for v in shared])
    for a in set(parts[0]) - set(shared):
        for b in set(parts[1]) - set(shared):
            if how := relation(q, a, b, ordered):
                rows = rows.where(packed.compare(F.col(f"v{a}"), how, F.col(f"v{b}")))
    return rows.select(*[f"v{v}" for v in q.vertices])
