"""The last vertex of a growth plan is counted without lists where it can trade places with one placed before."""

import pytest

from motifloom import api
from motifloom.operators import growth
from motifloom.operators.graph import from_lists
from motifloom.plans import optimize
from motifloom.plans.pattern import QueryGraph

EDGES = [(a, b) for a in range(1, 21) for b in range(a + 1, 21) if (a * 7 + b * 11) % 5 < 3]
LABELS = {v: v % 2 + 1 for v in range(1, 21)}
SQUARE = [(1, 2), (2, 3), (3, 4), (1, 4)]


@pytest.mark.parametrize("labels, order, symmetry", [([1, 2, 1, 2], (2, 1, 4, 3), "auto"), (None, (1, 2, 3, 4), "on"), (None, (2, 1, 4, 3), "on"), (None, (2, 1, 4, 3), "off"), ([1, 2, 1, 1], (2, 1, 4, 3), "auto")])
@pytest.mark.parametrize("batching", [None, 3])
def test_twins_are_counted_without_lists(spark, labels, order, symmetry, batching):
    q = QueryGraph.from_edges(SQUARE, labels=labels) if labels else QueryGraph.from_edges(SQUARE)
    g = from_lists(spark, EDGES, LABELS if labels else None)
    plan = optimize.growth_plan(q, order, True, symmetry=symmetry)
    got = api.match(g, q, "growth", order=order, compression=True, output="count", symmetry=symmetry, batching=batching)
    if growth.twin(q, plan, symmetry == "on") and not batching:
        assert "array_intersect" not in got._jdf.queryExecution().analyzed().toString()
    assert got.first()[0] == api.match(g, q, "replicated", symmetry=symmetry).count() > 0


def test_the_labelled_square_has_twins():
    q = QueryGraph.from_edges(SQUARE, labels=[1, 2, 1, 2])
    assert growth.twin(q, optimize.growth_plan(q, (2, 1, 4, 3), True), False) == 1
