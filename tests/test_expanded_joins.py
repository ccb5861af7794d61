"""Relations that explode made are never broadcast unasked: Spark takes them for no larger than the lists they come from."""

import pytest

from motifloom import api
from motifloom.operators.graph import from_lists
from motifloom.plans import catalogue

EDGES = [(a, b) for a in range(1, 21) for b in range(a + 1, 21) if (a * 7 + b * 11) % 5 < 3]


def joins(rows):
    """Names of the joins that Spark plans before it runs anything."""
    plan = rows._jdf.queryExecution().sparkPlan().toString()
    return [word for word in ("BroadcastHashJoin", "BroadcastNestedLoopJoin", "SortMergeJoin") if word in plan]


@pytest.mark.parametrize(
    "pattern, options",
    [
        ("q1", {"unit": "clique", "triangle_index": "ordered", "compression": True}),
        ("q2", {"order": "cover_first"}),
    ],
)
def test_join_units_meet_by_merge(spark, pattern, options):
    g, q = from_lists(spark, EDGES), catalogue.unlabelled(pattern)
    rows = api.match(g, q, "binary", **options)
    assert joins(rows) == ["SortMergeJoin"]
    assert rows.count() == api.match(g, q, "growth").count() > 0


def test_tagged_copies_meet_by_merge(spark):
    g, q = from_lists(spark, EDGES), catalogue.unlabelled("q2")
    rows = api.match(g, q, "hypercube", cells=16, dedupe="tagged")
    assert joins(rows) == ["SortMergeJoin"]
    assert rows.count() == api.match(g, q, "growth").count() > 0
