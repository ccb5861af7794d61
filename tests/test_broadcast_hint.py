"""A broadcast hint holds only while the hinted side is small enough for driver and executors."""

import pytest

from motifloom import api
from motifloom.operators import binary
from motifloom.operators.graph import from_lists
from motifloom.plans import catalogue

EDGES = [(a, b) for a in range(1, 21) for b in range(a + 1, 21) if (a * 7 + b * 11) % 5 < 3]


@pytest.mark.parametrize("budget, hinted", [(1 << 30, True), (10, False)])
def test_large_sides_are_not_broadcast(spark, monkeypatch, budget, hinted):
    g, q = from_lists(spark, EDGES), catalogue.unlabelled("q2")
    want = sorted(tuple(r) for r in api.match(g, q, "growth").collect())
    monkeypatch.setattr(binary, "BROADCAST_BYTES", budget)
    rows = api.match(g, q, "binary", unit="wedge", shape="left_deep", hint="broadcast")
    assert ("strategy=broadcast" in rows._jdf.queryExecution().analyzed().toString()) == hinted
    assert sorted(tuple(r) for r in rows.collect()) == want
