"""A broadcast hint is given up by what the table of its rows takes in the driver, not by the numbers in the rows."""

from motifloom import api
from motifloom.operators import binary
from motifloom.operators.graph import from_lists
from motifloom.plans import catalogue

EDGES = [(a, b) for a in range(1, 21) for b in range(a + 1, 21) if (a * 7 + b * 11) % 5 < 3]


def test_the_table_counts(spark, monkeypatch):
    g, q = from_lists(spark, EDGES), catalogue.unlabelled("q2")
    want = sorted(tuple(r) for r in api.match(g, q, "growth").collect())
    tree = binary.plan(g, q, "wedge", "left_deep")
    numbers = [8 * len(node.right.vertices) * binary.sizer(g, q)(node.right.edges) for node in binary.optimize.joins_of(tree)]
    for budget, hinted in ((min(numbers) + 1, False), (20 * max(numbers), True)):
        monkeypatch.setattr(binary, "BROADCAST_BYTES", budget)
        rows = api.match(g, q, "binary", unit="wedge", shape="left_deep", hint="broadcast")
        assert ("strategy=broadcast" in rows._jdf.queryExecution().analyzed().toString()) == hinted
        assert sorted(tuple(r) for r in rows.collect()) == want
