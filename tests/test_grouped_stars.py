"""Two stars over the same two leaves meet grouped by these: a dense graph's wedges are counted and never sent."""

import pytest

from motifloom import api
from motifloom.operators import binary
from motifloom.operators.graph import from_lists
from motifloom.plans import catalogue

DENSE = [(a, b) for a in range(1, 61) for b in range(a + 1, 61) if (a * 7 + b * 11) % 5 < 3]
SPARSE = [(a, a % 20 + 1) for a in range(1, 21)]
CLIQUE = {"strategy": "binary", "unit": "clique", "shape": "bushy", "triangle_index": "ordered", "compression": True}


@pytest.mark.parametrize("most", [None, 500])
def test_squares_of_a_dense_graph(spark, monkeypatch, most):
    g, q = from_lists(spark, DENSE), catalogue.unlabelled("q1")
    if most:
        monkeypatch.setattr(binary, "BLOCK_ARCS", most)
    blocks = binary.grouped(g, q, binary.plan(g, q, triangle_index="ordered"), True)
    assert blocks[1] == (1 if not most else -(-4 * len(DENSE) // (2 * most)))
    got = api.match(g, q, output="count", **CLIQUE)
    assert "Join" not in got._jdf.queryExecution().analyzed().toString()
    assert got.first()[0] == api.match(g, q, "replicated").count() > 0


def test_other_joins_stay_rows(spark):
    g, q = from_lists(spark, SPARSE), catalogue.unlabelled("q1")
    assert binary.grouped(g, q, binary.plan(g, q, triangle_index="ordered"), True) is None  # lists are short
    dense = from_lists(spark, DENSE)
    assert binary.grouped(dense, q, binary.plan(dense, q, triangle_index="ordered"), False) is None
    for other in ("q2", "q7"):
        p = catalogue.unlabelled(other)
        assert binary.grouped(dense, p, binary.plan(dense, p, triangle_index="ordered"), True) is None
