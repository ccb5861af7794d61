"""4-cliques of a dense graph grow within tasks: a neighbour's list goes to a cell of seeds once, not with each row."""

from itertools import combinations

import pytest

from motifloom import api
from motifloom.functions import kernels
from motifloom.operators import growth
from motifloom.operators.graph import from_lists
from motifloom.plans import catalogue

DENSE = [(a, b) for a in range(1, 91) for b in range(a + 1, 91) if (a * 7 + b * 11) % 5 < 3]
SPARSE = [(a, a % 20 + 1) for a in range(1, 21)]


@pytest.mark.parametrize("edges", [DENSE, SPARSE, DENSE[:300] + [(1, 2), (200, 201)]])
@pytest.mark.parametrize("cells, step", [(1, 1 << 18), (5, 3)])
def test_cliques_in_cells(spark, monkeypatch, edges, cells, step):
    monkeypatch.setattr(kernels, "STEP", step)
    g, q = from_lists(spark, edges), catalogue.unlabelled("q3")
    near = {frozenset(e) for e in edges}
    names = sorted({v for e in edges for v in e})
    want = api.match(g, q, "replicated").count()
    if len(edges) < 100:
        assert want == sum(all(frozenset(p) in near for p in combinations(c, 2)) for c in combinations(names, 4))
    assert growth.clique_count(g, q, cells).first()[0] == want


def test_growth_takes_cells_where_lists_would_take_batches(spark, monkeypatch):
    g, q = from_lists(spark, DENSE), catalogue.unlabelled("q3")
    monkeypatch.setattr(growth, "list_batches", lambda *a: 3)
    got = api.match(g, q, "growth", output="count", compression=True)
    plan = got._jdf.queryExecution().analyzed().toString()
    assert "MapInArrow" in plan and "array_intersect" not in plan
    assert got.first()[0] == api.match(g, q, "replicated").count() > 0
