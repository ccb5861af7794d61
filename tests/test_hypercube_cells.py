"""The number of cells grows with the graph: a given number is the least."""

from motifloom import api
from motifloom.operators import hypercube
from motifloom.operators.graph import from_lists
from motifloom.plans import catalogue

EDGES = [(a, b) for a in range(1, 21) for b in range(a + 1, 21) if (a * 7 + b * 11) % 5 < 3]


def test_more_cells_where_a_cell_would_not_fit(spark, monkeypatch):
    g, q = from_lists(spark, EDGES), catalogue.clique(3)
    want = sorted(tuple(r) for r in api.match(g, q, "growth").collect())
    used = []
    choose, shares = hypercube.choose_cells, hypercube.optimize.shares
    monkeypatch.setattr(hypercube, "choose_cells", lambda g, q: choose(g, q, 100))
    monkeypatch.setattr(hypercube.optimize, "shares", lambda q, cells, *a: used.append(cells) or shares(q, cells, *a))
    assert sorted(tuple(r) for r in hypercube.run(g, q, 2).collect()) == want
    assert used[-1] > 2 and used[-1] == choose(g, q, 100)
    hypercube.run(g, q, 4096)
    assert used[-1] == 4096
