"""An edge goes to each cell once, by one shuffle, and a cell's graph is held in small positions."""

import numpy as np
import pytest

from motifloom import api
from motifloom.functions import kernels
from motifloom.operators import hypercube
from motifloom.operators.graph import from_lists
from motifloom.plans import catalogue
from motifloom.plans.ir import use_symmetry
from motifloom.plans.pattern import QueryGraph

EDGES = [(a, b) for a in range(1, 21) for b in range(a + 1, 21) if (a * 7 + b * 11) % 5 < 3]
LABELS = {v: v % 3 + 1 for v in range(1, 21)}
PATH = QueryGraph.from_edges([(1, 2), (2, 3), (3, 4)], labels=[1, 2, 3, 1])


@pytest.mark.parametrize("q, shares", [(catalogue.unlabelled("q2"), (2, 2, 2, 2)), (catalogue.unlabelled("q1"), (2, 3, 1, 2)), (PATH, (1, 2, 3, 1))], ids=["q2", "q1", "path"])
def test_edges_are_dealt_once_per_cell(spark, q, shares):
    g = from_lists(spark, EDGES, LABELS if q.labelled else None)
    routed = hypercube.local_edges(hypercube.route(g, q, shares, use_symmetry(q)))
    got = hypercube.dealt_edges(g, q, shares, use_symmetry(q))
    rows = sorted(tuple(r)[:3] for r in got.collect())
    assert rows == sorted(map(tuple, routed.collect()))
    options = {"shares": shares, "cells": int(np.prod(shares))}
    found = api.match(g, q, "hypercube", **options)
    plan = found._jdf.queryExecution().sparkPlan().toString()
    assert "Join" not in plan and "Aggregate" not in plan
    want = api.match(g, q, "growth").count()
    assert found.count() == want > 0
    counted = api.match(g, q, "hypercube", output="count", **options)
    assert counted.first()[0] == want and "v4#" not in counted._jdf.queryExecution().analyzed().toString()


def test_cells_are_worked_off_in_rounds(spark, monkeypatch):
    g, q = from_lists(spark, EDGES), catalogue.unlabelled("q2")
    want = api.match(g, q, "growth")
    monkeypatch.setattr(hypercube, "ROUND_COPIES", 3 * len(EDGES))
    assert hypercube.rounds(g, q, (2, 2, 2, 2), True) == 6
    options = {"shares": "uniform", "cells": 16}
    assert sorted(api.match(g, q, "hypercube", **options).collect()) == sorted(want.collect())
    assert api.match(g, q, "hypercube", output="count", **options).first()[0] == want.count()


@pytest.mark.parametrize("labelled", [False, True])
def test_a_cells_graph_is_the_same_in_small_positions(labelled):
    u, v = np.array(EDGES, np.int64).T * 10**10
    kinds = [x // 10**10 % 3 for x in (u, v)] if labelled else []
    ids, at = np.unique(np.concatenate([u, v]), return_index=True)
    plain = kernels.Csr(np.concatenate([u, v]), np.concatenate([v, u]), (ids, np.concatenate(kinds)[at]) if labelled else None)
    columns = [u, v, *kinds]
    small = kernels.cell_csr(columns)
    assert not columns and small.indices.dtype == np.int32
    assert np.array_equal(small.ids, plain.ids) and np.array_equal(small.indptr, plain.indptr) and np.array_equal(small.indices, plain.indices)
    assert np.array_equal(small.labels, plain.labels) if labelled else small.labels is None
