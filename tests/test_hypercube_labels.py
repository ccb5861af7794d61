"""Cells and shares of a labelled pattern follow the arcs that its edges can use, not the size of the graph."""

import gc
import math

import numpy as np
import pyarrow as pa

from motifloom import api
from motifloom.functions import kernels
from motifloom.operators import hypercube
from motifloom.operators.graph import from_lists
from motifloom.plans import optimize
from motifloom.plans.pattern import QueryGraph

# many arcs between labels 3 and 4, few that the path can use
EDGES = [(a, b) for a in range(1, 5) for b in range(11, 31)] + [(b, 101 + b % 2) for b in range(11, 31)] + [(c, d) for c in range(201, 221) for d in range(301, 321)]
LABELS = {v: 1 if v < 10 else 2 if v < 100 else 5 if v < 200 else 3 if v < 300 else 4 for e in EDGES for v in e}
PATH = QueryGraph.from_edges([(1, 2), (2, 3)], labels=[1, 2, 5])


def test_cells_follow_the_arcs_that_fit(spark):
    g = from_lists(spark, EDGES, LABELS)
    assert hypercube.usable(g, PATH) == {(1, 2): 80, (2, 3): 20}
    assert hypercube.choose_cells(g, PATH, 800) == 1 and hypercube.choose_cells(g, PATH, 400) == 2
    assert optimize.shares(PATH, 8, "optimize", {(1, 2): 80, (2, 3): 20}, False) == (1, 8, 1)
    assert "Filter" in hypercube.dealt_edges(g, PATH, (1, 8, 1))._jdf.queryExecution().optimizedPlan().toString()
    assert api.match(g, PATH, "hypercube", cells=8).count() == api.match(g, PATH, "hypercube", cells=8, output="count").first()[0] == api.match(g, PATH, "growth").count() == 80


def test_rounds_follow_the_arcs_that_fit(spark, monkeypatch):
    g = from_lists(spark, EDGES, LABELS)
    monkeypatch.setattr(hypercube, "ROUND_COPIES", 100)
    assert hypercube.rounds(g, PATH, (1, 8, 1), False) == 1
    assert hypercube.rounds(g, PATH, (2, 1, 2), False) == 2


def test_shares_beyond_the_search_know_sizes():
    star = QueryGraph.from_edges([(1, i) for i in range(2, 8)], labels=[1, 2, 3, 4, 5, 6, 7])
    sizes = {(1, i): 10 ** (i - 2) for i in range(2, 8)}
    s = optimize.shares(star, 64, "optimize", sizes, False)
    assert math.prod(s) == 64 and optimize.routed_edges(star, s, sizes, False) <= optimize.routed_edges(star, optimize.doubled_shares(star, 64, sizes, False), sizes, False)


def test_a_task_lets_go_of_the_cells_before():
    ends = np.array(EDGES, np.int64).T
    kinds = [np.array([LABELS[x] for x in side], np.int32) for side in ends.tolist()]
    parts = [pa.RecordBatch.from_arrays([pa.array(np.full(len(EDGES), cell)), *map(pa.array, (*ends, *kinds))], names=list("cuvab")) for cell in range(6)]
    held = lambda: sum(isinstance(x, kernels.MappedCsr) for x in gc.get_objects())
    gc.collect()
    before, most = held(), 0
    gc.disable()
    try:
        for rows in hypercube._owned(PATH, "candidate", False, (1, 1, 1), iter(parts)):
            most = max(most, held() - before)
    finally:
        gc.enable()
    assert most == 1
