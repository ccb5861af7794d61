"""Twins of a square are counted by pairs of the other two vertices, in blocks, without a row per wedge."""

import numpy as np
import pytest

from motifloom import api
from motifloom.functions import kernels
from motifloom.operators import growth
from motifloom.operators.graph import from_lists
from motifloom.plans import optimize
from motifloom.plans.pattern import QueryGraph

EDGES = [(a, b) for a in range(1, 31) for b in range(a + 1, 31) if (a * 7 + b * 11) % 5 < 3]
LABELS = {v: v % 3 + 1 for v in range(1, 31)}
SQUARE = [(1, 2), (2, 3), (3, 4), (1, 4)]


@pytest.mark.parametrize("chunk", [65_536, 4])
@pytest.mark.parametrize("labels, order, symmetry", [([1, 2, 1, 2], (2, 1, 4, 3), "auto"), ([1, 2, 1, 3], (2, 1, 4, 3), "auto"), (None, (1, 2, 3, 4), "on"), (None, (2, 1, 4, 3), "on"), (None, (2, 1, 4, 3), "off")])
def test_square_in_blocks(spark, monkeypatch, labels, order, symmetry, chunk):
    monkeypatch.setattr(kernels, "STEP", 4)
    q = QueryGraph.from_edges(SQUARE, labels=labels) if labels else QueryGraph.from_edges(SQUARE)
    g = from_lists(spark, EDGES, LABELS if labels else None)
    g.chunk = chunk
    plan = optimize.growth_plan(q, order, True, symmetry=symmetry)
    y = growth.twin(q, plan, symmetry == "on")
    if y is None:
        pytest.skip("no twins in this order")
    want = api.match(g, q, "replicated", symmetry=symmetry).count()
    for blocks, held in (((1, 1), 1 << 30), ((3, 2), 1 << 30), ((2, 3), 64)):
        assert growth.pair_count(g, q, plan, y, blocks, symmetry, held).first()[0] == want > 0


def test_blocks_are_for_many_rows_only(spark):
    q = QueryGraph.from_edges(SQUARE, labels=[1, 2, 1, 2])
    g = from_lists(spark, EDGES, LABELS)
    plan = optimize.growth_plan(q, (2, 1, 4, 3), True)
    assert growth.pair_blocks(g, q, plan, 1, 1e9) and growth.pair_blocks(g, q, plan, 1, 1) is None


def test_pairs_of_long_and_short_lists():
    rng = np.random.default_rng(1)
    arcs = np.unique(rng.integers(0, 40, (500, 2)), axis=0)
    has = np.zeros((40, 40), np.int64)
    has[arcs[:, 0], arcs[:, 1]] = 1
    n = has.T @ has
    for how, mask in ((None, np.ones((40, 40), bool)), ("!=", ~np.eye(40, dtype=bool)), (">", np.triu(np.ones((40, 40), bool), 1))):
        for step in (1, 50, 1 << 18):
            kernels.STEP, kept = step, kernels.STEP
            got = kernels.pairs(how, arcs[:, 1], arcs[:, 0], arcs[:, 0], arcs[:, 1])
            kernels.STEP = kept
            assert got == int((n * (n - 1))[mask].sum())
