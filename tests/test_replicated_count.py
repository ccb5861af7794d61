"""Replication counts inside its tasks: no match travels, and the last vertex is not listed per match."""

import numpy as np
import pytest

from motifloom import api
from motifloom.functions import kernels
from motifloom.operators.graph import from_lists
from motifloom.plans import catalogue
from motifloom.plans.pattern import QueryGraph

EDGES = [(a, b) for a in range(1, 21) for b in range(a + 1, 21) if (a * 7 + b * 11) % 5 < 3]
LABELS = {v: v % 3 + 1 for v in range(1, 21)}
RING = [(1, 2), (2, 3), (3, 4), (4, 5), (5, 6), (1, 6)]
PATTERNS = [catalogue.unlabelled(q) for q in ("q1", "q2", "q3", "q5")] + [QueryGraph.from_edges(RING, labels=[1, 2, 3, 2, 1, 3]), QueryGraph.from_edges([(1, 2), (1, 3), (1, 4)], labels=[1, 2, 2, 2]), QueryGraph.from_edges([(1, 2), (2, 3)], labels=[1, 2, None])]


@pytest.mark.parametrize("q", PATTERNS, ids=str)
@pytest.mark.parametrize("symmetry", [True, False])
def test_kernels_count_what_they_find(q, symmetry):
    u, v = np.array([*EDGES, *[(b, a) for a, b in EDGES]]).T
    csr = kernels.Csr(u, v, LABELS if q.labelled else None)
    for kernel in kernels.KERNELS if q.n < 5 else ("cover", "candidate"):
        for seeds in (None, csr.ids[::2]):
            found = sum(len(rows) for rows in kernels.KERNELS[kernel](csr, q, symmetry, seeds))
            assert kernels.count(csr, q, kernel, symmetry, seeds) == found
            assert found or seeds is not None


def test_shared_candidates_are_listed_once(monkeypatch):
    """The ring's last vertex hangs on two others that take few images: their common neighbours are listed per pair."""
    hub = [(100, 200), (101, 200), (100, 300), (101, 300)]
    q = QueryGraph.from_edges([(1, 2), (2, 3), (3, 4), (1, 4)], labels=[1, 2, 1, 3])
    edges = [*hub, *[(a, b) for a in range(1000, 1400) for b in (200, 300)]]
    u, v = np.array([*edges, *[(b, a) for a, b in edges]]).T
    csr = kernels.Csr(u, v, {x: 2 if x == 200 else 3 if x == 300 else 1 for x in {*u.tolist(), *v.tolist()}})
    listed = []
    slow = kernels._candidates
    monkeypatch.setattr(kernels, "_candidates", lambda *a: (listed.append(len(cand)) or (who, cand) for who, cand in slow(*a)))
    assert kernels.count(csr, q, "candidate", False) == 402 * 401
    assert sum(listed) < 10_000


def test_no_match_leaves_a_task(spark):
    g, q = from_lists(spark, EDGES, LABELS), PATTERNS[4]
    rows = api.match(g, q, "replicated", output="count")
    assert "MapInArrow" in (plan := rows._jdf.queryExecution().analyzed().toString()) and "v6#" not in plan
    assert rows.first()[0] == api.match(g, q, "replicated").count() > 0
