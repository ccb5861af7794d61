"""Arcs carry the labels that edges are stored with: no join, and so no shuffle of all arcs, brings them."""

import os

import pytest

from motifloom.operators import graph
from motifloom.operators.graph import from_lists

EDGES = [(a, b) for a in range(1, 16) for b in range(1, 16) if a != b and (a * 7 + b * 11) % 5 < 2]
LABELS = {v: v % 3 + 1 for v in range(1, 18)}


@pytest.mark.parametrize("directed", [False, True])
@pytest.mark.parametrize("relabel", [False, True])
def test_arcs_have_the_labels_of_their_ends(spark, monkeypatch, directed, relabel):
    g = from_lists(spark, EDGES, LABELS, directed, relabel)
    monkeypatch.setattr(graph, "stored", None)  # nothing more is computed and written
    plan = g.arcs._jdf.queryExecution().sparkPlan().toString()
    assert "Join" not in plan and "Exchange" not in plan
    key = {r["id"]: int(r["orig"]) for r in g.vertices.collect()}
    got = [(key[r["u"]], key[r["v"]], r["ulabel"], r["vlabel"]) for r in g.arcs.collect()]
    want = set(EDGES) if directed else {p for a, b in EDGES for p in ((a, b), (b, a))}
    assert sorted(got) == sorted((a, b, LABELS[a], LABELS[b]) for a, b in want)
    assert g.edges.columns == ["src", "dst", "elabel"]
    assert directed or not g.edges.where("src >= dst").count()


def test_executors_read_a_mounted_folder_where_it_is(spark):
    """No executor keeps copies of the files beside the arrays that it builds."""
    from motifloom.operators import replicate

    token, names, labelled = replicate.replica(from_lists(spark, EDGES, LABELS))
    assert labelled and names and all(replicate._place(n) == n and os.path.exists(n) for n in names)
