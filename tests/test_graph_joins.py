"""A graph is built without sending its vertices or tables through the driver, however small their files are."""

import pytest

from motifloom.operators import graph
from motifloom.sources.builders import BUILDERS

SF_DIR = "/root/testdata/sf0.001"


def broadcasts(rows):
    """Joins by broadcast that Spark plans before it runs anything."""
    return rows._jdf.queryExecution().sparkPlan().toString().count("BroadcastHashJoin")


@pytest.mark.parametrize("name, few", [("cobuy", 0), ("coactive", 0), ("copurchase", 0), ("lattice", 0), ("sharedline", 0), ("doclines", 0), ("typed", 4)])
def test_tables_meet_by_merge(spark, name, few):
    """typed sends the names of four columns, a few each."""
    assert broadcasts(BUILDERS[name].pairs(spark, SF_DIR)) == few


def test_vertices_reach_their_edges_by_merge(spark, monkeypatch):
    plans = {}
    monkeypatch.setattr(graph, "stored", lambda df, name, keep=graph.stored: plans.update({name: broadcasts(df)}) or keep(df, name))
    g = graph.from_lists(spark, [(1, 2), (2, 3), (1, 3), (3, 4)])
    assert plans["edges"] == 0
    assert sorted(map(tuple, g.edges.select("src", "dst").collect())) == [(1, 4), (2, 3), (2, 4), (3, 4)]
