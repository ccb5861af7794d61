"""A vertex whose array is that of an earlier one takes it over: the lists are joined once."""

import pytest

from motifloom import api
from motifloom.operators import growth
from motifloom.operators.graph import from_lists
from motifloom.plans import catalogue
from motifloom.plans.pattern import QueryGraph

EDGES = [(a, b) for a in range(1, 21) for b in range(a + 1, 21) if (a * 7 + b * 11) % 5 < 3]


@pytest.mark.parametrize("chunk", [None, 3])
def test_lists_are_joined_once(spark, chunk):
    g, q = from_lists(spark, EDGES), catalogue.unlabelled("q2")
    if chunk:
        g.chunk = chunk
    got = api.match(g, q, "growth", compression=True, output="count")
    joins = got._jdf.queryExecution().analyzed().toString().count("Join Inner")
    assert chunk or joins == 2
    assert got.first()[0] == api.match(g, q, "replicated").count() > 0


@pytest.mark.parametrize("pattern", ["12 13 14 15", "12 13 23 14 24 15 25", "12 13 14 34"])
def test_taken_arrays_expand_to_the_same_rows(spark, pattern):
    g, q = from_lists(spark, EDGES), QueryGraph.from_edges([(int(e[0]), int(e[1])) for e in pattern.split()])
    for symmetry in ("on", "off"):
        want = api.match(g, q, "replicated", symmetry=symmetry)
        got = api.match(g, q, "growth", compression=True, symmetry=symmetry)
        assert api.match(g, q, "growth", compression=True, symmetry=symmetry, output="count").first()[0] == want.count() == got.count() == got.distinct().count()


@pytest.mark.parametrize("pattern", ["q2", "q3", "q4"])
def test_counts_run_in_batches_when_lists_are_large(spark, monkeypatch, pattern):
    g, q = from_lists(spark, EDGES), catalogue.unlabelled(pattern)
    whole = api.match(g, q, "growth", compression=True, output="count").first()[0]
    monkeypatch.setattr(growth, "LIST_BYTES", 1)
    monkeypatch.setattr(growth, "MOST_BATCHES", 3)
    asked = []
    monkeypatch.setattr(api, "_in_batches", lambda g, counted, b, spec, run=api._in_batches: asked.append(b) or run(g, counted, b, spec))
    assert api.match(g, q, "growth", compression=True, output="count").first()[0] == whole > 0
    assert 1 < asked[0] <= 3
