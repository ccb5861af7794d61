"""Every strategy and switch against worked examples, brute force and closed forms."""

import math
import random

import pytest
from pyspark.sql import functions as F

from motifloom import api
from motifloom.functions import udfs
from motifloom.operators import batching, cliquebud, compress, growth, hypercube, partition, replicate
from motifloom.operators.graph import build, from_lists, global_rank, normalise
from motifloom.plans import catalogue
from motifloom.plans.pattern import QueryGraph
from motifloom.sources import synthetic

SETTINGS = [
    {"strategy": "binary", "unit": "edge"},
    {"strategy": "binary", "unit": "star", "shape": "left_deep", "compression": True},
    {"strategy": "binary", "unit": "wedge", "shape": "left_deep"},
    {"strategy": "binary", "unit": "clique", "triangle_index": "ordered"},
    {"strategy": "binary", "unit": "clique", "compression": True, "batching": 2},
    {"strategy": "growth"},
    {"strategy": "growth", "compression": True, "triangle_index": "full"},
    {"strategy": "growth", "triangle_index": "ordered", "order": "cover_first", "batching": 2},
    {"strategy": "growth", "execution": "edge_semi"},
    {"strategy": "growth", "proposer": "first"},
    {"strategy": "hypercube", "cells": 8},
    {"strategy": "hypercube", "cells": 8, "dedupe": "tagged"},
    {"strategy": "hypercube", "cells": 4, "kernel": "decompose"},
    {"strategy": "replicated"},
    {"strategy": "replicated", "kernel": "backtrack"},
    {"strategy": "frontier", "heuristic": "fixed"},
    {"strategy": "frontier", "heuristic": "per_row"},
    {"strategy": "wco"},
    {"strategy": "hybrid"},
]
UNLABELLED_ONLY = [{"strategy": "cliquebud"}]


def found(g, q, **options):
    return sorted(map(tuple, api.match(g, q, **options).collect()))


@pytest.fixture(scope="module")
def example(spark):
    return from_lists(spark, catalogue.EXAMPLE_EDGES, relabel=False)


@pytest.mark.parametrize("options", SETTINGS + UNLABELLED_ONLY, ids=str)
def test_worked_example(spark, example, options):
    q = catalogue.example()
    assert found(example, q, **options) == [(1, 2, 6, 5), (2, 5, 3, 6), (4, 3, 6, 5)]


@pytest.mark.parametrize("options", SETTINGS[:1] + SETTINGS[3:7] + SETTINGS[10:14] + SETTINGS[15:16], ids=str)
def test_worked_example_labelled_and_without_order(spark, example, options):
    labelled = from_lists(spark, catalogue.EXAMPLE_EDGES, labels=catalogue.EXAMPLE_LABELS, relabel=False)
    q = QueryGraph.from_edges(catalogue.example().edges, labels=[1, 2, 3, 4])
    assert found(labelled, q, **options) == [(1, 2, 6, 5), (4, 3, 6, 5)]
    assert len(found(example, catalogue.example(), symmetry="off", **options)) == 12


def test_random_graphs_against_brute_force(spark):
    rng = random.Random(5)
    for _ in range(2):
        edges = [(a, b) for a in range(9) for b in range(a + 1, 9) if rng.random() < 0.45]
        labels = {v: rng.randrange(2) for v in range(9)}
        g = from_lists(spark, edges, relabel=False)
        gl = from_lists(spark, edges, labels=labels, relabel=False)
        pattern = rng.choice(["q1", "q4", "q5", "q6", "q7", "star3", "wheel4"])
        q = catalogue.by_name(pattern)
        want = sorted(q.brute_force(edges))
        for options in rng.sample(SETTINGS, 5) + UNLABELLED_ONLY:
            assert found(g, q, **options) == want, (pattern, options)
        ql = QueryGraph.from_edges(catalogue.by_name("q1").edges, labels=[0, 1, None, 0])
        want = sorted(ql.brute_force([e for e in edges], labels))
        for options in ({"strategy": "growth"}, {"strategy": "binary", "compression": True}, {"strategy": "replicated"}, {"strategy": "hypercube", "cells": 4}):
            assert found(gl, ql, **options) == want, options


def test_closed_forms(spark):
    k6 = normalise(synthetic(spark, "complete", n=6))
    for k in (3, 4, 5):
        assert len(found(k6, catalogue.clique(k), strategy="growth")) == math.comb(6, k)
        assert api.match(k6, catalogue.clique(k), "binary", output="count").first()[0] == math.comb(6, k)
        assert partition.clique_table(k6, k).count() == math.comb(6, k)
    assert len(found(normalise(synthetic(spark, "cycle", n=7)), catalogue.cycle(7), strategy="growth")) == 1
    assert len(found(normalise(synthetic(spark, "grid", rows=4, cols=5)), catalogue.cycle(4), strategy="binary")) == 12
    two = normalise(synthetic(spark, "bipartite", left=4, right=5))
    assert api.match(two, catalogue.cycle(4), "growth", compression=True, output="count").first()[0] == math.comb(4, 2) * math.comb(5, 2)
    hub = normalise(synthetic(spark, "star", n=9))
    assert api.match(hub, catalogue.star(3), "growth", compression=True, output="count").first()[0] == math.comb(8, 3)


def test_counts_without_expansion_agree(spark):
    g = normalise(synthetic(spark, "uniform", n=40, p=0.3, seed=3))
    for name in ("q1", "q2", "q6", "q7", "q9", "star3", "book3"):
        q = catalogue.by_name(name)
        plain = api.match(g, q, "growth").count()
        for options in ({"strategy": "growth", "compression": True}, {"strategy": "binary", "unit": "star", "shape": "left_deep", "compression": True}, {"strategy": "cliquebud"}):
            assert api.match(g, q, output="count", **options).first()[0] == plain, (name, options)
        assert api.match(g, q, "growth", symmetry="off", compression=True, output="count").first()[0] == plain * len(q.automorphisms)


def test_hub_lists_in_chunks_change_nothing(spark):
    g, again = (normalise(synthetic(spark, "uniform", n=30, p=0.5, seed=1)) for _ in range(2))
    again.chunk = 4
    want = api.match(g, catalogue.unlabelled("q2"), "growth").count()
    assert api.match(again, catalogue.unlabelled("q2"), "growth").count() == want
    assert api.match(again, catalogue.unlabelled("q2"), "growth", compression=True, output="count").first()[0] == want


def test_robustness(spark):
    messy = spark.createDataFrame([(1, 1), (1, 2), (2, 1), (2, 3), (3, 1), (1, 2)], "a long, b long")
    g = normalise(messy)
    assert g.stats["m"] == 3 and len(found(g, catalogue.clique(3), strategy="growth")) == 1
    nothing = normalise(messy.limit(0))
    for s in ("growth", "binary", "hypercube", "replicated"):
        assert found(nothing, catalogue.clique(3), strategy=s, **({"cells": 4} if s == "hypercube" else {})) == []
    assert found(g, catalogue.clique(4), strategy="binary") == []
    for bad in ({"strategy": "hypercube", "compression": True}, {"strategy": "replicated", "batching": 2}, {"strategy": "magic"}):
        with pytest.raises(ValueError):
            api.match(g, catalogue.clique(3), **bad)
    with pytest.raises(replicate.GraphTooLarge):
        replicate.check_size(g, 10)
    with pytest.raises(ValueError):
        cliquebud.run(g, QueryGraph.from_edges([(1, 2)], labels=[1, 1]))


def test_directed_and_edge_labels(spark):
    g = from_lists(spark, [(1, 2, 5), (2, 3, 6), (3, 1, 5), (3, 4, 6)], directed=True, relabel=False)
    assert found(g, QueryGraph.parse("a>b, b>c, c>a"), strategy="growth", symmetry="off") == [(1, 2, 3), (2, 3, 1), (3, 1, 2)]
    assert found(g, QueryGraph.parse("a-[5]->b, b-[6]->c"), strategy="growth", symmetry="off") == [(1, 2, 3)] == found(g, QueryGraph.parse("a-[5]->b, b-[6]->c"), strategy="binary", symmetry="off") == found(g, QueryGraph.parse("a-[5]->b, b-[6]->c"), strategy="hypercube", cells=4, symmetry="off")


def test_global_rank_by_ranges(spark, monkeypatch):
    from motifloom.operators import graph as module

    df = spark.range(500).select((F.col("id") * 7919 % 500).alias("k"), (F.col("id") % 3).alias("d"))
    one = {(r["d"], r["k"]): r["id"] for r in global_rank(df, ["d", "k"]).collect()}
    monkeypatch.setattr(module, "RANK_IN_ONE_TASK", 10)
    assert {(r["d"], r["k"]): r["id"] for r in global_rank(df, ["d", "k"]).collect()} == one


def test_batches_and_range_joins(spark, tmp_path):
    g = build(spark, "/root/testdata/sf0.001", "cobuy")
    q = catalogue.unlabelled("q2")
    make = lambda k, b: growth.run(g, q, batch=(k, b))
    whole = growth.run(g, q).count()
    assert whole == 2741
    assert all(batching.union(make, b).count() == whole for b in (1, 2, 7))
    batching.write(make, 2, str(tmp_path / "out"))
    assert spark.read.parquet(str(tmp_path / "out")).count() == whole
    assert batching.total(lambda k, b: compress.count(make(k, b), q, True), 3) == whole
    e = g.edges.select("src", "dst")
    assert batching.hash_range_join(e, e.withColumnRenamed("dst", "other"), ["src"], 4).count() == e.join(e.withColumnRenamed("dst", "other"), "src").count()


def test_hypercube_owner_example(spark):
    g = from_lists(spark, [(0, 2), (2, 4), (0, 4)], relabel=False)
    q = catalogue.clique(3)
    routed = hypercube.route(g, q, (2, 2, 2))
    cells = {r["cell"] for r in routed.collect()}
    assert {0, 1} <= cells
    assert found(g, q, strategy="hypercube", cells=8, shares=(2, 2, 2)) == [(0, 2, 4)]


def test_plans_have_no_cross_join_and_intersect_once(spark):
    g = build(spark, "/root/testdata/sf0.001", "cobuy")
    text = api.match(g, catalogue.unlabelled("q2"), "growth")._jdf.queryExecution().optimizedPlan().toString()
    assert "Cartesian" not in text and text.count("array_intersect(") == 2  # one for each of two rounds


def test_sql_surface(spark):
    g = build(spark, "/root/testdata/sf0.001", "cobuy")
    rows = api.sql_match(spark, "a-b, b-c, a-c", g, "tri", strategy="growth")
    assert spark.sql("select count(*) from tri").first()[0] == rows.count() == 768
    udfs.register(spark)
    assert spark.sql("select count(*) from combinations(array(1L,2L,3L,4L), 2)").first()[0] == 6
    got = spark.sql("select match from local_matches('a-b, b-c, a-c', array(struct(1L,2L), struct(2L,3L), struct(1L,3L)))").collect()
    assert [r[0] for r in got] == [[1, 2, 3]]
    sizes = g.adjacency().alias("x").join(g.adjacency().alias("y"), F.expr("x.u < y.u")).limit(50).select(udfs.sorted_intersect_size("x.nbrs", "y.nbrs").alias("n"), F.size(F.array_intersect("x.nbrs", "y.nbrs")).alias("m"))
    assert sizes.where("n <> m").count() == 0
