"""Replication holds the graph on the executors only, and only the arcs that the pattern can use."""

import numpy as np
import pytest
from pyspark.sql import DataFrame

from motifloom import api
from motifloom.functions.kernels import KERNELS, Csr, MappedCsr
from motifloom.operators import replicate
from motifloom.operators.graph import from_lists
from motifloom.plans import catalogue
from motifloom.plans.pattern import QueryGraph

EDGES = [(a, b) for a in range(1, 31) for b in range(a + 1, 31) if (a * 7 + b * 11) % 5 < 2]
LABELS = {v: v % 3 + 1 for v in range(1, 31)}


def mapped(tmp_path, monkeypatch, edges, labels=None, parts=3):
    """The executor's arrays of a graph, from sorted parts that cut lists."""
    import pyarrow as pa
    import pyarrow.parquet as pq

    rows = sorted({(a, b) for e in edges for a, b in (e, e[::-1])})
    names = []
    for k, some in enumerate(np.array_split(np.array(rows), parts)):
        columns = {"u": some[:, 0], "v": some[:, 1]} | ({"ulabel": np.array([labels[u] for u in some[:, 0]])} if labels else {})
        pq.write_table(pa.table(columns), tmp_path / f"p{k}")
        names.append(str(tmp_path / f"p{k}"))
    monkeypatch.setattr(replicate.SparkFiles, "get", staticmethod(lambda name: name))
    replicate._build(names, str(tmp_path / "out"), labels is not None)
    return MappedCsr(str(tmp_path / "out"))


@pytest.mark.parametrize("block", [1, 7, 1000])
@pytest.mark.parametrize("shift", [0, 10**12])
def test_mapped_arrays_are_the_rows_of_the_graph(tmp_path, monkeypatch, block, shift):
    monkeypatch.setattr(replicate, "BLOCK", block)
    edges = [(a * (shift + 1), b * (shift + 1)) for a, b in EDGES]
    labels = {v * (shift + 1): x for v, x in LABELS.items()}
    csr = mapped(tmp_path, monkeypatch, edges, labels)
    u, v = (np.array(x, np.int64) for x in zip(*edges))
    plain = Csr(np.concatenate([u, v]), np.concatenate([v, u]), labels)
    assert (csr.ids == plain.ids).all() and (csr.indptr == plain.indptr).all() and (csr.indices == plain.indices).all() and (csr.labels == plain.labels).all()
    a, b = np.meshgrid(np.arange(csr.n), np.arange(csr.n))
    assert (csr.has(a.ravel(), b.ravel()) == plain.has(a.ravel(), b.ravel())).all()
    for q in (catalogue.unlabelled("q2"), QueryGraph.parse("a-b, b-c, a-c; a:1, b:2, c:3")):
        for kernel in ("cover", "candidate", "decompose"):
            found, want = ({tuple(r) for rows in KERNELS[kernel](c, q, True) for r in rows.tolist()} for c in (csr, plain))
            assert found == want


@pytest.mark.parametrize("text", ["a-b, b-c, a-c; a:1, b:2, c:3", "a-b, a-c, a-d; a:1, b:2, c:3, d:2", "a-b, b-c; a:1"])
def test_the_driver_holds_no_graph(spark, monkeypatch, text):
    g, q = from_lists(spark, EDGES, LABELS), QueryGraph.parse(text)
    want = {tuple(r) for r in api.match(g, q, "growth").collect()}
    refuse = lambda *a, **b: pytest.fail("the graph went to the driver")
    monkeypatch.setattr(DataFrame, "toArrow", refuse)
    monkeypatch.setattr(spark.sparkContext, "broadcast", refuse)
    rows = replicate.run(g, q, kernel="candidate")
    monkeypatch.undo()
    found = [tuple(r) for r in rows.collect()]
    assert set(found) == want and len(found) == len(want)


def test_the_size_counts_the_arcs_that_travel(spark):
    g, q = from_lists(spark, EDGES, LABELS), QueryGraph.parse("a-b; a:1, b:2")
    arcs = g.label_pairs()[1, 2] + g.label_pairs()[2, 1]
    replicate.check_size(g, 8 * arcs + 24 * 30, q)
    with pytest.raises(replicate.GraphTooLarge):
        replicate.check_size(g, 8 * arcs + 24 * 30 - 1, q)
