"""Replicated arrays are as wide as their numbers need, are made once where the folder is mounted, and are refused by what they take."""

import os

import numpy as np
import pytest

from motifloom import api
from motifloom.functions.kernels import MappedCsr
from motifloom.operators import replicate
from motifloom.operators.graph import from_lists
from motifloom.plans.pattern import QueryGraph

EDGES = [(a, b) for a in range(1, 31) for b in range(a + 1, 31) if (a * 7 + b * 11) % 5 < 3]
LABELS = {v: v % 3 + 1 for v in range(1, 31)}
TEXTS = ["a-b, b-c, a-c; a:1, b:2, c:3", "a-b, a-c, a-d; a:1, b:2, c:3, d:2", "a-b, b-c, c-d, a-d"]


@pytest.mark.parametrize("text", TEXTS)
@pytest.mark.parametrize("round_arcs", [20, 1 << 30])
def test_arrays_take_what_the_guard_counts(spark, monkeypatch, text, round_arcs):
    monkeypatch.setattr(replicate, "ROUND_ARCS", round_arcs)
    g, q = from_lists(spark, EDGES, LABELS), QueryGraph.parse(text)
    size = replicate.held_bytes(g, q)
    assert replicate.count(g, q, kernel="candidate", budget=size).first()[0] == api.match(g, q, "growth", output="count").first()[0] > 0
    _, (folder,), _ = replicate.replica(g, size, q)
    assert sorted(os.listdir(folder)) == ["ids.npy", "indices.bin", "indptr.npy", "labels.npy"]
    csr = MappedCsr(folder)
    assert csr.nbytes - csr.indptr.itemsize == size < 8 * len(csr.indices) + 24 * csr.n
    assert (csr.ids.dtype, csr.indptr.dtype, csr.labels.dtype) == (np.int32, np.uint32, np.int8)
    with pytest.raises(replicate.GraphTooLarge):
        replicate.count(g, q, kernel="candidate", budget=size - 1)


def test_files_of_all_rounds_are_sent_where_no_folder_is_mounted(spark, monkeypatch):
    monkeypatch.setattr(replicate, "ROUND_ARCS", 40)
    monkeypatch.setattr(replicate, "local_path", lambda *a: None)
    g, q = from_lists(spark, EDGES, LABELS), QueryGraph.parse(TEXTS[0])
    _, names, _ = replicate.replica(g, q=q)
    assert len(names) == len(set(names)) > 1 and not any(os.path.isabs(n) for n in names)
    assert replicate.count(g, q, kernel="candidate").first()[0] == api.match(g, q, "growth", output="count").first()[0]
