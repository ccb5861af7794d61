"""A worker lists the candidates of the last vertex once per images that they hang on, over all its batches of seeds."""

import numpy as np
import pytest

from motifloom.functions import kernels
from motifloom.plans.pattern import QueryGraph


@pytest.mark.parametrize("most, of_block", [(1 << 16, 1 << 12), (1, 1 << 12), (1 << 16, 1), (0, 1 << 12)])
def test_later_batches_list_nothing_again(monkeypatch, most, of_block):
    monkeypatch.setattr(kernels, "KNOWN", most)
    monkeypatch.setattr(kernels, "KNOWN_OF_BLOCK", of_block)
    q = QueryGraph.from_edges([(1, 2), (2, 3), (3, 4), (1, 4)], labels=[1, 2, 1, 3])
    edges = [(a, b) for a in range(1000, 1400) for b in (200, 201, 300)]
    u, v = np.array(edges).T
    label = lambda x: np.where(x >= 1000, 1, np.where(x < 300, 2, 3))
    csr = kernels.cell_csr([u, v, label(u), label(v)])
    listed = []
    slow = kernels._candidates
    monkeypatch.setattr(kernels, "_candidates", lambda *a: (listed.append(len(cand)) or (who, cand) for who, cand in slow(*a)))
    found = [kernels.count(csr, q, "candidate", False, np.arange(k, k + 100)) for k in range(1000, 1400, 100)]
    assert found == [100 * 2 * 399] * 4
    if most > 1 and of_block > 1:
        assert len(listed) and sum(listed[len(listed) // 2 :]) <= 2 * 400
    plain = kernels.Csr(np.r_[u, v], np.r_[v, u], {int(x): int(label(x)) for x in {*u.tolist(), *v.tolist()}})
    assert sum(found) == kernels.count(plain, q, "candidate", False)
