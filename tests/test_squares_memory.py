"""A block of grouped stars holds its arcs as numbers of four bytes and one key each, with no sorted copies of eight bytes beside."""

import tracemalloc

import numpy as np
import pyarrow as pa

from motifloom.functions.kernels import _different, squares


def test_memory_per_arc():
    rng = np.random.default_rng(1)
    n, d = 100_000, 20
    leaves = np.sort(rng.integers(0, n, (n, d)).astype(np.int32), 1)
    lists = pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * d), pa.array(leaves.ravel()))
    tracemalloc.start()
    try:
        squares(0, (400, 1), np.arange(n, dtype=np.int64), lists)
        assert tracemalloc.get_traced_memory()[1] < 30 * n * d
    finally:
        tracemalloc.stop()


def test_different_values():
    x = np.random.default_rng(2).integers(0, 3_000_000, 4_000_000).astype(np.int32)
    assert (_different(x) == np.unique(x)).all() and len(_different(x[:0])) == 0
