"""Sides grown by arrays are those grown by lists, and cost a traced run no object for each arc."""

import tracemalloc

import numpy as np
import pytest

from graphblocks.model import Csr
from graphblocks.operators import kernels


def graph(n, m, seed, most=1, hubs=0):
    """Random edges; with hubs, only edges that end in one of so many vertices."""
    r = np.random.default_rng(seed)
    e = {(min(a, b), max(a, b)) for a, b in zip(r.integers(0, n, m).tolist(), r.integers(0, hubs or n, m).tolist()) if a != b}
    src, dst = np.array(sorted(e)).T
    return Csr.from_arrays(np.arange(n), r.integers(1, most + 1, n), src, dst, r.integers(1, 5, len(src)))


@pytest.mark.parametrize("n, m, most, hubs", [(300, 900, 1, 0), (1500, 700, 4, 0), (1200, 6000, 60, 0), (2000, 9000, 1, 12), (2000, 3000, 5, 12), (700, 650, 300, 3)])
def test_same_sides(n, m, most, hubs):
    for seed in range(6):
        csr = graph(n, m, seed, most, hubs)
        total = int(csr.vw.sum())
        for left in (total // 2, total // 3):
            caps = (left + seed, total - left + seed)
            a, b = np.random.default_rng(seed), np.random.default_rng(seed)
            assert (kernels._grow_by_arrays(csr, left, *caps, a) == kernels._grow(csr, left, *caps, b)).all()
            assert a.random() == b.random()


def test_large_sides_hold_less_memory():
    csr = graph(4000, 60_000, 1, 1, 40)
    tracemalloc.start()
    kernels.bisect(csr, 2000, 2060, 2060, np.random.default_rng(1), 1)
    whole = tracemalloc.get_traced_memory()[1]
    tracemalloc.reset_peak()
    kernels.GROW_BY_ARRAYS, kept = 1 << 40, kernels.GROW_BY_ARRAYS
    try:
        kernels.bisect(csr, 2000, 2060, 2060, np.random.default_rng(1), 1)
        lists = tracemalloc.get_traced_memory()[1]
    finally:
        kernels.GROW_BY_ARRAYS = kept
        tracemalloc.stop()
    assert whole < 0.8 * lists


def test_single_gains_by_lists_and_arrays():
    csr = graph(300, 3000, 2, 1, 9)
    block = np.arange(300) % 3
    for v in range(300):
        few, many = (kernels._alone(csr, block, v, 1, 0, n) for n in (1 << 40, 0))
        assert few[0] == many[0] and few[1] == many[1].tolist() and few[2] == many[2].tolist()
