"""Searches sort the border once; only what changes later goes through a heap."""

import heapq
from types import SimpleNamespace

import numpy as np
import pytest

from graphblocks.model import Csr
from graphblocks.operators import kernels


@pytest.mark.parametrize("k", [2, 4])
def test_border_is_not_pushed_one_by_one(monkeypatch, k):
    r = np.random.default_rng(k)
    n = 4000
    pairs = np.unique(np.sort(r.integers(0, n, (12_000, 2)), axis=1), axis=0)
    src, dst = pairs[pairs[:, 0] < pairs[:, 1]].T
    csr = Csr.from_arrays(np.arange(n), np.ones(n, np.int64), src, dst, np.ones(len(src), np.int64))
    block = np.arange(n) % k
    pushed = []
    monkeypatch.setattr(kernels, "heapq", SimpleNamespace(heappush=lambda h, e: pushed.append(e) or heapq.heappush(h, e), heappop=heapq.heappop))
    after = kernels.fm(csr, block, np.full(k, n // k + 1), np.random.default_rng(1), passes=1, patience=0)
    assert (after == block).all()
    assert len(kernels.border(csr, block)) > 1000 and not pushed
