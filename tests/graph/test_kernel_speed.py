"""Kernels made faster do the same moves as before, and no work twice."""

import numpy as np
import pytest

from graphblocks.config import config
from graphblocks.model import Csr
from graphblocks.operators import kernels
from graphblocks.plans import multilevel


def graph(n, m, seed, most=1):
    r = np.random.default_rng(seed)
    e = {(min(a, b), max(a, b)) for a, b in r.integers(0, n, (m, 2)).tolist() if a != b}
    src, dst = np.array(sorted(e)).T
    return Csr.from_arrays(np.arange(n), r.integers(1, most + 1, n), src, dst, r.integers(1, 5, len(src)))


@pytest.mark.parametrize("seed", range(12))
def test_two_blocks_as_general_search(seed):
    """A third block without room takes the general search, which must make the same moves with the same random numbers."""
    csr = graph(60 + 20 * seed, 150 + 120 * seed, seed, 1 + seed % 3)
    start = np.random.default_rng(seed + 50).integers(0, 2, csr.n)
    half = int(csr.vw.sum()) // 2 + seed % 4
    a, b = np.random.default_rng(seed), np.random.default_rng(seed)
    got = kernels.fm(csr, start, np.array([half, half + 2]), a)
    want = kernels.fm(csr, start, np.array([half, half + 2, -1]), b)
    assert (got == want).all() and a.random() == b.random()


def test_trials_run_once(monkeypatch):
    seeds = []
    real = multilevel.one_trial
    monkeypatch.setattr(multilevel, "one_trial", lambda csr, k, bound, seed, cfg: seeds.append(seed) or real(csr, k, bound, seed, cfg))
    csr = graph(80, 240, 3)
    block = multilevel.initial_partition(csr, 4, 22, config(), 4, 7)
    assert seeds == [7, 8, 9, 10]
    assert csr.cut(block) == min(real(csr, 4, 22, s, config())[1] for s in seeds)


def test_hill_reads_each_vertex_once():
    """A hill in a large block: what a vertex gains by itself is read once, however often the hill grows."""
    csr = graph(300, 2500, 5)
    block = np.arange(300) % 2
    reads = []

    class Counting(np.ndarray):
        def __getitem__(self, at):
            if isinstance(at, slice):
                reads.append(at.start)
            return super().__getitem__(at)

    counted = Csr(csr.ids, csr.indptr, csr.nbr, csr.w.view(Counting), csr.vw)
    for v in range(40):
        reads.clear()
        kernels._hill(counted, block, np.bincount(block), 400, v, 16)
        assert len(reads) <= 1 + len(set(reads))
