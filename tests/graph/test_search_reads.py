"""The localized search counts the arcs of many vertices at once, and a hub's arcs not for every move beside it."""

import numpy as np
import pytest

from graphblocks.model import Csr
from graphblocks.operators import kernels


def hubs(users, keys, seed=0):
    """Users with two arcs to each of some keys that all users share."""
    r = np.random.default_rng(seed)
    src, dst = np.repeat(np.arange(users), keys), np.tile(users + np.arange(keys), users)
    return Csr.from_arrays(np.arange(users + keys), np.ones(users + keys, np.int64), src, dst, r.integers(1, 9, len(src)))


def test_arcs_of_a_hub_are_not_read_for_each_move():
    csr, k = hubs(600, 6), 3
    block = np.random.default_rng(1).integers(0, k, csr.n)
    sizes = np.bincount(block, minlength=k)
    read = []

    class Counting(np.ndarray):
        def __getitem__(self, at):
            out = super().__getitem__(at)
            read.append(np.size(out))
            return out

    counted = Csr(csr.ids, csr.indptr, csr.nbr, csr.w.view(Counting), csr.vw)
    log = kernels.perform_moves(counted, block, sizes, int(sizes.max()) + 40, kernels.boundary(csr, block).tolist(), None, 0)
    assert len(log) > 30
    assert sum(read) < 5 * len(csr.w)


@pytest.mark.parametrize("low", [0, 5])
def test_many_probes_count_as_single_ones(low):
    one, many = kernels.ProbeTable(64, low=low), kernels.ProbeTable(64, low=low)
    for key in range(0, 700, 7):
        one[key] = many[key] = key % 4
    one.lookups = one.probes = many.lookups = many.probes = 0
    keys = np.arange(800)
    assert many.get_many(keys, keys + 9).tolist() == [one.get(u, u + 9) for u in keys.tolist()]
    assert (many.lookups, many.probes) == (one.lookups, one.probes) and one.probes > 0
