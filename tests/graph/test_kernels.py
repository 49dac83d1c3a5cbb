"""Kernels: bounds, equal modes, known optima, replay, the stopping rule, the tables."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from graphblocks.config import config
from graphblocks.functions.hashes import mix_np, tabular_hash_np
from graphblocks.model import Csr, GraphError
from graphblocks.operators import kernels as K
from graphblocks.operators.measures import l_max
from graphblocks.plans.evaluation import expected_time
from graphblocks.plans.multilevel import partition_csr
from graphblocks.sources.generators import delaunay_edges


def csr(n, edges, vw=None):
    e = np.array(edges).reshape(-1, 3)
    return Csr.from_arrays(np.arange(n), np.ones(n, np.int64) if vw is None else np.array(vw), e[:, 0], e[:, 1], e[:, 2])


def grid(a, b):
    i = np.arange(a * b).reshape(a, b)
    s, t = np.concatenate([i[:-1].ravel(), i[:, :-1].ravel()]), np.concatenate([i[1:].ravel(), i[:, 1:].ravel()])
    return Csr.from_arrays(np.arange(a * b), np.ones(a * b, np.int64), s, t, np.ones(len(s), np.int64))


def random_graph(seed, n=60, m=200):
    r = np.random.default_rng(seed)
    a, b = r.integers(0, n, m), r.integers(0, n, m)
    keep = a != b
    pair = np.unique(np.sort(np.stack([a[keep], b[keep]], 1), axis=1), axis=0)
    return Csr.from_arrays(np.arange(n), r.integers(1, 4, n), pair[:, 0], pair[:, 1], r.integers(1, 6, len(pair)))


def test_hash_reference_values():
    x = mix_np(np.arange(100_000), 7)
    assert x.sum() == 107590969648727 and len(np.unique(x)) == 100_000


def test_local_hash_keeps_groups_together():
    h = tabular_hash_np(np.arange(1 << 14), 10, 25, 3, 5)
    spread = h.reshape(-1, 32)
    assert (spread.max(1) - spread.min(1) < 32).all()
    assert len(np.unique(h)) > (1 << 14) // 64


@settings(max_examples=20, deadline=None)
@given(st.integers(0, 10_000))
def test_clusters_stay_within_bound(seed):
    g = random_graph(seed)
    for labels in (K.sclp(g, 9, 5, 3, seed), K.sclp_sequential(g, 9, 5, seed), K.matching(g, 9, 4, seed, True)):
        assert np.bincount(labels, g.vw).max() <= 9


@settings(max_examples=15, deadline=None)
@given(st.integers(0, 10_000))
def test_contraction_keeps_cut_and_weights(seed):
    g = random_graph(seed)
    coarse, to = K.contract(g, K.sclp(g, 12, 3, 2, seed))
    block = np.arange(coarse.n) % 3
    assert coarse.cut(block) == g.cut(block[to]) and (np.bincount(block, coarse.vw, 3) == np.bincount(block[to], g.vw, 3)).all()


@settings(max_examples=15, deadline=None)
@given(st.integers(0, 10_000), st.sampled_from([1, 3, 8]))
def test_search_and_replay_never_raise_the_cut(seed, p):
    g = random_graph(seed)
    k, bound = 3, l_max(int(g.vw.sum()), 3, 0.1)
    block = K.rebalance(g, np.arange(g.n) % k, k, bound)
    sizes = np.bincount(block, g.vw, k)
    buckets = K.todo_order(g, K.boundary(g, block), p, seed)
    owner = K.own_balls(g, buckets, seed)
    moves = [m for pe in range(p) for m in K.perform_moves(g, block, sizes, bound, buckets[pe], owner == pe, pe)]
    assert len({m[3] for m in moves}) == len(moves)
    after, gained, _ = K.replay(g, block, sizes, bound, moves)
    assert g.cut(block) - g.cut(after) == gained >= 0
    assert np.bincount(after, g.vw, k).max() <= bound


@pytest.mark.parametrize("store", ["dict", "array", "probe", "probe_local"])
@pytest.mark.parametrize("mode", ["recompute", "incremental"])
def test_stores_and_gain_modes_agree(store, mode):
    g = grid(12, 12)
    block = np.arange(g.n) % 2
    args = (g, block, np.bincount(block), 80, K.boundary(g, block).tolist(), None, 0)
    assert K.perform_moves(*args, store=store, gain_mode=mode) == K.perform_moves(*args)


def test_replay_drops_moves_that_only_pay_alone():
    # Two adjacent vertices would each gain by a move if the other stayed.
    g = csr(4, [(0, 1, 5), (0, 2, 6), (1, 3, 6), (2, 3, 1)])
    block = np.array([0, 0, 1, 1])
    moves = [(0, 0, 0, 0, 0, 1, 1), (1, 0, 0, 1, 0, 1, 1)]
    after, gained, _ = K.replay(g, block, np.array([2, 2]), 3, moves)
    assert gained >= 0 and g.cut(after) <= g.cut(block) and np.bincount(after, minlength=2).max() <= 3


def test_replay_keeps_balance_when_two_fill_the_last_place():
    g = csr(4, [(0, 2, 9), (1, 2, 9), (0, 3, 1)])
    moves = [(0, 0, 0, 0, 0, 1, 9), (1, 0, 0, 1, 0, 1, 9)]
    after, _, touched = K.replay(g, np.array([0, 0, 1, 1]), np.array([2, 2]), 3, moves)
    assert len(touched) == 1 and np.bincount(after, minlength=2).max() <= 3


def test_stop_rule():
    falling, flat = K.RandomWalkStop(1, 2), K.RandomWalkStop(1, 2)
    assert any(falling.push(-2) for _ in range(5))
    assert not any(flat.push(x) for x in [1, -1] * 20)


def test_known_optima():
    g = grid(10, 10)
    assert min(g.cut(partition_csr(g, 2, 0.0, seed=s)[0]) for s in range(3)) == 10
    path = csr(30, [(i, i + 1, 1) for i in range(29)])
    assert path.cut(partition_csr(path, 2, 0.0)[0]) == 1
    star = csr(10, [(0, i, 1) for i in range(1, 10)])
    assert star.cut(partition_csr(star, 2, 0.0)[0]) == 5


@pytest.mark.parametrize("preset", ["full", "seq_lp", "dist_lp", "matching_greedy"])
@pytest.mark.parametrize("k", [1, 3, 5, 16])
def test_presets_are_balanced(preset, k):
    g = grid(18, 18)
    block, _ = partition_csr(g, k, 0.03, 4, 1, config(preset))
    assert np.bincount(block, minlength=k).max() <= l_max(g.n, k, 0.03) and set(block.tolist()) <= set(range(k))


def test_edge_cases():
    with pytest.raises(GraphError):
        partition_csr(csr(3, [(0, 1, 1)], [10, 1, 1]), 2, 0.0)
    assert len(partition_csr(csr(4, np.zeros((0, 3), int)), 2)[0]) == 4
    assert len(partition_csr(csr(2, [(0, 1, 1)]), 5)[0]) == 2


def test_flow_never_worse():
    g = grid(14, 14)
    block = K.rebalance(g, (np.arange(g.n) // 7) % 2, 2, 103)
    after = K.flow_polish(g, block, 0, 1, 103)
    assert g.cut(after) <= g.cut(block) and np.bincount(after).max() <= 103


def test_star_shrinks_faster_by_clusters():
    g = csr(101, [(0, i, 1) for i in range(1, 101)])
    clusters = len(np.unique(K.pack_lone(g, K.sclp_sequential(g, 20, 10, 1), 20)))
    assert clusters < len(np.unique(K.matching(g, 20, 6, 1))) == 100


def test_equal_time_theorem():
    for times in ([3.0, 5.0], [2.0, 2.0, 7.0]):
        # Enough samples, so that the limit is always exceeded.
        assert expected_time(times * 2, 4.0) == pytest.approx(4.0)
    assert expected_time([3.0, 5.0, 3.0, 5.0], 4.0, from_first=False) == pytest.approx(4.0)


def test_delaunay_has_empty_circles():
    p = np.random.default_rng(3).random((60, 2))
    e = delaunay_edges(p)
    assert 60 <= len(e) <= 3 * 60 - 6
    near = ((p[:, None] - p[None]) ** 2).sum(2)
    near[np.diag_indices(60)] = 9
    found = {tuple(x) for x in e.tolist()}
    assert all((min(i, j), max(i, j)) in found for i, j in enumerate(near.argmin(1).tolist()))
