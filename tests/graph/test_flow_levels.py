"""Flows polish levels of all sizes and borders of all lengths, by kernels and by plans."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from graphblocks.config import config
from graphblocks.model import BlockGraph, Csr, collect_csr
from graphblocks.operators import kernels, refinement
from graphblocks.plans import multilevel


def ladder(n, rungs):
    """Columns of ``rungs`` vertices, each tied to the next one; ties of a column are strong."""
    at = np.arange(n * rungs)
    right = at[: (n - 1) * rungs]
    down = at[at % rungs < rungs - 1]
    src, dst = np.concatenate([right, down]), np.concatenate([right + rungs, down + 1])
    return Csr.from_arrays(at, np.ones(len(at), np.int64), src, dst, np.concatenate([np.full(len(right), 1), np.full(len(down), 3)]))


def jagged(n, rungs, k):
    """Blocks of columns whose borders are a saw."""
    at = np.arange(n * rungs)
    return np.clip((at // rungs + at % rungs % 2 * 2) * k // n, 0, k - 1)


def test_large_level_is_polished():
    csr = ladder(600, 10)
    assert csr.n > 5000
    block = jagged(600, 10, 2)
    after = multilevel.refine(csr, block, 2, 3100, config(flow=True, refiner="none"), 1, 0, {})
    assert csr.cut(after) == 10 < csr.cut(block) and np.bincount(after).max() <= 3100


def test_long_border_is_polished():
    csr = ladder(20, 3000)
    block = jagged(20, 3000, 2)
    after = kernels.flow_polish(csr, block, 0, 1, 33_000)
    assert csr.cut(after) == 3000 < csr.cut(block)


@pytest.mark.parametrize("k", [2, 3, 4])
def test_plans_polish_as_kernels(spark, k):
    csr = ladder(60, 6)
    block, bound = jagged(60, 6, k), 360 // k + 20
    src = csr.rows()
    e = [(int(a), int(b), int(w)) for a, b, w in zip(src, csr.nbr, csr.w) if a < b]
    one = F.lit(1).cast("long").alias("weight")
    g = BlockGraph(spark.range(360).select("id", one), spark.createDataFrame(e, "src long, dst long, weight long"))
    part = spark.createDataFrame([(i, int(b)) for i, b in enumerate(block)], "id long, block int")
    rows = refinement.flow_refine(g, part, k, bound).orderBy("id").collect()
    after = np.array([r.block for r in rows])
    assert [r.id for r in rows] == list(range(360)) and np.bincount(after).max() <= bound
    assert csr.cut(after) == 6 * (k - 1) == csr.cut(kernels.flow_all_pairs(csr, block, bound)) < csr.cut(block)
    assert collect_csr(g, 1 << 20).cut(after) == csr.cut(after)


@pytest.mark.parametrize("k", [1, 2, 5, 6])
def test_rounds_meet_each_pair_once(k):
    rounds = refinement.pair_rounds(k)
    assert all(len({b for p in r for b in p}) == 2 * len(r) for r in rounds)
    assert sorted(p for r in rounds for p in r) == [(a, b) for a in range(k) for b in range(a + 1, k)]
