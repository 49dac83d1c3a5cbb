"""Graphs of over 4 million arcs are taken by the experiments whose presets have no plans, as arrays."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from graphblocks.model import BlockGraph, Csr
from graphblocks.plans import workloads as W


def test_large_graph_is_not_refused(spark, monkeypatch):
    one = F.lit(1).cast("long").alias("weight")
    n, m = 50_000, 42

    def ring(s, d):
        e = s.range(n * m).select((F.col("id") % n).alias("a"), (F.col("id") % n + 1 + F.floor(F.col("id") / n)).alias("b"))
        e = e.select("a", (F.col("b") % n).alias("b")).select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"), one)
        return BlockGraph(s.range(n).select("id", one), e)

    monkeypatch.setitem(W.GRAPHS, "ring", ring)
    monkeypatch.setattr(W, "_graphs", {})
    csr = W.csr_of(spark, "nowhere", "ring")
    assert csr.n == n and len(csr.nbr) == 2 * n * m > 4_000_000 and set(csr.degrees().tolist()) == {2 * m}


@pytest.mark.parametrize("n, m", [(1, 0), (0, 0), (40, 300), (3000, 9000)])
def test_arrays_are_sorted_by_both_ends(n, m):
    r = np.random.default_rng(n)
    ids = r.permutation(10 * n + 1)[:n]
    e = {(min(a, b), max(a, b)) for a, b in ids[r.integers(0, max(n, 1), (m, 2))].tolist() if a != b} if m else set()
    src, dst = (np.array(sorted(e), np.int64).reshape(-1, 2)).T
    w = r.integers(1, 9, len(src))
    csr = Csr.from_arrays(ids, ids + 1, src, dst, w)
    want = sorted([(a, b, x) for a, b, x in zip(src.tolist(), dst.tolist(), w.tolist())] + [(b, a, x) for a, b, x in zip(src.tolist(), dst.tolist(), w.tolist())])
    got = list(zip(csr.ids[csr.rows()].tolist(), csr.ids[csr.nbr].tolist(), csr.w.tolist())) if n else []
    assert got == want and csr.vw.tolist() == (np.sort(ids) + 1).tolist() and len(csr.indptr) == n + 1
