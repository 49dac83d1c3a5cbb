"""Graphs beyond the bound for arrays are run by plans in the experiment on phases, not refused."""

import pytest

from graphblocks.plans import workloads as W

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("limit", [700, 0])
def test_phases_of_graphs_beyond_the_limit(spark, monkeypatch, limit):
    monkeypatch.setattr(W, "LIMIT", limit)
    monkeypatch.setattr(W, "_graphs", {})
    monkeypatch.setattr(W, "_logs", {})
    rows = W.QUERIES["w7_phase_share"](spark, SF).collect()
    assert len(rows) == 6 and all(abs(r.share_coarsen + r.share_init + r.share_refine - 1) < 0.001 for r in rows)
    log = next(iter(W._logs.values())).collect()
    assert len(log) == 12 and not any(r.imbalanced for r in log)
