"""The experiments on quality, equal time and memory run all their graphs, blocks, PEs and repetitions."""

import pytest

from graphblocks.config import config
from graphblocks.plans import workloads as W
from graphblocks.plans.multilevel import partition_csr

SF = "/root/testdata/sf0.001"


@pytest.fixture
def asked(spark, monkeypatch):
    """What the queries ask ``runs`` for, which then runs one small graph with few repetitions."""
    seen = {}
    whole = W.runs

    def few(s, d, graphs, ks, variants, ps=(1, 4), seeds=2, eps=0.03, log=None, memory=False):
        seen[log] = (tuple(graphs), ks, ps, seeds)
        return whole(s, d, {"nation_trade": W.csr_of(s, d, "nation_trade")}, (4,), variants, ps, 2, eps, log, memory)

    monkeypatch.setattr(W, "runs", few)
    monkeypatch.setattr(W, "_logs", {})
    monkeypatch.setattr(W, "csr_of", lambda s, d, name, of=W.csr_of: of(s, d, "nation_trade"))
    monkeypatch.setattr(W, "graph_of", lambda s, d, name: W.csr_of(s, d, name))
    return seen


def test_quality(spark, asked):
    rows = {q: W.QUERIES[q](spark, SF).collect() for q in ("w1_quality_runs", "w1_profile", "w1_geomean", "w2_effect_match")}
    graphs, ks, ps, seeds = asked["w1_all"]
    tables = {"page_links", "emb_rgg", "conv_path", "user_key", "nation_trade", "part_copurchase", "cust_supp", "part_supp", "doc_overlap", "emb_knn"}
    assert tables | {"rgg", "delaunay", "er", "rhg"} <= set(graphs)
    assert set(ks) >= {16, 64} and set(ps) >= {1, 16, 31} and seeds == 10
    assert len(rows["w1_quality_runs"]) == 2 * (3 * len(ps) + 1) and len(rows["w1_geomean"]) == 3 * len(ps) + 1
    assert [(r.p, r.n) for r in sorted(rows["w2_effect_match"])] == [(1, 20), (4, 20), (31, 20)]


def test_memory(spark, asked):
    rows = W.QUERIES["w8_memory"](spark, SF).collect()
    graphs, ks, ps, seeds = asked["w8"]
    assert len(graphs) == 3 and 16 in ks and {1, 31} <= set(ps) and seeds == 10
    assert sorted(r.p for r in rows) == [1, 4, 31]


@pytest.mark.parametrize("algo", list(W.VARIANTS))
def test_more_blocks_than_vertices(spark, algo):
    csr = W.csr_of(spark, SF, "nation_trade")
    block, _ = partition_csr(csr, 64, 0.03, 4, 0, W.VARIANTS[algo])
    assert csr.n < 64 and set(block.tolist()) <= set(range(64))


def test_large_graphs_run_with_methods_without_plans(spark):
    g = W.GRAPHS["nation_trade"](spark, SF).stored()
    for cfg in (config("seq_lp", local_arc_limit=10), config("matching", local_arc_limit=10)):
        assert W._run_by_plans(g, "nation_trade", 4, "x", 1, 0, cfg, 0.03)[6] == 25
