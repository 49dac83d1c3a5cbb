"""DataFrame plans against kernels, SQL and each other."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from graphblocks.config import config
from graphblocks.model import GraphError, collect_csr, encode_ids, normalize_graph
from graphblocks.operators import coarsening as C
from graphblocks.operators import kernels as K
from graphblocks.operators import measures as M
from graphblocks.operators import refinement as R
from graphblocks.plans import queries as Q
from graphblocks.plans.multilevel import floor_blocks, partition_graph
from graphblocks.sources import generators as G
from graphblocks.sources import tables as T

SF = "/root/testdata/sf0.001"


def db():
    con = duckdb.connect()
    for t in T.TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
    return con


NAMES = [n for n in Q.SQL if n.split("_")[0] in ("m", "h", "c", "r", "t") or n in ("e_profile", "e_effectiveness_match", "op_components", "g_doc_overlap")]


@pytest.mark.parametrize("name", NAMES)
def test_sql_parity(spark, name):
    got = Q.QUERIES[name](spark, SF)
    cols = sorted(got.columns)
    want = db().execute(Q.SQL[name]).df()
    assert sorted(want.columns) == cols
    norm = lambda rows: sorted(tuple("" if x is None or x != x else f"{x:.6f}" if isinstance(x, float) else str(x) for x in r) for r in rows)
    assert norm(got.select(*cols).toPandas().itertuples(index=False)) == norm(want[cols].itertuples(index=False))


def test_normalize(spark):
    rows = spark.createDataFrame([(1, 2, 3), (2, 1, 4), (3, 3, 1), (None, 1, 1), (1, 4, 0), (4, 5, -1), (5, 6, None)], "src long, dst long, weight long")
    g = normalize_graph(rows, spark.createDataFrame([(9, 2)], "id long, weight long"))
    assert [tuple(r) for r in g.edges.collect()] == [(1, 2, 7)]
    assert {tuple(r) for r in g.vertices.collect()} == {(1, 1), (2, 1), (9, 2)}
    with pytest.raises(GraphError):
        normalize_graph(rows, strict=True)


def test_string_ids(spark):
    edges, names = encode_ids(spark.createDataFrame([("b", "a"), ("c", "a")], "src string, dst string"))
    assert {tuple(r) for r in edges.collect()} == {(1, 0), (2, 0)} and names.count() == 3


def test_label_propagation_modes_agree(spark):
    g = T.supp_supp(spark, "/root/testdata/sf0.01").stored()
    lp = C.LabelPropagation(12, 2, 2, 5, packet=500)
    plan = {r["id"]: r["cluster"] for r in lp.run(g).collect()}
    csr = collect_csr(g, 1 << 30)
    kernel = csr.ids[K.sclp(csr, 12, 2, 2, 5, packet=500)]
    assert [plan[i] for i in csr.ids.tolist()] == kernel.tolist()


def test_matching_modes_agree(spark):
    g = T.page_links(spark, SF).stored()
    plan = {r["id"]: r["cluster"] for r in C.heavy_edge_matching(g, 2, 3, 1).collect()}
    csr = collect_csr(g, 1 << 30)
    assert [plan[i] for i in csr.ids.tolist()] == csr.ids[K.matching(csr, 2, 3, 1)].tolist()


def test_histogram_admits_what_the_window_admits(spark):
    p = spark.range(3000).select("id", (F.col("id") % 4 + 1).alias("weight"), (F.col("id") % 3).alias("target"), (F.col("id") * 7 % 11).alias("gain"))
    w = spark.range(3).select(F.col("id").alias("target"), (F.col("id") * 10).alias("cweight"))
    a, b = C.admit_by_capacity(p, w, 700, 4), C.admit_by_histogram(p, w, 700, 4)
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))


def test_distributed_search_keeps_balance_and_cut(spark):
    g = G.grid(spark, 12, 12).stored()
    part = floor_blocks(g, 3, "range")
    bound = M.l_max(144, 3, 0.05)
    before = M.edge_cut(g, part).first()["cut"]
    for limit in (10**6, 0):  # replay, bulk
        after, report = R.mts(g, part, 3, bound, 3, config(global_rounds=1, replay_limit=limit), 1)
        assert M.edge_cut(g, after).first()["cut"] == before - report["gain"] <= before
        assert max(r["weight"] for r in M.block_weights(g, after, 3).collect()) <= bound


def test_distributed_run(spark):
    cfg = config(execution_mode="distributed", lp_rounds_coarsen=1, lp_rounds_refine=1, sub_rounds=1, global_rounds=1, coarsest_min=60, coarsest_per_block=10, max_levels=1)
    r = partition_graph(G.grid(spark, 12, 12).stored(), 4, cfg=cfg)
    assert r.balanced and r.assignment.count() == 144 and r.cut < 120


def test_generators(spark):
    g = G.gen_rgg(spark, 8)
    points = G.random_points(spark, 256, 1).toPandas().sort_values("id")[["x", "y"]].to_numpy()
    d = ((points[:, None] - points[None]) ** 2).sum(2)
    assert g.edges.count() == np.triu(d < 0.55**2 * np.log(256) / 256, 1).sum()
    assert 0.7 < G.gen_er(spark, 300).edges.count() / (1.5 * np.log(300) * 299 / 2) < 1.3
    assert G.gen_rhg(spark, 200).edges.count() > 100
    assert G.clique_ring(spark, 4, 5).edges.count() == 44 and G.grid(spark, 4, 4, wrap=True).edges.count() == 32


def test_plans_have_no_cross_join_and_no_global_window(spark):
    g, part = Q._gp(spark, SF)
    for df in (M.gain(g, part), M.quotient(g, part).edges, C.propose(g, g.vertices.select("id", F.col("id").alias("cluster")), None, 10, 0)[0]):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in plan and "SinglePartition" not in plan
