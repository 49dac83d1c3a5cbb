"""Flows on graphs beyond ``local_arc_limit``: refused only where kernels would use them."""

import pytest
from pyspark.sql import functions as F

from graphblocks.config import config
from graphblocks.model import BlockGraph, GraphError
from graphblocks.operators import refinement
from graphblocks.plans import multilevel


def path(spark, n):
    v = spark.range(n).select("id", F.lit(1).cast("long").alias("weight"))
    e = spark.range(n - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1).cast("long").alias("weight"))
    return BlockGraph(v, e).stored()


def settings(limit):
    return config(flow=True, refiner="lp", coarsening="matching", match_rounds=2, growth_starts=1, trials=1, lp_rounds_refine=2, local_arc_limit=limit)


def test_large_levels_run_and_smaller_ones_use_flows(spark, monkeypatch):
    n, polished = 6000, []
    monkeypatch.setattr(refinement, "lp_refine", lambda g, part, *a, **k: part)
    monkeypatch.setattr(multilevel.kernels, "flow_all_pairs", lambda csr, block, bound: polished.append(csr.n) or block)
    r = multilevel.partition_graph(path(spark, n), 2, p=1, cfg=settings(11_000))
    assert sum(r.weights) == n and r.assignment.select("id").distinct().count() == n
    assert max(polished) > 1000


def test_small_levels_without_kernels_are_refused(spark):
    with pytest.raises(GraphError, match="no distributed form of flow"):
        multilevel.partition_graph(path(spark, 4000), 2, p=1, cfg=settings(1000))
