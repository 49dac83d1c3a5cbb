"""Large levels run all that the settings ask for, or refuse."""

import pytest
from pyspark.sql import functions as F

from graphblocks.config import config
from graphblocks.model import BlockGraph, GraphError
from graphblocks.operators import refinement
from graphblocks.plans.multilevel import partition_graph


@pytest.fixture(scope="module")
def ring(spark):
    v = spark.range(40).select("id", F.lit(1).cast("long").alias("weight"))
    e = spark.range(39).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1).cast("long").alias("weight"))
    return BlockGraph(v, e)


@pytest.mark.parametrize("changes", [{"refiner": "hill"}, {"refiner": "fm"}, {"flow": True}, {"sequential_lp": True}])
def test_settings_without_a_plan_are_refused(ring, changes):
    with pytest.raises(GraphError, match="no distributed form"):
        partition_graph(ring, 2, cfg=config(execution_mode="distributed", **changes))


@pytest.mark.parametrize("changes, want", [({"refiner": "lp"}, (25, "histogram")), ({"refiner": "lp", "quota": True}, (25, "quota")), ({"refiner": "greedy"}, (4, "histogram"))])
def test_rounds_are_passed_on(ring, monkeypatch, changes, want):
    seen = []

    def spy(g, part, k, bound, rounds=25, seed=0, sub_rounds=2, admission="histogram", ranges=1):
        seen.append((rounds, admission))
        return part

    monkeypatch.setattr(refinement, "lp_refine", spy)
    partition_graph(ring, 2, cfg=config(execution_mode="distributed", coarsening="matching", match_rounds=1, coarsest_min=10, coarsest_per_block=2, max_levels=1, cluster_factor=4, **changes))
    assert seen == [want]
