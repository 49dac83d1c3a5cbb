"""Hills, file formats, accounting and streams on small inputs."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from graphblocks.config import config
from graphblocks.model import Csr
from graphblocks.operators import accounting, kernels
from graphblocks.plans.multilevel import partition_csr
from graphblocks.sources import files, generators
from graphblocks.streaming import edges as streams


def of_edges(n, rows):
    a, b, w = (np.array(x, np.int64) for x in zip(*rows))
    return Csr.from_arrays(np.arange(n, dtype=np.int64), np.ones(n, np.int64), a, b, w)


def test_a_hill_moves_together():
    """Vertices 4 and 5 are tied to each other by 3 and to block 1 by 2 each: alone each loses, together they gain."""
    rows = [(0, 1, 5), (1, 2, 5), (2, 3, 5), (3, 4, 1), (4, 5, 3), (0, 5, 1), (4, 6, 2), (5, 7, 2), (6, 7, 5), (7, 8, 5), (8, 9, 5)]
    csr = of_edges(10, rows)
    block = np.array([0] * 6 + [1] * 4)
    load = np.bincount(block, csr.vw, 2)
    assert kernels._hill(csr, block, load, 8, 4, 1)[0] == []
    hill, target, gain = kernels._hill(csr, block, load, 8, 4, 16)
    assert sorted(hill) == [4, 5] and target == 1 and gain == 2
    after = kernels.hill_climb(csr, block, 2, 8, 1, 0)
    assert csr.cut(after) == csr.cut(block) - 2
    assert kernels._hill(csr, block, load, 5, 4, 16)[0] == []  # no room for two


def test_full_keeps_the_bound_with_flows_in_starts(spark):
    g = generators.grid(spark, 12, 12)
    from graphblocks.model import collect_csr

    csr = collect_csr(g, 10_000)
    for seed in range(2):
        block, report = partition_csr(csr, 4, 0.03, 4, seed, config())
        assert np.bincount(block, csr.vw, 4).max() <= 37 and csr.cut(block) <= 40 and report["levels"]


def test_edge_list_lines(spark, tmp_path):
    at = tmp_path / "e.txt"
    at.write_text("# comment\n\n1 2 3\n2 1\n4 4 9\n5 6\n")
    g = files.read_edge_list(spark, f"file://{at}", " ")
    assert {tuple(r) for r in g.edges.select("src", "dst", "weight").collect()} == {(1, 2, 4), (5, 6, 1)}


def test_adjacency_keeps_lone_vertices(spark, tmp_path):
    g = generators.path(spark, 5)
    lone = g.vertices.unionByName(spark.createDataFrame([(77, 1)], "id long, weight long"))
    numbers = files.write_adjacency(type(g)(lone, g.edges), f"file://{tmp_path}/a")
    back = files.read_adjacency(spark, f"file://{tmp_path}/a")
    assert back.vertices.count() == numbers.count() == lone.count() and back.edges.count() == g.edges.count()


@pytest.mark.parametrize("p", [1, 3])
def test_span_lies_between_work_and_its_share(spark, p):
    rows = [(i, i % 5, i // 4, i % 2) for i in range(40)]
    packets = spark.createDataFrame(rows, "id long, degree long, packet long, sub_round int")
    for r in accounting.work_and_span(packets, p).collect():
        assert r["work"] / p <= r["span"] <= r["work"] and (p > 1 or r["span"] == r["work"])


def test_late_rows_are_counted(spark):
    at = lambda *m: spark.createDataFrame([(x,) for x in m], "m long").select(F.timestamp_seconds(F.col("m") * 60).alias("ts"))
    got = [tuple(r) for r in streams.late_rows([at(0, 100), at(89, 90, 120), at(100, 111)], 600).orderBy("batch").collect()]
    assert got == [(0, 2, 0), (1, 3, 1), (2, 2, 1)]
