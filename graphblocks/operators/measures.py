"""Quantities of graphs and partitions, each a plan of joins and grouped sums."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashes import mix
from ..model import BlockGraph


def l_max(total: int, k: int, eps: float) -> int:
    """The largest weight that a block of a balanced partition may have, for whole weights: floor((1 + eps) * ceil(total / k))."""
    if k < 1 or eps < 0:
        raise ValueError("k >= 1 and eps >= 0")
    return (10**6 + round(eps * 10**6)) * -(-total // k) // 10**6


def degrees(g: BlockGraph) -> DataFrame:
    """(id, degree, wdegree) of all vertices."""
    d = g.arcs().groupBy("src").agg(F.count(F.lit(1)).alias("degree"), F.sum("weight").alias("wdegree"))
    return g.vertices.join(d, g.vertices["id"] == d["src"], "left").select("id", F.coalesce("degree", F.lit(0)).cast("long").alias("degree"), F.coalesce("wdegree", F.lit(0)).cast("long").alias("wdegree"))


def graph_stats(g: BlockGraph) -> DataFrame:
    """One row: n, m, total_vertex_weight, total_edge_weight, max_degree."""
    e = g.edges.agg(F.count(F.lit(1)).alias("m"), F.coalesce(F.sum("weight"), F.lit(0)).alias("total_edge_weight"))
    v = g.vertices.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("weight"), F.lit(0)).alias("total_vertex_weight"))
    d = g.arcs().groupBy("src").count().agg(F.coalesce(F.max("count"), F.lit(0)).alias("max_degree"))
    return v.join(e, F.lit(True)).join(d, F.lit(True)).select("n", "m", "total_vertex_weight", "total_edge_weight", "max_degree")


def block_weights(g: BlockGraph, part: DataFrame, k: int) -> DataFrame:
    """(block, vertices, weight) of the k blocks, empty ones too."""
    w = g.vertices.join(part, "id").groupBy("block").agg(F.count(F.lit(1)).alias("vertices"), F.sum("weight").alias("weight"))
    every = part.sparkSession.range(k).select(F.col("id").cast("int").alias("block"))
    return every.join(w, "block", "left").select("block", F.coalesce("vertices", F.lit(0)).cast("long").alias("vertices"), F.coalesce("weight", F.lit(0)).cast("long").alias("weight"))


def overloaded(g: BlockGraph, part: DataFrame, k: int, eps: float) -> DataFrame:
    """(block, weight, bound) of the blocks that weigh more than the bound."""
    total = g.vertices.agg(F.sum("weight").alias("total"))
    up = 10**6 + round(eps * 10**6)
    bound = F.floor(F.lit(up) * F.floor((F.col("total") + k - 1) / k) / 10**6).cast("long")
    return block_weights(g, part, k).join(total, F.lit(True)).withColumn("bound", bound).where("weight > bound").select("block", "weight", "bound")


def with_blocks(g: BlockGraph, part: DataFrame) -> DataFrame:
    """Edges with block_src and block_dst."""
    a = part.select(F.col("id").alias("src"), F.col("block").alias("block_src"))
    b = part.select(F.col("id").alias("dst"), F.col("block").alias("block_dst"))
    return g.edges.join(a, "src").join(b, "dst")


def edge_cut(g: BlockGraph, part: DataFrame) -> DataFrame:
    """One row: cut, cut_edges."""
    cut = with_blocks(g, part).where("block_src <> block_dst")
    return cut.agg(F.coalesce(F.sum("weight"), F.lit(0)).alias("cut"), F.count(F.lit(1)).alias("cut_edges"))


def boundary(g: BlockGraph, part: DataFrame) -> DataFrame:
    """(id) of the vertices with a neighbour in another block."""
    cut = with_blocks(g, part).where("block_src <> block_dst")
    return cut.select(F.col("src").alias("id")).union(cut.select("dst")).distinct()


def connections(g: BlockGraph, labels: DataFrame, label: str = "block") -> DataFrame:
    """(id, label, strength): the weight of a vertex's edges to each label beside it.  Partial sums come before the shuffle."""
    to = labels.select(F.col("id").alias("dst"), F.col(label).alias("label"))
    return g.arcs().join(to, "dst").groupBy(F.col("src").alias("id"), "label").agg(F.sum("weight").alias("strength"))


def gain(g: BlockGraph, part: DataFrame, bound: int | None = None, seed: int = 0, k: int | None = None) -> DataFrame:
    """(id, best_block, gain): what the cut would lose if a vertex went to the neighbouring block it is most tied to.

    With ``bound``, only to blocks that stay within it.  Vertices without a
    neighbour in another (feasible) block have no row.
    """
    c = connections(g, part)
    own = part.select("id", F.col("block").alias("own"))
    if bound is not None:
        fill = block_weights(g, part, k).select(F.col("block").alias("label"), F.col("weight").alias("filled"))
        c = c.join(F.broadcast(fill), "label").join(g.vertices, "id")  # k rows
    c = c.join(own, "id")
    ok = F.col("label") != F.col("own")
    if bound is not None:
        ok &= F.col("filled") + F.col("weight") <= bound
    stay = F.sum(F.when(F.col("label") == F.col("own"), F.col("strength")).otherwise(0)).alias("stay")
    best = F.max(F.when(ok, F.struct("strength", mix("label", seed).alias("tie"), "label"))).alias("best")
    return c.groupBy("id").agg(stay, best).where("best IS NOT NULL").select("id", F.col("best.label").cast("int").alias("best_block"), (F.col("best.strength") - F.col("stay")).alias("gain"))


def quotient(g: BlockGraph, part: DataFrame) -> BlockGraph:
    """The graph of the blocks: weights of blocks, and of the edges between them."""
    e = with_blocks(g, part).where("block_src <> block_dst")
    e = e.groupBy(F.least("block_src", "block_dst").cast("long").alias("src"), F.greatest("block_src", "block_dst").cast("long").alias("dst")).agg(F.sum("weight").alias("weight"))
    v = g.vertices.join(part, "id").groupBy(F.col("block").cast("long").alias("id")).agg(F.sum("weight").alias("weight"))
    return BlockGraph(v, e)


def check_partition(g: BlockGraph, part: DataFrame, k: int) -> DataFrame:
    """One row of counts that are 0 for a partition: uncovered, unknown, repeated, out_of_range."""
    missing = g.vertices.join(part, "id", "left_anti").agg(F.count(F.lit(1)).alias("uncovered"))
    unknown = part.join(g.vertices, "id", "left_anti").agg(F.count(F.lit(1)).alias("unknown"))
    twice = part.groupBy("id").count().where("count > 1").agg(F.count(F.lit(1)).alias("repeated"))
    out = part.where(f"block IS NULL OR block < 0 OR block >= {k}").agg(F.count(F.lit(1)).alias("out_of_range"))
    return missing.join(unknown, F.lit(True)).join(twice, F.lit(True)).join(out, F.lit(True))


def check_clustering(g: BlockGraph, clusters: DataFrame, bound: int) -> DataFrame:
    """(cluster, weight) of clusters of several vertices that weigh more than the bound."""
    w = g.vertices.join(clusters, "id").groupBy("cluster").agg(F.sum("weight").alias("weight"), F.count(F.lit(1)).alias("n"))
    return w.where((F.col("weight") > bound) & (F.col("n") > 1)).select("cluster", "weight")
