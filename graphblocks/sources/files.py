"""Graphs and partitions as files and tables: edge lists, adjacency lines, block files, bucketed levels, run logs, views.

All paths are read and written by Spark alone, so they can be in any store that
the executors share.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import BlockGraph, encode_ids, normalize_graph
from ..operators.prefix import dense_ids, prefix_sum


def write_edge_list(g: BlockGraph, path: str, separator: str = "\t") -> None:
    """A line ``src separator dst separator weight`` for each edge; vertices without an edge aren't written."""
    g.edges.select(F.concat_ws(separator, "src", "dst", "weight").alias("value")).write.mode("overwrite").text(path)


def read_edge_list(spark: SparkSession, path: str, separator: str = "\t", comment: str = "#", names: bool = False) -> BlockGraph:
    """Lines of two ends and, if there is a third field, a weight; else 1.  Empty lines and those that start with ``comment`` are left out.

    With ``names`` the ends are strings, numbered by name; else they are integers.  Edges in both directions and
    repeated ones are summed, loops go.
    """
    lines = spark.read.text(path).where((F.trim("value") != "") & ~F.col("value").startswith(comment))
    cut = F.split("value", separator)
    edges = lines.select(F.get(cut, F.lit(0)).alias("src"), F.get(cut, F.lit(1)).alias("dst"), F.coalesce(F.get(cut, F.lit(2)).cast("long"), F.lit(1)).cast("long").alias("weight"))
    if names:
        edges, _ = encode_ids(edges)
    else:
        edges = edges.select(F.col("src").cast("long"), F.col("dst").cast("long"), "weight")
    return normalize_graph(edges)


def write_adjacency(g: BlockGraph, path: str) -> DataFrame:
    """A line ``number TAB neighbour:weight ...`` for each vertex, numbered from 1 by id; returns (id, number).

    The number in front makes the lines independent of their order, so many tasks read and write them.
    """
    numbers = dense_ids(g.vertices.select("id"), "id", "number").select("id", (F.col("number") + 1).alias("number"))
    ends = g.arcs().join(numbers.select(F.col("id").alias("src"), F.col("number").alias("a")), "src").join(numbers.select(F.col("id").alias("dst"), F.col("number").alias("b")), "dst")
    lists = ends.groupBy("a").agg(F.array_sort(F.collect_list(F.struct("b", "weight"))).alias("near"))
    lines = numbers.join(lists, F.col("number") == F.col("a"), "left")
    near = F.array_join(F.transform("near", lambda x: F.concat_ws(":", x["b"], x["weight"])), " ")
    lines.select(F.concat_ws("\t", "number", F.coalesce(near, F.lit(""))).alias("value")).write.mode("overwrite").text(path)
    return numbers


def read_adjacency(spark: SparkSession, path: str) -> BlockGraph:
    """The graph of ``write_adjacency``'s lines, with the numbers as ids; every edge stands at both ends and counts once."""
    lines = spark.read.text(path).select(F.split("value", "\t").alias("cut"))
    lines = lines.select(F.get("cut", F.lit(0)).cast("long").alias("src"), F.get("cut", F.lit(1)).alias("near"))
    arcs = lines.where("near <> ''").select("src", F.explode(F.split("near", " ")).alias("x"))
    cut = F.split("x", ":")
    arcs = arcs.select("src", F.get(cut, F.lit(0)).cast("long").alias("dst"), F.get(cut, F.lit(1)).cast("long").alias("weight"))
    return normalize_graph(arcs.where("src < dst"), lines.select(F.col("src").alias("id"), F.lit(1).cast("long").alias("weight")))


def write_partition(part: DataFrame, path: str) -> None:
    """(id, block) as lines ``place block`` by ascending id, places from 0 on; lines can be read in any order."""
    placed = prefix_sum(part, [F.col("id")], F.lit(1).cast("long"), "place")
    placed.select(F.concat_ws(" ", "place", "block").alias("value")).write.mode("overwrite").text(path)


def read_partition(vertices: DataFrame, path: str) -> DataFrame:
    """(id, block) of ``write_partition``'s lines for these vertices."""
    cut = F.split("value", " ")
    lines = vertices.sparkSession.read.text(path).select(F.get(cut, F.lit(0)).cast("long").alias("place"), F.get(cut, F.lit(1)).cast("int").alias("block"))
    return dense_ids(vertices.select("id"), "id", "place").join(lines, "place").select("id", "block")


def save_level(g: BlockGraph, name: str, path: str, buckets: int = 8) -> None:
    """Arcs and vertices of a level as tables bucketed and sorted by vertex, so that steps join them without a shuffle."""
    g.arcs().write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").option("path", f"{path}/arcs").saveAsTable(f"{name}_arcs")
    g.vertices.write.mode("overwrite").bucketBy(buckets, "id").sortBy("id").option("path", f"{path}/vertices").saveAsTable(f"{name}_vertices")


def load_level(spark: SparkSession, name: str) -> tuple[DataFrame, DataFrame]:
    """(arcs, vertices) of a saved level."""
    return spark.table(f"{name}_arcs"), spark.table(f"{name}_vertices")


def append_runs(runs: DataFrame, path: str) -> None:
    """Adds rows to a run log, a folder for each graph; reads of one graph touch its folder only."""
    runs.write.mode("append").partitionBy("graph").parquet(path)


def read_runs(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def register_views(g: BlockGraph, part: DataFrame | None, prefix: str = "graph") -> None:
    """Views ``prefix_vertices``, ``prefix_edges``, ``prefix_arcs`` and, with a partition, ``prefix_blocks`` for SQL."""
    g.vertices.createOrReplaceTempView(f"{prefix}_vertices")
    g.edges.createOrReplaceTempView(f"{prefix}_edges")
    g.arcs().createOrReplaceTempView(f"{prefix}_arcs")
    if part is not None:
        part.createOrReplaceTempView(f"{prefix}_blocks")
