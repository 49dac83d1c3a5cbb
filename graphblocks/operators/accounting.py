"""Work and span of a step as DataFrames, and how local a distribution of vertices is."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashes import mix
from ..model import BlockGraph


def work_and_span(packets: DataFrame, p: int) -> DataFrame:
    """(sub_round, work, span) of label propagation over packets (id, degree, packet, sub_round) dealt round to p PEs.

    Work is what all PEs scan, span what the busiest one does; the span is between work / p and work.
    """
    by_pe = packets.groupBy("sub_round", F.pmod("packet", F.lit(p)).alias("pe")).agg(F.sum(F.col("degree") + 1).alias("scanned"))
    return by_pe.groupBy("sub_round").agg(F.sum("scanned").alias("work"), F.max("scanned").alias("span"))


def search_work(moves: DataFrame, degrees: DataFrame) -> DataFrame:
    """(pe, moved, scanned): the moves of each PE and the degrees of the moved vertices, which a replay has to scan."""
    return moves.join(degrees, "id").groupBy("pe").agg(F.count(F.lit(1)).alias("moved"), F.sum("degree").alias("scanned"))


def by_range(g: BlockGraph, parts: int) -> Column:
    """The part of an id if ids from the least to the largest are cut into equal ranges: neighbours by number stay together."""
    low, high = g.vertices.agg(F.min("id"), F.max("id")).first()
    width = max(1, -(-((high or 0) - (low or 0) + 1) // parts))
    return F.floor((F.col("id") - F.lit(low or 0)) / F.lit(width)).cast("int")


def by_hash(parts: int, seed: int = 1) -> Column:
    return F.pmod(mix("id", seed), F.lit(parts)).cast("int")


def inner_edges(g: BlockGraph, part: Column) -> DataFrame:
    """(inner, edges): the edges whose ends are in one part of a distribution of the ids, and all."""
    home = g.vertices.select("id", part.alias("home"))
    e = g.edges.join(home.select(F.col("id").alias("src"), F.col("home").alias("a")), "src").join(home.select(F.col("id").alias("dst"), F.col("home").alias("b")), "dst")
    return e.agg(F.coalesce(F.sum((F.col("a") == F.col("b")).cast("long")), F.lit(0)).alias("inner"), F.count(F.lit(1)).alias("edges"))
