"""Sums and numbers over a global order, in two levels: never one window over all rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..storage import stash


def prefix_sum(df: DataFrame, order: list[Column], value: Column, name: str = "before") -> DataFrame:
    """Adds the sum of ``value`` over all rows that come earlier in ``order`` (which must tell rows apart).

    Rows are dealt out by ranges and stored; a window runs inside each range, and
    the totals of the ranges, as many rows as there are tasks, are summed up and
    joined back.
    """
    parts = stash(df.repartitionByRange(*order).withColumns({"_part": F.spark_partition_id(), "_value": value}))
    totals = parts.groupBy("_part").agg(F.sum("_value").alias("_sum"))
    earlier = totals.select(F.col("_part").alias("_p"), "_sum")
    offsets = totals.select("_part").join(earlier, F.col("_p") < F.col("_part"), "left").groupBy("_part").agg(F.coalesce(F.sum("_sum"), F.lit(0)).alias("_offset"))
    inside = Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    out = parts.withColumn("_inside", F.coalesce(F.sum("_value").over(inside), F.lit(0))).join(F.broadcast(offsets), "_part")
    return out.withColumn(name, (F.col("_inside") + F.col("_offset")).cast("long")).drop("_part", "_value", "_inside", "_offset")


def dense_ids(df: DataFrame, by: str, name: str) -> DataFrame:
    """Adds numbers 0, 1, ... in the order of a column with distinct values."""
    return prefix_sum(df, [F.col(by)], F.lit(1).cast("long"), name)
