"""Queries on keys beyond those of the small tables."""

import duckdb
from pyspark.sql import functions as F

from graphblocks.plans import queries


def same(got, want):
    return sorted(map(tuple, got)) == sorted(want)


def test_math_bound_of_large_customer_keys(spark, tmp_path):
    """Customers up to 60 times those of sf0.1, and those at which cosh overflows."""
    rows = spark.range(1, 900001, 7).select(F.col("id").alias("o_orderkey"), F.col("id").alias("o_custkey"), (F.col("id") % 997 + 1.25).alias("o_totalprice"))
    rows.write.parquet(f"{tmp_path}/orders.parquet")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW orders AS SELECT * FROM read_parquet('{tmp_path}/orders.parquet/*.parquet')")
    assert same(queries.QUERIES["fn_math_bound"](spark, str(tmp_path)).collect(), con.sql(queries.SQL["fn_math_bound"]).fetchall())
