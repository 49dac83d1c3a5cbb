"""A stored graph makes its edges once; its vertices come from them."""

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from graphblocks.sources import tables


def test_edges_are_made_once(spark):
    made = spark.sparkContext.accumulator(0)

    @F.udf(LongType())
    def seen(x):
        made.add(1)
        return x

    edges = spark.range(0, 50, 1, 2).select(seen.asNondeterministic()("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1).cast("long").alias("weight"))
    g = tables._graph(edges, spark.range(60).select("id")).stored()
    assert g.vertices.count() == 60 and g.edges.count() == 50
    assert made.value == 50


def test_shingles_of_too_many_documents_give_no_edge(spark, tmp_path):
    texts = ["a b c d e"] * 3 + ["f g h i j a b c d e"] * 2 + [None, "a b"]
    pd.DataFrame({"doc_id": range(7), "text": texts}).to_parquet(tmp_path / "documents.parquet")
    pairs = lambda most: sorted((r.src, r.dst, r.weight) for r in tables.doc_overlap(spark, str(tmp_path), most=most).edges.collect())
    assert pairs(4) == [(3, 4, 5)]
    assert pairs(5) == [(0, 1, 1), (0, 2, 1), (0, 3, 1), (0, 4, 1), (1, 2, 1), (1, 3, 1), (1, 4, 1), (2, 3, 1), (2, 4, 1), (3, 4, 6)]
