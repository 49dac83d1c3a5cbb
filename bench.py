"""Runs the headline queries once each and prints one JSON line with their seconds."""

from __future__ import annotations

import json
import os
import time
from importlib.util import find_spec

from pyspark.sql import SparkSession

from graphblocks.plans import queries as Q
from graphblocks.plans import surface  # noqa: F401  (adds to the queries)
from graphblocks.plans import workloads as W

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
GRAPH = ["g_part_copurchase", "g_doc_overlap", "m_cut", "m_gain", "m_quotient", "c_packets", "c_contract", "c_matching_round1", "h_local_tabular", "e_effectiveness_match", "s_adjacency", "s_bucketed_level", "a_work_span"]


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    queries = {n: Q.QUERIES[n] for n in GRAPH}
    if find_spec("graphblocks.llm") is not None:
        from graphblocks.llm import queries as L

        queries |= L.queries()
        if find_spec("corpus_pipeline") is not None:
            import corpus_pipeline

            queries["pipeline"] = corpus_pipeline.run
    spark.range(1000).selectExpr("sum(id)").collect()  # starts the session's code
    seconds: dict[str, float] = {}
    for name, f in queries.items():
        began = time.perf_counter()
        f(spark, SF_DIR).write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - began, 3)

    # The full pipeline and its rivals on the link graph: cut and nanoseconds per edge.
    csr = W.csr_of(spark, SF_DIR, "page_links")
    m = len(csr.nbr) // 2
    cuts, per_edge = {}, {}
    for algo, cfg in W.VARIANTS.items():
        began = time.perf_counter()
        block, _ = W.partition_csr(csr, 16, 0.03, 4, 0, cfg)
        seconds[f"partition_{algo}"] = round(time.perf_counter() - began, 3)
        cuts[algo], per_edge[algo] = csr.cut(block), round(seconds[f"partition_{algo}"] * 1e9 / m, 1)
    print(json.dumps({"metric": "sum of the headline queries", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(SF_DIR.rstrip("/")), "cuts": cuts, "ns_per_edge": per_edge}))
    spark.stop()


if __name__ == "__main__":
    main()
