"""Evaluation queries read their log from a given table and agree with SQL."""

import duckdb
import pytest

from graphblocks.plans import queries, surface  # noqa: F401

READ = ("e_best_share", "e_by_type", "e_component_effect", "e_effectiveness_dist", "e_effectiveness_match", "e_effectiveness_seq", "e_geomean", "e_memory_saving", "e_ns_per_edge", "e_phase_speedup", "e_profile", "e_relative")


@pytest.mark.parametrize("name", READ)
def test_log_is_read(spark, name):
    """On two sizes with other results, so the table counts."""
    seen = []
    for d in ("/root/testdata/sf0.001", "/root/testdata/sf0.01"):
        out = queries.QUERIES[name](spark, d)
        assert any(f.endswith("lineitem.parquet") for f in out.inputFiles())
        con = duckdb.connect()
        con.sql(f"CREATE VIEW lineitem AS SELECT * FROM '{d}/lineitem.parquet'")
        want = con.sql(f"SELECT {', '.join(f'"{c}"' for c in out.columns)} FROM ({queries.SQL[name]})").fetchall()
        seen.append(sorted(tuple(x) for x in out.collect()))
        assert seen[-1] == sorted(tuple(float(v) if type(v).__name__ == "Decimal" else v for v in x) for x in want) and want
    assert seen[0] != seen[1]
