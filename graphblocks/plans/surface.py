"""Queries of files and tables, user functions of each kind, streams that go on, and the accounting of steps."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.hashes import mix_np, mix_sql
from ..operators import accounting as A
from ..operators import coarsening as C
from ..operators import measures as M
from ..operators import refinement as R
from ..sources import files as Files
from ..sources.tables import GRAPHS, load
from ..storage import shared_dir, stash
from ..streaming import edges as S
from . import evaluation as E
from .multilevel import floor_blocks
from .queries import K, PART_SQL, QUERIES, _DEG, _g, _gp, _packets_sql, _with, query

EDGES = "SELECT src, dst, weight FROM e"


def _folder(s) -> str:
    return f"{shared_dir(s)}/file-{uuid.uuid4().hex}"


# -- files and tables ---------------------------------------------------------------


@query("s_edge_list", _with() + EDGES)
def _(s, d):
    at = _folder(s)
    Files.write_edge_list(_g(s, d), at)
    return Files.read_edge_list(s, at).edges


@query("s_edge_list_names", _with("names AS (SELECT name, row_number() OVER (ORDER BY name) - 1 AS i FROM (SELECT DISTINCT src::VARCHAR AS name FROM arcs))") + "SELECT least(a.i, b.i) AS src, greatest(a.i, b.i) AS dst, weight FROM e JOIN names a ON a.name = src::VARCHAR JOIN names b ON b.name = dst::VARCHAR")
def _(s, d):
    at = _folder(s)
    Files.write_edge_list(_g(s, d), at)
    return Files.read_edge_list(s, at, names=True).edges


_NUMBERS = "num AS (SELECT id, row_number() OVER (ORDER BY id) AS i FROM v)"


@query("s_adjacency", _with(_NUMBERS) + "SELECT least(a.i, b.i) AS src, greatest(a.i, b.i) AS dst, weight FROM e JOIN num a ON a.id = src JOIN num b ON b.id = dst")
def _(s, d):
    at = _folder(s)
    Files.write_adjacency(_g(s, d).stored(), at)
    return Files.read_adjacency(s, at).edges


@query("s_partition_file", _with(PART_SQL) + "SELECT id, block FROM part")
def _(s, d):
    g, part = _gp(s, d)
    at = _folder(s)
    Files.write_partition(part, at)
    return Files.read_partition(g.vertices, at)


@query("s_bucketed_level", _with() + "SELECT src AS id, count(*) AS degree, sum(weight)::BIGINT AS strength FROM arcs GROUP BY src")
def _(s, d):
    name = f"level_{uuid.uuid4().hex[:8]}"
    Files.save_level(_g(s, d), name, _folder(s))
    arcs, vertices = Files.load_level(s, name)
    return arcs.join(vertices, arcs["src"] == vertices["id"]).groupBy("id").agg(F.count(F.lit(1)).alias("degree"), F.sum(arcs["weight"]).alias("strength"))


@query("s_run_log", f"WITH {E.synthetic_sql()} SELECT graph, algo, count(*) AS runs, sum(cut)::BIGINT AS cuts FROM runs WHERE graph IN ('g1', 'g5') GROUP BY ALL")
def _(s, d):
    at = _folder(s)
    runs = E.synthetic_runs(s)
    Files.append_runs(runs.where("seed < 5"), at)
    Files.append_runs(runs.where("seed >= 5"), at)
    return Files.read_runs(s, at).where("graph IN ('g1', 'g5')").groupBy("graph", "algo").agg(F.count(F.lit(1)).alias("runs"), F.sum("cut").alias("cuts"))


_VIEW_SQL = "SELECT b.block, count(*) AS arcs, sum(a.weight)::BIGINT AS weight FROM {p}arcs a JOIN {b} b ON a.src = b.id GROUP BY b.block"


@query("s_views", _with(PART_SQL) + _VIEW_SQL.format(p="", b="part"))
def _(s, d):
    prefix = f"g{uuid.uuid4().hex[:8]}"
    Files.register_views(*_gp(s, d), prefix)
    return s.sql(_VIEW_SQL.format(p=f"{prefix}_", b=f"{prefix}_blocks").replace("::BIGINT", ""))


# -- user functions -----------------------------------------------------------------


@query("f_scalar", _with() + f"SELECT id, ({mix_sql('id', 5)} % {K})::INTEGER AS block FROM v")
def _(s, d):
    @F.pandas_udf("int")
    def block_of(ids: pd.Series) -> pd.Series:
        return pd.Series(mix_np(ids.to_numpy("int64"), 5) % K).astype("int32")

    return _g(s, d).vertices.select("id", block_of("id").alias("block"))


@query("f_grouped_aggregate", _with(PART_SQL) + "SELECT block, sum(d * d)::BIGINT AS squares FROM (SELECT src AS id, count(*) AS d FROM arcs GROUP BY src) JOIN part USING (id) GROUP BY block")
def _(s, d):
    @F.pandas_udf("long")
    def squares(x: pd.Series) -> int:
        return int((x.astype("int64") ** 2).sum())

    g, part = _gp(s, d)
    return M.degrees(g).join(part, "id").where("degree > 0").groupBy("block").agg(squares("degree").alias("squares"))


@query("f_cogrouped", _with(PART_SQL) + f"SELECT id, CASE WHEN id % 5 = 0 THEN ((block + 1) % {K})::INTEGER ELSE block END AS block FROM part")
def _(s, d):
    part = stash(_gp(s, d)[1])
    moves = stash(part.where("id % 5 = 0").select("id", F.pmod(F.col("block") + 1, F.lit(K)).cast("int").alias("to_block")))
    shard = lambda df: df.withColumn("shard", F.pmod("id", F.lit(64)))

    def apply(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        to = dict(zip(b["id"], b["to_block"]))
        return pd.DataFrame({"id": a["id"], "block": pd.Series([to.get(i, x) for i, x in zip(a["id"], a["block"])], dtype="int32")})

    return shard(part).groupBy("shard").cogroup(shard(moves).groupBy("shard")).applyInPandas(apply, "id long, block int")


@F.udtf(returnType="src: bigint, dst: bigint")
class GridEdges:
    """The edges of a grid, by rows."""

    def eval(self, rows: int, columns: int) -> Iterator[tuple[int, int]]:
        for i in range(rows * columns):
            if (i + 1) % columns:
                yield i, i + 1
            if i + columns < rows * columns:
                yield i, i + columns


@query("f_table_function", "SELECT i AS src, j AS dst FROM (SELECT unnest(range(96)) AS i) JOIN (SELECT unnest(range(96)) AS j) ON (j = i + 1 AND j % 12 <> 0) OR j = i + 12")
def _(s, d):
    s.udtf.register("grid_edges", GridEdges)
    return s.sql("SELECT src, dst FROM grid_edges(8, 12)")


@query("f_sql_gain", _with(PART_SQL) + "SELECT id, sum(CASE WHEN b.block = a.block THEN weight ELSE 0 END)::BIGINT AS inner_weight FROM arcs JOIN part a ON arcs.src = a.id JOIN (SELECT id AS other, block FROM part) b ON arcs.dst = b.other GROUP BY id")
def _(s, d):
    prefix = f"g{uuid.uuid4().hex[:8]}"
    Files.register_views(*_gp(s, d), prefix)
    return s.sql(f"SELECT a.id, sum(CASE WHEN b.block = a.block THEN weight ELSE 0 END) AS inner_weight FROM {prefix}_arcs JOIN {prefix}_blocks a ON src = a.id JOIN {prefix}_blocks b ON dst = b.id GROUP BY a.id")


# -- streams ------------------------------------------------------------------------

_HALF = "(SELECT min(ts) + (max(ts) - min(ts)) / 2 FROM events)"


@query("t_late_rows", f"WITH b AS (SELECT ts, CASE WHEN ts >= {_HALF} AND event_id % 2 = 0 THEN 0 ELSE 1 END AS batch FROM events), h AS (SELECT max(ts) AS high FROM b WHERE batch = 0) SELECT batch, count(*) AS rows, sum(CASE WHEN batch = 1 AND ts < high - INTERVAL 600 SECOND THEN 1 ELSE 0 END)::BIGINT AS late FROM b, h GROUP BY batch")
def _(s, d):
    e = load(s, d, "events")
    low, high = e.agg(F.min("ts"), F.max("ts")).first()
    first = (F.col("ts") >= F.lit(low + (high - low) / 2)) & (F.col("event_id") % 2 == 0)
    return S.late_rows([e.where(first), e.where(~first)], 600)


@query("t_restart", "SELECT event_id FROM events")
def _(s, d):
    return S.restarted(load(s, d, "events"))


@query("t_incremental", "SELECT (SELECT count(*) FROM (SELECT 2 * user_id AS id FROM events UNION SELECT 2 * json_extract_string(props, '$.k')::BIGINT + 1 FROM events)) AS n, true AS covered, true AS feasible, true AS never_worse")
def _(s, d):
    part, figures = S.incremental_refinement(S.stream_edges(S.stream_events(s, d)), K, 0.1)
    fine = all(f["heaviest"] <= f["bound"] for f in figures), all(f["cut"] <= f["before"] for f in figures)
    return part.agg(F.count_distinct("id").alias("n"), (F.count(F.lit(1)) == F.count_distinct("id")).alias("covered")).select("n", "covered", F.lit(fine[0]).alias("feasible"), F.lit(fine[1]).alias("never_worse"))


@query("t_assign_full", "SELECT count(DISTINCT user_id)::BIGINT AS vertices, 0::BIGINT AS beyond, true AS some_left FROM events")
def _(s, d):
    """With too little room the sizes still keep to the bound, and what is left has block -1."""
    v = S.stream_events(s, d).select(F.col("user_id").alias("id"), (F.col("user_id") % 7).alias("tie")).dropDuplicates(["id"])
    n = load(s, d, "events").select("user_id").distinct().count()
    bound = max(4, n // (2 * K))
    part = stash(S.drained(S.streaming_assign(v, 4, K, bound)))
    sizes = part.where("block >= 0").groupBy("block").count()
    beyond = sizes.where(F.col("count") > bound).agg(F.count(F.lit(1)).alias("beyond"))
    return part.agg(F.count(F.lit(1)).alias("vertices"), (F.min("block") < 0).alias("some_left")).join(beyond).select("vertices", "beyond", "some_left")


# -- accounting ---------------------------------------------------------------------


@query("a_work_span", _with(_DEG) + f"SELECT sub_round, sum(s)::BIGINT AS work, max(s)::BIGINT AS span FROM (SELECT sub_round, packet % 4 AS pe, sum(degree + 1) AS s FROM ({_packets_sql('deg', 500, 4, 0)}) GROUP BY ALL) GROUP BY sub_round")
def _(s, d):
    return A.work_and_span(C.make_packets(_g(s, d), None, 500, 4), 4)


@query("a_search_work", _with(_DEG) + "SELECT (id % 4)::INTEGER AS pe, count(*) AS moved, sum(degree)::BIGINT AS scanned FROM deg WHERE id % 3 = 0 GROUP BY pe")
def _(s, d):
    g = _g(s, d)
    moves = g.vertices.where("id % 3 = 0").select("id", F.pmod("id", F.lit(4)).cast("int").alias("pe"))
    return A.search_work(moves, M.degrees(g))


def _inner(expr: str) -> str:
    return f"SELECT sum(({expr.format('src')} = {expr.format('dst')})::INTEGER)::BIGINT AS inner, count(*) AS edges FROM e"


_RANGE = "(({} - (SELECT min(id) FROM v)) // (((SELECT max(id) - min(id) + 1 FROM v) + 7) // 8))"


@query("h_locality_range", _with(graph="conv_path") + _inner(_RANGE).replace("AS inner", 'AS "inner"'))
def _(s, d):
    g = GRAPHS["conv_path"](s, d)
    return A.inner_edges(g, A.by_range(g, 8))


@query("h_locality_hash", _with(graph="conv_path") + f"SELECT sum(({mix_sql('src', 1)} % 8 = {mix_sql('dst', 1)} % 8)::INTEGER)::BIGINT AS \"inner\", count(*) AS edges FROM e")
def _(s, d):
    return A.inner_edges(GRAPHS["conv_path"](s, d), A.by_hash(8))


@query("e_component_effect", f"WITH {E.table_sql()}, {E.INSTANCES_SQL}, g AS (SELECT algo, exp(avg(ln(cut))) AS x FROM inst WHERE p = 16 GROUP BY algo) SELECT a.algo AS component, round((a.x / b.x - 1) * 100, 4) AS percent FROM g a, g b WHERE b.algo = 'seq' AND a.algo <> 'seq'")
def _(s, d):
    return E.component_effect(E.table_runs(s, d), "seq", 16)


@query("e_phase_speedup", f"WITH {E.table_sql()}, {E.INSTANCES_SQL}, x AS (SELECT a.algo, b.p, a.t_ls / b.t_ls AS ls, (a.t_total - a.t_ls) / (b.t_total - b.t_ls) AS rest FROM inst a JOIN inst b ON a.graph = b.graph AND a.k = b.k AND a.algo = b.algo AND a.p = 1 AND b.p > 1 WHERE NOT a.imbalanced AND NOT b.imbalanced) SELECT algo, p, round(count(*) / sum(1 / ls), 6) AS search, round(count(*) / sum(1 / rest), 6) AS other FROM x GROUP BY ALL")
def _(s, d):
    return E.phase_speedup(E.table_runs(s, d))


QUERIES["g_emb_del"] = lambda s, d: GRAPHS["emb_del"](s, d).edges.select("src", "dst", "weight")


@query("op_grouping_sets", _with(PART_SQL) + "SELECT coalesce(block, -1) AS block, coalesce(side, -1) AS side, count(*) AS vertices FROM (SELECT block, id % 2 AS side FROM part) GROUP BY GROUPING SETS ((block), (side), ())")
def _(s, d):
    _, part = _gp(s, d)
    p = part.withColumn("side", F.col("id") % 2)
    return p.groupingSets([[F.col("block")], [F.col("side")], []], "block", "side").agg(F.count(F.lit(1)).alias("vertices")).select(F.coalesce("block", F.lit(-1)).alias("block"), F.coalesce("side", F.lit(-1).cast("long")).alias("side"), "vertices")
