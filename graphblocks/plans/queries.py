"""The registered queries of the graph engine, with the DuckDB SQL of the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.floats import cosh_rounded
from ..functions.hashes import mix, mix_sql, tabular_hash, tabular_hash_sql
from ..model import BlockGraph
from ..operators import coarsening as C
from ..operators import measures as M
from ..operators import refinement as R
from ..sources import tables as T
from ..sources.tables import GRAPHS, graph_ctes, load
from ..storage import stash
from ..streaming import edges as S
from . import evaluation as E
from .multilevel import floor_blocks

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}

K, EPS = 4, 0.03
#: The graph of the step queries, and its floor partition.
G0 = "cust_supp"
PART_SQL = f"part AS (SELECT id, ({mix_sql('id', 1)} % {K})::INTEGER AS block FROM v)"


def query(name: str, sql: str | None = None):
    def put(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return put


def _g(s: SparkSession, d: str, name: str = G0) -> BlockGraph:
    return GRAPHS[name](s, d)


def _gp(s: SparkSession, d: str, name: str = G0) -> tuple[BlockGraph, DataFrame]:
    g = _g(s, d, name)
    return g, floor_blocks(g, K, "hash")


def _with(*ctes: str, graph: str = G0, recursive: bool = False) -> str:
    return f"WITH {'RECURSIVE ' if recursive else ''}" + ", ".join([graph_ctes(graph), *ctes]) + " "


# -- sources ------------------------------------------------------------------

for _name in GRAPHS:
    if _name in T.EDGES_SQL:
        QUERIES[f"g_{_name}"] = lambda s, d, n=_name: GRAPHS[n](s, d).edges.select("src", "dst", "weight")
        SQL[f"g_{_name}"] = T.EDGES_SQL[_name]

_ALL = [n for n in GRAPHS if n in T.EDGES_SQL and n not in ("doc_overlap", "contamination", "emb_knn")]


@query("w16_instances", " UNION ALL ".join(f"SELECT * FROM (WITH {graph_ctes(n)} SELECT '{n}' AS graph, (SELECT count(*) FROM v) AS n, (SELECT count(*) FROM e) AS m, (SELECT sum(weight)::BIGINT FROM e) AS total_edge_weight)" for n in _ALL))
def _(s, d):
    out = None
    for n in _ALL:
        row = M.graph_stats(_g(s, d, n)).select(F.lit(n).alias("graph"), "n", "m", "total_edge_weight")
        out = row if out is None else out.unionByName(row)
    return out


# -- measures -----------------------------------------------------------------


@query("m_degrees", _with() + "SELECT v.id, count(a.src)::BIGINT AS degree, coalesce(sum(a.weight), 0)::BIGINT AS wdegree FROM v LEFT JOIN arcs a ON v.id = a.src GROUP BY v.id")
def _(s, d):
    return M.degrees(_g(s, d))


@query("m_stats", _with() + "SELECT (SELECT count(*) FROM v) AS n, (SELECT count(*) FROM e) AS m, (SELECT sum(weight)::BIGINT FROM v) AS total_vertex_weight, (SELECT sum(weight)::BIGINT FROM e) AS total_edge_weight, (SELECT max(c) FROM (SELECT count(*) AS c FROM arcs GROUP BY src)) AS max_degree")
def _(s, d):
    return M.graph_stats(_g(s, d))


_WEIGHTS = f"bw AS (SELECT b.block, count(p.id)::BIGINT AS vertices, coalesce(sum(v.weight), 0)::BIGINT AS weight FROM (SELECT unnest(range({K}))::INTEGER AS block) b LEFT JOIN part p ON p.block = b.block LEFT JOIN v ON v.id = p.id GROUP BY b.block)"


@query("m_block_weights", _with(PART_SQL, _WEIGHTS) + "SELECT * FROM bw")
def _(s, d):
    return M.block_weights(*_gp(s, d), K)


@query("m_lmax", _with() + f"SELECT floor({1 + EPS} * ceil(sum(weight) / {K}))::BIGINT AS bound, sum(weight)::BIGINT AS total FROM v")
def _(s, d):
    total = _g(s, d).vertices.agg(F.sum("weight").alias("total"))
    return total.select(F.floor(F.lit(1030000) * F.ceil(F.col("total") / K) / 1000000).cast("long").alias("bound"), "total")


@query("m_overloaded", _with(PART_SQL, _WEIGHTS) + f"SELECT block, weight, floor(1.0 * ceil((SELECT sum(weight) FROM v) / {K}))::BIGINT AS bound FROM bw WHERE weight > floor(1.0 * ceil((SELECT sum(weight) FROM v) / {K}))")
def _(s, d):
    g, p = _gp(s, d)
    return M.overloaded(g, p, K, 0.0)


_BLOCKS = "eb AS (SELECT e.*, a.block AS ba, b.block AS bb FROM e JOIN part a ON a.id = e.src JOIN part b ON b.id = e.dst)"


@query("m_cut", _with(PART_SQL, _BLOCKS) + "SELECT sum(weight)::BIGINT AS cut, count(*) AS cut_edges FROM eb WHERE ba <> bb")
def _(s, d):
    return M.edge_cut(*_gp(s, d))


@query("m_boundary", _with(PART_SQL, _BLOCKS) + "SELECT src AS id FROM eb WHERE ba <> bb UNION SELECT dst FROM eb WHERE ba <> bb")
def _(s, d):
    return M.boundary(*_gp(s, d))


_CONN = "conn AS (SELECT a.src AS id, p.block AS label, sum(a.weight)::BIGINT AS strength FROM arcs a JOIN part p ON p.id = a.dst GROUP BY ALL)"


@query("m_connections", _with(PART_SQL, _CONN) + "SELECT * FROM conn")
def _(s, d):
    return M.connections(*_gp(s, d))


def _gain_sql(extra: str, ctes: str = "") -> str:
    return _with(PART_SQL, _CONN, *([ctes] if ctes else [])) + f"""SELECT id, best_block, (s - stay)::BIGINT AS gain FROM (
 SELECT c.id, c.label AS best_block, c.strength AS s, coalesce((SELECT strength FROM conn o WHERE o.id = c.id AND o.label = p.block), 0) AS stay,
 row_number() OVER (PARTITION BY c.id ORDER BY c.strength DESC, {mix_sql('c.label::BIGINT', 0)} DESC, c.label DESC) AS r
 FROM conn c JOIN part p ON p.id = c.id JOIN v ON v.id = c.id WHERE c.label <> p.block {extra}) WHERE r = 1"""


@query("m_gain", _gain_sql(""))
def _(s, d):
    return M.gain(*_gp(s, d))


@query("m_feasible_gain", _gain_sql(f"AND (SELECT weight FROM bw WHERE bw.block = c.label) + v.weight <= ceil((SELECT sum(weight) FROM v) / {K})", _WEIGHTS))
def _(s, d):
    g, p = _gp(s, d)
    total = g.vertices.agg(F.sum("weight")).first()[0]
    return M.gain(g, p, M.l_max(total, K, 0.0), 0, K)


@query("m_quotient", _with(PART_SQL, _BLOCKS) + "SELECT least(ba, bb)::BIGINT AS src, greatest(ba, bb)::BIGINT AS dst, sum(weight)::BIGINT AS weight FROM eb WHERE ba <> bb GROUP BY ALL")
def _(s, d):
    return M.quotient(*_gp(s, d)).edges


@query("m_check_partition", _with(PART_SQL) + f"SELECT (SELECT count(*) FROM v ANTI JOIN part USING (id)) AS uncovered, (SELECT count(*) FROM part ANTI JOIN v USING (id)) AS unknown, (SELECT count(*) FROM (SELECT id FROM part GROUP BY id HAVING count(*) > 1)) AS repeated, (SELECT count(*) FROM part WHERE block < 0 OR block >= {K} OR block IS NULL) AS out_of_range")
def _(s, d):
    return M.check_partition(*_gp(s, d), K)


@query("m_check_clustering", _with("cl AS (SELECT id, id // 3 AS cluster FROM v)") + "SELECT cluster, sum(weight)::BIGINT AS weight FROM cl JOIN v USING (id) GROUP BY cluster HAVING count(*) > 1 AND sum(weight) > 2")
def _(s, d):
    g = _g(s, d)
    return M.check_clustering(g, g.vertices.select("id", F.floor(F.col("id") / 3).alias("cluster")), 2)


# -- hashing ------------------------------------------------------------------


@query("h_mix", f"SELECT o_orderkey AS id, {mix_sql('o_orderkey', 7)} AS h FROM orders")
def _(s, d):
    return load(s, d, "orders").select(F.col("o_orderkey").alias("id"), mix("o_orderkey", 7).alias("h"))


@query("h_tabular", f"SELECT o_orderkey AS id, {tabular_hash_sql('o_orderkey', 10, 20, 3)} AS h FROM orders")
def _(s, d):
    return load(s, d, "orders").select(F.col("o_orderkey").alias("id"), tabular_hash("o_orderkey", 10, 20, 3).alias("h"))


@query("h_local_tabular", f"SELECT o_orderkey AS id, {tabular_hash_sql('o_orderkey', 10, 25, 3, 5)} AS h FROM orders")
def _(s, d):
    return load(s, d, "orders").select(F.col("o_orderkey").alias("id"), tabular_hash("o_orderkey", 10, 25, 3, 5).alias("h"))


@query("h_locality", f"SELECT o_orderkey >> 5 AS grp, (max(h) - min(h))::BIGINT AS spread, count(*) AS n FROM (SELECT o_orderkey, {tabular_hash_sql('o_orderkey', 10, 25, 3, 5)} AS h FROM orders) GROUP BY ALL")
def _(s, d):
    o = load(s, d, "orders").select("o_orderkey", tabular_hash("o_orderkey", 10, 25, 3, 5).alias("h"))
    return o.groupBy(F.shiftright("o_orderkey", 5).alias("grp")).agg((F.max("h") - F.min("h")).alias("spread"), F.count(F.lit(1)).alias("n"))


# -- coarsening ---------------------------------------------------------------

_DEG = "deg AS (SELECT v.id, count(a.src)::BIGINT AS degree FROM v LEFT JOIN arcs a ON v.id = a.src GROUP BY v.id)"


@query("c_degree_order", _with(_DEG) + f"SELECT id, degree, row_number() OVER (ORDER BY degree, {mix_sql('id', 0)}, id) - 1 AS position FROM deg")
def _(s, d):
    return C.degree_order(_g(s, d))


def _packets_sql(source: str, bound: int, rounds: int, seed: int) -> str:
    return f"SELECT id, degree, packet, (packet * {rounds} // (max(packet) OVER () + 1))::INTEGER AS sub_round FROM (SELECT id, degree, (coalesce(sum(degree) OVER (ORDER BY degree, {mix_sql('id', seed)}, id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) // {bound})::BIGINT AS packet FROM {source})"


@query("c_packets", _with(_DEG) + _packets_sql("deg", 1000, 4, 0))
def _(s, d):
    return C.make_packets(_g(s, d), None, 1000, 4)


_PROP = "prop AS (SELECT o_orderkey AS id, (o_orderkey % 5 + 1)::BIGINT AS weight, o_custkey % 16 AS target, o_orderkey % 7 AS gain FROM orders)"
_ADMIT_SQL = f"WITH {_PROP} SELECT id, target FROM (SELECT *, sum(weight) OVER (PARTITION BY target ORDER BY gain DESC, {mix_sql('id', 2)}, id) AS fill FROM prop) WHERE fill <= 600 - target"


def _proposals(s, d):
    o = load(s, d, "orders")
    p = o.select(F.col("o_orderkey").alias("id"), (F.col("o_orderkey") % 5 + 1).alias("weight"), (F.col("o_custkey") % 16).alias("target"), (F.col("o_orderkey") % 7).alias("gain"))
    return p, s.range(16).select(F.col("id").alias("target"), F.col("id").alias("cweight"))


@query("c_admission", _ADMIT_SQL)
def _(s, d):
    return C.admit_by_capacity(*_proposals(s, d), 600, 2)


@query("c_admission_hist", _ADMIT_SQL)
def _(s, d):
    return C.admit_by_histogram(*_proposals(s, d), 600, 2)


@query("c_admission_quota", f"WITH {_PROP} SELECT id, target FROM (SELECT *, sum(weight) OVER (PARTITION BY target, {mix_sql('id', 3)} % 4 ORDER BY gain DESC, {mix_sql('id', 2)}, id) AS fill FROM prop) WHERE fill <= (600 - target) // 4")
def _(s, d):
    return C.admit_by_quota(*_proposals(s, d), 600, 4, 2)


def lp_sql(graph: str, bound: int, rounds: int, sub_rounds: int, packet: int, seed: int = 0) -> str:
    """Label propagation unrolled into CTEs."""
    ctes = [_DEG, "l0 AS (SELECT id, id AS cluster FROM v)"]
    now, active = "l0", "deg"
    step = 0
    for r in range(rounds):
        ctes.append(f"pk{r} AS MATERIALIZED ({_packets_sql(active, packet, sub_rounds, seed + r)})")
        moved = []
        for q in range(sub_rounds):
            z = seed + 1000 * r + q
            ctes.append(f"cw{step} AS (SELECT cluster AS target, sum(weight) AS cweight FROM v JOIN {now} USING (id) GROUP BY cluster)")
            ctes.append(f"cn{step} AS MATERIALIZED (SELECT a.src AS id, l.cluster AS label, sum(a.weight) AS s FROM arcs a JOIN pk{r} ON pk{r}.id = a.src AND pk{r}.sub_round = {q} JOIN {now} l ON l.id = a.dst GROUP BY ALL)")
            ctes.append(
                f"pr{step} AS (SELECT id, label, weight, s - stay AS gain FROM (SELECT c.id, c.label, c.s, v.weight, coalesce(o.s, 0) AS stay, row_number() OVER (PARTITION BY c.id ORDER BY c.s DESC, {mix_sql('c.label', z)} DESC, c.label DESC) AS r "
                f"FROM cn{step} c JOIN v ON v.id = c.id JOIN {now} l ON l.id = c.id LEFT JOIN cn{step} o ON o.id = c.id AND o.label = l.cluster JOIN cw{step} w ON w.target = c.label WHERE c.label <> l.cluster AND w.cweight + v.weight <= {bound}) WHERE r = 1 AND s > stay)"
            )
            ctes.append(f"mv{step} AS MATERIALIZED (SELECT id, label AS target FROM (SELECT p.*, w.cweight, sum(p.weight) OVER (PARTITION BY label ORDER BY gain DESC, {mix_sql('p.id', z)}, p.id ROWS UNBOUNDED PRECEDING) AS fill FROM pr{step} p JOIN cw{step} w ON w.target = p.label) WHERE fill <= {bound} - cweight)")
            ctes.append(f"l{step + 1} AS MATERIALIZED (SELECT l.id, coalesce(m.target, l.cluster) AS cluster FROM {now} l LEFT JOIN mv{step} m ON m.id = l.id)")
            moved.append(f"SELECT id FROM mv{step}")
            step += 1
            now = f"l{step}"
        ctes.append(f"ac{r} AS MATERIALIZED (SELECT DISTINCT deg.* FROM arcs a JOIN ({' UNION '.join(moved)}) m ON m.id = a.src JOIN deg ON deg.id = a.dst)")
        active = f"ac{r}"
    return _with(*ctes, graph=graph) + f"SELECT id, cluster FROM {now}"


@query("c_sclp_round1", lp_sql("supp_supp", 12, 1, 2, 1000))
def _(s, d):
    return C.LabelPropagation(12, 1, 2, packet=1000).run(_g(s, d, "supp_supp").stored())


@query("c_sclp_round2", lp_sql("doc_source", 40, 2, 2, 200))
def _(s, d):
    return C.LabelPropagation(40, 2, 2, packet=200).run(_g(s, d, "doc_source").stored())


_TIE = f"{mix_sql(f'({mix_sql(chr(115) + chr(114) + chr(99), 3)} + {mix_sql(chr(100) + chr(115) + chr(116), 3)})', 3)}"


@query("c_matching_round1", _with(f"t AS MATERIALIZED (SELECT src, dst, weight, {_TIE} AS tie FROM e)", "b AS (SELECT src, src AS lo, dst AS hi, weight, tie FROM t UNION ALL SELECT dst, src, dst, weight, tie FROM t)", "ch AS (SELECT src, lo, hi FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY weight DESC, tie DESC, lo DESC, hi DESC) AS r FROM b) WHERE r = 1)") + "SELECT lo AS a, hi AS b FROM ch GROUP BY lo, hi HAVING count(*) = 2")
def _(s, d):
    return C.match_round(_g(s, d), None, 100, 3)


@query("c_remap", _with("cl AS (SELECT id, id // 7 * 5 AS cluster FROM v)") + "SELECT cluster, row_number() OVER (ORDER BY cluster) - 1 AS coarse_id FROM (SELECT DISTINCT cluster FROM cl)")
def _(s, d):
    return C.remap_ids(_g(s, d).vertices.select("id", (F.floor(F.col("id") / 7) * 5).alias("cluster")))


@query("c_contract", _with("cl AS (SELECT id, dense_rank() OVER (ORDER BY id // 7) - 1 AS c FROM v)") + "SELECT least(a.c, b.c) AS src, greatest(a.c, b.c) AS dst, sum(e.weight)::BIGINT AS weight FROM e JOIN cl a ON a.id = e.src JOIN cl b ON b.id = e.dst WHERE a.c <> b.c GROUP BY ALL")
def _(s, d):
    g = _g(s, d)
    return C.contract(g, g.vertices.select("id", F.floor(F.col("id") / 7).alias("cluster")))[0].edges


@query("c_contract_region", _with("cl AS (SELECT n_nationkey AS id, dense_rank() OVER (ORDER BY n_regionkey) - 1 AS c FROM nation)", graph="nation_trade") + "SELECT least(a.c, b.c)::BIGINT AS src, greatest(a.c, b.c)::BIGINT AS dst, sum(e.weight)::BIGINT AS weight FROM e JOIN cl a ON a.id = e.src JOIN cl b ON b.id = e.dst WHERE a.c <> b.c GROUP BY ALL")
def _(s, d):
    clusters = load(s, d, "nation").select(F.col("n_nationkey").cast("long").alias("id"), F.col("n_regionkey").cast("long").alias("cluster"))
    return C.contract(_g(s, d, "nation_trade"), clusters)[0].edges


@query("c_projection_equal", _with("cl AS (SELECT id, id // 7 AS c FROM v)", f"pc AS (SELECT cl.id, (dense_rank() OVER (ORDER BY c) - 1) % {K} AS block FROM cl)") + f"SELECT (SELECT sum(e.weight)::BIGINT FROM e JOIN pc a ON a.id = e.src JOIN pc b ON b.id = e.dst WHERE a.block <> b.block) AS fine_cut, (SELECT sum(e.weight)::BIGINT FROM e JOIN pc a ON a.id = e.src JOIN pc b ON b.id = e.dst WHERE a.block <> b.block) AS coarse_cut, true AS same_weights")
def _(s, d):
    g = _g(s, d)
    coarse, to = C.contract(g, g.vertices.select("id", F.floor(F.col("id") / 7).alias("cluster")))
    part = floor_blocks(coarse, K, "mod")
    fine = C.project(part, to)
    w = M.block_weights(g, fine, K).select("block", F.col("weight").alias("w")).join(M.block_weights(coarse, part, K), "block").agg(F.every(F.col("w") == F.col("weight")).alias("same_weights"))
    return M.edge_cut(g, fine).select(F.col("cut").alias("fine_cut")).join(M.edge_cut(coarse, part).select(F.col("cut").alias("coarse_cut")), F.lit(True)).join(w, F.lit(True))


@query("c_pack_isolated", "WITH lone AS (SELECT doc_id AS id FROM documents), b AS (SELECT id, (row_number() OVER (ORDER BY id) - 1) // 5 AS bin FROM lone) SELECT id, min(id) OVER (PARTITION BY bin) AS cluster FROM b")
def _(s, d):
    v = load(s, d, "documents").select(F.col("doc_id").alias("id"), F.lit(1).cast("long").alias("weight"))
    return C.pack_isolated(BlockGraph(v, s.createDataFrame([], "src long, dst long, weight long")), 10)


@query("c_next_active", _with() + "SELECT DISTINCT dst AS id FROM arcs WHERE src % 50 = 0")
def _(s, d):
    g = _g(s, d)
    return C.next_active(g, g.vertices.where("id % 50 = 0").select("id"))


# -- refinement ---------------------------------------------------------------


@query("r_project", _with() + f"SELECT id, ((dense_rank() OVER (ORDER BY id // 7) - 1) % {K})::INTEGER AS block FROM v")
def _(s, d):
    g = _g(s, d)
    coarse, to = C.contract(g, g.vertices.select("id", F.floor(F.col("id") / 7).alias("cluster")))
    return C.project(floor_blocks(coarse, K, "mod"), to)


@query("r_todo_order", _with(PART_SQL, _BLOCKS, "bd AS (SELECT src AS id FROM eb WHERE ba <> bb UNION SELECT dst FROM eb WHERE ba <> bb)") + f"SELECT id, ({mix_sql('id', 6)} % 4)::INTEGER AS pe, row_number() OVER (PARTITION BY {mix_sql('id', 6)} % 4 ORDER BY {mix_sql('id', 5)}, id)::INTEGER AS rank FROM bd")
def _(s, d):
    return R.todo_order(M.boundary(*_gp(s, d)), 4, 5)


@query("r_best_prefix", "WITH g AS (SELECT l_orderkey AS seq, l_linenumber AS step, (l_quantity::BIGINT % 11) - 5 AS gain FROM lineitem), t AS (SELECT *, sum(gain) OVER (PARTITION BY seq ORDER BY step) AS total FROM g) SELECT seq, CASE WHEN max(total) > 0 THEN arg_max(step, total * 1000 - step) ELSE 0 END::INTEGER AS best_step, greatest(max(total), 0)::BIGINT AS best_gain FROM t GROUP BY seq")
def _(s, d):
    g = load(s, d, "lineitem").select(F.col("l_orderkey").alias("seq"), F.col("l_linenumber").alias("step"), (F.col("l_quantity").cast("long") % 11 - 5).alias("gain"))
    t = g.withColumn("total", F.sum("gain").over(Window.partitionBy("seq").orderBy("step")))
    best = F.max(F.struct("total", (-F.col("step")).alias("s")))
    out = t.groupBy("seq").agg(best.alias("b"))
    return out.select("seq", F.when(F.col("b.total") > 0, -F.col("b.s")).otherwise(0).cast("int").alias("best_step"), F.greatest(F.col("b.total"), F.lit(0)).cast("long").alias("best_gain"))


@query("r_conflicts", _with("mv AS (SELECT id, (id % 3)::INTEGER AS pe, (id // 3 % 40)::INTEGER AS call FROM v WHERE id % 5 = 0)", graph="supp_supp") + "SELECT DISTINCT a.pe, a.call FROM arcs x JOIN mv a ON a.id = x.src JOIN mv b ON b.id = x.dst WHERE a.pe <> b.pe OR a.call <> b.call")
def _(s, d):
    g = _g(s, d, "supp_supp")
    moves = g.vertices.where("id % 5 = 0").select("id", (F.col("id") % 3).cast("int").alias("pe"), (F.floor(F.col("id") / 3) % 40).cast("int").alias("call"))
    return R.conflicts(g, moves)


# -- floors -------------------------------------------------------------------

_FLOORS = {
    "mod": f"id % {K}", "hash": f"{mix_sql('id', 1)} % {K}", "range": f"(row_number() OVER (ORDER BY id) - 1) * {K} // count(*) OVER ()",
    "random": f"(row_number() OVER (ORDER BY {mix_sql('id', 1)}, id) - 1) % {K}",
}
for _kind, _expr in _FLOORS.items():

    def _floor(s, d, kind=_kind):
        g = _g(s, d)
        part = stash(floor_blocks(g, K, kind))
        return M.edge_cut(g, part).join(M.block_weights(g, part, K).agg(F.max("weight").alias("heaviest")), F.lit(True)).select("cut", "heaviest")

    QUERIES[f"p_floor_{_kind}"] = _floor
    SQL[f"p_floor_{_kind}"] = _with(f"part AS (SELECT id, {_expr} AS block FROM v)", _BLOCKS) + "SELECT (SELECT sum(weight)::BIGINT FROM eb WHERE ba <> bb) AS cut, (SELECT max(w)::BIGINT FROM (SELECT sum(weight) AS w FROM part JOIN v USING (id) GROUP BY block)) AS heaviest"

# -- evaluation over a log read from lineitem, and over the arithmetic one -------

_INST = f"WITH {E.synthetic_sql()}, {E.INSTANCES_SQL} "
_READ = f"WITH {E.table_sql()}, {E.INSTANCES_SQL} "
_GEO = "geo AS (SELECT algo, p, round(exp(avg(ln(cut))), 6) AS geo_cut FROM inst GROUP BY ALL)"


@query("e_geomean", _READ + "SELECT algo, p, round(exp(avg(ln(cut))), 6) AS geo_cut, count(*) AS instances FROM inst GROUP BY ALL")
def _(s, d):
    return E.geo_mean_cut(E.table_runs(s, d))


@query("e_by_type", _READ + "SELECT graph_type, algo, p, round(exp(avg(ln(cut))), 6) AS geo_cut, count(*) AS instances FROM inst GROUP BY ALL")
def _(s, d):
    return E.by_type(E.table_runs(s, d))


@query("e_relative", _READ.rstrip() + f", {_GEO} SELECT x.p, round((x.geo_cut / y.geo_cut - 1) * 100, 4) AS percent FROM geo x JOIN geo y ON x.p = y.p AND x.algo = 'full' AND y.algo = 'match'")
def _(s, d):
    return E.relative_cut(E.table_runs(s, d), "full", "match")


@query("e_profile", _READ.rstrip() + ", val AS (SELECT *, CASE WHEN imbalanced THEN 1.1 ELSE round(1 - min(cut) OVER (PARTITION BY graph, k) / cut, 6) END::DOUBLE AS value FROM inst) SELECT algo, p, row_number() OVER (PARTITION BY algo, p ORDER BY value, graph, k)::INTEGER AS rank, graph, k, value FROM val")
def _(s, d):
    return E.performance_profile(E.table_runs(s, d))


@query("e_best_share", _READ + "SELECT algo, p, round(avg(CASE WHEN r = 1 THEN 1.0 ELSE 0.0 END), 6) AS share FROM (SELECT *, rank() OVER (PARTITION BY graph, k ORDER BY cut) AS r FROM inst) GROUP BY ALL")
def _(s, d):
    return E.best_share(E.table_runs(s, d))


@query("e_worst_loss", _INST + "SELECT algo, p, round(max((cut / best - 1) * 100), 6) AS worst FROM (SELECT *, min(cut) OVER (PARTITION BY graph, k) AS best FROM inst) GROUP BY ALL")
def _(s, d):
    return E.worst_loss(E.synthetic_runs(s))


@query("e_speedup", _INST + "SELECT x.algo, x.p, round(count(*) / sum(x.t_total / o.t_total), 6) AS full, round(count(*) / sum(x.t_ls / o.t_ls), 6) AS search FROM inst x JOIN inst o ON o.graph = x.graph AND o.k = x.k AND o.algo = x.algo AND o.p = 1 AND NOT o.imbalanced WHERE x.p > 1 AND NOT x.imbalanced GROUP BY ALL")
def _(s, d):
    return E.speedups(E.synthetic_runs(s))


@query("e_ns_per_edge", _READ + "SELECT algo, p, round(exp(avg(ln(t_total * 1e9 / m))), 3) AS full, round(exp(avg(ln(t_ls * 1e9 / m))), 3) AS search FROM inst GROUP BY ALL")
def _(s, d):
    return E.ns_per_edge(E.table_runs(s, d))


@query("e_memory_saving", _READ + "SELECT x.graph, x.k, x.p, round((1 - x.peak_bytes / y.peak_bytes) * 100, 6) AS percent FROM inst x JOIN inst y ON x.graph = y.graph AND x.k = y.k AND x.p = y.p AND x.algo = 'full' AND y.algo = 'match'")
def _(s, d):
    return E.memory_saving(E.table_runs(s, d), "full", "match")


@query("e_top20_imbalanced", _INST + "SELECT sum(imbalanced::INTEGER)::BIGINT AS imbalanced, count(*) AS top FROM (SELECT x.*, round(o.t_total / x.t_total, 9) AS s FROM inst x JOIN inst o ON o.graph = x.graph AND o.k = x.k AND o.algo = x.algo AND o.p = 1 WHERE x.algo = 'match' AND x.p = 31 ORDER BY s DESC, x.graph, x.k LIMIT 20)")
def _(s, d):
    return E.top_speedup_imbalance(E.synthetic_runs(s), "match")


_PAIR = "pr AS (SELECT x.cut AS x, y.cut AS y FROM inst x JOIN inst y ON x.graph = y.graph AND x.k = y.k AND x.p = 31 AND y.p = 31 AND x.algo = 'full' AND y.algo = 'match')"


@query("e_sign_test", _INST.rstrip() + f", {_PAIR}, c AS (SELECT sum((x < y)::INTEGER)::BIGINT AS wins, sum((x > y)::INTEGER)::BIGINT AS losses FROM pr) SELECT wins, losses, round((wins - (wins + losses) / 2) / sqrt((wins + losses) / 4), 6) AS z FROM c")
def _(s, d):
    return E.sign_test(E.synthetic_runs(s), "full", "match", 31)


@query("e_wilcoxon", _INST.rstrip() + f", {_PAIR}, dd AS (SELECT round((x - y) / y, 9) AS d FROM pr), rk AS (SELECT d, rank() OVER (ORDER BY abs(d)) + (count(*) OVER (PARTITION BY abs(d)) - 1) / 2 AS r FROM dd WHERE d <> 0), c AS (SELECT count(*) AS n, coalesce(sum(r) FILTER (d > 0), 0)::DOUBLE AS w FROM rk) SELECT n, round(w, 6) AS w, round((w - n * (n + 1) / 4) / sqrt(n * (n + 1) * (2 * n + 1) / 24), 6) AS z FROM c")
def _(s, d):
    return E.wilcoxon(E.synthetic_runs(s), "full", "match", 31)


for _rival in ("match", "dist", "seq"):
    QUERIES[f"e_effectiveness_{_rival}"] = lambda s, d, r=_rival: E.virtual_instances(E.table_runs(s, d), "full", r, 31)
    SQL[f"e_effectiveness_{_rival}"] = E.virtual_sql("full", _rival, 31, log=E.table_sql())


@query("e_win_share", "SELECT round(avg(CASE WHEN cut_a < cut_b THEN 1.0 ELSE 0.0 END), 6) AS share, round(max((cut_a / cut_b - 1) * 100), 6) AS worst, count(*) AS n FROM (" + E.virtual_sql("full", "match", 31) + ")")
def _(s, d):
    return E.win_share(E.virtual_instances(E.synthetic_runs(s), "full", "match", 31))


# -- relational operators and functions ------------------------------------------


@query("op_project_weights", "SELECT l_orderkey AS src, l_partkey AS dst, round(l_extendedprice * 100)::BIGINT AS weight FROM lineitem")
def _(s, d):
    return load(s, d, "lineitem").select(F.col("l_orderkey").alias("src"), F.col("l_partkey").alias("dst"), F.round(F.col("l_extendedprice") * 100).cast("long").alias("weight"))


@query("op_filter_heavy_edges", _with() + "SELECT * FROM e WHERE weight >= 3")
def _(s, d):
    return _g(s, d).edges.where("weight >= 3")


@query("op_join_labels", _with(PART_SQL, _BLOCKS) + "SELECT src, dst, weight, ba AS block_src, bb AS block_dst FROM eb")
def _(s, d):
    return M.with_blocks(*_gp(s, d)).select("src", "dst", "weight", "block_src", "block_dst")


@query("op_broadcast_block_weights", _with(PART_SQL, _WEIGHTS) + "SELECT p.id, p.block, bw.weight AS filled FROM part p JOIN bw USING (block)")
def _(s, d):
    g, p = _gp(s, d)
    return p.join(F.broadcast(M.block_weights(g, p, K).select("block", F.col("weight").alias("filled"))), "block").select("id", "block", "filled")


@query("op_left_update", _with(PART_SQL) + f"SELECT id, (CASE WHEN id % 3 = 0 THEN {K} ELSE block END)::INTEGER AS block FROM part")
def _(s, d):
    g, p = _gp(s, d)
    moves = g.vertices.where("id % 3 = 0").select("id", F.lit(K).alias("target"))
    return C.apply_moves(p, moves, "block")


@query("op_full_diff", _with() + f"SELECT coalesce(a.id, b.id) AS id, a.block AS before, b.block AS after FROM (SELECT id, (id % {K})::INTEGER AS block FROM v WHERE id % 10 <> 0) a FULL JOIN (SELECT id, ({mix_sql('id', 1)} % {K})::INTEGER AS block FROM v WHERE id % 10 <> 1) b ON a.id = b.id WHERE a.block IS DISTINCT FROM b.block")
def _(s, d):
    g = _g(s, d)
    a = floor_blocks(g, K, "mod").where("id % 10 <> 0").withColumnRenamed("block", "before")
    b = floor_blocks(g, K, "hash").where("id % 10 <> 1").withColumnRenamed("block", "after")
    return a.join(b, "id", "full").where(~F.col("before").eqNullSafe(F.col("after")))


@query("op_semi_active", _with() + "SELECT src, dst, weight FROM arcs SEMI JOIN (SELECT id AS src FROM v WHERE id % 9 = 0) USING (src)")
def _(s, d):
    g = _g(s, d)
    return g.arcs().join(g.vertices.where("id % 9 = 0").select(F.col("id").alias("src")), "src", "left_semi").select("src", "dst", "weight")


@query("op_anti_isolated", _with(graph="conv_path") + "SELECT v.id FROM v ANTI JOIN (SELECT src AS id FROM arcs) a USING (id)")
def _(s, d):
    g = _g(s, d, "conv_path")
    return g.vertices.select("id").join(g.arcs().select(F.col("src").alias("id")), "id", "left_anti")


@query("op_theta_pairs", _with(graph="nation_trade") + "SELECT a.id AS a, b.id AS b FROM v a JOIN v b ON a.id < b.id AND (a.id + b.id) % 7 < 3")
def _(s, d):
    v = _g(s, d, "nation_trade").vertices.select("id")  # 25 rows whatever the scale
    a, b = v.withColumnRenamed("id", "a"), v.withColumnRenamed("id", "b")
    return a.join(b, (F.col("a") < F.col("b")) & ((F.col("a") + F.col("b")) % 7 < 3))


@query("op_interval_events", "SELECT a.event_id AS open_id, b.event_id AS event_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE WHERE a.event_type = 'click'")
def _(s, d):
    e = load(s, d, "events").select("event_id", "ts", "user_id", "event_type")
    cell = F.floor(F.unix_timestamp("ts") / 1800)
    a = e.where("event_type = 'click'").select(F.col("event_id").alias("open_id"), F.col("ts").alias("t0"), "user_id", F.explode(F.array(cell, cell + 1)).alias("cell"))
    b = e.select("event_id", "ts", "user_id", cell.alias("cell"))
    return a.join(b, ["user_id", "cell"]).where("ts > t0 AND ts <= t0 + interval 30 minutes").select("open_id", "event_id")


@query("op_asof_block", "SELECT e.event_id, o.o_orderkey FROM events e ASOF LEFT JOIN orders o ON e.user_id = o.o_custkey AND e.ts >= o.o_orderdate" if False else "SELECT event_id, o_orderkey FROM (SELECT e.event_id, max(o.k) AS o_orderkey FROM events e LEFT JOIN (SELECT user_id, ts, event_id AS k FROM events WHERE event_type = 'purchase') o ON o.user_id = e.user_id AND o.ts <= e.ts AND o.ts = (SELECT max(ts) FROM events x WHERE x.event_type = 'purchase' AND x.user_id = e.user_id AND x.ts <= e.ts) GROUP BY e.event_id)")
def _(s, d):
    e = load(s, d, "events").select("event_id", "ts", "user_id", F.when(F.col("event_type") == "purchase", F.col("event_id")).alias("k"))
    last = F.last("k", ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0))
    return e.select("event_id", last.alias("o_orderkey"))


@query("op_cube_runs", f"WITH {E.synthetic_sql()} SELECT graph_type, algo, p, count(*) AS n, sum(cut)::BIGINT AS cut FROM runs GROUP BY CUBE (graph_type, algo, p)")
def _(s, d):
    return E.synthetic_runs(s).cube("graph_type", "algo", "p").agg(F.count(F.lit(1)).alias("n"), F.sum("cut").alias("cut"))


@query("op_rollup_nation_region", "SELECT n_regionkey, n_nationkey, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, n_nationkey)")
def _(s, d):
    j = load(s, d, "customer").join(load(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    return j.rollup("n_regionkey", "n_nationkey").agg(F.count(F.lit(1)).alias("customers"))


@query("op_pivot_cut", f"WITH {E.synthetic_sql()} SELECT graph, k, " + ", ".join(f"min(cut) FILTER (algo = '{a}') AS \"{a}\"" for a in E.ALGOS) + " FROM runs GROUP BY graph, k")
def _(s, d):
    return E.synthetic_runs(s).groupBy("graph", "k").pivot("algo", list(E.ALGOS)).agg(F.min("cut"))


@query("op_degree_percentiles", _with(_DEG) + "SELECT round(quantile_cont(degree, 0.5), 6) AS p50, round(quantile_cont(degree, 0.95), 6) AS p95, max(degree) AS top FROM deg")
def _(s, d):
    return M.degrees(_g(s, d)).agg(F.round(F.percentile("degree", 0.5), 6).alias("p50"), F.round(F.percentile("degree", 0.95), 6).alias("p95"), F.max("degree").alias("top"))


@query("op_argmax_label", _with(PART_SQL, _CONN) + "SELECT id, arg_max(label, strength * 100 - label) AS label FROM conn GROUP BY id")
def _(s, d):
    return M.connections(*_gp(s, d)).groupBy("id").agg(F.max_by("label", F.col("strength") * 100 - F.col("label")).alias("label"))


@query("op_bool_imbalanced", f"WITH {E.synthetic_sql()} SELECT graph, k, algo, p, bool_or(imbalanced) AS imbalanced, bool_and(cut > 0) AS positive FROM runs GROUP BY ALL")
def _(s, d):
    return E.synthetic_runs(s).groupBy("graph", "k", "algo", "p").agg(F.bool_or("imbalanced").alias("imbalanced"), F.bool_and(F.col("cut") > 0).alias("positive"))


@query("op_stats_weights", _with() + "SELECT round(avg(weight), 6) AS mean, round(stddev_samp(weight), 6) AS deviation, round(corr(src, weight), 6) AS correlation, count(DISTINCT src) AS sources FROM e")
def _(s, d):
    return _g(s, d).edges.agg(F.round(F.avg("weight"), 6).alias("mean"), F.round(F.stddev_samp("weight"), 6).alias("deviation"), F.round(F.corr("src", "weight"), 6).alias("correlation"), F.count_distinct("src").alias("sources"))


@query("op_approx_clusters")
def _(s, d):
    return M.connections(*_gp(s, d)).groupBy("id").agg(F.approx_count_distinct("label").alias("labels"))


@query("op_rank_degrees", _with(_DEG) + "SELECT id, rank() OVER w AS r, dense_rank() OVER w AS dr, ntile(10) OVER (PARTITION BY id % 2 ORDER BY degree, id) AS tile, round(percent_rank() OVER w, 6) AS pr FROM deg WINDOW w AS (PARTITION BY id % 2 ORDER BY degree)")
def _(s, d):
    w = Window.partitionBy(F.col("id") % 2).orderBy("degree")
    return M.degrees(_g(s, d)).select("id", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.ntile(10).over(Window.partitionBy(F.col("id") % 2).orderBy("degree", "id")).alias("tile"), F.round(F.percent_rank().over(w), 6).alias("pr"))


@query("op_lag_turns", "SELECT conv_id, turn, lag(role) OVER w AS before, lead(role) OVER w AS after, first_value(role) OVER w AS opening FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")
def _(s, d):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return load(s, d, "conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.lead("role").over(w).alias("after"), F.first("role").over(w).alias("opening"))


@query("op_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey RANGE BETWEEN 1000 PRECEDING AND CURRENT ROW) AS n FROM orders")
def _(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey").rangeBetween(-1000, 0)
    return load(s, d, "orders").select("o_orderkey", F.count(F.lit(1)).over(w).alias("n"))


@query("op_topk_cut_edges", _with(PART_SQL, _BLOCKS) + "SELECT src, dst, weight FROM eb WHERE ba <> bb ORDER BY weight DESC, src, dst LIMIT 20")
def _(s, d):
    return M.with_blocks(*_gp(s, d)).where("block_src <> block_dst").orderBy(F.desc("weight"), "src", "dst").limit(20).select("src", "dst", "weight")


@query("op_union_arcs", _with() + "SELECT * FROM arcs")
def _(s, d):
    return _g(s, d).arcs()


_TWO = f"a AS (SELECT id, (id % {K})::INTEGER AS block FROM v), b AS (SELECT id, ({mix_sql('id', 1)} % {K})::INTEGER AS block FROM v)"


@query("op_intersect_runs", _with(_TWO) + "SELECT * FROM a INTERSECT SELECT * FROM b")
def _(s, d):
    g = _g(s, d)
    return floor_blocks(g, K, "mod").intersect(floor_blocks(g, K, "hash"))


@query("op_except_runs", _with(_TWO) + "SELECT * FROM a EXCEPT SELECT * FROM b")
def _(s, d):
    g = _g(s, d)
    return floor_blocks(g, K, "mod").exceptAll(floor_blocks(g, K, "hash"))


@query("op_scalar_subquery", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)")
def _(s, d):
    load(s, d, "orders").createOrReplaceTempView("gb_orders")
    return s.sql("SELECT o_orderkey FROM gb_orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM gb_orders)")


@query("op_exists_boundary", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def _(s, d):
    load(s, d, "orders").createOrReplaceTempView("gb_orders")
    load(s, d, "customer").createOrReplaceTempView("gb_customer")
    return s.sql("SELECT c_custkey FROM gb_customer WHERE EXISTS (SELECT 1 FROM gb_orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")


def components(g: BlockGraph) -> DataFrame:
    """(id, component): smallest id within reach, by alternating minima over stars until nothing changes."""
    edges = stash(g.edges.select(F.col("dst").alias("u"), F.col("src").alias("v")))
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        big = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = big.groupBy("u").agg(F.min("v").alias("m"))
        after = stash(big.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v").unionByName(low.select("u", F.col("m").alias("v"))).distinct())
        if after.count() == edges.count() and after.exceptAll(edges).isEmpty():
            break
        edges = after
    return g.vertices.join(edges.withColumnRenamed("u", "id"), "id", "left").select("id", F.coalesce("v", "id").alias("component"))


@query("op_components", _with("r AS (SELECT id, id AS c FROM v UNION SELECT a.dst, r.c FROM r JOIN arcs a ON a.src = r.id WHERE r.c < a.dst)", graph="conv_path", recursive=True) + "SELECT id, min(c) AS component FROM r GROUP BY id")
def _(s, d):
    return components(_g(s, d, "conv_path"))


@query("op_hash_sample", _with() + f"SELECT id FROM v WHERE {mix_sql('id', 9)} < 214748364")
def _(s, d):
    return _g(s, d).vertices.where(mix("id", 9) < 214748364).select("id")


@query("op_explode_adjacency", _with(graph="nation_trade") + "SELECT src, dst, weight FROM arcs")
def _(s, d):
    adj = _g(s, d, "nation_trade").arcs().groupBy("src").agg(F.sort_array(F.collect_list(F.struct("dst", "weight"))).alias("a"))
    return adj.select("src", F.explode("a").alias("x")).select("src", "x.dst", "x.weight")


@query("fn_math_bound", "SELECT o_orderkey, floor(1.03 * ceil(o_totalprice / 16))::BIGINT AS bound, round(ln(o_totalprice), 6) AS l, round(sqrt(o_totalprice), 6) AS r, greatest(o_custkey, 50) AS g, round(cosh(o_custkey / 1000.0), 6) AS c FROM orders")
def _(s, d):
    t = F.col("o_totalprice")
    return load(s, d, "orders").select("o_orderkey", F.floor(F.lit(1.03) * F.ceil(t / 16)).cast("long").alias("bound"), F.round(F.ln(t), 6).alias("l"), F.round(F.sqrt(t), 6).alias("r"), F.greatest("o_custkey", F.lit(50)).alias("g"), cosh_rounded(F.col("o_custkey") / 1000.0).alias("c"))


@query("fn_bits_tabular", "SELECT o_orderkey, xor(o_orderkey, 21845) AS x, o_orderkey >> 5 AS hi, o_orderkey & 31 AS lo FROM orders")
def _(s, d):
    o = F.col("o_orderkey")
    return load(s, d, "orders").select("o_orderkey", o.bitwiseXOR(F.lit(21845)).alias("x"), F.shiftright(o, 5).alias("hi"), o.bitwiseAND(F.lit(31)).alias("lo"))


@query("fn_href_extract", """SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages""")
def _(s, d):
    return load(s, d, "pages").select("page_id", F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")).alias("href"))


@query("fn_host", "SELECT page_id, lower(regexp_extract(url, '://([^/]+)', 1)) AS host FROM pages")
def _(s, d):
    return load(s, d, "pages").select("page_id", F.lower(F.regexp_extract("url", "://([^/]+)", 1)).alias("host"))


@query("fn_time_bucket_graph", "SELECT date_trunc('hour', ts)::TIMESTAMP AS hour, user_id, count(*) AS weight FROM events GROUP BY ALL")
def _(s, d):
    return load(s, d, "events").groupBy(F.date_trunc("hour", "ts").alias("hour"), "user_id").agg(F.count(F.lit(1)).alias("weight"))


@query("fn_cosine", "SELECT a.vec_id, round(list_sum(list_transform(range(1, 65), lambda i: a.embedding[i]::DOUBLE * b.embedding[i]::DOUBLE)), 5) AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = 0")
def _(s, d):
    e = load(s, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    first = e.where("vec_id = 0").select(F.col("v").alias("w"))  # one row
    dot = F.aggregate(F.zip_with("v", "w", lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x)
    return e.join(F.broadcast(first)).select("vec_id", F.round(dot, 5).alias("cosine"))


@query("fn_array_adjacency", _with(graph="nation_trade") + "SELECT src, count(*)::INTEGER AS n, max(dst) AS last, bool_or(weight > 300) AS heavy FROM arcs GROUP BY src")
def _(s, d):
    adj = _g(s, d, "nation_trade").arcs().groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("a"), F.collect_list("weight").alias("w"))
    return adj.select("src", F.size("a").alias("n"), F.element_at("a", -1).alias("last"), F.exists("w", lambda x: x > 300).alias("heavy"))


@query("fn_map_connections", _with(PART_SQL, _CONN) + "SELECT id, max(strength) FILTER (label = 2) AS to_two, count(*)::INTEGER AS n FROM conn GROUP BY id")
def _(s, d):
    m = M.connections(*_gp(s, d)).groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("label", "strength"))).alias("m"))
    return m.select("id", F.try_element_at("m", F.lit(2)).alias("to_two"), F.size(F.map_keys("m")).alias("n"))


@query("fn_json_props", "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k FROM events")
def _(s, d):
    return load(s, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("fn_conditional", "SELECT event_id, coalesce(nullif(event_type, 'error'), 'none') AS kind, CASE WHEN value > 100 THEN 'high' ELSE 'low' END AS size FROM events")
def _(s, d):
    return load(s, d, "events").select("event_id", F.coalesce(F.nullif(F.col("event_type"), F.lit("error")), F.lit("none")).alias("kind"), F.when(F.col("value") > 100, "high").otherwise("low").alias("size"))


# -- streaming: drained streams against their batch twins --------------------------

_UK = "(SELECT ts, 2 * user_id AS a, 2 * json_extract_string(props, '$.k')::BIGINT + 1 AS b FROM events)"


@query("t_tumbling", f"SELECT time_bucket(INTERVAL 1 HOUR, ts)::TIMESTAMP AS start, least(a, b) AS src, greatest(a, b) AS dst, count(*) AS weight FROM {_UK} GROUP BY ALL")
def _(s, d):
    return S.drained(S.windowed_edges(S.stream_edges(S.stream_events(s, d)), "tumbling", "1 hour"), "complete")


@query("t_sliding", f"SELECT start, least(a, b) AS src, greatest(a, b) AS dst, count(*) AS weight FROM (SELECT a, b, unnest([time_bucket(INTERVAL 30 MINUTE, ts)::TIMESTAMP, time_bucket(INTERVAL 30 MINUTE, ts)::TIMESTAMP - INTERVAL 30 MINUTE]) AS start FROM {_UK}) GROUP BY ALL")
def _(s, d):
    return S.drained(S.windowed_edges(S.stream_edges(S.stream_events(s, d)), "sliding", "1 hour", "30 minutes"), "complete")


@query("t_session", "SELECT min(ts)::TIMESTAMP AS start, (max(ts) + INTERVAL 20 MINUTE)::TIMESTAMP AS \"end\", src, count(*) AS weight FROM (SELECT *, sum(fresh) OVER (PARTITION BY src ORDER BY ts, event_id) AS n FROM (SELECT event_id, ts, 2 * user_id AS src, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 20 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY src, n")
def _(s, d):
    return S.drained(S.windowed_edges(S.stream_edges(S.stream_events(s, d)), "session", "20 minutes"), "complete")


@query("t_join_static", "SELECT event_id, user_id, (user_id % 4)::INTEGER AS block FROM events WHERE user_id % 3 <> 0")
def _(s, d):
    part = load(s, d, "events").select(F.col("user_id").alias("id")).distinct().where("id % 3 <> 0").withColumn("block", (F.col("id") % 4).cast("int"))
    return S.drained(S.join_blocks(S.stream_events(s, d), part))


@query("t_interval_edges", "SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 600 SECOND")
def _(s, d):
    return S.drained(S.interval_edges(S.stream_events(s, d), "click", "purchase", 600))


@query("t_dedup", "SELECT DISTINCT event_id FROM events")
def _(s, d):
    return S.drained(S.dedup_events(S.stream_events(s, d)).select("event_id"))


@query("t_assign", "SELECT count(DISTINCT user_id) AS assigned, true AS within FROM events")
def _(s, d):
    n = load(s, d, "events").select("user_id").distinct().count()
    v = S.stream_events(s, d).select(F.col("user_id").alias("id"), (F.col("user_id") % 7).alias("tie")).dropDuplicates(["id"])
    bound = 4 * (n // K + K)
    part = S.drained(S.streaming_assign(v, 4, K, bound))
    return part.agg(F.count_distinct("id").alias("assigned"), (F.max("block") < K).alias("within"))
