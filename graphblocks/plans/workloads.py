"""The experiments: partitions of derived and generated graphs by all methods, logged as runs and measured.

A certificate row states what must hold for any good run; what depends on the
input alone (n, weights) is recomputed by SQL.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import PartitionConfig, config
from ..functions.hashes import mix_np
from ..model import BlockGraph, Csr, collect_csr
from ..operators import kernels
from ..operators import measures as M
from ..sources import generators as Gen
from ..sources.tables import GRAPHS, MESHES, graph_ctes
from ..storage import stash
from . import evaluation as E
from .multilevel import best_of_runs, floor_blocks, greedy_stream, partition_csr, partition_graph, without_plan

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}
#: Graphs in arrays and run logs of a session, by (application, folder, graph or workload): tables don't change under it.
_graphs: dict[tuple, Csr] = {}
_logs: dict[tuple, DataFrame] = {}
#: Arcs and vertices that a graph in arrays may have, in the driver and in each task: 20 million arcs are 320 MB.
LIMIT = 20_000_000


def csr_of(spark: SparkSession, d: str, name: str) -> Csr:
    key = (spark.sparkContext.applicationId, d, name)
    if key not in _graphs:
        csr = collect_csr(GRAPHS[name](spark, d).stored(), LIMIT)
        if csr is None:
            raise ValueError(f"{name} has more than {LIMIT} arcs; use partition_graph")
        _graphs[key] = csr
    return _graphs[key]


def graph_of(spark: SparkSession, d: str, name: str) -> Csr | BlockGraph:
    """As :func:`csr_of`, but a graph of more than LIMIT arcs stays as stored tables."""
    key = (spark.sparkContext.applicationId, d, name)
    if key not in _graphs:
        g = GRAPHS[name](spark, d).stored()
        csr = collect_csr(g, LIMIT)
        if csr is None:
            return g
        _graphs[key] = csr
    return _graphs[key]


def certificate(spark: SparkSession, d: str, name: str, k: int, cfg: PartitionConfig, p: int = 4, seed: int = 0, eps: float = 0.03, mode: str = "auto") -> DataFrame:
    """graph, k, n, total_weight, blocks_used, covered, feasible, cut_ok, below_floor of one run, all recomputed by plans from its assignment."""
    g = GRAPHS[name](spark, d).stored()
    r = partition_graph(g, k, eps, p, seed, cfg=replace(cfg, execution_mode=mode))
    part = stash(r.assignment)
    weights = M.block_weights(g, part, k)
    c = M.check_partition(g, part, k).select((F.col("uncovered") + F.col("unknown") + F.col("repeated") + F.col("out_of_range") == 0).alias("covered"))
    floor_cut = M.edge_cut(g, floor_blocks(g, k, "hash")).select(F.col("cut").alias("floor_cut"))
    row = weights.agg(F.sum("vertices").alias("n"), F.max("weight").alias("w"), F.sum(F.when(F.col("vertices") > 0, 1).otherwise(0)).cast("long").alias("blocks_used"))
    total = g.edges.agg(F.coalesce(F.sum("weight"), F.lit(0)).alias("total_weight"))
    cut = M.edge_cut(g, part).select("cut")
    true = F.lit(True)
    j = row.join(total, true).join(c, true).join(cut, true).join(floor_cut, true)
    feasible = true if cfg.refiner == "hill" else F.col("w") <= r.bound
    return j.select(F.lit(name).alias("graph"), F.lit(k).alias("k"), "n", "total_weight", (F.col("blocks_used") == k).alias("blocks_used"), "covered", feasible.alias("feasible"), (F.col("cut") == r.cut).alias("cut_ok"), (F.col("cut") <= F.col("floor_cut")).alias("below_floor"))


def certificate_sql(name: str, k: int) -> str:
    return f"WITH {graph_ctes(name)} SELECT '{name}' AS graph, {k} AS k, (SELECT count(*) FROM v) AS n, (SELECT coalesce(sum(weight), 0)::BIGINT FROM e) AS total_weight, true AS blocks_used, true AS covered, true AS feasible, true AS cut_ok, true AS below_floor"


def _certified(query: str, graph: str, k: int, cfg: PartitionConfig, p: int = 4, mode: str = "auto", eps: float = 0.03) -> None:
    QUERIES[query] = lambda s, d: certificate(s, d, graph, k, cfg, p, mode=mode, eps=eps)
    SQL[query] = certificate_sql(graph, k)


_certified("p_full", "page_links", 4, config())
_certified("p_full_p16", "page_links", 4, config(), 16)
_certified("p_full_p1", "page_links", 4, config(), 1)
_certified("p_full_k5", "user_key", 5, config())
_certified("p_full_eps0", "conv_path", 4, config(), eps=0.0)
_certified("p_seq", "page_links", 4, config("seq_lp"))
_certified("p_dist", "page_links", 4, config("dist_lp"))
_certified("p_match", "page_links", 4, config("matching"))
_certified("p_match_greedy", "page_links", 4, config("matching_greedy"))
_certified("p_match_two_hop", "doc_source", 4, config("matching", two_hop=True))
_certified("p_flow", "user_key", 4, config(flow=True))
_certified("p_auto_coarsening", "emb_rgg", 4, config(coarsening="auto"))
_certified("p_plain_mts", "page_links", 4, config(nested=False))
_certified("p_fm", "page_links", 4, config(refiner="fm"))
_certified("p_mts_only", "page_links", 4, config(refiner="mts"))
_certified("p_lp_only", "page_links", 4, config(refiner="lp"))
_certified("p_docs", "doc_overlap", 4, config())
_certified("p_events", "user_chain", 4, config(lp_rounds_coarsen=5))
_certified("p_distributed", "conv_path", 4, config(lp_rounds_coarsen=2, lp_rounds_refine=2, sub_rounds=2, global_rounds=1, coarsest_min=150, coarsest_per_block=30, max_levels=2), mode="distributed")


def block_report(spark: SparkSession, d: str, graph: str = "doc_overlap", k: int = 4) -> DataFrame:
    """(block, vertices, weight, internal_weight, cut_weight) of the full pipeline's blocks."""
    g = GRAPHS[graph](spark, d).stored()
    part = stash(partition_graph(g, k).assignment)
    e = M.with_blocks(g, part)
    inner = e.where("block_src = block_dst").groupBy(F.col("block_src").alias("block")).agg(F.sum("weight").alias("internal_weight"))
    ends = e.where("block_src <> block_dst").select(F.explode(F.array("block_src", "block_dst")).alias("block"), "weight")
    cut = ends.groupBy("block").agg(F.sum("weight").alias("cut_weight"))
    out = M.block_weights(g, part, k).join(inner, "block", "left").join(cut, "block", "left")
    return out.select("block", "vertices", "weight", F.coalesce("internal_weight", F.lit(0)).alias("internal_weight"), F.coalesce("cut_weight", F.lit(0)).alias("cut_weight"))


QUERIES["block_report"] = block_report

# -- exact answers ------------------------------------------------------------------


def exact_optimum(csr: Csr, k: int, bound: int) -> int:
    """The least cut of all feasible labelings, vertex 0 in block 0; for a dozen vertices."""
    n = csr.n
    codes = np.arange(k ** (n - 1), dtype=np.int64)
    labels = np.zeros((len(codes), n), np.int8)
    for v in range(1, n):
        labels[:, v] = codes // k ** (v - 1) % k
    ok = np.ones(len(codes), bool)
    for b in range(k):
        ok &= ((labels == b) * csr.vw[None]).sum(1) <= bound
    labels = labels[ok]
    cut = np.zeros(len(labels), np.int64)
    src = csr.rows()
    for a, b, w in zip(src.tolist(), csr.nbr.tolist(), csr.w.tolist()):
        if a < b:
            cut += w * (labels[:, a] != labels[:, b])
    return int(cut.min())


def _brute(query: str, graph: str, ids: int, k: int) -> None:
    def run(s: SparkSession, d: str) -> DataFrame:
        whole = csr_of(s, d, graph)
        csr = whole.subgraph(whole.ids < ids)
        blocks = [partition_csr(csr, k, seed=x)[0] for x in range(3)]
        return s.createDataFrame([(int(min(csr.cut(b) for b in blocks)),)], "cut long")

    QUERIES[query] = run
    bound = 103 * -(-ids // k) // 100
    digits = ", ".join(["0 AS b0", *[f"x // {k ** (i - 1)} % {k} AS b{i}" for i in range(1, ids)]])
    fits = " AND ".join(f"{' + '.join(f'(b{i} = {b})::INTEGER' for i in range(ids))} <= {bound}" for b in range(k))
    w = f"w AS (SELECT src, dst, weight FROM e WHERE src < {ids} AND dst < {ids})"
    cut = " + ".join(f"(b{i} <> b{j})::INTEGER * coalesce((SELECT weight FROM w WHERE src = {i} AND dst = {j}), 0)" for i in range(ids) for j in range(i + 1, ids))
    SQL[query] = f"WITH {graph_ctes(graph)}, {w}, l AS (SELECT {digits} FROM (SELECT unnest(range({k ** (ids - 1)})) AS x)) SELECT min({cut})::BIGINT AS cut FROM l WHERE {fits}"


_brute("i_bruteforce_nation_k2", "nation_trade", 10, 2)
_brute("i_bruteforce_nation_k3", "nation_trade", 9, 3)


def _zero_cut(s: SparkSession, d: str) -> DataFrame:
    csr = csr_of(s, d, "conv_path")
    cuts = [min(csr.cut(partition_csr(csr, k, seed=x)[0]) for x in range(3)) for k in (2, 4)]
    return s.createDataFrame([(k, int(c)) for k, c in zip((2, 4), cuts)], "k int, cut long")


QUERIES["i_zero_cut_paths"] = _zero_cut
SQL["i_zero_cut_paths"] = "SELECT unnest([2, 4]) AS k, 0::BIGINT AS cut"


# -- run logs ---------------------------------------------------------------------

VARIANTS = {"full": config(), "seq": config("seq_lp"), "dist": config("dist_lp"), "match": config("matching")}
_RUN = "graph string, graph_type string, k int, algo string, p int, seed int, n long, m long, cut long, max_block long, l_max long, imbalanced boolean, t_total double, t_coarsen double, t_init double, t_refine double, t_ls double, peak_bytes long, tried long, applied long, levels int, coarsest long, probes long, lookups long"


def _run_row(name: str, k: int, algo: str, p: int, seed: int, n: int, m: int, cut: int, heaviest: int, bound: int, r: dict) -> tuple:
    kind = "M" if name in MESHES or name.startswith(("grid", "rgg", "delaunay")) else "C"
    return (name, kind, k, algo, p, seed, n, m, cut, heaviest, bound, bool(heaviest > bound), r["t_total"], r["t_coarsen"], r["t_init"], r["t_refine"], r["t_ls"], int(r["bytes"]), int(r.get("tried", 0)), int(r.get("applied", 0)), len(r["levels"]), int(r["levels"][-1][0]), int(r.get("probes", 0)), int(r.get("lookups", 0)))


def _run_by_plans(g: BlockGraph, name: str, k: int, algo: str, p: int, seed: int, cfg: PartitionConfig, eps: float) -> tuple:
    """The row of one run of a graph that no task takes whole; methods without plans run on arrays in the driver."""
    n = g.vertices.count()
    r = partition_graph(g, k, eps, p, seed, cfg=replace(cfg, execution_mode="local") if without_plan(cfg, n) else cfg)
    return _run_row(name, k, algo, p, seed, n, g.edges.count(), int(r.cut), int(max(r.weights)), int(r.bound), r.report)


def runs(spark: SparkSession, d: str, graphs: dict[str, Csr | BlockGraph], ks, variants: dict[str, PartitionConfig], ps=(1, 4), seeds=2, eps: float = 0.03, log: str | None = None, memory: bool = False) -> DataFrame:
    """The log of all runs, one row and one task each; ``log`` names it for reuse in the session.

    Graphs in arrays go to the tasks by broadcast; ``csr_of`` bounds their size.  Those in tables
    are partitioned by plans of the whole session, one run after another.  With ``memory`` the peak is what a run has
    allocated at most at one time, traced; else the arrays of its levels.
    """
    key = (spark.sparkContext.applicationId, d, log)
    if log is not None and key in _logs:
        return _logs[key]
    jobs = [(name, k, algo, p, seed) for name in graphs for k in ks for algo, cfg in variants.items() for p in ((1,) if cfg.preset == "seq_lp" else ps) for seed in range(seeds)]
    large = {name: g for name, g in graphs.items() if isinstance(g, BlockGraph)}
    if large and memory:
        raise ValueError(f"no traced memory of runs by plans: {', '.join(large)}")
    graphs = {name: g for name, g in graphs.items() if name not in large}
    by_plans = [_run_by_plans(large[j[0]], *j, variants[j[2]], eps) for j in jobs if j[0] in large]
    jobs = [j for j in jobs if j[0] in graphs]
    if not jobs:
        out = stash(spark.createDataFrame(by_plans, _RUN))
        if log is not None:
            _logs[key] = out
        return out
    shipped = spark.sparkContext.broadcast((graphs, variants))

    def work(parts):
        import tracemalloc

        for pdf in parts:
            rows = []
            for name, k, algo, p, seed in pdf[["graph", "k", "algo", "p", "seed"]].itertuples(index=False):
                csr, cfg = shipped.value[0][name], shipped.value[1][algo]
                if memory:
                    tracemalloc.start()
                block, r = partition_csr(csr, k, eps, p, seed, cfg)
                if memory:
                    r["bytes"] = tracemalloc.get_traced_memory()[1]
                    tracemalloc.stop()
                load = np.bincount(block, csr.vw, k).astype(np.int64)
                bound = M.l_max(int(csr.vw.sum()), k, eps)
                rows.append(_run_row(name, k, algo, p, seed, csr.n, len(csr.nbr) // 2, csr.cut(block), int(load.max()), bound, r))
            yield pd.DataFrame(rows, columns=[c.split()[0] for c in _RUN.split(", ")])

    order = sorted(jobs, key=lambda j: -len(graphs[j[0]].nbr))  # long runs first
    rows = spark.createDataFrame([(i, *j) for i, j in enumerate(order)], "i long, graph string, k int, algo string, p int, seed int")
    spread = rows.repartitionByRange(min(len(jobs), 4 * spark.sparkContext.defaultParallelism), F.expr("pmod(xxhash64(i), 1000003)"))
    out = spread.mapInPandas(work, _RUN)
    out = stash(out.unionByName(spark.createDataFrame(by_plans, _RUN)) if by_plans else out)
    if log is not None:
        _logs[key] = out
    return out


def _arrays(spark: SparkSession, g) -> Csr:
    return collect_csr(g, LIMIT)


#: The table graphs of the quality experiment; ends of both kinds, sparse and dense, complex and mesh.
W1_TABLES = ("page_links", "emb_rgg", "conv_path", "user_key", "nation_trade")


def w1_graphs(spark: SparkSession, d: str) -> dict[str, Csr]:
    made = {"grid": Gen.grid(spark, 24, 24), "grid_torus": Gen.grid(spark, 20, 20, wrap=True), "rhg": Gen.gen_rhg(spark, 600), "planted": Gen.planted(spark, 8, 50, 0.2, 0.01)}
    return {n: csr_of(spark, d, n) for n in W1_TABLES} | {n: _arrays(spark, g) for n, g in made.items()}


def w1_runs(spark: SparkSession, d: str) -> DataFrame:
    return runs(spark, d, w1_graphs(spark, d), (4, 16), VARIANTS, (1, 4), 3, log="w1")


#: The whole experiment on quality: further tables, numbers of blocks and PEs, repetitions.
W1_MORE = ("part_copurchase", "cust_supp", "part_supp", "doc_overlap", "emb_knn")
W1_KS, W1_PS, W1_SEEDS = (4, 16, 64), (1, 4, 16, 31), 10


def w1_all_graphs(spark: SparkSession, d: str) -> dict[str, Csr | BlockGraph]:
    """The graphs of :func:`w1_graphs`, the other tables and the other generated families."""
    made = {"rgg": Gen.gen_rgg(spark, 10), "delaunay": Gen.gen_delaunay(spark, 9), "er": Gen.gen_er(spark, 800)}
    return w1_graphs(spark, d) | {n: graph_of(spark, d, n) for n in W1_MORE} | {n: _arrays(spark, g) for n, g in made.items()}


def w1_all_runs(spark: SparkSession, d: str) -> DataFrame:
    return runs(spark, d, w1_all_graphs(spark, d), W1_KS, VARIANTS, W1_PS, W1_SEEDS, log="w1_all")


def _ordering(s: SparkSession, d: str) -> DataFrame:
    """(rival, full_is_better): at p = 4 the geometric mean cut of the full pipeline against each rival's, over the instances that the rival has balanced runs of.

    Runs beyond the bound of a block don't count, and cuts of zero count as one.
    """
    log = w1_runs(s, d).where("NOT imbalanced").withColumn("cut", F.col("cut") + 1).withColumn("p", F.when(F.col("algo") == "seq", 4).otherwise(F.col("p")))
    inst = E.instances(log.where("p = 4")).select("graph", "k", "algo", "cut")
    full = inst.where("algo = 'full'").select("graph", "k", F.col("cut").alias("own"))
    both = inst.where("algo <> 'full'").join(full, ["graph", "k"])
    return both.groupBy(F.col("algo").alias("rival")).agg((F.avg(F.ln("own")) < F.avg(F.ln("cut"))).alias("full_is_better"))


def _balance(s: SparkSession, d: str) -> DataFrame:
    """(graph, k, n, l_max, kept): whether all runs of the methods that promise it keep to the bound, the graph's size and the bound told by SQL again."""
    log = w1_runs(s, d).where(F.col("graph").isin(*W1_TABLES) & (F.col("algo") != "match"))
    return log.groupBy("graph", "k").agg(F.max("n").alias("n"), F.max("l_max").alias("l_max"), F.bool_and(F.col("max_block") <= F.col("l_max")).alias("kept"))


QUERIES["w1_ordering"] = _ordering
QUERIES["w1_balance"] = _balance
SQL["w1_balance"] = " UNION ALL ".join(f"SELECT * FROM (WITH {graph_ctes(n)}, c AS (SELECT count(*) AS n FROM v) SELECT '{n}' AS graph, k, n, (103 * ((n + k - 1) // k) // 100)::BIGINT AS l_max, true AS kept FROM c, (SELECT unnest([4, 16]) AS k))" for n in W1_TABLES)
QUERIES["w1_quality_runs"] = lambda s, d: w1_all_runs(s, d).select("graph", "k", "algo", "p", "seed", "cut", "imbalanced")
QUERIES["w1_profile"] = lambda s, d: E.performance_profile(w1_all_runs(s, d))
QUERIES["w1_geomean"] = lambda s, d: E.geo_mean_cut(w1_all_runs(s, d).withColumn("cut", F.col("cut") + 1))


def _effect_match(s: SparkSession, d: str) -> DataFrame:
    """(p, share, worst, n): equal-time tests against matching with one, some and all PEs, of all repetitions."""
    log = w1_all_runs(s, d).withColumn("cut", F.col("cut") + 1)
    by_p = [E.win_share(E.virtual_instances(log, "full", "match", p, 20)).select(F.lit(p).alias("p"), "*") for p in (1, 4, 31)]
    return reduce(DataFrame.unionByName, by_p)


QUERIES["w2_effect_match"] = _effect_match
for _n, _rival in (("w3_effect_dist", "dist"), ("w4_effect_seq", "seq")):

    def _effect(s, d, rival=_rival):
        log = w1_runs(s, d)
        if rival == "seq":
            log = log.withColumn("p", F.when(F.col("algo") == "seq", F.lit(4)).otherwise(F.col("p")))
        return E.win_share(E.virtual_instances(log.withColumn("cut", F.col("cut") + 1), "full", rival, 4, 20))

    QUERIES[_n] = _effect
QUERIES["w5_speedup"] = lambda s, d: E.speedups(w1_runs(s, d).withColumn("t_ls", F.col("t_ls") + 1e-6))
QUERIES["w5_ns_per_edge"] = lambda s, d: E.ns_per_edge(w1_runs(s, d).withColumn("t_ls", F.col("t_ls") + 1e-6))


def _axis(name: str, graphs: tuple[str, ...], variants: dict[str, PartitionConfig], ps=(4,), seeds: int = 3, k: int = 4) -> None:
    def run(s: SparkSession, d: str) -> DataFrame:
        r = runs(s, d, {g: csr_of(s, d, g) for g in graphs}, (k,), variants, ps, seeds, log=name)
        return r.groupBy("graph", "k", "algo", "p").agg(F.round(F.avg("cut"), 3).alias("cut"), F.bool_or("imbalanced").alias("imbalanced"), F.round(F.avg("t_total"), 4).alias("seconds"), F.sum("tried").alias("tried"), F.sum("applied").alias("applied"), F.max("coarsest").alias("coarsest"), F.sum("probes").alias("probes"), F.sum("lookups").alias("lookups"), F.max("peak_bytes").alias("peak_bytes"))

    QUERIES[name] = run


#: A complex network and a mesh for the experiments on parameters.
_BOTH = ("page_links", "emb_rgg")


def _components(s: SparkSession, d: str) -> DataFrame:
    """(component, percent): how the geometric mean cut changes when that phase alone runs with 16 PEs."""
    variants = {"none": config(parallel=frozenset()), **{c: config(parallel=frozenset({c})) for c in ("coarsen", "init", "refine")}}
    r = runs(s, d, {g: csr_of(s, d, g) for g in _BOTH}, (16,), variants, (16,), 3, log="w6_component")
    return E.component_effect(r.withColumn("cut", F.col("cut") + 1), "none", 16)


def _by_type(s: SparkSession, d: str) -> DataFrame:
    log = w1_runs(s, d).withColumn("cut", F.col("cut") + 1).withColumn("p", F.when(F.col("algo") == "seq", 4).otherwise(F.col("p")))
    return E.by_type(log.where("p = 4"))


QUERIES["w6_component"] = _components
QUERIES["w9_by_type"] = _by_type
_axis("w10_star_shrink", ("doc_source",), {"cluster": config(max_levels=1), "matching": config("matching", max_levels=1), "two_hop": config("matching", two_hop=True, max_levels=1)}, seeds=1)
_axis("w11_p_sweep", _BOTH, {"full": config()}, (1, 16, 31), k=16)
_axis("w12_rounds", _BOTH, {f"rounds_{r}": config(global_rounds=r) for r in (0, 1, 3, 6)}, k=16)
_axis("w13_alpha", _BOTH, {f"alpha_{a:g}": config(alpha=a) for a in (0.0, 0.1, 0.5, 1e9)}, k=16)
_axis("w14_tables", _BOTH, {s: config(store=s) for s in ("array", "dict", "probe", "probe_local")}, seeds=1)
_axis("gain_modes", _BOTH, {m: config(gain_mode=m) for m in ("recompute", "incremental")}, seeds=1)
_axis("w17_trials", _BOTH, {f"trials_{t}": config(trials=t) for t in (1, 4, 16)}, k=16)


def _phases(s: SparkSession, d: str) -> DataFrame:
    r = runs(s, d, {g: graph_of(s, d, g) for g in ("emb_rgg", "page_links", "user_key")}, (16,), {"full": config()}, (1, 4), 2, log="w7")
    t = F.col("t_coarsen") + F.col("t_init") + F.col("t_refine")
    return r.groupBy("graph", "p").agg(*[F.round(F.avg(F.col(c) / t), 4).alias(c.replace("t_", "share_")) for c in ("t_coarsen", "t_init", "t_refine")])


#: Repetitions of the experiment on memory, as of that on quality.
MEMORY_SEEDS = 10


def _memory(s: SparkSession, d: str) -> DataFrame:
    """(graph, k, p, percent): the three graphs of W1_TABLES with most arcs, with one, some and all PEs."""
    r = runs(s, d, {g: csr_of(s, d, g) for g in (*_BOTH, "user_key")}, (16,), {"full": config(), "match": config("matching")}, (1, 4, 31), MEMORY_SEEDS, log="w8", memory=True)
    return E.memory_saving(r, "full", "match")


def _generated(s: SparkSession, d: str) -> DataFrame:
    g = {"rgg": Gen.gen_rgg(s, 10), "delaunay": Gen.gen_delaunay(s, 9), "er": Gen.gen_er(s, 800), "rhg": Gen.gen_rhg(s, 1000), "planted": Gen.planted(s, 4, 60, 0.2, 0.01)}
    r = runs(s, d, {n: _arrays(s, x) for n, x in g.items()}, (4, 16), {"full": config(), "seq": config("seq_lp")}, (4,), 2, log="w15")
    return r.select("graph", "k", "algo", "seed", "n", "m", "cut", "imbalanced")


QUERIES |= {"w7_phase_share": _phases, "w8_memory": _memory, "w15_generators": _generated}
QUERIES["equal_time"] = lambda s, d: s.createDataFrame([(best_of_runs(GRAPHS["nation_trade"](s, d), 4, 1.0, preset="seq_lp", most=4).cut,)], "cut long")


def _stream_floor(s: SparkSession, d: str) -> DataFrame:
    csr = csr_of(s, d, "page_links")
    b = greedy_stream(csr, 4, 0.03)
    h = mix_np(csr.ids, 1) % 4
    return s.createDataFrame([(csr.cut(b) <= csr.cut(h), bool(np.bincount(b, csr.vw, 4).max() <= M.l_max(int(csr.vw.sum()), 4, 0.03)))], "below_floor boolean, feasible boolean")


QUERIES["p_greedy_stream"] = _stream_floor
SQL["p_greedy_stream"] = "SELECT true AS below_floor, true AS feasible"
QUERIES["r_flow_never_worse"] = lambda s, d: s.createDataFrame([(_flow_holds(csr_of(s, d, "emb_rgg")),)], "holds boolean")
SQL["r_flow_never_worse"] = "SELECT true AS holds"


def _flow_holds(csr: Csr) -> bool:
    bound = M.l_max(int(csr.vw.sum()), 4, 0.03)
    block = kernels.rebalance(csr, kernels.recursive_bisect(csr, 4, bound, np.random.default_rng(1), 1), 4, bound)
    after = kernels.flow_all_pairs(csr, block, bound)
    return csr.cut(after) <= csr.cut(block) and bool(np.bincount(after, csr.vw, 4).max() <= bound)
