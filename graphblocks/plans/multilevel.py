"""The multilevel driver: coarsen, partition the coarsest graph many times, refine on the way back."""

from __future__ import annotations

import math
import time
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import PartitionConfig, config
from ..model import BlockGraph, Csr, GraphError, collect_csr
from ..operators import coarsening, kernels, refinement
from ..operators.measures import block_weights, edge_cut, l_max


@dataclass
class PartitionResult:
    """assignment: (id, block); report: seconds of the phases, levels, search counters."""

    assignment: DataFrame
    cut: int
    weights: list[int]
    bound: int
    report: dict = field(default_factory=dict)

    @property
    def balanced(self) -> bool:
        return max(self.weights, default=0) <= self.bound


@dataclass
class _Clock:
    report: dict

    def add(self, phase: str, began: float) -> None:
        self.report[phase] = self.report.get(phase, 0.0) + time.perf_counter() - began


def cluster_bound(vw_max: int, total: int, k: int, bound: int, cfg: PartitionConfig) -> int:
    """The weight that a cluster may have: a fraction of a block, and not much more than a vertex of the coarsest graph should have."""
    small = max(cfg.coarsest_min, cfg.coarsest_per_block * k)
    return max(vw_max, min(bound // cfg.cluster_factor, -(-2 * total // small)), 1)


def _mesh_like(csr: Csr) -> bool:
    d = csr.degrees()
    return bool(len(d)) and d.max() < 4 * max(d.mean(), 1e-9)


def cluster_once(csr: Csr, k: int, bound: int, cfg: PartitionConfig, p: int, seed: int) -> np.ndarray:
    """The labels by which a level is contracted."""
    limit = cluster_bound(int(csr.vw.max(initial=1)), int(csr.vw.sum()), k, bound, cfg)
    kind = cfg.coarsening
    if kind == "auto":
        kind = "matching" if _mesh_like(csr) else "cluster"
    if kind == "matching":
        labels = kernels.matching(csr, limit, cfg.match_rounds, seed, cfg.two_hop)
    elif cfg.sequential_lp or p == 1:
        labels = kernels.sclp_sequential(csr, limit, cfg.lp_rounds_coarsen, seed)
    else:
        labels = kernels.sclp(csr, limit, cfg.lp_rounds_coarsen, cfg.sub_rounds, seed, packet=cfg.packet, stay_on_tie=cfg.stay_on_tie, ranges=p if cfg.quota and limit >= 4 * p else 0)
    return kernels.pack_lone(csr, labels, limit)


def coarsen(csr: Csr, k: int, bound: int, cfg: PartitionConfig, p: int, seed: int) -> tuple[list[tuple[Csr, np.ndarray]], Csr]:
    """Levels (graph, map to the next) and the coarsest graph."""
    levels: list[tuple[Csr, np.ndarray]] = []
    small = max(cfg.coarsest_min, cfg.coarsest_per_block * k)
    while csr.n > small and len(levels) < cfg.max_levels:
        coarse, to = kernels.contract(csr, cluster_once(csr, k, bound, cfg, p, seed + len(levels)))
        if coarse.n > (1 - cfg.min_shrink) * csr.n:
            break
        levels.append((csr, to))
        csr = coarse
    return levels, csr


def one_trial(csr: Csr, k: int, bound: int, seed: int, cfg: PartitionConfig) -> tuple[int, int, np.ndarray]:
    """(overload, cut, blocks) of one recursive bisection with its polish."""
    rng = np.random.default_rng(seed)
    block = kernels.recursive_bisect(csr, k, bound, rng, cfg.growth_starts)
    block = kernels.rebalance(csr, block, k, bound)
    block = kernels.sclp(csr, bound, 5, 2, seed, block, k, keep_best=True)
    block = kernels.fm(csr, block, np.full(k, bound), rng, 2)
    if cfg.flow or cfg.flow_start:
        block = kernels.flow_all_pairs(csr, block, bound)
    if np.bincount(block, csr.vw, k).max(initial=0) <= bound:
        block = kernels.swap_polish(csr, block, k, bound)
    load = np.bincount(block, csr.vw, k)
    return int(np.maximum(load - bound, 0).sum()), csr.cut(block), block


def initial_partition(csr: Csr, k: int, bound: int, cfg: PartitionConfig, p: int, seed: int, spark: SparkSession | None = None) -> np.ndarray:
    """The best of max(p, trials) independent trials; with a session and a graph worth it, a task for each."""
    count = max(p, cfg.trials)
    if spark is not None and count * len(csr.nbr) > 2_000_000:
        shipped = spark.sparkContext.broadcast(csr)  # bounded by the coarsest level's size

        def run(parts):
            for pdf in parts:
                for s in pdf["id"].tolist():
                    over, cut, block = one_trial(shipped.value, k, bound, seed + s, cfg)
                    yield pd.DataFrame({"over": [over], "cut": [cut], "seed": [s], "block": [block.astype(np.int32).tobytes()]})

        rows = spark.range(count, numPartitions=count).mapInPandas(run, "over long, cut long, seed long, block binary")
        best = rows.agg(F.min_by("block", F.struct("over", "cut", "seed"))).first()[0]
        return np.frombuffer(best, np.int32).astype(np.int64)
    # The first of the best, as min keeps it; its blocks come with it.
    return min((one_trial(csr, k, bound, seed + s, cfg) for s in range(count)), key=lambda x: x[:2])[2]


def mts_local(csr: Csr, block: np.ndarray, k: int, bound: int, p: int, cfg: PartitionConfig, seed: int, report: dict) -> np.ndarray:
    """The nested loops of localized search, with p virtual PEs."""
    for r in range(cfg.global_rounds):
        todo, total, local = kernels.boundary(csr, block), 0, 0
        round_gain = 0
        while len(todo):
            s = seed + 100 * r + local
            buckets = kernels.todo_order(csr, todo, p, s)
            owner = kernels.own_balls(csr, buckets, s) if p > 1 else None
            sizes = np.bincount(block, csr.vw, k).astype(np.int64)
            moves = []
            for pe in range(p):
                own = None if owner is None else owner == pe
                moves += kernels.perform_moves(csr, block, sizes, bound, buckets[pe], own, pe, cfg.stop_a, cfg.stop_b, s, cfg.store, cfg.gain_mode, cfg.max_steps_per_pe, cfg.mark, report)
            block, gained, touched = kernels.replay(csr, block, sizes, bound, moves)
            report["applied"] = report.get("applied", 0) + len(touched)
            round_gain += gained
            local += 1
            if not touched or not cfg.nested or gained <= cfg.alpha * total:
                break
            total += gained
            todo = np.unique(np.array(touched))
        if not round_gain:
            break
    return block


#: Levels of fewer vertices and still more than ``local_arc_limit`` arcs are refused with flows; all others, of any size, are polished by them.
FLOW_VERTICES = 5000


def refine(csr: Csr, block: np.ndarray, k: int, bound: int, cfg: PartitionConfig, p: int, seed: int, report: dict) -> np.ndarray:
    clock = _Clock(report)
    if "lp" in cfg.refiner.split("+"):
        ranges = p if cfg.quota else 0
        block = kernels.sclp(csr, bound, cfg.lp_rounds_refine, 2 if p > 1 else 8, seed, block, k, ranges=ranges, keep_best=True)
    began = time.perf_counter()
    if "mts" in cfg.refiner.split("+") and cfg.global_rounds:
        block = mts_local(csr, block, k, bound, p, cfg, seed, report)
    elif cfg.refiner == "fm":
        block = kernels.fm(csr, block, np.full(k, bound), np.random.default_rng(seed))
    elif cfg.refiner == "hill":
        block = kernels.hill_climb(csr, block, k, bound, p, seed)
    elif cfg.refiner == "greedy":
        block = kernels.sclp(csr, bound, 4, 4, seed, block, k, keep_best=True)
    clock.add("t_ls", began)
    if cfg.flow:
        block = kernels.flow_all_pairs(csr, block, bound)
    return block


def partition_csr(csr: Csr, k: int, eps: float = 0.03, p: int = 4, seed: int = 0, cfg: PartitionConfig | None = None, spark: SparkSession | None = None) -> tuple[np.ndarray, dict]:
    """Blocks of a graph in arrays, and the report."""
    cfg = cfg or config()
    bound = l_max(int(csr.vw.sum()), k, eps)
    if csr.n and int(csr.vw.max()) > bound:
        raise GraphError(f"a vertex weighs {int(csr.vw.max())}, more than the bound {bound} of a block")
    report: dict = {"t_coarsen": 0.0, "t_init": 0.0, "t_refine": 0.0, "t_ls": 0.0}
    clock = _Clock(report)
    pes = {phase: p if phase in cfg.parallel else 1 for phase in ("coarsen", "init", "refine")}
    began = time.perf_counter()
    levels, coarsest = coarsen(csr, k, bound, cfg, pes["coarsen"], seed)
    clock.add("t_coarsen", began)
    report["levels"] = [(c.n, len(c.nbr) // 2) for c, _ in levels] + [(coarsest.n, len(coarsest.nbr) // 2)]
    report["bytes"] = sum(c.nbytes() + to.nbytes for c, to in levels) + coarsest.nbytes()
    began = time.perf_counter()
    block = initial_partition(coarsest, k, bound, cfg, pes["init"], seed, spark) if csr.n else np.zeros(0, np.int64)
    clock.add("t_init", began)
    began = time.perf_counter()
    block = refine(coarsest, block, k, bound, cfg, pes["refine"], seed, report)
    for fine, to in reversed(levels):
        block = refine(fine, block[to], k, bound, cfg, pes["refine"], seed, report)
    if cfg.refiner != "hill" and csr.n and np.bincount(block, csr.vw, k).max() > bound:
        block = kernels.rebalance(csr, block, k, bound)
    clock.add("t_refine", began)
    report["t_total"] = report["t_coarsen"] + report["t_init"] + report["t_refine"]
    return block, report


def partition_graph(g: BlockGraph, k: int, eps: float = 0.03, p: int = 4, seed: int = 0, preset: str = "full", cfg: PartitionConfig | None = None) -> PartitionResult:
    """Partitions a graph into k blocks of at most (1 + eps) ceil(c(V) / k).

    Levels of more than ``local_arc_limit`` arcs are clustered, contracted and
    refined as DataFrame plans; from the first smaller one on, kernels take over.
    """
    cfg = cfg or config(preset)
    spark = g.vertices.sparkSession
    if k < 1 or eps < 0 or p < 1:
        raise ValueError("k >= 1, eps >= 0 and p >= 1")
    limit = 0 if cfg.execution_mode == "distributed" else cfg.local_arc_limit
    csr = collect_csr(g, limit) if limit else None
    if csr is not None or cfg.execution_mode == "local":
        csr = csr if csr is not None else collect_csr(g, 1 << 40)
        block, report = partition_csr(csr, k, eps, p, seed, cfg, spark)
        rows = spark.createDataFrame(pd.DataFrame({"id": csr.ids, "block": block.astype(np.int32)}), "id long, block int")
        return PartitionResult(rows, csr.cut(block), np.bincount(block, csr.vw, k).astype(int).tolist(), l_max(int(csr.vw.sum()), k, eps), report)
    return _distributed(g, k, eps, p, seed, cfg)


def without_plan(cfg: PartitionConfig, n: int) -> list[str]:
    """What of the settings has no DataFrame plan on a level of n vertices.

    Flows have one, but small levels that don't fit ``local_arc_limit`` are refused with them.
    """
    missing = sorted(set(cfg.refiner.split("+")) - {"lp", "mts", "greedy"})
    missing += [name for name in ("flow", "sequential_lp") if getattr(cfg, name) and (name != "flow" or n < FLOW_VERTICES)]
    return missing + (["coarsening auto"] if cfg.coarsening == "auto" else [])


def _must_run_distributed(cfg: PartitionConfig, n: int) -> None:
    """Raises for settings that have no DataFrame plan; they would otherwise do nothing on large levels."""
    if missing := without_plan(cfg, n):
        raise GraphError(f"no distributed form of {', '.join(missing)}; raise local_arc_limit or take execution_mode local")


def _distributed(g: BlockGraph, k: int, eps: float, p: int, seed: int, cfg: PartitionConfig) -> PartitionResult:
    spark = g.vertices.sparkSession
    total, heaviest, n = g.vertices.agg(F.coalesce(F.sum("weight"), F.lit(0)), F.coalesce(F.max("weight"), F.lit(0)), F.count(F.lit(1))).first()
    _must_run_distributed(cfg, n)
    bound = l_max(int(total), k, eps)
    if heaviest > bound:
        raise GraphError(f"a vertex weighs {heaviest}, more than the bound {bound} of a block")
    report: dict = {"t_coarsen": 0.0, "t_init": 0.0, "t_refine": 0.0, "t_ls": 0.0, "levels": []}
    clock = _Clock(report)
    levels: list[tuple[BlockGraph, DataFrame]] = []
    small = max(cfg.coarsest_min, cfg.coarsest_per_block * k)
    forced = cfg.execution_mode == "distributed"
    csr = None
    began = time.perf_counter()
    while len(levels) < cfg.max_levels and n > small:
        _must_run_distributed(cfg, n)
        report["levels"].append((int(n), g.edges.count()))
        limit = cluster_bound(int(heaviest), int(total), k, bound, cfg)
        if cfg.coarsening == "matching":
            clusters = coarsening.heavy_edge_matching(g, limit, cfg.match_rounds, seed + len(levels), cfg.two_hop)
        else:
            lp = coarsening.LabelPropagation(limit, cfg.lp_rounds_coarsen, cfg.sub_rounds, seed + len(levels), cfg.packet, cfg.stay_on_tie, "quota" if cfg.quota else "window", p)
            clusters = lp.run(g)
        lone = coarsening.pack_isolated(g, limit)
        clusters = clusters.join(lone.withColumnRenamed("cluster", "packed"), "id", "left").select("id", F.coalesce("packed", "cluster").alias("cluster"))
        coarse, to = coarsening.contract(g, clusters)
        coarse = coarse.stored()
        heaviest, after = coarse.vertices.agg(F.max("weight"), F.count(F.lit(1))).first()
        if after > (1 - cfg.min_shrink) * n:
            break
        levels.append((g, to))
        g, n = coarse, after
        if not forced and (csr := collect_csr(g, cfg.local_arc_limit)) is not None:
            break
    clock.add("t_coarsen", began)
    csr = csr if csr is not None else collect_csr(g, max(cfg.local_arc_limit, 20_000_000))
    if csr is None:
        raise GraphError("the coarsest graph does not fit one task; raise cluster bounds or levels")
    block, inner = partition_csr(csr, k, eps, p, seed, replace(cfg, execution_mode="local"), spark)
    # The kernels' phases and counters are added to those of the plans.
    report["levels"] += inner.pop("levels")
    report["bytes"] = inner.pop("bytes")
    for c, v in inner.items():
        report[c] = report.get(c, 0) + v
    began = time.perf_counter()
    part = spark.createDataFrame(pd.DataFrame({"id": csr.ids, "block": block.astype(np.int32)}), "id long, block int")
    for fine, to in reversed(levels):
        part = coarsening.project(part, to)
        if "lp" in cfg.refiner.split("+"):
            part = refinement.lp_refine(fine, part, k, bound, cfg.lp_rounds_refine, seed, admission="quota" if cfg.quota else "histogram", ranges=p if cfg.quota else 1)
        if cfg.refiner == "greedy":
            part = refinement.lp_refine(fine, part, k, bound, 4, seed, 4)
        if "mts" in cfg.refiner.split("+") and cfg.global_rounds:
            mts_began = time.perf_counter()
            part, counters = refinement.mts(fine, part, k, bound, p, cfg, seed)
            clock.add("t_ls", mts_began)
            for c, v in counters.items():
                report[c] = report.get(c, 0) + v
        if cfg.flow:
            part = refinement.flow_refine(fine, part, k, bound)
        g = fine
    clock.add("t_refine", began)
    report["t_total"] = report["t_coarsen"] + report["t_init"] + report["t_refine"]
    weights = [r["weight"] for r in block_weights(g, part, k).orderBy("block").collect()]  # k rows
    return PartitionResult(part, int(edge_cut(g, part).first()["cut"]), weights, bound, report)


def best_of_runs(g: BlockGraph, k: int, seconds: float, eps: float = 0.03, p: int = 4, preset: str = "full", most: int = 50) -> PartitionResult:
    """Repeats with new seeds as long as the time lasts, at least once; keeps the best balanced cut."""
    best, spent, seed = None, 0.0, 0
    while best is None or (spent < seconds and seed < most):
        began = time.perf_counter()
        r = partition_graph(g, k, eps, p, seed, preset)
        spent += time.perf_counter() - began
        seed += 1
        if best is None or (not r.balanced, r.cut) < (not best.balanced, best.cut):
            best = r
    best.report["repetitions"] = seed
    return best


def floor_blocks(g: BlockGraph, k: int, kind: str = "mod", seed: int = 1) -> DataFrame:
    """Simple floors: ``mod`` (id), ``hash`` (of the id), ``range`` (equal counts by id), ``random`` (equal counts by hash)."""
    from ..functions.hashes import mix
    from ..operators.prefix import prefix_sum

    if kind == "mod":
        return g.vertices.select("id", F.pmod("id", F.lit(k)).cast("int").alias("block"))
    if kind == "hash":
        return g.vertices.select("id", F.pmod(mix("id", seed), F.lit(k)).cast("int").alias("block"))
    n = g.vertices.count()
    if kind == "range":
        v = prefix_sum(g.vertices, [F.col("id")], F.lit(1).cast("long"), "r")
        return v.select("id", F.floor(F.col("r") * k / F.lit(n)).cast("int").alias("block"))
    if kind == "random":
        v = prefix_sum(g.vertices.withColumn("t", mix("id", seed)), [F.col("t"), F.col("id")], F.lit(1).cast("long"), "r")
        return v.select("id", F.pmod("r", F.lit(k)).cast("int").alias("block"))
    raise ValueError(kind)


def greedy_stream(csr: Csr, k: int, eps: float) -> np.ndarray:
    """One pass in id order: the block with the strongest tie that has room, else the lightest."""
    bound = l_max(int(csr.vw.sum()), k, eps)
    block, load = np.full(csr.n, -1), np.zeros(k, np.int64)
    for v in range(csr.n):
        a, b = csr.indptr[v], csr.indptr[v + 1]
        at = block[csr.nbr[a:b]]
        s = np.bincount(at[at >= 0], csr.w[a:b][at >= 0], k) * (1 - load / max(bound, 1))
        s = np.where(load + csr.vw[v] <= bound, s - 1e-9 * load, -1e18)
        t = int(np.argmax(s)) if s.max() > -1e17 else int(np.argmin(load))
        block[v] = t
        load[t] += csr.vw[v]
    return block


def log2_bits(n: int) -> int:
    return max(1, math.ceil(math.log2(max(n, 2))))
