"""Refinement of large levels as DataFrame plans: label propagation within the bound, and localized search by PE."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..config import PartitionConfig
from ..functions.hashes import mix
from ..model import BlockGraph, Csr
from ..storage import stash
from . import kernels
from .coarsening import LabelPropagation
from .measures import block_weights, boundary, edge_cut

MOVES = "pe int, call int, step int, id long, from_block int, to_block int, gain long"


def lp_refine(g: BlockGraph, part: DataFrame, k: int, bound: int, rounds: int = 25, seed: int = 0, sub_rounds: int = 2, admission: str = "histogram", ranges: int = 1) -> DataFrame:
    """Label propagation from the blocks; the best state of all rounds is returned, so the cut never rises."""
    best, best_cut = part, edge_cut(g, part).first()["cut"]
    now = part
    for r in range(rounds):
        lp = LabelPropagation(bound, 1, sub_rounds, seed + 1000 * r, admission=admission, ranges=ranges)
        after = lp.run(g, now, "block")
        cut = edge_cut(g, after).first()["cut"]
        if cut < best_cut:
            best, best_cut = after, cut
        elif cut == edge_cut(g, now).first()["cut"]:
            break
        now = after
    return best


def todo_order(todo: DataFrame, p: int, seed: int) -> DataFrame:
    """(id, pe, rank): the todo list dealt to PEs, each in its own hashed order."""
    t = todo.select("id", F.pmod(mix("id", seed + 1), F.lit(p)).cast("int").alias("pe"), mix("id", seed).alias("tie"))
    return t.withColumn("rank", F.row_number().over(Window.partitionBy("pe").orderBy("tie", "id"))).select("id", "pe", "rank")


def own_balls(g: BlockGraph, todo: DataFrame, seed: int, radius: int) -> DataFrame:
    """(id, pe): seeds and what lies within ``radius`` hops, each owned by the PE that came first (ties by hash)."""
    owned = stash(todo.select("id", "pe"))
    rim = owned
    for _ in range(radius):
        reach = g.arcs().join(rim.select(F.col("id").alias("src"), "pe"), "src").select(F.col("dst").alias("id"), "pe", mix(F.col("pe") * 1_000_003 + F.col("dst"), seed).alias("tie"))
        rim = reach.join(owned, "id", "left_anti").groupBy("id").agg(F.min(F.struct("tie", "pe")).alias("m")).select("id", F.col("m.pe").alias("pe"))
        rim = stash(rim)
        owned = stash(owned.unionByName(rim))
    return owned


def local_searches(g: BlockGraph, part: DataFrame, k: int, bound: int, todo: DataFrame, cfg: PartitionConfig, seed: int) -> DataFrame:
    """The move log of all PEs.  A PE's task gets the arcs that leave its own vertices, with the blocks at both ends; tasks don't talk."""
    owned = own_balls(g, todo, seed, cfg.ball_radius)
    sizes = [r["weight"] for r in block_weights(g, part, k).orderBy("block").collect()]  # k rows
    ends = g.vertices.join(part, "id")
    a = ends.select(F.col("id").alias("src"), F.col("block").alias("bs"), F.col("weight").alias("ws"))
    b = part.select(F.col("id").alias("dst"), F.col("block").alias("bd"))
    ranks = todo.select(F.col("id").alias("src"), "rank")
    rows = g.arcs().join(owned.withColumnRenamed("id", "src"), "src").join(a, "src").join(b, "dst").join(ranks, "src", "left")

    def search(pdf: pd.DataFrame) -> pd.DataFrame:
        pe = int(pdf.pe.iloc[0])
        src, dst = pdf.src.to_numpy(), pdf.dst.to_numpy()
        ids = np.unique(np.concatenate([src, dst]))
        s, t = np.searchsorted(ids, src), np.searchsorted(ids, dst)
        block, vw, own = np.zeros(len(ids), np.int64), np.ones(len(ids), np.int64), np.zeros(len(ids), bool)
        block[t], block[s] = pdf.bd, pdf.bs
        vw[s], own[s] = pdf.ws, True
        order = np.lexsort((t, s))
        csr = Csr(ids, np.searchsorted(s[order], np.arange(len(ids) + 1)), t[order], pdf.weight.to_numpy()[order], vw)
        first = pdf.dropna(subset=["rank"]).drop_duplicates("src").sort_values("rank")
        seeds = np.searchsorted(ids, first.src.to_numpy()).tolist()
        log = kernels.perform_moves(csr, block, np.array(sizes), bound, seeds, own, pe, cfg.stop_a, cfg.stop_b, seed, cfg.store, cfg.gain_mode, cfg.max_steps_per_pe, cfg.mark)
        out = pd.DataFrame(log, columns=["pe", "call", "step", "id", "from_block", "to_block", "gain"])
        out["id"] = ids[out["id"].to_numpy(np.int64)] if len(out) else out["id"]
        return out.astype({"pe": "int32", "call": "int32", "step": "int32", "id": "int64", "from_block": "int32", "to_block": "int32", "gain": "int64"})

    return rows.groupBy("pe").applyInPandas(search, MOVES)


def conflicts(g: BlockGraph, moves: DataFrame) -> DataFrame:
    """(pe, call) of sequences with a vertex beside one that another sequence moves."""
    m = moves.select("id", "pe", "call")
    a, b = m.select(F.col("id").alias("src"), F.col("pe").alias("pe_a"), F.col("call").alias("call_a")), m.select(F.col("id").alias("dst"), F.col("pe").alias("pe_b"), F.col("call").alias("call_b"))
    hit = g.arcs().join(a, "src").join(b, "dst").where("pe_a <> pe_b OR call_a <> call_b")
    return hit.select(F.col("pe_a").alias("pe"), F.col("call_a").alias("call")).distinct()


def apply_moves(g: BlockGraph, part: DataFrame, k: int, bound: int, moves: DataFrame, limit: int) -> tuple[DataFrame, int, DataFrame | None]:
    """(partition, gain, moved ids).  The log, if it has at most ``limit`` moves, is replayed with the arcs beside it; a longer one is applied in bulk.

    In bulk, sequences beside no other are taken whole where the inflow of all of
    them fits each block; the rest is left to the next round.
    """
    count = moves.count()
    if not count:
        return part, 0, None
    if count > limit:
        calm = stash(moves.join(conflicts(g, moves), ["pe", "call"], "left_anti").join(g.vertices, "id"))
        inflow = calm.groupBy("pe", "call", "to_block").agg(F.sum("weight").alias("w"), F.sum("gain").alias("gain"))
        fill = F.sum("w").over(Window.partitionBy("to_block").orderBy(F.desc("gain"), "pe", "call").rowsBetween(Window.unboundedPreceding, 0))
        sizes = block_weights(g, part, k).select(F.col("block").alias("to_block"), "weight")
        refused = inflow.withColumn("fill", fill).join(F.broadcast(sizes), "to_block").where(F.col("fill") + F.col("weight") > bound).select("pe", "call").distinct()
        taken = stash(calm.join(refused, ["pe", "call"], "left_anti"))
        gained = taken.agg(F.coalesce(F.sum("gain"), F.lit(0))).first()[0]
        after = part.join(taken.select("id", "to_block"), "id", "left").select("id", F.coalesce("to_block", "block").alias("block"))
        return stash(after), gained, taken.select("id")
    ids = moves.select(F.col("id").alias("src")).distinct()
    blocks = part.select(F.col("id").alias("dst"), F.col("block").alias("bd"))
    near = g.arcs().join(ids, "src", "left_semi").join(blocks, "dst").toPandas()
    own = g.vertices.join(ids.withColumnRenamed("src", "id"), "id", "left_semi").join(part, "id").toPandas()
    log = moves.toPandas()
    sizes = np.array([r["weight"] for r in block_weights(g, part, k).orderBy("block").collect()])
    names = np.unique(np.concatenate([near.src, near.dst, own.id]))
    s, t = np.searchsorted(names, near.src), np.searchsorted(names, near.dst)
    block, vw = np.zeros(len(names), np.int64), np.ones(len(names), np.int64)
    block[t] = near.bd
    at = np.searchsorted(names, own.id)
    block[at], vw[at] = own.block, own.weight
    order = np.lexsort((t, s))
    csr = Csr(names, np.searchsorted(s[order], np.arange(len(names) + 1)), t[order], near.weight.to_numpy()[order], vw)
    rows = list(zip(log.pe, log.call, log.step, np.searchsorted(names, log.id), log.from_block, log.to_block, log.gain))
    after, gained, touched = kernels.replay(csr, block, sizes, bound, rows)
    if not touched:
        return part, 0, None
    changed = np.unique(np.array(touched))
    delta = part.sparkSession.createDataFrame(pd.DataFrame({"id": names[changed], "new": after[changed].astype(np.int32)}))
    out = part.join(delta, "id", "left").select("id", F.coalesce("new", "block").cast("int").alias("block"))
    return stash(out), gained, delta.select("id")


def mts(g: BlockGraph, part: DataFrame, k: int, bound: int, p: int, cfg: PartitionConfig, seed: int) -> tuple[DataFrame, dict]:
    """Localized multi-try search by p PEs; balance is kept, and the cut never rises."""
    report = {"gain": 0, "tried": 0, "applied": 0, "local_rounds": 0}
    for r in range(cfg.global_rounds):
        todo_ids, total = boundary(g, part), 0
        while True:
            s = seed + 100 * r + report["local_rounds"]
            todo = stash(todo_order(todo_ids, p, s))
            moves = stash(local_searches(g, part, k, bound, todo, cfg, s))
            part, gained, moved = apply_moves(g, part, k, bound, moves, cfg.replay_limit)
            report["local_rounds"] += 1
            report["tried"] += moves.count()
            report["applied"] += 0 if moved is None else moved.count()
            report["gain"] += gained
            if moved is None or gained <= cfg.alpha * total or not cfg.nested:
                break
            total += gained
            todo_ids = moved
        if total == 0 and r and not report["gain"]:
            break
    return part, report


def pair_rounds(k: int) -> list[list[tuple[int, int]]]:
    """All pairs of blocks, in rounds in which no block is met twice."""
    ring: list[int] = list(range(k + k % 2))
    rounds = []
    for _ in range(len(ring) - 1):
        pairs = [tuple(sorted((ring[i], ring[-1 - i]))) for i in range(len(ring) // 2)]
        rounds.append([p for p in pairs if p[1] < k])
        ring = [ring[0], ring[-1], *ring[1:-1]]
    return rounds


def _polish(pairs: list[tuple[int, int]], loads: np.ndarray, bound: int):
    def polish(pdf: pd.DataFrame) -> pd.DataFrame:
        src, dst = pdf.src.to_numpy(), pdf.dst.to_numpy()
        ids, first = np.unique(np.concatenate([src, dst]), return_index=True)
        vw, block = np.concatenate([pdf.ws, pdf.wd])[first], np.concatenate([pdf.bs, pdf.bd])[first].astype(np.int64)
        csr = Csr.from_arrays(ids, vw, src, dst, pdf.weight.to_numpy())
        after = kernels.flow_polish(csr, block, *pairs[int(pdf.pair.iloc[0])], bound, loads)
        moved = after != block
        return pd.DataFrame({"id": ids[moved], "new": after[moved].astype(np.int32)})

    return polish


def flow_refine(g: BlockGraph, part: DataFrame, k: int, bound: int) -> DataFrame:
    """Borders of all pairs of blocks polished by flows; balance is kept, and the cut never rises.

    Pairs without a block in common are polished side by side; a task gets the edges within and between two blocks.
    """
    ends = g.vertices.join(part, "id")
    for pairs in pair_rounds(k):
        loads = np.zeros(k, np.int64)
        for r in block_weights(g, part, k).collect():  # k rows
            loads[r["block"]] = r["weight"]
        of = F.create_map(*[F.lit(x) for i, p in enumerate(pairs) for b in p for x in (b, i)])
        a = ends.select(F.col("id").alias("src"), F.col("block").alias("bs"), F.col("weight").alias("ws"), of[F.col("block")].alias("pair"))
        b = ends.select(F.col("id").alias("dst"), F.col("block").alias("bd"), F.col("weight").alias("wd"), of[F.col("block")].alias("other"))
        rows = g.edges.join(a, "src").join(b, "dst").where("pair = other").drop("other")

        new = stash(rows.groupBy("pair").applyInPandas(_polish(pairs, loads, bound), "id long, new int"))
        if not new.isEmpty():
            part = stash(part.join(new, "id", "left").select("id", F.coalesce("new", "block").cast("int").alias("block")))
            ends = g.vertices.join(part, "id")
    return part
