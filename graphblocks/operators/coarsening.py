"""Clustering with bounded cluster weights, matchings, contraction, and the hierarchy's tables."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashes import mix
from ..model import BlockGraph
from ..storage import stash
from .measures import connections, degrees
from .prefix import dense_ids, prefix_sum


def degree_order(g: BlockGraph, seed: int = 0) -> DataFrame:
    """(id, degree, position): vertices by (degree, hash, id)."""
    d = degrees(g).select("id", "degree").withColumn("tie", mix("id", seed))
    return prefix_sum(d, [F.col("degree"), F.col("tie"), F.col("id")], F.lit(1).cast("long"), "position").select("id", "degree", "position")


def make_packets(g: BlockGraph, active: DataFrame | None = None, bound: int | None = None, sub_rounds: int = 4, seed: int = 0) -> DataFrame:
    """(id, degree, packet, sub_round): packets hold about ``bound`` neighbours, low degrees first.

    The bound is max(1000, sqrt(m)) by default.  Packets are dealt to sub-rounds
    in consecutive runs.
    """
    if bound is None:
        bound = max(1000, int(g.edges.count() ** 0.5))
    d = degrees(g).select("id", "degree").withColumn("tie", mix("id", seed))
    if active is not None:
        d = d.join(active, "id", "left_semi")
    d = prefix_sum(d, [F.col("degree"), F.col("tie"), F.col("id")], F.col("degree"), "before")
    d = d.withColumn("packet", F.floor(F.col("before") / bound).cast("long"))
    last = d.agg(F.max("packet").alias("last"))
    out = d.join(F.broadcast(last), F.lit(True))
    return out.select("id", "degree", "packet", F.floor(F.col("packet") * sub_rounds / (F.col("last") + 1)).cast("int").alias("sub_round"))


def admit_by_capacity(proposals: DataFrame, weights: DataFrame, bound: int, seed: int = 0) -> DataFrame:
    """(id, target) of the proposals (id, weight, target, gain) that fit.

    Per target, by (gain down, hash, id), as long as the sum stays within
    ``bound`` less the target's weight in ``weights`` (target, cweight).  What
    leaves a target isn't credited, so no order of moves breaks the bound.
    """
    order = Window.partitionBy("target").orderBy(F.desc("gain"), mix("id", seed), "id").rowsBetween(Window.unboundedPreceding, 0)
    p = proposals.join(weights, "target", "left").withColumn("fill", F.sum("weight").over(order))
    return p.where(F.col("fill") <= bound - F.coalesce("cweight", F.lit(0))).select("id", "target")


def admit_by_histogram(proposals: DataFrame, weights: DataFrame, bound: int, seed: int = 0, cells: int = 1024) -> DataFrame:
    """The same for few targets, with no window over all rows of a target.

    Sums by (target, gain) tell which gains fit whole; in the gain that doesn't,
    sums by hash cells do the same, and only the rows of one cell meet a window.
    The rows are those that :func:`admit_by_capacity` admits.
    """
    shift = 2147483648 // cells
    p = proposals.withColumn("cell", F.floor(mix("id", seed) / shift))
    room = weights.select("target", (F.lit(bound) - F.col("cweight")).alias("room"))
    sums = p.groupBy("target", "gain", "cell").agg(F.sum("weight").alias("w"))
    by_gain = sums.groupBy("target", "gain").agg(F.sum("w").alias("w"))
    best_first = Window.partitionBy("target").orderBy(F.desc("gain")).rowsBetween(Window.unboundedPreceding, 0)
    by_gain = by_gain.withColumn("fill", F.sum("w").over(best_first)).join(room, "target", "left").withColumn("room", F.coalesce("room", F.lit(bound)))
    whole = by_gain.where("fill <= room").select("target", "gain")
    cut = by_gain.where("fill > room").groupBy("target").agg(F.max(F.struct("gain", (F.col("fill") - F.col("w")).alias("used"), "room")).alias("c"))
    cut = cut.select("target", F.col("c.gain").alias("gain"), F.col("c.used").alias("used"), F.col("c.room").alias("room"))
    inside = Window.partitionBy("target").orderBy("cell").rowsBetween(Window.unboundedPreceding, 0)
    by_cell = sums.join(cut, ["target", "gain"]).withColumn("fill", F.sum("w").over(inside) + F.col("used"))
    whole_cells = by_cell.where("fill <= room").select("target", "gain", "cell")
    last = by_cell.where("fill > room").groupBy("target").agg(F.min(F.struct("cell", "gain", (F.col("fill") - F.col("w")).alias("used"), "room")).alias("c"))
    last = last.select("target", F.col("c.gain").alias("gain"), F.col("c.cell").alias("cell"), F.col("c.used").alias("used"), F.col("c.room").alias("room"))
    order = Window.partitionBy("target").orderBy(mix("id", seed), "id").rowsBetween(Window.unboundedPreceding, 0)
    rest = p.join(F.broadcast(last), ["target", "gain", "cell"]).withColumn("fill", F.sum("weight").over(order) + F.col("used")).where("fill <= room")
    return p.join(whole, ["target", "gain"], "left_semi").select("id", "target").unionByName(p.join(whole_cells, ["target", "gain", "cell"], "left_semi").select("id", "target")).unionByName(rest.select("id", "target"))


def admit_by_quota(proposals: DataFrame, weights: DataFrame, bound: int, ranges: int, seed: int = 0) -> DataFrame:
    """Each of ``ranges`` hash ranges of ids may fill its equal part of a target's room: no word between ranges."""
    p = proposals.withColumn("_range", F.pmod(mix("id", 3), F.lit(ranges)))
    order = Window.partitionBy("target", "_range").orderBy(F.desc("gain"), mix("id", seed), "id").rowsBetween(Window.unboundedPreceding, 0)
    p = p.join(weights, "target", "left").withColumn("fill", F.sum("weight").over(order))
    return p.where(F.col("fill") <= F.floor((F.lit(bound) - F.coalesce("cweight", F.lit(0))) / ranges)).select("id", "target")


def cluster_weights(g: BlockGraph, labels: DataFrame, label: str) -> DataFrame:
    return g.vertices.join(labels, "id").groupBy(F.col(label).alias("target")).agg(F.sum("weight").alias("cweight"))


def propose(g: BlockGraph, labels: DataFrame, active: DataFrame | None, bound: int, seed: int, label: str = "cluster", stay_on_tie: bool = True) -> tuple[DataFrame, DataFrame]:
    """Proposals (id, weight, target, gain) of active vertices, and (target, cweight)."""
    weights = cluster_weights(g, labels, label)
    arcs = g if active is None else _only(g, active)
    c = connections(arcs, labels, label)
    own = g.vertices.join(labels, "id").select("id", F.col("weight"), F.col(label).alias("own"))
    c = c.join(own, "id").join(weights.select(F.col("target").alias("label"), "cweight"), "label")
    ok = (F.col("label") != F.col("own")) & (F.col("cweight") + F.col("weight") <= bound)
    stay = F.coalesce(F.sum(F.when(F.col("label") == F.col("own"), F.col("strength"))), F.lit(0)).alias("stay")
    best = F.max(F.when(ok, F.struct("strength", mix("label", seed).alias("tie"), "label"))).alias("best")
    p = c.groupBy("id", "weight", "own").agg(stay, best).where("best IS NOT NULL")
    wanted: Column = F.col("best.strength") > F.col("stay")
    if not stay_on_tie:
        wanted |= (F.col("best.strength") == F.col("stay")) & (F.col("best.tie") > mix("own", seed))
    return p.where(wanted).select("id", "weight", F.col("best.label").alias("target"), (F.col("best.strength") - F.col("stay")).alias("gain")), weights


class _Arcs(BlockGraph):
    """A graph of which only the arcs that leave some vertices are looked at."""

    def __init__(self, g: BlockGraph, active: DataFrame):
        super().__init__(g.vertices, g.edges)
        object.__setattr__(self, "_active", active)

    def arcs(self) -> DataFrame:
        return super().arcs().join(self._active.select(F.col("id").alias("src")), "src", "left_semi")


def _only(g: BlockGraph, active: DataFrame) -> BlockGraph:
    return _Arcs(g, active)


def next_active(g: BlockGraph, moved: DataFrame) -> DataFrame:
    """(id): the neighbours of moved vertices."""
    return g.arcs().join(moved.select(F.col("id").alias("src")), "src", "left_semi").select(F.col("dst").alias("id")).distinct()


def apply_moves(labels: DataFrame, moves: DataFrame, label: str) -> DataFrame:
    return labels.join(moves.select("id", "target"), "id", "left").select("id", F.coalesce("target", label).alias(label))


@dataclass(frozen=True)
class LabelPropagation:
    """Size-constrained label propagation as DataFrame rounds.

    A round deals the active vertices to ``sub_rounds`` by packets, low degrees
    first; within a sub-round all read the same labels, and admission keeps every
    target within ``bound``.  ``admission`` is ``window``, ``histogram`` (for few
    targets) or ``quota`` (with ``ranges``).  Labels are stored after each
    sub-round, which cuts the lineage and survives the loss of executors.
    """

    bound: int
    rounds: int = 10
    sub_rounds: int = 4
    seed: int = 0
    packet: int | None = None
    stay_on_tie: bool = True
    admission: str = "window"
    ranges: int = 1

    def seed_of(self, round_: int, group: int) -> int:
        return self.seed + 1000 * round_ + group

    def step(self, g: BlockGraph, labels: DataFrame, group: DataFrame, seed: int, label: str) -> DataFrame:
        """The moves (id, target) of one sub-round."""
        p, weights = propose(g, labels, group, self.bound, seed, label, self.stay_on_tie)
        if self.admission == "histogram":
            return admit_by_histogram(stash(p), weights, self.bound, seed)
        if self.admission == "quota":
            return admit_by_quota(p, weights, self.bound, self.ranges, seed)
        return admit_by_capacity(p, weights, self.bound, seed)

    def run(self, g: BlockGraph, start: DataFrame | None = None, label: str = "cluster") -> DataFrame:
        labels = start if start is not None else g.vertices.select("id", F.col("id").alias(label))
        active: DataFrame | None = None
        for r in range(self.rounds):
            groups = stash(make_packets(g, active, self.packet, self.sub_rounds, self.seed + r))
            moved: DataFrame | None = None
            for s in range(self.sub_rounds):
                moves = stash(self.step(g, labels, groups.where(F.col("sub_round") == s), self.seed_of(r, s), label))
                labels = stash(apply_moves(labels, moves, label))
                moved = moves if moved is None else moved.unionByName(moves)
            if moved.isEmpty():
                break
            active = stash(next_active(g, moved))
        return labels


def heavy_edge_matching(g: BlockGraph, bound: int, rounds: int = 6, seed: int = 0, two_hop: bool = False) -> DataFrame:
    """(id, cluster): pairs of vertices that are each other's heaviest free neighbour; the smaller id names the pair.

    Ties go by a hash of the pair, so a heaviest edge is always mutual.  With
    ``two_hop``, vertices that are left over and share their heaviest neighbour
    are paired too.
    """
    matched: DataFrame | None = None
    for r in range(rounds):
        pairs = stash(match_round(g, matched, bound, seed + r))
        if r and pairs.isEmpty():
            break
        both = pairs.select(F.col("a").alias("id"), F.col("a").alias("cluster")).unionByName(pairs.select(F.col("b").alias("id"), F.col("a").alias("cluster")))
        matched = both if matched is None else matched.unionByName(both)
    if two_hop:
        matched = stash(matched)
        arcs = g.arcs().join(matched.select(F.col("id").alias("src")), "src", "left_anti")
        hub = arcs.groupBy("src").agg(F.max(F.struct("weight", mix("dst", seed).alias("t"), "dst")).alias("h")).select(F.col("src").alias("id"), F.col("h.dst").alias("hub"))
        hub = hub.join(g.vertices, "id").where(F.col("weight") * 2 <= bound)
        half = F.floor((F.row_number().over(Window.partitionBy("hub").orderBy("weight", "id")) - 1) / 2)
        hub = hub.withColumn("half", half)
        name = hub.groupBy("hub", "half").agg(F.min("id").alias("cluster"))
        matched = matched.unionByName(hub.join(name, ["hub", "half"]).select("id", "cluster"))
    return g.vertices.select("id").join(matched, "id", "left").select("id", F.coalesce("cluster", "id").alias("cluster"))


def match_round(g: BlockGraph, matched: DataFrame | None, bound: int, seed: int) -> DataFrame:
    """Pairs (a, b), a < b, of one handshake among free vertices."""
    w = g.vertices
    e = g.edges
    if matched is not None:
        e = e.join(matched.select(F.col("id").alias("src")), "src", "left_anti").join(matched.select(F.col("id").alias("dst")), "dst", "left_anti")
    e = e.join(w.select(F.col("id").alias("src"), F.col("weight").alias("wa")), "src").join(w.select(F.col("id").alias("dst"), F.col("weight").alias("wb")), "dst").where(F.col("wa") + F.col("wb") <= bound)
    tie = mix(mix("src", seed) + mix("dst", seed), seed)
    e = e.select("src", "dst", "weight", tie.alias("tie"))
    both = e.unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight", "tie"))
    key = F.struct("weight", "tie", F.least("src", "dst").alias("lo"), F.greatest("src", "dst").alias("hi"))
    choice = both.groupBy("src").agg(F.max(key).alias("k")).select("src", F.col("k.lo").alias("lo"), F.col("k.hi").alias("hi"))
    return choice.groupBy("lo", "hi").agg(F.count(F.lit(1)).alias("n")).where("n = 2").select(F.col("lo").alias("a"), F.col("hi").alias("b"))


def pack_isolated(g: BlockGraph, bound: int) -> DataFrame:
    """(id, cluster) of vertices without an edge, gathered in id order into clusters of at most ``bound`` (twice halved sums)."""
    lone = g.vertices.join(g.edges.select(F.col("src").alias("id")).union(g.edges.select("dst")).distinct(), "id", "left_anti")
    half = max(1, bound // 2)
    small = prefix_sum(lone.where(F.col("weight") <= half), [F.col("id")], F.col("weight"), "before").withColumn("bin", F.floor(F.col("before") / half))
    name = small.groupBy("bin").agg(F.min("id").alias("cluster"))
    return small.join(name, "bin").select("id", "cluster").unionByName(lone.where(F.col("weight") > half).select("id", F.col("id").alias("cluster")))


def remap_ids(clusters: DataFrame) -> DataFrame:
    """(cluster, coarse_id): clusters numbered 0, 1, ... in their order."""
    return dense_ids(clusters.select("cluster").distinct(), "cluster", "coarse_id")


def contract(g: BlockGraph, clusters: DataFrame) -> tuple[BlockGraph, DataFrame]:
    """The coarse graph and (id, coarse_id): weights are summed, edges inside a cluster go."""
    to = stash(clusters.join(remap_ids(clusters), "cluster").select("id", "coarse_id"))
    v = g.vertices.join(to, "id").groupBy(F.col("coarse_id").alias("id")).agg(F.sum("weight").alias("weight"))
    a, b = to.select(F.col("id").alias("src"), F.col("coarse_id").alias("ca")), to.select(F.col("id").alias("dst"), F.col("coarse_id").alias("cb"))
    e = g.edges.join(a, "src").join(b, "dst").where("ca <> cb").groupBy(F.least("ca", "cb").alias("src"), F.greatest("ca", "cb").alias("dst")).agg(F.sum("weight").alias("weight"))
    return BlockGraph(v, e), to


def project(part: DataFrame, to: DataFrame) -> DataFrame:
    """The blocks of the finer level: (id, block)."""
    return to.join(part.select(F.col("id").alias("coarse_id"), "block"), "coarse_id").select("id", "block")


def shuffle_hint(m: int, n: int, n_coarse: int, rows_per_task: int = 2_000_000) -> int:
    """Tasks for summing up coarse edges, from the smaller of the two size guesses."""
    guess = max(1, min(2 * m * max(n_coarse, 1) // max(n, 1), max(m // 10, 1)))
    return max(1, -(-guess // rows_per_task))
