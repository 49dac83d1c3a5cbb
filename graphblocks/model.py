"""The graph of the engine: vertices (id, weight) and canonical edges (src < dst, weight)."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import stash


class GraphError(ValueError):
    """The input is no graph that can be partitioned as asked."""


@dataclass(frozen=True)
class BlockGraph:
    """vertices: (id long, weight long), edges: (src long, dst long, weight long) with src < dst, a row for each pair.

    Where vertices are told by the edges, ``vertices_of`` does so again from the stored edges, so that these are made once.
    """

    vertices: DataFrame
    edges: DataFrame
    vertices_of: Callable[[DataFrame], DataFrame] | None = field(default=None, compare=False)

    def arcs(self) -> DataFrame:
        """(src, dst, weight) in both directions."""
        back = self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight")
        return self.edges.select("src", "dst", "weight").unionByName(back)

    def stored(self) -> BlockGraph:
        edges = stash(self.edges)
        return BlockGraph(stash(self.vertices if self.vertices_of is None else self.vertices_of(edges)), edges)

    def with_weights(self, weights: DataFrame) -> BlockGraph:
        """Vertex weights replaced by (id, weight); ids without one keep theirs."""
        new = weights.select("id", F.col("weight").cast("long").alias("new"))
        v = self.vertices.join(new, "id", "left").select("id", F.coalesce("new", "weight").alias("weight"))
        return BlockGraph(v, self.edges)


def normalize_graph(edges: DataFrame, vertices: DataFrame | None = None, strict: bool = False) -> BlockGraph:
    """A graph of any rows (src, dst[, weight]): self loops go, repeated and reversed pairs are summed up.

    Rows with a null end or a weight that is null or not positive go, or raise
    :class:`GraphError` if ``strict``.  Ends that ``vertices`` lacks are added
    with weight 1; isolated vertices stay.
    """
    if "weight" not in edges.columns:
        edges = edges.withColumn("weight", F.lit(1))
    e = edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), F.col("weight").cast("long").alias("weight"))
    good = "src IS NOT NULL AND dst IS NOT NULL AND weight IS NOT NULL AND weight > 0"
    if strict and not e.where(f"NOT coalesce({good}, false)").isEmpty():
        raise GraphError("edges have null ends or weights that aren't positive")
    e = e.where(good).where("src <> dst").groupBy(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).agg(F.sum("weight").alias("weight"))
    ends = e.select(F.col("src").alias("id")).union(e.select("dst")).distinct()
    if vertices is None:
        return BlockGraph(ends.select("id", F.lit(1).cast("long").alias("weight")), e)
    if "weight" not in vertices.columns:
        vertices = vertices.withColumn("weight", F.lit(1))
    v = vertices.where("id IS NOT NULL").groupBy(F.col("id").cast("long").alias("id")).agg(F.max(F.col("weight").cast("long")).alias("weight"))
    if strict and not v.where("weight IS NULL OR weight <= 0").isEmpty():
        raise GraphError("vertices have weights that aren't positive")
    v = v.join(ends.withColumn("_end", F.lit(True)), "id", "full").select("id", F.greatest(F.coalesce("weight", F.lit(1)), F.lit(1)).cast("long").alias("weight"))
    return BlockGraph(v, e)


def encode_ids(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Edges with string ends as numbers, and the dictionary (name, id): ids count up by name, over a two-level prefix sum."""
    from .operators.prefix import dense_ids

    names = edges.select(F.col("src").cast("string").alias("name")).union(edges.select(F.col("dst").cast("string"))).where("name IS NOT NULL").distinct()
    names = stash(dense_ids(names, "name", "id"))
    a, b = names.select(F.col("name").alias("src"), F.col("id").alias("a")), names.select(F.col("name").alias("dst"), F.col("id").alias("b"))
    rest = [c for c in edges.columns if c not in ("src", "dst")]
    out = edges.withColumns({"src": F.col("src").cast("string"), "dst": F.col("dst").cast("string")}).join(a, "src").join(b, "dst")
    return out.select(F.col("a").alias("src"), F.col("b").alias("dst"), *rest), names


class Csr:
    """A graph as arrays, for kernels: ids ascending, indptr, neighbours, arc weights, vertex weights."""

    __slots__ = ("ids", "indptr", "nbr", "w", "vw")

    def __init__(self, ids: np.ndarray, indptr: np.ndarray, nbr: np.ndarray, w: np.ndarray, vw: np.ndarray):
        self.ids, self.indptr, self.nbr, self.w, self.vw = ids, indptr, nbr, w, vw

    @property
    def n(self) -> int:
        return len(self.ids)

    def degrees(self) -> np.ndarray:
        return np.diff(self.indptr)

    def rows(self) -> np.ndarray:
        """The source of each arc."""
        return np.repeat(np.arange(self.n), np.diff(self.indptr))

    @staticmethod
    def from_arrays(ids: np.ndarray, vw: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray) -> Csr:
        """Of ids in any order and each edge once."""
        order = np.argsort(ids, kind="stable")
        ids, vw = np.asarray(ids, np.int64)[order], np.asarray(vw, np.int64)[order]
        a, b, n = np.searchsorted(ids, src), np.searchsorted(ids, dst), len(ids)
        # One number for both ends: a sort of one column, and fewer columns at a time where there are millions of arcs.
        key = np.concatenate([a * n + b, b * n + a])
        del a, b
        order = np.argsort(key, kind="stable")
        key = key[order]
        s, t = np.divmod(key, n) if n else (key, key)
        return Csr(ids, np.searchsorted(s, np.arange(n + 1)), t, np.concatenate([w, w]).astype(np.int64)[order], vw)

    def subgraph(self, keep: np.ndarray) -> Csr:
        """Induced by the vertices with true flags."""
        new = np.cumsum(keep) - 1
        arc = keep[self.rows()] & keep[self.nbr]
        rows = new[self.rows()[arc]]
        n = int(keep.sum())
        return Csr(self.ids[keep], np.searchsorted(rows, np.arange(n + 1)), new[self.nbr[arc]], self.w[arc], self.vw[keep])

    def cut(self, block: np.ndarray) -> int:
        return int(self.w[block[self.rows()] != block[self.nbr]].sum()) // 2

    def nbytes(self) -> int:
        return sum(getattr(self, s).nbytes for s in self.__slots__)


def collect_csr(graph: BlockGraph, limit: int) -> Csr | None:
    """The graph in the driver if it has at most ``limit`` arcs and vertices, else None: the count comes first."""
    m = graph.edges.count()
    if 2 * m > limit or graph.vertices.count() > limit:
        return None
    v = graph.vertices.toArrow()
    e = graph.edges.select("src", "dst", "weight").toArrow()
    col = lambda t, c: t.column(c).to_numpy()
    return Csr.from_arrays(col(v, "id"), col(v, "weight"), col(e, "src"), col(e, "dst"), col(e, "weight"))
