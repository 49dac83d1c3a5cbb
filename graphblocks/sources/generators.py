"""Instance generators: random geometric, Delaunay, G(n, p), hyperbolic, and regular graphs with known cuts."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashes import P, mix
from ..model import BlockGraph, normalize_graph


def _edges(spark: SparkSession, n: int, a: np.ndarray, b: np.ndarray) -> BlockGraph:
    pdf = pd.DataFrame({"src": np.asarray(a, np.int64), "dst": np.asarray(b, np.int64)})
    edges = spark.createDataFrame(pdf) if len(pdf) else spark.createDataFrame([], "src long, dst long")
    return normalize_graph(edges, spark.range(n))


def random_points(spark: SparkSession, n: int, seed: int) -> DataFrame:
    """(id, x, y) in the unit square."""
    return spark.range(n).select("id", (mix("id", seed) / F.lit(float(P))).alias("x"), (mix("id", seed + 7919) / F.lit(float(P))).alias("y"))


def gen_rgg(spark: SparkSession, x: int, seed: int = 1) -> BlockGraph:
    """2**x random points, joined below 0.55 sqrt(ln n / n), by a join on cells."""
    from .tables import near_points

    n = 1 << x
    points = random_points(spark, n, seed)
    return BlockGraph(points.select("id", F.lit(1).cast("long").alias("weight")), near_points(points, 0.55 * math.sqrt(math.log(n) / n)))


def gen_er(spark: SparkSession, n: int, factor: float = 1.5, seed: int = 1) -> BlockGraph:
    """G(n, p) with p = factor ln n / n: each vertex skips to its next larger neighbour by a geometric step, task by task."""
    p = min(1.0, factor * math.log(max(n, 2)) / n)

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in parts:
            src, dst = [], []
            for v in pdf["id"].tolist():
                rng = np.random.default_rng((seed, v))
                room = n - 1 - v
                count = rng.binomial(room, p) if room > 0 else 0
                if count:
                    dst.append(v + 1 + rng.choice(room, count, replace=False))
                    src.append(np.full(count, v))
            if src:
                yield pd.DataFrame({"src": np.concatenate(src), "dst": np.concatenate(dst)})

    return normalize_graph(spark.range(n).mapInPandas(run, "src long, dst long"), spark.range(n))


def gen_rhg(spark: SparkSession, n: int, alpha: float = 0.75, degree: float = 10.0, seed: int = 1) -> BlockGraph:
    """Random hyperbolic graph by the threshold model: points in a disc, joined below its radius.

    Points are dealt to radial bands and, within a pair of bands, to angle cells
    as wide as an edge between them can reach: equi-joins again.
    """
    radius = 2 * math.log(8 * n * alpha**2 / (math.pi * degree * (2 * alpha - 1) ** 2)) if n > 1 else 1.0
    u, v = mix("id", seed) / F.lit(float(P)), mix("id", seed + 104729) / F.lit(float(P))
    r = F.acosh(1 + (math.cosh(alpha * radius) - 1) * u) / alpha
    points = spark.range(n).select("id", r.alias("r"), (v * 2 * math.pi).alias("phi"))
    bands = max(1, int(radius))
    low = F.least(F.floor(F.col("r") / (radius / bands)), F.lit(bands - 1)).cast("int")
    points = points.withColumn("band", low)
    plan = []
    for a in range(bands):
        for b in range(a, bands):
            ra, rb = a * radius / bands, b * radius / bands
            top = (math.cosh(ra) * math.cosh(rb) - math.cosh(radius)) / (math.sinh(ra) * math.sinh(rb)) if ra > 0 and rb > 0 else -1.0
            reach = math.acos(max(-1.0, min(1.0, top)))
            plan.append((a, b, max(1, int(2 * math.pi / max(reach, 2 * math.pi / 65536)))))
    pairs = F.broadcast(spark.createDataFrame(plan, "band_a int, band_b int, cells int"))
    cell = F.least(F.floor(F.col("phi") / (2 * math.pi) * F.col("cells")), F.col("cells") - 1).cast("int")
    a = points.join(pairs, F.col("band") == F.col("band_a")).select("band_a", "band_b", "cells", F.col("id").alias("src"), F.col("r").alias("r1"), F.col("phi").alias("p1"), cell.alias("cell"))
    b = points.join(pairs, F.col("band") == F.col("band_b")).select("band_a", "band_b", "cells", F.col("id").alias("dst"), F.col("r").alias("r2"), F.col("phi").alias("p2"), cell.alias("own"))
    b = b.withColumn("cell", F.explode(F.array_distinct(F.array(*[F.pmod(F.col("own") + s, F.col("cells")) for s in (-1, 0, 1)]))))
    near = F.cosh("r1") * F.cosh("r2") - F.sinh("r1") * F.sinh("r2") * F.cos(F.col("p1") - F.col("p2")) < math.cosh(radius)
    rows = a.join(b, ["band_a", "band_b", "cells", "cell"]).where("src <> dst").where(near)
    rows = rows.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()
    return BlockGraph(spark.range(n).select("id", F.lit(1).cast("long").alias("weight")), rows.withColumn("weight", F.lit(1).cast("long")))


def delaunay_edges(points: np.ndarray) -> np.ndarray:
    """Edges (i < j) of the Delaunay triangulation, by inserting points into a triangulation and flipping no edge: cavities are re-filled."""
    n = len(points)
    if n < 2:
        return np.zeros((0, 2), np.int64)
    if n == 2:
        return np.array([[0, 1]])
    far = 50.0
    pts = [tuple(p) for p in points.tolist()] + [(-far, -far), (far, -far), (0.5, far)]
    triangles: dict[int, tuple[int, int, int]] = {0: (n, n + 1, n + 2)}
    beside: dict[tuple[int, int], int] = {(n, n + 1): 0, (n + 1, n + 2): 0, (n + 2, n): 0}
    count, last = 1, 0

    def side(a: int, b: int, p: tuple[float, float]) -> float:
        (ax, ay), (bx, by) = pts[a], pts[b]
        return (bx - ax) * (p[1] - ay) - (by - ay) * (p[0] - ax)

    def in_circle(t: int, p: tuple[float, float]) -> bool:
        m = [(pts[v][0] - p[0], pts[v][1] - p[1]) for v in triangles[t]]
        s = [x * x + y * y for x, y in m]
        (ax, ay), (bx, by), (cx, cy) = m
        return ax * (by * s[2] - cy * s[1]) - ay * (bx * s[2] - cx * s[1]) + s[0] * (bx * cy - cx * by) > 0

    order = np.lexsort((points[:, 1], np.floor(points[:, 0] * math.sqrt(n))))
    for i in order.tolist():
        p = pts[i]
        t = last if last in triangles else next(iter(triangles))
        for _ in range(4 * n + 10):  # walk towards the point
            a, b, c = triangles[t]
            for u, v in ((a, b), (b, c), (c, a)):
                if side(u, v, p) < 0:
                    t = beside[v, u]
                    break
            else:
                break
        bad, todo = {t}, [t]
        while todo:
            a, b, c = triangles[todo.pop()]
            for u, v in ((a, b), (b, c), (c, a)):
                o = beside.get((v, u))
                if o is not None and o not in bad and in_circle(o, p):
                    bad.add(o)
                    todo.append(o)
        rim = []
        for x in bad:
            a, b, c = triangles[x]
            rim += [(u, v) for u, v in ((a, b), (b, c), (c, a)) if beside.get((v, u)) not in bad]
        for x in bad:
            a, b, c = triangles.pop(x)
            for e in ((a, b), (b, c), (c, a)):
                beside.pop(e, None)
        for u, v in rim:
            triangles[count] = (u, v, i)
            for e in ((u, v), (v, i), (i, u)):
                beside[e] = count
            last, count = count, count + 1
    found = {(min(u, v), max(u, v)) for u, v in beside if u < n and v < n}
    return np.array(sorted(found), np.int64)


def gen_delaunay(spark: SparkSession, x: int, seed: int = 1) -> BlockGraph:
    """The Delaunay triangulation of 2**x random points, up to x = 16 in one kernel."""
    if x > 16:
        raise ValueError("the kernel takes up to 2**16 points")
    p = random_points(spark, 1 << x, seed).toPandas().sort_values("id")
    e = delaunay_edges(p[["x", "y"]].to_numpy())
    return _edges(spark, 1 << x, e[:, 0], e[:, 1])


def path(spark: SparkSession, n: int) -> BlockGraph:
    return _edges(spark, n, np.arange(n - 1), np.arange(1, n))


def star(spark: SparkSession, leaves: int) -> BlockGraph:
    return _edges(spark, leaves + 1, np.zeros(leaves), np.arange(1, leaves + 1))


def complete(spark: SparkSession, n: int) -> BlockGraph:
    return _edges(spark, n, *np.triu_indices(n, 1))


def grid(spark: SparkSession, *sides: int, wrap: bool = False) -> BlockGraph:
    """A grid of any dimension, or a torus."""
    index = np.arange(int(np.prod(sides))).reshape(sides)
    a, b = [], []
    for axis, size in enumerate(sides):
        if size > 1:
            a.append(np.take(index, range(size - 1), axis).ravel())
            b.append(np.take(index, range(1, size), axis).ravel())
            if wrap and size > 2:
                a.append(np.take(index, [size - 1], axis).ravel())
                b.append(np.take(index, [0], axis).ravel())
    return _edges(spark, index.size, np.concatenate(a), np.concatenate(b))


def clique_ring(spark: SparkSession, cliques: int, size: int) -> BlockGraph:
    """Cliques joined in a ring by single edges."""
    i, j = np.triu_indices(size, 1)
    base = np.arange(cliques) * size
    a, b = (base[:, None] + i).ravel(), (base[:, None] + j).ravel()
    return _edges(spark, cliques * size, np.concatenate([a, base + size - 1]), np.concatenate([b, np.roll(base, -1)]))


def planted(spark: SparkSession, blocks: int, size: int, inside: float, outside: float, seed: int = 1) -> BlockGraph:
    """Random edges, more likely inside blocks of consecutive ids; for small n."""
    n = blocks * size
    i, j = np.triu_indices(n, 1)
    keep = np.random.default_rng(seed).random(len(i)) < np.where(i // size == j // size, inside, outside)
    return _edges(spark, n, i[keep], j[keep])
