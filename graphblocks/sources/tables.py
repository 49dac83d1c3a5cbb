"""Graphs derived from the given tables, each as a plan and as the DuckDB SQL of its edges.

Every function takes (spark, sf_dir) and gives a :class:`BlockGraph`.  Scans are
pruned to two to four columns.  Bipartite ids are 2 * x on the left and
2 * y + 1 on the right.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import BlockGraph, normalize_graph

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"no table {name}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _summed(pairs: DataFrame) -> DataFrame:
    return pairs.groupBy("src", "dst").agg(F.sum("weight").alias("weight"))


def _counted(pairs: DataFrame) -> DataFrame:
    return pairs.groupBy(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")).agg(F.count(F.lit(1)).alias("weight"))


def _graph(edges: DataFrame, vertices: DataFrame | None = None) -> BlockGraph:
    """Edges that are canonical already; vertices are their ends, and those given."""

    def vertices_of(e: DataFrame) -> DataFrame:
        ends = e.select(F.col("src").alias("id")).union(e.select("dst"))
        if vertices is not None:
            ends = ends.union(vertices.select(F.col("id").cast("long")))
        return ends.distinct().select("id", F.lit(1).cast("long").alias("weight"))

    return BlockGraph(vertices_of(edges), edges, vertices_of)


def _same_order(spark: SparkSession, d: str, column: str) -> DataFrame:
    """Pairs of different values in one order, a row for each pair of lines."""
    lines = load(spark, d, "lineitem").select("l_orderkey", column)
    a, b = lines.withColumnRenamed(column, "src"), lines.withColumnRenamed(column, "dst")
    return _counted(a.join(b, "l_orderkey").where("src < dst"))


def part_copurchase(spark: SparkSession, d: str) -> BlockGraph:
    """Parts in the same order."""
    return _graph(_same_order(spark, d, "l_partkey"), load(spark, d, "part").select(F.col("p_partkey").alias("id")))


def supp_supp(spark: SparkSession, d: str) -> BlockGraph:
    """Suppliers that share an order."""
    return _graph(_same_order(spark, d, "l_suppkey"), load(spark, d, "supplier").select(F.col("s_suppkey").alias("id")))


def _bipartite(rows: DataFrame, left: str, right: str) -> BlockGraph:
    a, b = F.col(left) * 2, F.col(right) * 2 + 1
    return _graph(_counted(rows.select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst"))))


def cust_supp(spark: SparkSession, d: str) -> BlockGraph:
    """Customers and suppliers, by lines."""
    o = load(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    return _bipartite(load(spark, d, "lineitem").select("l_orderkey", "l_suppkey").join(o, "l_orderkey"), "o_custkey", "l_suppkey")


def order_part(spark: SparkSession, d: str) -> BlockGraph:
    return _bipartite(load(spark, d, "lineitem").select("l_orderkey", "l_partkey"), "l_orderkey", "l_partkey")


def part_supp(spark: SparkSession, d: str) -> BlockGraph:
    return _bipartite(load(spark, d, "lineitem").select("l_partkey", "l_suppkey"), "l_partkey", "l_suppkey")


def nation_trade(spark: SparkSession, d: str) -> BlockGraph:
    """Nations, by lines from a customer's to another supplier's."""
    o = load(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("c_custkey"))
    c = load(spark, d, "customer").select("c_custkey", "c_nationkey")
    s = load(spark, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey")
    rows = load(spark, d, "lineitem").select("l_orderkey", "l_suppkey").join(o, "l_orderkey").join(c, "c_custkey").join(s, "l_suppkey").where("c_nationkey <> s_nationkey")
    e = _counted(rows.select(F.least("c_nationkey", "s_nationkey").alias("src"), F.greatest("c_nationkey", "s_nationkey").alias("dst")))
    return _graph(e, load(spark, d, "nation").select(F.col("n_nationkey").alias("id")))


def doc_overlap(spark: SparkSession, d: str, size: int = 5, most: int = 50) -> BlockGraph:
    """Documents that share shingles of ``size`` words found in 2 to ``most`` documents; weight is how many.

    The upper bound belongs to the graph's definition; it also bounds the pairs of a shingle.
    """
    words = F.expr(r"regexp_extract_all(text, '[^ \\n\\t\\r]+', 0)")
    docs = load(spark, d, "documents").select("doc_id", words.alias("w")).where(F.size("w") >= size)
    grams = docs.select("doc_id", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - (size - 1)), lambda i: F.concat_ws(" ", F.slice("w", i, size))))).alias("g"))
    # Of each shingle at most one document beyond ``most`` is kept, which tells that there are too many; so texts are cut into shingles once, and no list gets longer.
    # A hash before the shingle lets most comparisons in sorts end at a number.
    place = F.row_number().over(Window.partitionBy("h", "g").orderBy("doc_id"))
    first = grams.withColumn("h", F.xxhash64("g")).withColumn("place", place).where(F.col("place") <= most + 1)
    ids = first.groupBy("h", "g").agg(F.sort_array(F.collect_list("doc_id")).alias("ids")).where(f"size(ids) BETWEEN 2 AND {most}").select("ids")
    pairs = ids.select("ids", F.posexplode("ids").alias("i", "src")).select("src", F.explode(F.slice("ids", F.col("i") + 2, F.size("ids"))).alias("dst"))
    return _graph(_counted(pairs), load(spark, d, "documents").select(F.col("doc_id").alias("id")))


def page_links(spark: SparkSession, d: str) -> BlockGraph:
    """Pages and the targets that they link to; targets are numbered by name."""
    from ..operators.prefix import dense_ids

    refs = load(spark, d, "pages").select("page_id", F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")).alias("href")).distinct()
    names = dense_ids(refs.select("href").distinct(), "href", "target")
    return _bipartite(refs.join(names, "href"), "page_id", "target")


def user_chain(spark: SparkSession, d: str) -> BlockGraph:
    """Users of consecutive events by (ts, event_id).

    A window runs within each day; the last user of the day before is joined to
    it, so no window holds all events.
    """
    day = load(spark, d, "events").select("event_id", "ts", "user_id", F.to_date("ts").alias("day"))
    inside = Window.partitionBy("day").orderBy("ts", "event_id")
    edge = day.groupBy("day").agg(F.max(F.struct("ts", "event_id", "user_id")).alias("last"))
    before = edge.select("day", F.lag("last.user_id").over(Window.partitionBy(F.lit(0)).orderBy("day")).alias("carry"))  # a row for each day
    rows = day.withColumn("prev", F.lag("user_id").over(inside)).join(before, "day").withColumn("prev", F.coalesce("prev", "carry")).where("prev IS NOT NULL AND prev <> user_id")
    return _graph(_counted(rows.select(F.least("prev", "user_id").alias("src"), F.greatest("prev", "user_id").alias("dst"))))


def user_key(spark: SparkSession, d: str) -> BlockGraph:
    """Users and the k of their events' properties."""
    rows = load(spark, d, "events").select("user_id", F.get_json_object("props", "$.k").cast("long").alias("k"))
    return _bipartite(rows, "user_id", "k")


def conv_path(spark: SparkSession, d: str) -> BlockGraph:
    """Consecutive turns of conversations; the id of a turn is conv_id * 1024 + turn."""
    t = load(spark, d, "conversations").select("conv_id", (F.col("conv_id") * 1024 + F.col("turn")).alias("id"), "turn")
    rows = t.withColumn("src", F.lag("id").over(Window.partitionBy("conv_id").orderBy("turn"))).where("src IS NOT NULL")
    return _graph(_counted(rows.select("src", F.col("id").alias("dst"))), t.select("id"))


def doc_source(spark: SparkSession, d: str) -> BlockGraph:
    """Documents and their sources: stars."""
    rows = load(spark, d, "documents").select("doc_id", F.regexp_extract("source", r"(\d+)", 1).cast("long").alias("s"))
    return _bipartite(rows, "doc_id", "s")


def contamination(spark: SparkSession, d: str) -> BlockGraph:
    """Benchmark items (right) and the documents that contain their text, found by a shared five-word start."""
    start = F.expr(r"concat_ws(' ', slice(regexp_extract_all({0}, '[^ \\n\\t\\r]+', 0), 1, 5))".replace("{0}", "text"))
    items = load(spark, d, "benchmark").select("item_id", F.col("text").alias("passage"), start.alias("g"))
    words = F.expr(r"regexp_extract_all(text, '[^ \\n\\t\\r]+', 0)")
    docs = load(spark, d, "documents").select("doc_id", "text", words.alias("w")).where("size(w) >= 5")
    grams = docs.select("doc_id", "text", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - 4), lambda i: F.concat_ws(" ", F.slice("w", i, 5))))).alias("g"))
    hits = grams.join(items, "g").where(F.contains("text", "passage")).select("doc_id", "item_id").distinct()
    return _bipartite(hits, "doc_id", "item_id")


def _points(spark: SparkSession, d: str) -> pd.DataFrame:
    """Ranks of the first two coordinates, centred in n cells; the embeddings table is small by definition here."""
    return unit_points(load(spark, d, "embeddings")).toPandas().sort_values("id")


def unit_points(embeddings: DataFrame) -> DataFrame:
    """(id, x, y): (rank - 1/2) / n of the first two coordinates, ties by id; ranks come from two-level prefix sums."""
    from ..operators.prefix import prefix_sum

    n = embeddings.count()
    v = embeddings.select(F.col("vec_id").alias("id"), F.col("embedding")[0].cast("double").alias("c0"), F.col("embedding")[1].cast("double").alias("c1"))
    rx = prefix_sum(v.select("id", "c0"), [F.col("c0"), F.col("id")], F.lit(1).cast("long"), "r0").select("id", "r0")
    ry = prefix_sum(v.select("id", "c1"), [F.col("c1"), F.col("id")], F.lit(1).cast("long"), "r1").select("id", "r1")
    return rx.join(ry, "id").select("id", ((F.col("r0") + 0.5) / F.lit(float(n))).alias("x"), ((F.col("r1") + 0.5) / F.lit(float(n))).alias("y"))


def near_points(points: DataFrame, radius: float) -> DataFrame:
    """Edges of points that are closer than ``radius``: an equi-join on cells of that size and a filter, no cross join."""
    r2 = radius * radius
    cell = points.withColumns({"cx": F.floor(F.col("x") / radius), "cy": F.floor(F.col("y") / radius)})
    step = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in (-1, 0, 1) for j in (-1, 0, 1)])
    around = cell.withColumn("s", F.explode(step)).select(F.col("id").alias("dst"), F.col("x").alias("x2"), F.col("y").alias("y2"), (F.col("cx") + F.col("s.i")).alias("cx"), (F.col("cy") + F.col("s.j")).alias("cy"))
    dist = (F.col("x") - F.col("x2")) * (F.col("x") - F.col("x2")) + (F.col("y") - F.col("y2")) * (F.col("y") - F.col("y2"))
    return cell.join(around, ["cx", "cy"]).where(F.col("id") < F.col("dst")).where(dist < r2).select(F.col("id").alias("src"), "dst", F.lit(1).cast("long").alias("weight"))


def emb_rgg(spark: SparkSession, d: str) -> BlockGraph:
    """The random geometric graph of the points: edges below 0.55 sqrt(ln n / n)."""
    e = load(spark, d, "embeddings")
    n = e.count()
    points = unit_points(e)
    return _graph(near_points(points, 0.55 * float(np.sqrt(np.log(n) / n))), points.select("id"))


def emb_knn(spark: SparkSession, d: str, neighbours: int = 8) -> BlockGraph:
    """The nearest neighbours of each vector by cosine, made symmetric.

    Vectors are compared in blocks: each task has one block of rows against all
    blocks in turn and keeps the best of each row, so memory is bounded.
    """
    e = load(spark, d, "embeddings").select("vec_id", "embedding")
    n = e.count()
    side = max(1, -(-n // 2048))
    block = F.pmod(F.xxhash64("vec_id"), F.lit(side))
    rows = e.withColumn("a", block).withColumn("b", F.explode(F.sequence(F.lit(0), F.lit(side - 1)))).withColumn("mine", F.lit(True))
    other = e.withColumn("b", block).withColumn("a", F.explode(F.sequence(F.lit(0), F.lit(side - 1)))).withColumn("mine", F.lit(False))

    def nearest(pdf: pd.DataFrame) -> pd.DataFrame:
        q, r = pdf[pdf.mine], pdf[~pdf.mine]
        x, y = np.array(q.embedding.tolist(), np.float64), np.array(r.embedding.tolist(), np.float64)
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        y /= np.linalg.norm(y, axis=1, keepdims=True)
        s = np.round(x @ y.T, 12)
        ids = r.vec_id.to_numpy()
        s[q.vec_id.to_numpy()[:, None] == ids[None]] = -2
        best = np.argsort(np.where(s > -2, -s, 9), axis=1, kind="stable")[:, :neighbours] if len(ids) <= neighbours else np.array([np.lexsort((ids, -row))[:neighbours] for row in s])
        take = np.take_along_axis(s, best, 1)
        keep = take > -2
        return pd.DataFrame({"id": np.repeat(q.vec_id.to_numpy(), best.shape[1])[keep.ravel()], "nbr": ids[best].ravel()[keep.ravel()], "s": take.ravel()[keep.ravel()]})

    pairs = rows.unionByName(other).groupBy("a", "b").applyInPandas(nearest, "id long, nbr long, s double")
    rank = F.row_number().over(Window.partitionBy("id").orderBy(F.desc("s"), "nbr"))
    top = pairs.withColumn("r", rank).where(F.col("r") <= neighbours)
    edges = top.select(F.least("id", "nbr").alias("src"), F.greatest("id", "nbr").alias("dst")).distinct().withColumn("weight", F.lit(1).cast("long"))
    return _graph(edges, e.select(F.col("vec_id").alias("id")))


def emb_del(spark: SparkSession, d: str) -> BlockGraph:
    """The Delaunay triangulation of the points of :func:`emb_rgg`; a kernel on one task's worth of points."""
    from .generators import delaunay_edges

    p = _points(spark, d)
    pairs = delaunay_edges(p[["x", "y"]].to_numpy())
    ids = p["id"].to_numpy()
    a, b = ids[pairs[:, 0]], ids[pairs[:, 1]]
    edges = spark.createDataFrame(pd.DataFrame({"src": np.minimum(a, b), "dst": np.maximum(a, b), "weight": np.ones(len(a), np.int64)}))
    return _graph(edges, spark.createDataFrame(p[["id"]]))


GRAPHS: dict[str, Callable[[SparkSession, str], BlockGraph]] = {
    "part_copurchase": part_copurchase, "cust_supp": cust_supp, "order_part": order_part, "part_supp": part_supp, "supp_supp": supp_supp,
    "nation_trade": nation_trade, "doc_overlap": doc_overlap, "page_links": page_links, "emb_knn": emb_knn, "emb_rgg": emb_rgg, "emb_del": emb_del,
    "user_chain": user_chain, "user_key": user_key, "conv_path": conv_path, "doc_source": doc_source, "contamination": contamination,
}
#: Mesh-like graphs; the others are complex networks.
MESHES = {"emb_knn", "emb_rgg", "emb_del", "conv_path"}


def _pairs_sql(column: str) -> str:
    return f"SELECT a.{column} AS src, b.{column} AS dst, count(*)::BIGINT AS weight FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.{column} < b.{column} GROUP BY ALL"


def _bipartite_sql(rows: str, left: str, right: str) -> str:
    return f"SELECT least(2 * {left}, 2 * {right} + 1) AS src, greatest(2 * {left}, 2 * {right} + 1) AS dst, count(*)::BIGINT AS weight FROM {rows} GROUP BY ALL"


#: DuckDB SQL of the edges (src, dst, weight).
EDGES_SQL: dict[str, str] = {
    "part_copurchase": _pairs_sql("l_partkey"),
    "supp_supp": _pairs_sql("l_suppkey"),
    "cust_supp": _bipartite_sql("lineitem JOIN orders ON l_orderkey = o_orderkey", "o_custkey", "l_suppkey"),
    "order_part": _bipartite_sql("lineitem", "l_orderkey", "l_partkey"),
    "part_supp": _bipartite_sql("lineitem", "l_partkey", "l_suppkey"),
    "nation_trade": "SELECT least(c_nationkey, s_nationkey)::BIGINT AS src, greatest(c_nationkey, s_nationkey)::BIGINT AS dst, count(*)::BIGINT AS weight FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE c_nationkey <> s_nationkey GROUP BY ALL",
    "doc_overlap": r"SELECT a.doc_id AS src, b.doc_id AS dst, count(*)::BIGINT AS weight FROM (SELECT *, count(*) OVER (PARTITION BY g) AS df FROM (SELECT DISTINCT doc_id, array_to_string(w[i : i + 4], ' ') AS g FROM (SELECT doc_id, regexp_extract_all(text, '[^ \n\t\r]+') AS w FROM documents), LATERAL unnest(range(1, len(w) - 3)) AS u(i))) a JOIN (SELECT DISTINCT doc_id, array_to_string(w[i : i + 4], ' ') AS g FROM (SELECT doc_id, regexp_extract_all(text, '[^ \n\t\r]+') AS w FROM documents), LATERAL unnest(range(1, len(w) - 3)) AS u(i)) b ON a.g = b.g AND a.doc_id < b.doc_id WHERE a.df BETWEEN 2 AND 50 GROUP BY ALL",
    "page_links": """SELECT least(2 * page_id, 2 * t + 1) AS src, greatest(2 * page_id, 2 * t + 1) AS dst, 1::BIGINT AS weight FROM (SELECT page_id, dense_rank() OVER (ORDER BY href) - 1 AS t FROM (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages))""",
    "user_chain": "SELECT least(p, user_id) AS src, greatest(p, user_id) AS dst, count(*)::BIGINT AS weight FROM (SELECT user_id, lag(user_id) OVER (ORDER BY ts, event_id) AS p FROM events) WHERE p <> user_id GROUP BY ALL",
    "user_key": _bipartite_sql("(SELECT user_id, json_extract_string(props, '$.k')::BIGINT AS k FROM events)", "user_id", "k"),
    "conv_path": "SELECT p AS src, id AS dst, count(*)::BIGINT AS weight FROM (SELECT conv_id * 1024 + turn AS id, lag(conv_id * 1024 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS p FROM conversations) WHERE p IS NOT NULL GROUP BY ALL",
    "doc_source": _bipartite_sql("(SELECT doc_id, regexp_extract(source, '(\\d+)', 1)::BIGINT AS s FROM documents)", "doc_id", "s"),
    "contamination": _bipartite_sql("(SELECT DISTINCT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text))", "doc_id", "item_id"),
    "emb_rgg": "WITH p AS (SELECT vec_id AS id, (row_number() OVER (ORDER BY embedding[1], vec_id) - 0.5::DOUBLE) / (SELECT count(*) FROM embeddings) AS x, (row_number() OVER (ORDER BY embedding[2], vec_id) - 0.5::DOUBLE) / (SELECT count(*) FROM embeddings) AS y FROM embeddings) SELECT a.id AS src, b.id AS dst, 1::BIGINT AS weight FROM p a JOIN p b ON a.id < b.id WHERE (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) < (SELECT 0.55 * 0.55 * ln(count(*)) / count(*) FROM embeddings)",
    "emb_knn": "WITH s AS (SELECT a.vec_id AS a, b.vec_id AS b, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 12) DESC, b.vec_id) AS r FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst, 1::BIGINT AS weight FROM s WHERE r <= 8",
}
#: DuckDB SQL of further vertices (id) besides the edges' ends.
MORE_VERTICES_SQL = {
    "part_copurchase": "SELECT p_partkey AS id FROM part", "supp_supp": "SELECT s_suppkey AS id FROM supplier", "nation_trade": "SELECT n_nationkey::BIGINT AS id FROM nation",
    "doc_overlap": "SELECT doc_id AS id FROM documents", "conv_path": "SELECT conv_id * 1024 + turn AS id FROM conversations",
    "emb_rgg": "SELECT vec_id AS id FROM embeddings", "emb_knn": "SELECT vec_id AS id FROM embeddings",
}


def graph_ctes(name: str) -> str:
    """CTEs ``e`` (src, dst, weight), ``v`` (id, weight) and ``arcs`` of a graph, to start a WITH."""
    more = f" UNION {MORE_VERTICES_SQL[name]}" if name in MORE_VERTICES_SQL else ""
    return (
        f"e AS MATERIALIZED ({EDGES_SQL[name]}), v AS MATERIALIZED (SELECT id, 1::BIGINT AS weight FROM (SELECT src AS id FROM e UNION SELECT dst FROM e{more})), "
        "arcs AS MATERIALIZED (SELECT src, dst, weight FROM e UNION ALL SELECT dst, src, weight FROM e)"
    )
