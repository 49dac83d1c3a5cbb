"""Measures over a log of runs: means, profiles, speed-ups, equal-time tests, significance.

A log has (graph, graph_type, k, algo, p, seed, m, cut, imbalanced, t_total, t_ls, peak_bytes).
"""

from __future__ import annotations

from itertools import permutations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashes import P, mix, mix_sql

ALGOS = ("full", "match", "dist", "seq")


def synthetic_runs(spark: SparkSession, graphs: int = 12, seeds: int = 10) -> DataFrame:
    """A log made by arithmetic, the same in Spark and SQL."""
    base = spark.range(graphs * 2 * 4 * 3 * seeds)
    r = base.select(
        "id", (F.floor(F.col("id") / seeds) % 3).cast("int").alias("pi"), (F.col("id") % seeds).cast("int").alias("seed"),
        (F.floor(F.col("id") / (3 * seeds)) % 4).cast("int").alias("ai"), (F.floor(F.col("id") / (12 * seeds)) % 2).cast("int").alias("ki"), F.floor(F.col("id") / (24 * seeds)).cast("int").alias("gi"),
    )
    pick = lambda names, i: F.element_at(F.array(*[F.lit(x) for x in names]), F.col(i) + 1)
    return r.select(
        F.concat(F.lit("g"), F.col("gi").cast("string")).alias("graph"), F.when(F.col("gi") % 3 == 0, "M").otherwise("C").alias("graph_type"),
        pick((16, 64), "ki").alias("k"), pick(ALGOS, "ai").alias("algo"), pick((1, 16, 31), "pi").alias("p"), "seed",
        ((F.col("gi") + 1) * 10000).cast("long").alias("m"),
        (1000 + F.col("gi") * 500 + F.col("ki") * 300 + F.col("ai") * 60 + mix("id", 5) % 100).cast("long").alias("cut"),
        ((F.col("ai") == 1) & (mix("id", 6) % 40 == 0)).alias("imbalanced"),
        ((100 + mix("id", 7) % 900) * (4 - F.col("ai")) / (1 + F.col("pi"))).alias("t_total"), ((10 + mix("id", 8) % 90) / (1 + 2 * F.col("pi"))).alias("t_ls"),
        (1000000 + mix("id", 9) % 1000000).cast("long").alias("peak_bytes"),
    )


def synthetic_sql(graphs: int = 12, seeds: int = 10) -> str:
    """CTE ``runs`` with the same rows."""
    algos = ", ".join(f"'{a}'" for a in ALGOS)
    return f"""r0 AS (SELECT id, (id // {seeds}) % 3 AS pi, id % {seeds} AS seed, (id // {3 * seeds}) % 4 AS ai, (id // {12 * seeds}) % 2 AS ki, id // {24 * seeds} AS gi FROM (SELECT unnest(range({graphs * 24 * seeds})) AS id)),
runs AS (SELECT 'g' || gi AS graph, CASE WHEN gi % 3 = 0 THEN 'M' ELSE 'C' END AS graph_type, ([16, 64])[ki + 1] AS k, ([{algos}])[ai + 1] AS algo, ([1, 16, 31])[pi + 1] AS p, seed::INTEGER AS seed,
 (gi + 1) * 10000 AS m, (1000 + gi * 500 + ki * 300 + ai * 60 + {mix_sql("id", 5)} % 100)::BIGINT AS cut, ai = 1 AND {mix_sql("id", 6)} % 40 = 0 AS imbalanced,
 ((100 + {mix_sql("id", 7)} % 900) * (4 - ai))::DOUBLE / (1 + pi) AS t_total, (10 + {mix_sql("id", 8)} % 90)::DOUBLE / (1 + 2 * pi) AS t_ls, 1000000 + {mix_sql("id", 9)} % 1000000 AS peak_bytes FROM r0)"""


#: The table log has the size of the arithmetic one: 12 graphs, two k, the algorithms, three p and 10 seeds.
_CELLS = 12 * 2 * 4 * 3 * 10


def table_runs(spark: SparkSession, d: str) -> DataFrame:
    """The log read from ``lineitem``: every line belongs to one run, and what the run measures is summed over its lines.

    A line's part and supplier are blocks of the run's k by their hash; a line between two blocks counts as cut. Times
    come from quantities, memory from the lines' orders. Each measure has a floor for runs with few lines or none.
    """
    lines = spark.read.parquet(f"{d}/lineitem.parquet").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", F.col("l_quantity").cast("long").alias("q"))
    lines = lines.withColumn("id", mix(F.col("l_orderkey") * 8 + F.col("l_linenumber"), 4) % _CELLS)
    k = F.when(F.floor(F.col("id") / 120) % 2 == 0, 16).otherwise(64)
    crosses = mix(F.col("l_partkey"), 1) % k != mix(F.col("l_suppkey"), 2) % k
    sums = lines.groupBy("id").agg(F.sum(crosses.cast("long")).alias("crossing"), F.sum("q").alias("q"), F.max("q").alias("top"), F.sum(F.col("l_orderkey") % 1000).alias("spread"))
    r = spark.range(_CELLS).join(sums, "id", "left").na.fill(0)
    r = r.select("*", (F.col("id") % 10).cast("int").alias("seed"), (F.floor(F.col("id") / 10) % 3).cast("int").alias("pi"), (F.floor(F.col("id") / 30) % 4).cast("int").alias("ai"), (F.floor(F.col("id") / 120) % 2).cast("int").alias("ki"), F.floor(F.col("id") / 240).alias("gi"))
    pick = lambda names, i: F.element_at(F.array(*[F.lit(x) for x in names]), F.col(i) + 1)
    return r.select(
        F.concat(F.lit("g"), F.col("gi").cast("string")).alias("graph"), F.when(F.col("gi") % 3 == 0, "M").otherwise("C").alias("graph_type"),
        pick((16, 64), "ki").alias("k"), pick(ALGOS, "ai").alias("algo"), pick((1, 16, 31), "pi").alias("p"), "seed",
        ((F.col("gi") + 1) * 10000).cast("long").alias("m"),
        (1000 + F.col("gi") * 500 + F.col("ki") * 300 + F.col("ai") * 60 + F.col("crossing")).cast("long").alias("cut"),
        ((F.col("ai") == 1) & ((F.col("q") + F.col("top")) % 40 == 0)).alias("imbalanced"),
        ((100 + F.col("q") % 900) * (4 - F.col("ai")) / (1 + F.col("pi"))).alias("t_total"), ((10 + F.col("spread") % 90) / (1 + 2 * F.col("pi"))).alias("t_ls"),
        (1000000 + F.col("spread") % 1000000).cast("long").alias("peak_bytes"),
    )


def table_sql() -> str:
    """CTE ``runs`` with the rows of :func:`table_runs`."""
    algos = ", ".join(f"'{a}'" for a in ALGOS)
    k = "(CASE WHEN (id // 120) % 2 = 0 THEN 16 ELSE 64 END)"
    return f"""l0 AS (SELECT {mix_sql("l_orderkey * 8 + l_linenumber", 4)} % {_CELLS} AS id, l_orderkey, l_partkey, l_suppkey, l_quantity::BIGINT AS q FROM lineitem),
l1 AS (SELECT id, sum(({mix_sql("l_partkey", 1)} % {k} <> {mix_sql("l_suppkey", 2)} % {k})::INTEGER)::BIGINT AS crossing, sum(q)::BIGINT AS q, max(q) AS top, sum(l_orderkey % 1000)::BIGINT AS spread FROM l0 GROUP BY id),
r0 AS (SELECT g.id, coalesce(crossing, 0) AS crossing, coalesce(q, 0) AS q, coalesce(top, 0) AS top, coalesce(spread, 0) AS spread, g.id % 10 AS seed, (g.id // 10) % 3 AS pi, (g.id // 30) % 4 AS ai, (g.id // 120) % 2 AS ki, g.id // 240 AS gi
 FROM (SELECT unnest(range({_CELLS})) AS id) g LEFT JOIN l1 ON l1.id = g.id),
runs AS (SELECT 'g' || gi AS graph, CASE WHEN gi % 3 = 0 THEN 'M' ELSE 'C' END AS graph_type, ([16, 64])[ki + 1] AS k, ([{algos}])[ai + 1] AS algo, ([1, 16, 31])[pi + 1] AS p, seed::INTEGER AS seed,
 (gi + 1) * 10000 AS m, (1000 + gi * 500 + ki * 300 + ai * 60 + crossing)::BIGINT AS cut, ai = 1 AND (q + top) % 40 = 0 AS imbalanced,
 ((100 + q % 900) * (4 - ai))::DOUBLE / (1 + pi) AS t_total, (10 + spread % 90)::DOUBLE / (1 + 2 * pi) AS t_ls, 1000000 + spread % 1000000 AS peak_bytes FROM r0)"""


def instances(runs: DataFrame) -> DataFrame:
    """A row for each (graph, k, algo, p): mean cut and times, and whether any repetition is imbalanced."""
    return runs.groupBy("graph", "graph_type", "k", "algo", "p").agg(
        F.avg("cut").alias("cut"), F.avg("t_total").alias("t_total"), F.avg("t_ls").alias("t_ls"), F.max("m").alias("m"), F.bool_or("imbalanced").alias("imbalanced"), F.max("peak_bytes").alias("peak_bytes")
    )


INSTANCES_SQL = "inst AS (SELECT graph, graph_type, k, algo, p, avg(cut) AS cut, avg(t_total) AS t_total, avg(t_ls) AS t_ls, max(m) AS m, bool_or(imbalanced) AS imbalanced, max(peak_bytes) AS peak_bytes FROM runs GROUP BY ALL)"


def geo_mean(c: str):
    return F.round(F.exp(F.avg(F.ln(c))), 6)


def harm_mean(c):
    return F.round(F.count(c) / F.sum(1 / c), 6)


def geo_mean_cut(runs: DataFrame) -> DataFrame:
    """(algo, p, geo_cut) over all instances, imbalanced ones too."""
    return instances(runs).groupBy("algo", "p").agg(geo_mean("cut").alias("geo_cut"), F.count(F.lit(1)).alias("instances"))


def by_type(runs: DataFrame) -> DataFrame:
    return instances(runs).groupBy("graph_type", "algo", "p").agg(geo_mean("cut").alias("geo_cut"), F.count(F.lit(1)).alias("instances"))


def relative_cut(runs: DataFrame, a: str, b: str) -> DataFrame:
    """(p, percent): how much smaller or larger the mean cut of ``a`` is than that of ``b``."""
    g = geo_mean_cut(runs)
    x, y = g.where(F.col("algo") == a).select("p", F.col("geo_cut").alias("x")), g.where(F.col("algo") == b).select("p", F.col("geo_cut").alias("y"))
    return x.join(y, "p").select("p", F.round((F.col("x") / F.col("y") - 1) * 100, 4).alias("percent"))


def performance_profile(runs: DataFrame) -> DataFrame:
    """(algo, p, rank, graph, k, value): 1 - best / cut of each instance, sorted; imbalanced ones are 1.1 and come last."""
    inst = instances(runs)
    best = F.min("cut").over(Window.partitionBy("graph", "k"))
    value = F.when(F.col("imbalanced"), F.lit(1.1)).when(F.col("cut") == 0, F.lit(0.0)).otherwise(F.round(1 - F.col("best") / F.col("cut"), 6))
    v = inst.withColumn("best", best).withColumn("value", value)
    rank = F.row_number().over(Window.partitionBy("algo", "p").orderBy("value", "graph", "k"))
    return v.withColumn("rank", rank).select("algo", "p", "rank", "graph", "k", "value")


def best_share(runs: DataFrame) -> DataFrame:
    """(algo, p, share): on how many instances nobody has a smaller cut."""
    inst = instances(runs)
    r = F.rank().over(Window.partitionBy("graph", "k").orderBy("cut"))
    return inst.withColumn("r", r).groupBy("algo", "p").agg(F.round(F.avg(F.when(F.col("r") == 1, 1.0).otherwise(0.0)), 6).alias("share"))


def worst_loss(runs: DataFrame) -> DataFrame:
    """(algo, p, worst): the largest distance from the best cut, in percent."""
    inst = instances(runs).withColumn("best", F.min("cut").over(Window.partitionBy("graph", "k")))
    return inst.groupBy("algo", "p").agg(F.round(F.max((F.col("cut") / F.col("best") - 1) * 100), 6).alias("worst"))


def speedups(runs: DataFrame) -> DataFrame:
    """(algo, p, full, search): harmonic means of T(1) / T(p) over balanced instances."""
    inst = instances(runs)
    one = inst.where("p = 1").select("graph", "k", "algo", F.col("t_total").alias("t1"), F.col("t_ls").alias("s1"), F.col("imbalanced").alias("i1"))
    j = inst.where("p > 1 AND NOT imbalanced").join(one.where("NOT i1"), ["graph", "k", "algo"])
    return j.groupBy("algo", "p").agg(harm_mean(F.col("t1") / F.col("t_total")).alias("full"), harm_mean(F.col("s1") / F.col("t_ls")).alias("search"))


def ns_per_edge(runs: DataFrame) -> DataFrame:
    """(algo, p, full, search): geometric means of nanoseconds per edge (times in seconds)."""
    inst = instances(runs).withColumns({"a": F.col("t_total") * 1e9 / F.col("m"), "b": F.col("t_ls") * 1e9 / F.col("m")})
    return inst.groupBy("algo", "p").agg(F.round(F.exp(F.avg(F.ln("a"))), 3).alias("full"), F.round(F.exp(F.avg(F.ln("b"))), 3).alias("search"))


def memory_saving(runs: DataFrame, a: str, b: str) -> DataFrame:
    """(graph, k, p, percent): how much less peak memory ``a`` takes than ``b``."""
    inst = instances(runs)
    x, y = (inst.where(F.col("algo") == n).select("graph", "k", "p", F.col("peak_bytes").alias(c)) for n, c in ((a, "x"), (b, "y")))
    return x.join(y, ["graph", "k", "p"]).select("graph", "k", "p", F.round((1 - F.col("x") / F.col("y")) * 100, 6).alias("percent"))


def top_speedup_imbalance(runs: DataFrame, algo: str, p: int = 31, top: int = 20) -> DataFrame:
    """One row (imbalanced, top): how many of an algorithm's best speed-ups are of imbalanced instances."""
    inst = instances(runs).where(F.col("algo") == algo)
    one = inst.where("p = 1").select("graph", "k", F.col("t_total").alias("t1"))
    j = inst.where(F.col("p") == p).join(one, ["graph", "k"]).withColumn("s", F.round(F.col("t1") / F.col("t_total"), 9))
    return j.orderBy(F.desc("s"), "graph", "k").limit(top).agg(F.sum(F.col("imbalanced").cast("int")).cast("long").alias("imbalanced"), F.count(F.lit(1)).alias("top"))


def sign_test(runs: DataFrame, a: str, b: str, p: int) -> DataFrame:
    """One row (wins, losses, z): instances on which ``a`` has the smaller and the larger cut."""
    inst = instances(runs).where(F.col("p") == p)
    x, y = (inst.where(F.col("algo") == n).select("graph", "k", F.col("cut").alias(c)) for n, c in ((a, "x"), (b, "y")))
    j = x.join(y, ["graph", "k"]).agg(F.sum((F.col("x") < F.col("y")).cast("long")).alias("wins"), F.sum((F.col("x") > F.col("y")).cast("long")).alias("losses"))
    n = F.col("wins") + F.col("losses")
    return j.select("wins", "losses", F.round((F.col("wins") - n / 2) / F.sqrt(n / 4), 6).alias("z"))


def wilcoxon(runs: DataFrame, a: str, b: str, p: int) -> DataFrame:
    """One row (n, w, z): the signed rank test of relative differences, normal approximation, tied ranks averaged."""
    inst = instances(runs).where(F.col("p") == p)
    x, y = (inst.where(F.col("algo") == n).select("graph", "k", F.col("cut").alias(c)) for n, c in ((a, "x"), (b, "y")))
    d = x.join(y, ["graph", "k"]).withColumn("d", F.round((F.col("x") - F.col("y")) / F.col("y"), 9)).where("d <> 0").withColumn("size", F.abs("d"))
    d = d.withColumn("r", F.rank().over(Window.orderBy("size")) + (F.count(F.lit(1)).over(Window.partitionBy("size")) - 1) / 2)  # a row for each instance
    s = d.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.when(F.col("d") > 0, F.col("r"))), F.lit(0.0)).alias("w"))
    n = F.col("n")
    return s.select("n", F.round("w", 6).alias("w"), F.round((F.col("w") - n * (n + 1) / 4) / F.sqrt(n * (n + 1) * (2 * n + 1) / 24), 6).alias("z"))


def virtual_instances(runs: DataFrame, a: str, b: str, p: int, count: int = 20, seed: int = 1) -> DataFrame:
    """(graph, k, vi, slow, cut_a, cut_b, time_a, time_b, samples): the faster algorithm gets the slower one's time for more repetitions.

    Each virtual instance samples a repetition of both; the faster one goes on,
    without replacement, until its time exceeds the other's, and the last sample
    counts with the probability that makes the expected times equal.
    """
    r = runs.where(F.col("p") == p).where(F.col("algo").isin(a, b)).select("graph", "k", "algo", "seed", "cut", "t_total")
    v = r.withColumn("vi", F.explode(F.sequence(F.lit(0), F.lit(count - 1))))
    key = F.col("seed") * 64 + F.col("vi") + F.lit(seed * 4096)
    v = v.withColumn("draw", F.when(F.col("algo") == a, mix(key, 11)).otherwise(mix(key, 13)))
    v = v.withColumn("first", F.row_number().over(Window.partitionBy("graph", "k", "vi", "algo").orderBy("draw", "seed")) == 1)
    group = Window.partitionBy("graph", "k", "vi")
    t = lambda n: F.max(F.when(F.col("first") & (F.col("algo") == n), F.col("t_total"))).over(group)
    c = lambda n: F.max(F.when(F.col("first") & (F.col("algo") == n), F.col("cut"))).over(group)
    v = v.withColumns({"ta": t(a), "tb": t(b), "ca": c(a), "cb": c(b)})
    v = v.withColumn("slow", F.when(F.col("ta") >= F.col("tb"), F.lit(a)).otherwise(F.lit(b))).withColumn("ts", F.greatest("ta", "tb"))
    f = v.where(F.col("algo") != F.col("slow"))
    order = Window.partitionBy("graph", "k", "vi").orderBy(F.desc("first"), mix(key, 17), "seed")
    f = f.withColumn("before", F.coalesce(F.sum("t_total").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
    chance = mix(F.col("vi") * 131 + seed, 19) < F.lit(P) * (F.col("ts") - F.col("before")) / F.col("t_total")
    f = f.where("first OR before <= ts").where((F.col("before") + F.col("t_total") <= F.col("ts")) | F.col("first") | chance)
    f = f.groupBy("graph", "k", "vi", "slow", "ta", "tb", "ca", "cb").agg(F.min("cut").alias("best"), F.sum("t_total").alias("used"), F.count(F.lit(1)).alias("samples"))
    slow_a = F.col("slow") == a
    return f.select(
        "graph", "k", "vi", "slow", F.when(slow_a, F.col("ca")).otherwise(F.col("best")).alias("cut_a"), F.when(slow_a, F.col("best")).otherwise(F.col("cb")).alias("cut_b"),
        F.round(F.when(slow_a, F.col("ta")).otherwise(F.col("used")), 6).alias("time_a"), F.round(F.when(slow_a, F.col("used")).otherwise(F.col("tb")), 6).alias("time_b"), "samples",
    )


def virtual_sql(a: str, b: str, p: int, count: int = 20, seed: int = 1, log: str | None = None) -> str:
    """The SQL of :func:`virtual_instances` over the CTE ``log``, the arithmetic one if not given."""
    key = f"(seed * 64 + vi + {seed * 4096})"
    return f"""WITH {log or synthetic_sql()},
v0 AS (SELECT graph, k, algo, seed, cut, t_total, vi FROM runs, (SELECT unnest(range({count})) AS vi) WHERE p = {p} AND algo IN ('{a}', '{b}')),
v1 AS (SELECT *, row_number() OVER (PARTITION BY graph, k, vi, algo ORDER BY CASE WHEN algo = '{a}' THEN {mix_sql(key, 11)} ELSE {mix_sql(key, 13)} END, seed) = 1 AS first FROM v0),
v2 AS (SELECT *, max(CASE WHEN first AND algo = '{a}' THEN t_total END) OVER w AS ta, max(CASE WHEN first AND algo = '{b}' THEN t_total END) OVER w AS tb,
 max(CASE WHEN first AND algo = '{a}' THEN cut END) OVER w AS ca, max(CASE WHEN first AND algo = '{b}' THEN cut END) OVER w AS cb FROM v1 WINDOW w AS (PARTITION BY graph, k, vi)),
v3 AS (SELECT *, CASE WHEN ta >= tb THEN '{a}' ELSE '{b}' END AS slow, greatest(ta, tb) AS ts FROM v2),
f AS (SELECT *, coalesce(sum(t_total) OVER (PARTITION BY graph, k, vi ORDER BY first DESC, {mix_sql(key, 17)}, seed ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM v3 WHERE algo <> slow),
h AS (SELECT graph, k, vi, slow, ta, tb, ca, cb, min(cut) AS best, sum(t_total) AS used, count(*) AS samples FROM f
 WHERE (first OR before <= ts) AND (before + t_total <= ts OR first OR {mix_sql(f"(vi * 131 + {seed})", 19)} < {P} * (ts - before) / t_total) GROUP BY ALL)
SELECT graph, k, vi::INTEGER AS vi, slow, CASE WHEN slow = '{a}' THEN ca ELSE best END AS cut_a, CASE WHEN slow = '{a}' THEN best ELSE cb END AS cut_b,
 round(CASE WHEN slow = '{a}' THEN ta ELSE used END, 6) AS time_a, round(CASE WHEN slow = '{a}' THEN used ELSE tb END, 6) AS time_b, samples::BIGINT AS samples FROM h"""


def win_share(virtual: DataFrame) -> DataFrame:
    """One row (share, worst, n): virtual instances with a smaller cut for a, and a's worst loss in percent."""
    return virtual.agg(
        F.round(F.avg(F.when(F.col("cut_a") < F.col("cut_b"), 1.0).otherwise(0.0)), 6).alias("share"), F.round(F.max((F.col("cut_a") / F.col("cut_b") - 1) * 100), 6).alias("worst"), F.count(F.lit(1)).alias("n")
    )


def expected_time(times: list[float], limit: float, from_first: bool = True) -> float:
    """The mean accepted time over all orders of ``times``, computed by enumeration: ``limit`` if the first sample counts."""
    total, orders = 0.0, list(permutations(times))
    for order in orders:
        before = 0.0
        for i, t in enumerate(order):
            if not from_first and i == 0:
                continue
            if before + t <= limit:
                before += t
            else:
                before += t * (limit - before) / t
                break
        total += before
    return total / len(orders)


def component_effect(runs: DataFrame, base: str, p: int) -> DataFrame:
    """(component, percent): how the geometric mean cut changes against the runs in which no component is parallel."""
    g = instances(runs.where(F.col("p") == p)).groupBy("algo").agg(F.exp(F.avg(F.ln("cut"))).alias("x"))
    ground = g.where(F.col("algo") == base).select(F.col("x").alias("y"))
    return g.where(F.col("algo") != base).crossJoin(F.broadcast(ground)).select(F.col("algo").alias("component"), F.round((F.col("x") / F.col("y") - 1) * 100, 4).alias("percent"))


def phase_speedup(runs: DataFrame) -> DataFrame:
    """(algo, p, search, other): harmonic mean speed-ups of local search and of all other phases over balanced instances."""
    i = instances(runs).where("NOT imbalanced")
    one = i.where("p = 1").select("graph", "k", "algo", F.col("t_ls").alias("a_ls"), (F.col("t_total") - F.col("t_ls")).alias("a_rest"))
    x = i.where("p > 1").join(one, ["graph", "k", "algo"])
    x = x.select("algo", "p", (F.col("a_ls") / F.col("t_ls")).alias("search"), (F.col("a_rest") / (F.col("t_total") - F.col("t_ls"))).alias("other"))
    return x.groupBy("algo", "p").agg(harm_mean(F.col("search")).alias("search"), harm_mean(F.col("other")).alias("other"))
