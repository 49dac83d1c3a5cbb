"""Edges from a stream of events: windows, sessions, late rows, joins, and assignment on the fly."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..storage import shared_dir

EVENTS = T.StructType([
    T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampType()), T.StructField("user_id", T.LongType()),
    T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType()),
])


def stream_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of files."""
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", "events*.parquet").parquet(sf_dir)


def stream_edges(events: DataFrame) -> DataFrame:
    """(ts, src, dst): user and the k of its event, as bipartite ids."""
    k = F.get_json_object("props", "$.k").cast("long")
    return events.where("user_id IS NOT NULL AND props IS NOT NULL").select("ts", (F.col("user_id") * 2).alias("src"), (k * 2 + 1).alias("dst"))


def windowed_edges(edges: DataFrame, kind: str, length: str, slide: str | None = None, delay: str | None = None) -> DataFrame:
    """Edge weights by window: ``tumbling``, ``sliding`` or ``session`` (per user, closed by a gap of ``length``)."""
    if delay is not None:
        edges = edges.withWatermark("ts", delay)
    if kind == "session":
        g = edges.groupBy(F.session_window("ts", length).alias("w"), "src")
        return g.agg(F.count(F.lit(1)).alias("weight")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "src", "weight")
    w = F.window("ts", length, slide) if kind == "sliding" else F.window("ts", length)
    g = edges.groupBy(w.alias("w"), F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"))
    return g.agg(F.count(F.lit(1)).alias("weight")).select(F.col("w.start").alias("start"), "src", "dst", "weight")


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there, into a table of the shared folder, and reads it."""
    import uuid

    spark = stream.sparkSession
    at = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", f"{at}/out").option("checkpointLocation", f"{at}/log").outputMode(mode).trigger(availableNow=True).start()
    else:
        # Each batch brings all changed rows; the last state of the table is the newest complete batch.
        def keep(df: DataFrame, batch: int) -> None:
            df.write.mode("overwrite").parquet(f"{at}/out")

        q = stream.writeStream.foreachBatch(keep).option("checkpointLocation", f"{at}/log").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/out")


def join_blocks(events: DataFrame, part: DataFrame) -> DataFrame:
    """Each event with the current block of its user: stream and static table."""
    return events.join(part.select(F.col("id").alias("user_id"), "block"), "user_id").select("event_id", "user_id", "block")


def dedup_events(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Events without those that were delivered again."""
    if events.isStreaming:
        return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])
    return events.dropDuplicates(["event_id"])


def interval_edges(events: DataFrame, first: str, then: str, seconds: int, delay: str = "1 hour") -> DataFrame:
    """(src, dst): event ids of a user where an event of one type follows another within some seconds."""
    a = events.where(F.col("event_type") == first).select(F.col("event_id").alias("src"), F.col("ts").alias("ta"), F.col("user_id").alias("ua"))
    b = events.where(F.col("event_type") == then).select(F.col("event_id").alias("dst"), F.col("ts").alias("tb"), F.col("user_id").alias("ub"))
    if events.isStreaming:
        a, b = a.withWatermark("ta", delay), b.withWatermark("tb", delay)
    near = F.expr(f"ua = ub AND tb >= ta AND tb <= ta + interval {seconds} seconds AND src <> dst")
    return a.join(b, near).select("src", "dst")


def streaming_assign(vertices: DataFrame, shards: int, k: int, bound: int) -> DataFrame:
    """(id, block): one pass with state; vertices (id, tie, ts) go to the block that their tie's earlier vertices took, while it has room.

    Each shard keeps the sizes of its part of every block's room, bound / shards,
    so shards don't talk and no block grows beyond the bound.  A vertex for which
    a shard has no room in any block gets block -1, to be placed by refinement.
    """
    room = bound // shards

    def assign(key, batches, state):
        sizes, places = state.get if state.exists else ([0] * k, "{}")
        import json

        sizes, places = list(sizes), json.loads(places)
        for pdf in batches:
            out = []
            for i, tie in zip(pdf["id"].tolist(), pdf["tie"].tolist()):
                b = places.get(str(tie))
                if b is None or sizes[b] >= room:
                    b = min(range(k), key=lambda x: (sizes[x], x))
                if sizes[b] >= room:
                    out.append(-1)
                    continue
                places[str(tie)] = b
                sizes[b] += 1
                out.append(b)
            yield pd.DataFrame({"id": pdf["id"], "block": pd.array(out, dtype="int32")})
        state.update((sizes, json.dumps(places)))

    keyed = vertices.withColumn("shard", F.pmod("id", F.lit(shards)))
    return keyed.groupBy("shard").applyInPandasWithState(assign, "id long, block int", "sizes array<long>, places string", "append", "NoTimeout")


def late_rows(batches: list[DataFrame], delay_seconds: int) -> DataFrame:
    """(batch, rows, late): of batches in the order of their arrival, the rows older than the watermark that the batches before have set.

    The watermark is the latest time seen less the delay, as Spark has it between micro-batches; such rows are left out of windows.
    """
    out, seen = None, None
    for n, df in enumerate(batches):
        bar = F.lit(None).cast("timestamp") if seen is None else F.lit(seen) - F.expr(f"interval {delay_seconds} seconds")
        row = df.agg(F.lit(n).alias("batch"), F.count(F.lit(1)).alias("rows"), F.coalesce(F.sum((F.col("ts") < bar).cast("long")), F.lit(0)).alias("late"), F.max("ts").alias("high"))
        high = row.first()["high"]
        seen = high if seen is None or (high is not None and high > seen) else seen
        row = row.drop("high")
        out = row if out is None else out.unionByName(row)
    return out


def restarted(events: DataFrame, halves: int = 2) -> DataFrame:
    """The ids of events that a stream writes which is stopped after each part of its input and started again from its log: each once."""
    import uuid

    spark = events.sparkSession
    at = f"{shared_dir(spark)}/restart-{uuid.uuid4().hex}"
    for h in range(halves):
        events.where(F.pmod("event_id", F.lit(halves)) == h).write.mode("append").parquet(f"{at}/in")
        stream = spark.readStream.schema(EVENTS).parquet(f"{at}/in").select("event_id")
        q = stream.writeStream.format("parquet").option("path", f"{at}/out").option("checkpointLocation", f"{at}/log").trigger(availableNow=True).start()
        q.awaitTermination()
    return spark.read.parquet(f"{at}/out")


def incremental_refinement(edges: DataFrame, k: int, eps: float, rounds: int = 1) -> tuple[DataFrame, list[dict]]:
    """Keeps a partition of a growing graph: (id, block) after the last batch of a stream of (src, dst), and a row of figures for each batch.

    A batch's new vertices go to the blocks by hash order where there is room; then label propagation refines
    within the bound of the graph so far.  Each batch's graph and blocks are stored.
    """
    from ..functions.hashes import mix
    from ..model import BlockGraph, normalize_graph
    from ..operators.measures import block_weights, edge_cut, l_max
    from ..operators.prefix import prefix_sum
    from ..operators.refinement import lp_refine
    from ..storage import stash

    state: dict = {"edges": None, "part": None}
    figures: list[dict] = []

    def take(batch: DataFrame, number: int) -> None:
        fresh = batch.select("src", "dst", F.lit(1).cast("long").alias("weight"))
        rows = fresh if state["edges"] is None else state["edges"].unionByName(fresh)
        state["edges"] = stash(rows)
        g = normalize_graph(state["edges"]).stored()
        n = g.vertices.count()
        if not n:
            return
        bound = l_max(n, k, eps)
        known = state["part"]
        new = g.vertices.select("id") if known is None else g.vertices.select("id").join(known, "id", "left_anti")
        # New vertices fill the blocks' room up to an equal share, block by block: offsets tell where each block's room begins.
        load = [0] * k if known is None else [r["weight"] for r in block_weights(g, known, k).orderBy("block").collect()]  # k rows
        share, start, steps = -(-n // k), 0, []
        for b in range(k):
            steps.append((b, start))
            start += max(0, share - load[b])
        placed = prefix_sum(new.withColumn("tie", mix("id", 7)), [F.col("tie"), F.col("id")], F.lit(1).cast("long"), "place")
        block = F.lit(steps[0][0])
        for b, s in steps[1:]:
            block = F.when(F.col("place") >= s, F.lit(b)).otherwise(block)
        part = placed.select("id", block.cast("int").alias("block"))
        part = stash(part if known is None else known.unionByName(part))
        before = edge_cut(g, part).first()["cut"]
        state["part"] = stash(lp_refine(BlockGraph(g.vertices, g.edges), part, k, bound, rounds, number))
        heaviest = block_weights(g, state["part"], k).agg(F.max("weight")).first()[0]
        figures.append({"batch": number, "n": n, "before": before, "cut": edge_cut(g, state["part"]).first()["cut"], "heaviest": heaviest, "bound": bound})

    import uuid

    log = f"{shared_dir(edges.sparkSession)}/refine-{uuid.uuid4().hex}"
    q = edges.writeStream.foreachBatch(take).option("checkpointLocation", log).trigger(availableNow=True).start()
    q.awaitTermination()
    return state["part"], figures
