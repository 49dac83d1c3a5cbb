"""Shared storage, component and tokenizer-file helpers of the operators."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; where it is unset (tests), one of this machine."""
    conf = spark.sparkContext.getConf()
    at = conf.get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if not at:
        if not spark.sparkContext.master.split("[")[0] == "local":
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        at = "file://" + tempfile.mkdtemp(prefix="graphblocks-")
        spark.sparkContext.setCheckpointDir(at)
    return at.rstrip("/")


def stash(df: DataFrame) -> DataFrame:
    """Writes the rows as Parquet in the shared folder and reads them again: lineage ends there."""
    spark = df.sparkSession
    at = f"{shared_dir(spark)}/stash-{uuid.uuid4().hex}"
    df.write.parquet(at)
    return spark.read.schema(df.schema).parquet(at)


def unstash(df: DataFrame) -> None:
    """Deletes the files of a stash that nothing reads any more."""
    jvm = df.sparkSession._jvm
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        at = jvm.org.apache.hadoop.fs.Path(folder)
        at.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(at, True)


def drop_shuffles(df: DataFrame) -> None:
    """Lets Spark delete the shuffle files of jobs that are done: its cleaner does when the driver collects what refers to them."""
    df.sparkSession._jvm.java.lang.System.gc()


def connected(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(id, component): the smallest id that is reachable by rows (a, b) of ``links``.

    Alternating large-star and small-star rounds: each is one grouped minimum
    and one join on a key, so no component is ever gathered in one place, and
    the number of rounds is logarithmic in a component's diameter.  The minimum is
    taken in part before the shuffle, and the join with it can be split by Spark
    where one id has very many links.  Ids without
    a link have no row.  Null ends are ignored.
    """
    edges = links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u > v").distinct()
    edges = stash(edges)
    told = _signature(edges)
    for _ in range(max_rounds):
        if not told[0]:
            break
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v")
        after = stash(small.unionByName(low.select("u", F.col("m").alias("v"))).distinct())
        before, told = told, _signature(after)
        unstash(edges)
        edges = after
        if told == before:
            break
    else:
        raise RuntimeError("components did not settle")
    return edges.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(
        edges.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct()
    )


def _signature(edges: DataFrame) -> tuple:
    row = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return tuple(row)


def with_fields(schema: T.StructType, ddl: str) -> T.StructType:
    """A new schema with further fields, given as ``name type, ...``."""
    return T.StructType([*schema.fields, *T.StructType.fromDDL(ddl).fields])


def typed(docs: DataFrame) -> DataFrame:
    """The rows with a long doc_id and a string text; columns that are so already stay as they are, so that plans of one table look alike."""
    for name, kind in (("doc_id", T.LongType()), ("text", T.StringType())):
        if docs.schema[name].dataType != kind:
            docs = docs.withColumn(name, F.col(name).cast(kind))
    return docs


def text_column(docs: DataFrame, name: str = "text"):
    """The text as a string, null as it is."""
    return F.col(name).cast(T.StringType())


def tokenizer_json(path: str | None) -> bytes:
    """The content of a tokenizer file; the driver reads it and ships it to the tasks."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("word_bpe_49k.json")
    with open(path, "rb") as f:
        return f.read()
