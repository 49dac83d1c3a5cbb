"""A training corpus from ``documents``: five stages, each over all that the one before kept.

A stage is f(spark, docs, sf_dir); all but the last return the columns of
documents, with ``n_chars`` brought up to date where they change texts.  In all
of them a null doc_id is kept as it is and stands for nothing else, repeated rows
are rows of their own unless a stage says otherwise, columns besides those of
documents go, and no rows give no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphblocks.llm import jaccard_join, language_id, line_dedup, packing, substring_dedup
from graphblocks.llm.common import stash

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _documents(df: DataFrame) -> DataFrame:
    return df.withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def keep_known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a letter whose nearest codeword is clear stay; null, empty and letterless texts and ambiguous ones go.

    The classifiers learn from a bounded sample of rows that name their language.
    Where no row does, there is no model, and every text with a letter stays.
    """
    model = language_id.train(docs)
    if model is None:
        return docs.where(F.col("text").rlike(r"\p{L}")).select(*COLUMNS)
    found = language_id.identify(docs, model)
    return found.where((F.col("lang_pred") != language_id.UNKNOWN) & ~F.col("ambiguous")).select(*COLUMNS)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of lines that are alike the first by (doc_id, number) stays; documents that have no letter or digit left go, as all they had is elsewhere.

    A null text has no lines and stays null.
    """
    out = line_dedup.line_dedup(docs.select(*COLUMNS), "blocks")
    emptied = (F.col("n_removed") > 0) & ~F.col("text").rlike(r"[\p{L}\p{N}]")
    return _documents(out.where(~F.coalesce(emptied, F.lit(False))))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by their 5-word shingles (similarity 0.75) the one with the smallest doc_id stays; texts without words are linked with nothing."""
    return jaccard_join.keep_representatives(docs.select(*COLUMNS)).select(*COLUMNS)


def drop_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Words covered by 13-word windows that also start in a document with a smaller doc_id go; what stays is joined by spaces, and a null text becomes empty."""
    return _documents(substring_dedup.substring_dedup(docs.select(*COLUMNS)))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every token of every document in one piece of a sequence; texts without tokens have the end id alone, a null source is ''."""
    return packing.pack(docs)


STAGES = [
    ("language_id", keep_known_language),
    ("line_dedup", drop_repeated_lines),
    ("ngram_jaccard_join", drop_near_copies),
    ("substring_dedup", drop_repeated_passages),
    ("packing", pack_sequences),
]

#: Language scores, groups of alike lines and token ids can't be told in SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what one stage returns is stored and read again by the next."""
    df = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        df = stage(spark, df, sf_dir)
        if k + 1 < len(STAGES):
            df = stash(df)
    return df
