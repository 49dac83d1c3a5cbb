"""The pipeline's stages, each against what it must do with its own input."""

import corpus_pipeline as P
import duckdb

from graphblocks.llm import jaccard_join, language_id
from graphblocks.llm.line_dedup import line_dedup
from graphblocks.llm.substring_dedup import brute_force

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def planted():
    """Rows that a stage must reject or link: without a letter, null, and a copy with other line breaks, which shares no line."""
    words = [f"word{chr(97 + i % 26)}{chr(97 + i // 26)}{'xyz'[i % 3]}" for i in range(120)]
    by = lambda n: "\n".join(" ".join(words[i : i + n]) for i in range(0, 120, n))
    return [(1, "###", "en", "a", 3), (2, None, None, None, None), (3, by(120), "en", "a", None), (4, by(7), "en", None, None)]


def test_stages(spark):
    docs = spark.createDataFrame([(d + 10**6, *r) for d, *r in planted()], SCHEMA)
    df = spark.read.parquet(f"{SF}/documents.parquet").unionByName(docs)
    names = [n for n, _ in P.STAGES]
    assert names == ["language_id", "line_dedup", "ngram_jaccard_join", "substring_dedup", "packing"]
    out = {}
    for name, f in P.STAGES:
        before = df.cache()
        df = f(spark, before, SF)
        out[name] = (before, df)
        if name != "packing":
            assert df.columns == list(P.COLUMNS)
    a, b = out["language_id"]
    found = language_id.identify(a, language_id.train(a)).where("lang_pred <> 'und' AND NOT ambiguous")
    assert a.count() - b.count() >= 2 and {r[0] for r in b.select("doc_id").collect()} == {r[0] for r in found.select("doc_id").collect()}
    assert b.where(f"doc_id IN ({10**6 + 1}, {10**6 + 2})").count() == 0
    a, b = out["line_dedup"]
    lost = {r["doc_id"]: r["n_lines"] - r["n_removed"] for r in line_dedup(a.select("doc_id", "text"), "blocks").collect()}
    assert any(v == 0 for v in lost.values())
    gone = {r[0] for r in a.select("doc_id").collect()} - {r[0] for r in b.select("doc_id").collect()}
    assert {d for d, v in lost.items() if v == 0} <= gone and b.where("text = ''").count() == 0
    a, b = out["ngram_jaccard_join"]
    told = duckdb.connect()
    told.register("documents", a.toPandas())
    want = {d for d, _, c in told.execute(jaccard_join.SQL).fetchall() if d == c}
    assert {r[0] for r in b.select("doc_id").collect()} == want and 10**6 + 3 in want and 10**6 + 4 not in want
    a, b = out["substring_dedup"]
    want = {d: n - r for d, n, r, _ in brute_force([(r["doc_id"], r["text"]) for r in a.collect()], 13)}
    assert {r["doc_id"]: len((r["text"] or "").split()) for r in b.collect()} == want
    a, b = out["packing"]
    assert b.select("doc_id").distinct().count() == a.count()


def test_nothing(spark):
    df = spark.createDataFrame([], SCHEMA)
    for _, f in P.STAGES:
        df = f(spark, df, SF)
        assert df.count() == 0


def test_no_language_is_named(spark):
    df = spark.createDataFrame([(1, "some words here", None, None, None), (2, "123", None, None, None), (None, "more", None, None, None)], SCHEMA)
    assert {r[1] for r in P.keep_known_language(spark, df, SF).collect()} == {"some words here", "more"}
