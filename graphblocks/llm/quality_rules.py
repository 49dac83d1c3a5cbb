"""Rule-based quality filter: one threshold table, compiled into one projection.

Every measure is a built-in expression of the text, so the whole filter runs in
the scan's stage: no shuffle, no join, no user function.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_column

#: Space and the characters 0x09 to 0x0D part words.
_BLANKS = "\t\n\x0b\x0c\r"
_ALL_BLANKS = " " + _BLANKS
#: Characters that count as symbols.
_SYMBOLS = "#*$%&|<>"
#: Frequent function words of the corpus languages.
STOP_WORDS = (
    "a an and are as at be by for from has he in is it its of on or that the this to was were will with "
    "au aux ce dans de des du elle en est et il la le les ne par pas pour que qui sur un une "
    "als am auf das dem den der die ein eine für im ist mit nicht sich sie und von zu "
    "al como con del el es los más no para por se su una y"
).split()


@dataclass(frozen=True)
class Rule:
    """Keeps a row while ``low`` * denominator <= 1000 * numerator <= ``high`` * denominator (thousandths).

    A bound of None holds always, and a rule holds for texts of fewer than
    ``from_words`` words.
    """

    name: str
    numerator: str
    denominator: str
    low: int | None = None
    high: int | None = None
    from_words: int = 0


#: The threshold table.
RULES = (
    Rule("word_length", "word_chars", "n_words", low=1500, high=20000),
    Rule("symbols", "n_symbols", "word_chars", high=40),
    Rule("exclamations", "n_exclaims", "n_words", high=150),
    Rule("duplicate_lines", "n_dup_lines", "n_text_lines", high=400),
    Rule("stop_words", "n_stop_words", "n_words", low=10, from_words=60),
)
MIN_WORDS, WINDOW, MAX_REPEAT_PERCENT = 20, 8, 30


def split_words(text: Column) -> Column:
    """Runs of characters other than space and 0x09 to 0x0D."""
    return F.array_remove(F.split(F.translate(text, _BLANKS, " " * len(_BLANKS)), " "), "")


def _repeat_words(windows: Column, size: int) -> Column:
    """Words that lie in windows (given by their hashes) found twice or more."""
    by_hash = F.sort_array(F.transform(windows, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    n = F.size(windows)

    def again(x: Column, k: Column) -> Column:
        before, after = F.get(by_sorted, k - 1)["h"], F.get(by_sorted, k + 1)["h"]
        return F.coalesce(before == x["h"], F.lit(False)) | F.coalesce(after == x["h"], F.lit(False))

    by_sorted = F.col("_sorted")
    starts = F.sort_array(F.transform(F.filter(by_sorted, again), lambda x: x["i"].cast("long")))
    zero = F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("end"))
    covered = F.aggregate(
        starts, zero,
        lambda a, p: F.struct((a["n"] + p + size - F.greatest(a["end"], p)).alias("n"), (p + size).alias("end")),
    )["n"]
    return F.when(F.size(F.array_distinct(windows)) < n, by_hash), covered


def quality_measures(docs: DataFrame) -> DataFrame:
    """Adds the measures that the rules use to the rows (null text: as empty)."""
    text = F.coalesce(text_column(docs), F.lit(""))
    own = ["_text", "_words", "_lines", "_windows", "_sorted"]
    df = docs.withColumn("_text", text).withColumn("_words", split_words(F.col("_text")))
    lines = F.filter(F.split("_text", "\n"), lambda x: F.translate(x, _ALL_BLANKS, "") != "")
    df = df.withColumns({
        "n_words": F.size("_words").cast("long"),
        "word_chars": F.length(F.translate("_text", _ALL_BLANKS, "")).cast("long"),
        "n_symbols": (F.length("_text") - F.length(F.translate("_text", _SYMBOLS, ""))).cast("long"),
        "n_exclaims": (F.length("_text") - F.length(F.translate("_text", "!", ""))).cast("long"),
        "_lines": lines,
        "n_stop_words": F.size(F.filter("_words", lambda w: F.lower(w).isin(STOP_WORDS))).cast("long"),
        "_windows": F.when(F.size("_words") > WINDOW, F.transform(F.sequence(F.lit(1), F.size("_words") - (WINDOW - 1)), lambda i: F.xxhash64(F.slice("_words", i, WINDOW)))),
    })
    by_hash, covered = _repeat_words(F.col("_windows"), WINDOW)
    return df.withColumn("_sorted", by_hash).withColumns({
        "n_text_lines": F.size("_lines").cast("long"),
        "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"),
        "n_repeat_words": F.coalesce(F.when(F.col("_sorted").isNotNull(), covered), F.lit(0).cast("long")),
    }).drop(*own)


def verdict(rules: tuple[Rule, ...] = RULES) -> Column:
    """The conjunction of the table's rules over the columns of :func:`quality_measures`."""
    out = F.lit(True)
    for r in rules:
        share, whole = F.col(r.numerator) * 1000, F.col(r.denominator)
        holds = F.lit(True)
        if r.low is not None:
            holds &= share >= whole * r.low
        if r.high is not None:
            holds &= share <= whole * r.high
        out &= (F.col("n_words") < r.from_words) | holds if r.from_words else holds
    return out


def quality_rules(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """One row per document with its measures, ``base_failed`` and ``kept``.

    A null or empty text has all measures 0 and fails the base rule.  Columns of
    the input with the names of measures are overwritten; other columns and
    repeated rows are passed on.  No rows give no rows.
    """
    base = (F.col("n_words") < MIN_WORDS) | (F.col("n_repeat_words") * 100 > F.col("n_words") * MAX_REPEAT_PERCENT)
    return quality_measures(docs).withColumn("base_failed", base).withColumn("kept", ~F.col("base_failed") & verdict(rules))


def digest(docs: DataFrame) -> DataFrame:
    """The contract's columns."""
    names = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"]
    return quality_rules(docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_column(docs).alias("text"))).select(*names)


def _sql_rule(r: Rule) -> str:
    parts = []
    if r.low is not None:
        parts.append(f"{r.numerator} * 1000 >= {r.denominator} * {r.low}")
    if r.high is not None:
        parts.append(f"{r.numerator} * 1000 <= {r.denominator} * {r.high}")
    both = " AND ".join(parts) or "true"
    return f"({both})" if not r.from_words else f"(n_words < {r.from_words} OR ({both}))"


#: DuckDB SQL of the digest over ``documents``.
SQL = f"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, text, regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+') AS words,
             list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS lines FROM t),
g AS (SELECT doc_id, i, words[i : i + {WINDOW - 1}] AS win FROM w, LATERAL unnest(range(1, len(words) - {WINDOW - 2})) AS u(i)),
d AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, win) AS c FROM g) WHERE c > 1),
r AS (SELECT doc_id, count(DISTINCT i + o) AS n FROM d, range({WINDOW}) AS k(o) GROUP BY doc_id),
m AS (SELECT doc_id, len(words)::BIGINT AS n_words,
             length(regexp_replace(text, '[\\x20\\x09-\\x0D]+', '', 'g'))::BIGINT AS word_chars,
             (length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
             (length(text) - length(replace(text, '!', '')))::BIGINT AS n_exclaims,
             len(lines)::BIGINT AS n_text_lines, (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines,
             len(list_filter(words, lambda x: lower(x) IN ({", ".join(f"'{s}'" for s in STOP_WORDS)})))::BIGINT AS n_stop_words,
             coalesce(r.n, 0)::BIGINT AS n_repeat_words
      FROM w LEFT JOIN r USING (doc_id)),
b AS (SELECT *, n_words < {MIN_WORDS} OR n_repeat_words * 100 > n_words * {MAX_REPEAT_PERCENT} AS base_failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND {" AND ".join(map(_sql_rule, RULES))} AS kept
FROM b
"""
