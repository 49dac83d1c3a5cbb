"""Language identification by error-correcting output codes over byte trigrams.

Every language has a codeword of +1 and -1; for each bit a linear classifier on
hashed trigram frequencies tells the sign.  A text gets the language whose
codeword has the least loss, with bits weighted by how well their classifiers
did on the rows they learned from.  When two codewords are close, the row is
flagged as ambiguous.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import kernels as K
from .common import text_column, with_fields

CELLS = 4096
#: The classifiers are fitted on at most this many rows, evenly over the languages.
SAMPLE_ROWS = 4000
UNKNOWN = "und"
#: Below this score a row is ambiguous.
AMBIGUOUS = 0.6


def codebook(n: int, seed: int = 7) -> np.ndarray:
    """(n, bits) codewords of +1 and -1: all splits for up to 5 languages, else random ones far apart."""
    if n <= 1:
        return np.ones((n, 1))
    if n <= 5:
        bits = np.arange(1, 2 ** (n - 1))
        return np.array([[1.0 if i == 0 or not (b >> (i - 1)) & 1 else -1.0 for b in bits.tolist()] for i in range(n)])
    rng = np.random.default_rng(seed)
    size = max(15, math.ceil(10 * math.log2(n)))
    best, apart = None, -1
    for _ in range(64):
        code = rng.choice([-1.0, 1.0], (n, size))
        gap = int((code[:, None] != code[None]).sum(2)[np.triu_indices(n, 1)].min())
        if gap > apart:
            best, apart = code, gap
    return best


def _cells(data: np.ndarray) -> np.ndarray:
    """The cell of the trigram that starts at each byte, after lower-casing ASCII and making blanks spaces."""
    low = K.LOWER[data]
    low = np.where(K.SEPARATOR[low], np.uint8(32), low).astype(np.uint32)
    if len(low) < 3:
        return np.zeros(0, np.int64)
    h = low[:-2] * np.uint32(0x9E3779B1) + low[1:-1] * np.uint32(0x85EBCA77) + low[2:] * np.uint32(0xC2B2AE3D)
    h ^= h >> np.uint32(15)
    h *= np.uint32(0x27D4EB2F)
    return (h >> np.uint32(20)).astype(np.int64)


def _row_bounds(offsets: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """First and past last trigram of each row."""
    first = np.minimum(offsets[:-1], n)
    return first, np.maximum(np.minimum(offsets[1:] - 2, n), first)


def trigram_counts(data: np.ndarray, offsets: np.ndarray, out: np.ndarray | None = None) -> np.ndarray:
    """(rows, CELLS) counts, in ``out`` if it is given."""
    cells = _cells(data)
    first, last = _row_bounds(offsets, len(cells))
    out = np.zeros((len(first), CELLS), np.float32) if out is None else out
    for r, (a, b) in enumerate(zip(first.tolist(), last.tolist())):
        out[r] = np.bincount(cells[a:b], minlength=CELLS)
    return out


@dataclass
class LanguageModel:
    """Languages in ascending order, their codewords, and the bits' linear classifiers."""

    languages: list[str]
    code: np.ndarray
    weight: np.ndarray
    bias: np.ndarray
    trust: np.ndarray

    def bits(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """(rows, bits) outputs of the classifiers, over whole texts."""
        cells = _cells(data)
        first, last = _row_bounds(offsets, len(cells))
        out = np.zeros((len(first), len(self.bias)))
        full = np.flatnonzero(last > first)
        if len(full):
            edge = np.stack([first[full], last[full]], 1).ravel()
            value = np.concatenate([self.weight[cells], np.zeros((1, self.weight.shape[1]), np.float32)])
            sums = np.add.reduceat(value, edge, axis=0)[::2]
            out[full] = sums / (last - first)[full, None]
        return out + self.bias

    def decode(self, outputs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Index of the nearest codeword by weighted logistic loss, and how sure that is (0 to 1)."""
        margin = outputs[:, None, :] * self.code[None]
        loss = (np.logaddexp(0, -margin) * self.trust).sum(2)
        away = np.exp(-(loss - loss.min(1, keepdims=True)))
        share = away / away.sum(1, keepdims=True)
        best = loss.argmin(1)
        return best, share[np.arange(len(best)), best]


def fit(counts: np.ndarray, languages: list[str], steps: int = 150) -> LanguageModel:
    """Fits the bits' classifiers (logistic loss, ridge) on the rows' counts, which are overwritten: the driver has room for them once."""
    names = sorted(set(languages))
    code = codebook(len(names))
    want = code[[names.index(x) for x in languages]]
    x = np.asarray(counts, np.float32)
    x /= np.maximum(x.sum(1, keepdims=True), 1)
    scale = 1 / (np.concatenate([x[:, i : i + 256].std(0) for i in range(0, CELLS, 256)]) + 1e-4)
    mean = x.mean(0)
    x -= mean
    x *= scale
    w = np.zeros((CELLS, code.shape[1]), np.float32)
    b = np.zeros(code.shape[1], np.float32)
    m, v = np.zeros_like(w), np.zeros_like(w)
    for t in range(1, steps + 1):
        out = x @ w + b
        slope = -want / (1 + np.exp(np.clip(want * out, -30, 30))) / len(x)
        grad = x.T @ slope.astype(np.float32) + 1e-4 * w
        b -= slope.sum(0).astype(np.float32)
        m = 0.9 * m + 0.1 * grad
        v = 0.999 * v + 0.001 * grad * grad
        w -= 0.01 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    right = ((x @ w + b) * want > 0).mean(0)
    trust = np.log(np.clip(right, 0.55, 0.999) / (1 - np.clip(right, 0.55, 0.999)))
    weight = (w * scale[:, None]).astype(np.float32)
    return LanguageModel(names, code, weight, (b - mean @ weight).astype(np.float64), trust / trust.max())


def train(docs: DataFrame, sample_rows: int = SAMPLE_ROWS) -> LanguageModel | None:
    """Fits a model on at most ``sample_rows`` rows, or one for each language, with a language and a text of over 20 characters; None if there is none.

    Every language has the same room, so a rare one keeps its rows however many languages there are.
    """
    known = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (F.length("text") > 20)).select("doc_id", "lang", "text")
    sizes = {r["lang"]: r["n"] for r in known.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not sizes:
        return None
    each = max(1, sample_rows // len(sizes))
    bar = F.lit(0.0)
    for name, n in sizes.items():
        bar = F.when(F.col("lang") == name, F.lit(min(1.0, 1.1 * each / n))).otherwise(bar)
    order = F.pmod(F.xxhash64("doc_id", F.lit(11)), F.lit(1 << 30))
    # Few rows pass the bar; of these, each language keeps its own first ones.
    picked = known.withColumn("order", order).where(F.col("order") < bar * (1 << 30))
    picked = picked.withColumn("place", F.row_number().over(Window.partitionBy("lang").orderBy("order", "doc_id"))).where(F.col("place") <= each)
    rows = picked.select("text", "lang").toArrow()
    return fit(*sample_counts(rows))


def sample_counts(rows: pa.Table) -> tuple[np.ndarray, list[str]]:
    """The counts of the sample's texts and their languages, without copies of either."""
    counts = np.zeros((rows.num_rows, CELLS), np.float32)
    for i, j, data, offsets in K.byte_chunks(rows.column("text")):
        trigram_counts(data, offsets, counts[i:j])
    return counts, rows.column("lang").to_pylist()


def identify(docs: DataFrame, model: LanguageModel | None) -> DataFrame:
    """The rows with ``lang_pred``, ``lang_score`` (0 to 1) and ``ambiguous``.

    A null text and one without a letter are ``und`` with score 0; without a
    model all are.  Texts of under three bytes get the language that the
    classifiers' constants favour.  Other columns and repeated rows are passed
    on; columns of the input with these three names are replaced.
    """
    docs = docs.drop("lang_pred", "lang_score", "ambiguous").withColumn("text", text_column(docs))
    names = docs.columns
    shipped = docs.sparkSession.sparkContext.broadcast(model)
    text_at = names.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shipped.value
        for batch in batches:
            lettered = np.asarray(batch.column(len(names)).fill_null(False))
            for i, j, data, offsets in K.byte_chunks(batch.column(text_at)):
                own = lettered[i:j]
                if m is None:
                    own = np.zeros(j - i, bool)
                    best, sure = np.zeros(j - i, int), np.zeros(j - i)
                else:
                    best, sure = m.decode(m.bits(data, offsets))
                lang = [m.languages[k] if o else UNKNOWN for k, o in zip(best.tolist(), own.tolist())]
                sure = np.where(own, sure, 0.0)
                part = batch.slice(i, j - i)
                yield pa.RecordBatch.from_arrays([*part.columns[: len(names)], pa.array(lang, pa.string()), pa.array(sure), pa.array(sure < AMBIGUOUS)], [*names, "lang_pred", "lang_score", "ambiguous"])

    schema = with_fields(docs.schema, "lang_pred string, lang_score double, ambiguous boolean")
    return docs.withColumn("_lettered", F.col("text").rlike(r"\p{L}")).mapInArrow(run, schema)


def held_out(remainder: int, of: int):
    """Whether the checksum of the doc_id as text has this remainder; false for null ids."""
    return F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(of)) == remainder, F.lit(False))


def digest(docs: DataFrame) -> DataFrame:
    """The contract's columns: learned from rows with remainders 0 and 2 only."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_column(docs).alias("text"), F.col("lang").cast("string").alias("lang"))
    model = train(docs.where(~held_out(1, 3)))
    out = identify(docs.select("doc_id", "text").withColumn("held_out", held_out(1, 3)), model)
    return out.select("doc_id", "held_out", "lang_pred", F.col("lang_score").alias("score"), "ambiguous")
