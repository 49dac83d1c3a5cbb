"""Quality classifier: a factorisation machine over hashed words, structure statistics and metadata.

The score of a row is w0 + sum w_i x_i + sum over pairs <v_i, v_j> x_i x_j.  The
pairs take linear time: for each factor, half of (sum v x)^2 - sum (v x)^2.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .common import text_column, with_fields
from .language_id import held_out

WORD_CELLS = 8192
FACTORS = 6
#: The machine is fitted on at most this many labelled rows.
SAMPLE_ROWS = 3000
THRESHOLD = 0.3
#: Structure statistics (per byte, word or line) and metadata (sizes), in this order.
STATISTICS = ("symbols", "marks", "bars", "capitals", "digits", "letters_beyond_ascii", "mean_word", "distinct_words", "next_word_same", "repeated_lines", "repeated_grams", "log_bytes", "log_words", "log_lines")
_N_STATS = len(STATISTICS)

_KIND = np.zeros((6, 256), bool)
for _k, _chars in enumerate((b"#*$%&<>@~^_=", b"!?", b"|", bytes(range(65, 91)), b"0123456789", bytes(range(128, 256)))):
    _KIND[_k, list(_chars)] = True


def _per_row(flags: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(flags)])
    return (total[bounds[1:]] - total[bounds[:-1]]).astype(np.float64)


def _repeats(h: np.ndarray, row: np.ndarray, n_rows: int) -> np.ndarray:
    """How many of each row's values occurred in it before."""
    order = np.lexsort((h, row))
    a, b = h[order], row[order]
    again = np.zeros(len(a), bool)
    again[1:] = (a[1:] == a[:-1]) & (b[1:] == b[:-1])
    return np.bincount(b[again], minlength=n_rows).astype(np.float64)


def features(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(row, cell, value) of the hashed words, by row, and the (rows, statistics) table."""
    n_rows = len(offsets) - 1
    starts, ends, first = K.word_spans(data, offsets)
    low = K.LOWER[data]
    words = K.span_hash(K.prefix_hash(low), starts, ends)
    n_words = np.diff(first).astype(np.float64)
    row = np.repeat(np.arange(n_rows), np.diff(first))
    key, count = np.unique(row * WORD_CELLS + (words >> np.uint64(51)).astype(np.int64), return_counts=True)
    word_row, cell = key // WORD_CELLS, key % WORD_CELLS
    value = count / np.sqrt(np.maximum(np.bincount(word_row, count.astype(np.float64) ** 2, n_rows), 1))[word_row]

    n_bytes = np.diff(offsets).astype(np.float64)
    stats = np.zeros((n_rows, _N_STATS))
    per_byte = np.maximum(n_bytes, 1)
    per_word = np.maximum(n_words, 1)
    for k in range(6):
        stats[:, k] = _per_row(_KIND[k][data], offsets) / (per_byte if k not in (1, 2) else per_word)
    stats[:, 6] = np.minimum(_per_row(~K.SEPARATOR[data], offsets) / per_word, 50) / 10
    stats[:, 7] = 1 - _repeats(words, row, n_rows) / per_word
    same = np.zeros(len(words), bool)
    same[1:] = (words[1:] == words[:-1]) & (row[1:] == row[:-1])
    stats[:, 8] = _per_row(same, first) / per_word
    # Lines: spans between line ends.
    at = np.flatnonzero(data == 10)
    cut = np.unique(np.concatenate([offsets, at, at + 1]))
    a, b = cut[:-1], cut[1:]
    line = np.flatnonzero(data[np.minimum(a, max(len(data) - 1, 0))] != 10) if len(data) else np.zeros(0, np.int64)
    line_row = np.searchsorted(offsets, a[line], "right") - 1
    n_lines = np.bincount(line_row, minlength=n_rows).astype(np.float64)
    stats[:, 9] = _repeats(K.span_hash(K.prefix_hash(data), a[line], b[line]), line_row, n_rows) / np.maximum(n_lines, 1)
    grams = K.gram_hash(words, 4)
    index, gram_row = K.gram_rows(first, 4, len(grams))
    stats[:, 10] = _repeats(grams[index], gram_row, n_rows) / np.maximum(np.bincount(gram_row, minlength=n_rows), 1)
    stats[:, 11] = np.log1p(n_bytes) / 10
    stats[:, 12] = np.log1p(n_words) / 10
    stats[:, 13] = np.log1p(n_lines) / 10
    return word_row, cell, value, stats


@dataclass
class FactorMachine:
    """Features 0..WORD_CELLS-1 are words, then come the statistics, which are centred and scaled."""

    constant: float
    linear: np.ndarray
    factor: np.ndarray
    mean: np.ndarray
    scale: np.ndarray

    def sums(self, word_row: np.ndarray, cell: np.ndarray, value: np.ndarray, stats: np.ndarray):
        """Of each row: the linear part, sum v x, and sum (v x)^2."""
        n = len(stats)
        x = np.clip((stats - self.mean) * self.scale, -6, 6)
        flat = x @ self.linear[WORD_CELLS:] + np.bincount(word_row, self.linear[cell] * value, n)
        vs = self.factor[WORD_CELLS:]
        first = x @ vs
        square = (x * x) @ (vs * vs)
        vw = self.factor[cell] * value[:, None]
        bound = np.searchsorted(word_row, np.arange(n + 1))
        for out, add in ((first, vw), (square, vw * vw)):
            total = np.concatenate([np.zeros((1, FACTORS)), np.cumsum(add, 0)])
            out += total[bound[1:]] - total[bound[:-1]]
        return flat, first, square, x

    def margin(self, word_row, cell, value, stats) -> np.ndarray:
        flat, first, square, _ = self.sums(word_row, cell, value, stats)
        return self.constant + flat + 0.5 * (first * first - square).sum(1)


def fit(parts: tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray], labels: np.ndarray, steps: int = 80, seed: int = 5) -> FactorMachine:
    """Full-batch Adam on the logistic loss, both classes weighted alike."""
    word_row, cell, value, stats = parts
    rng = np.random.default_rng(seed)
    m = FactorMachine(0.0, np.zeros(WORD_CELLS + _N_STATS), rng.normal(0, 0.02, (WORD_CELLS + _N_STATS, FACTORS)), stats.mean(0), 1 / (stats.std(0) + 1e-3))
    weight = np.where(labels == 1, 0.5 / max(labels.mean(), 1e-9), 0.5 / max(1 - labels.mean(), 1e-9))
    state = [np.zeros_like(m.linear), np.zeros_like(m.linear), np.zeros_like(m.factor), np.zeros_like(m.factor)]
    for t in range(1, steps + 1):
        flat, first, square, x = m.sums(word_row, cell, value, stats)
        out = m.constant + flat + 0.5 * (first * first - square).sum(1)
        slope = weight * (1 / (1 + np.exp(-np.clip(out, -30, 30))) - labels) / len(labels)
        m.constant -= 0.5 * slope.sum()
        linear = np.concatenate([np.bincount(cell, slope[word_row] * value, WORD_CELLS), x.T @ slope]) + 2e-4 * m.linear
        factor = np.empty_like(m.factor)
        for f in range(FACTORS):
            v = m.factor[:, f]
            factor[:WORD_CELLS, f] = np.bincount(cell, slope[word_row] * value * (first[word_row, f] - v[cell] * value), WORD_CELLS)
            factor[WORD_CELLS:, f] = x.T @ (slope * first[:, f]) - v[WORD_CELLS:] * ((x * x).T @ slope)
        factor += 5e-4 * m.factor
        for k, (theta, grad, rate) in enumerate(((m.linear, linear, 0.05), (m.factor, factor, 0.02))):
            a, b = state[2 * k], state[2 * k + 1]
            a *= 0.9
            a += 0.1 * grad
            b *= 0.999
            b += 0.001 * grad * grad
            theta -= rate * (a / (1 - 0.9**t)) / (np.sqrt(b / (1 - 0.999**t)) + 1e-8)
    return m


def train(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS) -> FactorMachine | None:
    """Fits on at most ``sample_rows`` rows with a label 0 or 1, taken by a hash of the id; None without both labels."""
    named = labels.where("quality IN (0, 1) AND doc_id IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality"))
    picked = named.orderBy(F.xxhash64("doc_id", F.lit(3)), "doc_id").limit(sample_rows)
    rows = docs.join(F.broadcast(picked), "doc_id").select("text", "quality").toArrow()
    y = np.asarray(rows.column("quality").combine_chunks() if rows.num_rows else pa.array([], pa.int32()), dtype=np.float64)
    if len(np.unique(y)) < 2:
        return None
    parts = []
    for i, j, data, offsets in K.byte_chunks(rows.column("text")):
        word_row, cell, value, stats = features(data, offsets)
        parts.append((word_row + i, cell, value, stats))
    return fit(tuple(np.concatenate(x) for x in zip(*parts)), y)


def score(docs: DataFrame, model: FactorMachine | None) -> DataFrame:
    """The rows with ``score`` (0 to 1) and ``predicted`` (1 from THRESHOLD on).

    Inputs of a score come from the text alone.  A null text counts as empty;
    without a model the score is 0.5.  Other columns and repeated rows are
    passed on; columns of the input with these two names are replaced.
    """
    docs = docs.drop("score", "predicted").withColumn("text", text_column(docs))
    names = docs.columns
    text_at = names.index("text")
    shipped = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shipped.value
        for batch in batches:
            for i, j, data, offsets in K.byte_chunks(batch.column(text_at)):
                out = np.zeros(j - i) if m is None else m.margin(*features(data, offsets))
                p = 1 / (1 + np.exp(-np.clip(out, -30, 30)))
                yield pa.RecordBatch.from_arrays([*batch.slice(i, j - i).columns, pa.array(p), pa.array((p >= THRESHOLD).astype(np.int32))], [*names, "score", "predicted"])

    return docs.mapInArrow(run, with_fields(docs.schema, "score double, predicted int"))


def digest(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The contract's columns: labels are learned from rows with remainders 1 to 4 only."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_column(docs).alias("text"))
    model = train(docs, labels.where(~held_out(0, 5)))
    return score(docs.withColumn("held_out", held_out(0, 5)), model).select("doc_id", "held_out", "score", "predicted")
