"""Removal of word windows that other documents have already: level-wise doubling.

A window of ``length`` words can only be repeated if the windows inside it are.
So windows of FIRST_LEVEL words come first, and only where they are repeated are
they extended to twice the words, and only where these are repeated to ``length``.

* The first level is thinned by content: of the short windows inside a full one,
  the one with the least hash stands for it.  Equal full windows have equal
  representatives, so nothing is missed, and one word in five makes a row.
* The second level extends survivors to twice the words.  Neighbouring full
  windows with one representative, dealt into parts by their distance from it,
  have a window of that length in common.  Parts whose common window is found in
  no smaller document have no repeated window and go.  Parts that are repeated
  with all their words are settled as a whole, in all documents but the smallest.
* Only parts whose common window survives, but which are not repeated as a whole,
  are extended to full windows one by one.

Each step is one shuffle.  Before it, a task settles what it can see itself: of
equal windows in one task a single row goes on, so a passage that a third of all
documents share costs one row for each task.  Windows of the last level are told
by two hashes, 128 bits.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import kernels as K
from .common import typed, with_fields

FIRST_LEVEL = 4
_KEY_BITS = np.uint64(24)
#: The first level only filters, so 48 bits of its hashes do.
_FILTER_BITS = np.uint64(16)
_SEGMENT = 1 << 22
#: A place packs 16 bits that tell texts of one id apart, a start, and how many windows start from it on.
TAG, START, MANY = 40, 8, (1 << 8) - 1
_NORMAL, _EVIDENCE, _SURE = 0, 1, 2
_ROWS = "h long, run long, doc long, place long, kind int"


def least_positions(grams: np.ndarray, width: int) -> np.ndarray:
    """For each of len - width + 1 starts, the position of the least of ``width`` hashes (their upper 40 bits, then the leftmost)."""
    n = len(grams) - width + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    out = np.empty(n, np.int64)
    for a in range(0, n, _SEGMENT):
        part = grams[a : min(a + _SEGMENT, n) + width - 1]
        low = (part >> _KEY_BITS << _KEY_BITS) | np.arange(len(part), dtype=np.uint64)
        reach, best = 1, low
        while reach * 2 <= width:
            best = np.minimum(best[:-reach], best[reach:])
            reach *= 2
        if reach < width:
            rest = width - reach
            best = np.minimum(best[: len(best) - rest], best[rest:])
        out[a : a + len(best)] = (best & np.uint64((1 << int(_KEY_BITS)) - 1)).astype(np.int64) + a
    return out


def runs_of(stands: np.ndarray, starts: np.ndarray, row: np.ndarray) -> tuple[np.ndarray, ...]:
    """(start, row, representative, size) of the runs of neighbouring windows with one representative; a run has MANY windows at most."""
    first = np.ones(len(starts), bool)
    first[1:] = (stands[1:] != stands[:-1]) | (row[1:] != row[:-1])
    begin = np.flatnonzero(first)
    start, run_row, stand = starts[begin], row[begin], stands[begin]
    size = np.diff(np.append(begin, len(starts)))
    if (size > MANY).any():
        parts = -(-size // MANY)
        step = K.ranges(np.zeros(len(parts), np.int64), parts)
        size = np.minimum(np.repeat(size, parts) - step * MANY, MANY)
        start, run_row, stand = np.repeat(start, parts) + step * MANY, np.repeat(run_row, parts), np.repeat(stand, parts)
    return start, run_row, stand, size


def list_column(column: pa.Array, i: int, j: int) -> tuple[np.ndarray, np.ndarray]:
    """The values of rows i to j - 1 of a list column, and their rows counted from i."""
    own = column.slice(i, j - i)
    counts = np.asarray(own.value_lengths().fill_null(0))
    return own.flatten().to_numpy(zero_copy_only=False).astype(np.int64), np.repeat(np.arange(j - i), counts)


class _Chunk:
    """The words of some rows, with the runs of their windows."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, length: int):
        self.length, self._sums = length, None
        self.starts, self.ends, self.first = K.word_spans(data, offsets)
        prefix = K.prefix_hash(data)
        self.words = K.word_hash(data, self.starts, self.ends, prefix)
        self.tag = (K.span_hash(prefix, offsets[:-1], offsets[1:]) & np.uint64(0xFFFF)).astype(np.int64)

    def runs(self) -> tuple[np.ndarray, ...]:
        """Start, row, representative and size of the runs, and the hashes of the first level's windows."""
        at, row = K.gram_rows(self.first, self.length, max(0, len(self.words) - self.length + 1))
        level = min(FIRST_LEVEL, self.length)
        grams = K.gram_hash(self.words, level)
        stands = least_positions(grams, self.length - level + 1)[at] if len(at) else at
        return (*runs_of(stands, at, row), grams)

    def span_hashes(self, starts: np.ndarray, sizes: np.ndarray, more: np.ndarray) -> np.ndarray:
        """Hashes of the words of spans, and of a further number for each."""
        if self._sums is None:
            power, _ = K.power_tables(len(self.words) + 1)
            self._sums = np.concatenate([[np.uint64(0)], np.cumsum(self.words * power[: len(self.words)])])
        _, inverse = K.power_tables(len(self.words) + 1)
        sums = (self._sums[starts + sizes] - self._sums[starts]) * inverse[starts]
        return K.mix64(K.mix64(sums) + more.astype(np.uint64) * np.uint64(MANY + 1) + sizes.astype(np.uint64))

    def parts(self, start: np.ndarray, row: np.ndarray, stand: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, ...]:
        """Hash of the common window, hash of all words, row, start and size of the parts of runs; parts are counted from the representative."""
        common = min(2 * FIRST_LEVEL, self.length)
        step = self.length - common + 1
        last, first = (stand - start) // step, (stand - start - size + 1) // step
        count = last - first + 1
        run, number = np.repeat(np.arange(len(start)), count), K.ranges(first, count)
        begin = stand[run] - number * step
        a = np.maximum(begin - (step - 1), start[run])
        many = np.minimum(begin, start[run] + size[run] - 1) - a + 1
        core = self.span_hashes(begin, np.full(len(begin), common), number)
        return core, self.span_hashes(a, many + self.length - 1, begin - a), row[run], a, many

    def window_hashes(self) -> np.ndarray:
        """Hashes of all full windows, by doubling from the first level on."""
        level = min(FIRST_LEVEL, self.length)
        h = K.gram_hash(self.words, level)
        while level < self.length:
            step = min(level, self.length - level)
            if len(h) <= step:
                return np.zeros(0, np.uint64)
            h = K.mix64(h[:-step] * np.uint64(0x9FB21C651E98DF25) + h[step:])
            level += step
        return h

    def places(self, starts: np.ndarray, rows: np.ndarray, many) -> np.ndarray:
        return self.tag[rows] << TAG | (starts - self.first[rows]) << START | many

    def given(self, places: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts, counts and rows of the places that are of this text."""
        own = places >> TAG == self.tag[rows]
        places, rows = places[own], rows[own]
        return self.first[rows] + (places >> START & 0xFFFFFFFF), places & MANY, rows


def _settle(step: int, h: np.ndarray, run: np.ndarray, doc: np.ndarray, place: np.ndarray, kind: np.ndarray) -> pa.RecordBatch:
    """What a task can tell by itself.

    Step 1: a place is sure if the task has its window in another document too,
    and one row of evidence goes on for each such window.  Steps 2 and 3: a
    place is sure if the task has its run or window in a smaller document; those
    of the smallest document go on.
    """
    order = np.lexsort((doc, run, h))
    h, run, doc, place, kind = (x[order] for x in (h, run, doc, place, kind))
    first = np.ones(len(h), bool)
    first[1:] = (h[1:] != h[:-1]) | (run[1:] != run[:-1])
    group = np.cumsum(first) - 1
    begin = np.flatnonzero(first)
    if step == 1:
        last = np.append(begin[1:], len(h)) - 1
        sure = (doc[last] > doc[begin])[group]
        on = np.flatnonzero(~sure)
        lone = begin[sure[begin]]
    else:
        later = doc > doc[begin][group]
        sure = later & (kind == _NORMAL)
        on, lone = np.flatnonzero(~later), np.zeros(0, np.int64)
    told = np.flatnonzero(sure)
    scattered = K.mix64(h[told] ^ place[told].astype(np.uint64) ^ doc[told].astype(np.uint64) << np.uint64(20))
    at = np.concatenate([told, on, lone])
    key = np.concatenate([scattered, h[on], h[lone]])
    kinds = np.concatenate([np.full(len(told), _SURE), kind[on], np.full(len(lone), _EVIDENCE)]).astype(np.int32)
    return pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(run[at].view(np.int64)), pa.array(doc[at]), pa.array(place[at]), pa.array(kinds)], ["h", "run", "doc", "place", "kind"])


def _emit(step: int, length: int, id_at: int, text_at: int, lists_at: int):
    """Rows of the steps: 1 representatives, 2 parts of runs (h is the common window), 3 windows."""
    rows_at_once = 3_000_000

    def of_chunk(chunk: _Chunk, batch: pa.RecordBatch, i: int, j: int) -> list[tuple[np.ndarray, ...]]:
        if step < 3:
            start, row, stand, size, grams = chunk.runs()
            if step == 1:
                one = np.ones(len(stand), bool)
                one[1:] = stand[1:] != stand[:-1]
                stand, row = stand[one], row[one]
                return [(grams[stand] >> _FILTER_BITS, np.zeros(len(stand), np.uint64), row, chunk.places(stand, row, 0), np.zeros(len(stand), np.int32))]
            at, _, _ = chunk.given(*list_column(batch.column(lists_at), i, j))
            seen = np.zeros(len(chunk.words), bool)
            seen[at] = True
            open_ = seen[stand] if len(stand) else np.zeros(0, bool)
            start, row, stand, size = start[open_], row[open_], stand[open_], size[open_]
            if not len(start):
                return []
            core, whole, row, start, size = chunk.parts(start, row, stand, size)
            return [(core, whole, row, chunk.places(start, row, size), np.zeros(len(start), np.int32))]
        out = []
        windows = None
        for column, kind in ((lists_at, _NORMAL), (lists_at + 1, _EVIDENCE)):
            at, many, row = chunk.given(*list_column(batch.column(column), i, j))
            if len(at):
                windows = chunk.window_hashes() if windows is None else windows
                starts, row = K.ranges(at, many), np.repeat(row, many)
                out.append((windows[starts], chunk.span_hashes(starts, np.full(len(starts), length), np.zeros(len(starts), np.int64)), row, chunk.places(starts, row, 1), np.full(len(starts), kind, np.int32)))
        return out

    def flush(parts: list[tuple[np.ndarray, ...]]) -> pa.RecordBatch:
        return _settle(step, *(np.concatenate(x) for x in zip(*parts)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, held = [], 0
        for batch in batches:
            ids = batch.column(id_at).to_numpy(zero_copy_only=False)
            for i, j, data, offsets in K.byte_chunks(batch.column(text_at)):
                for h, run_hash, row, place, kind in of_chunk(_Chunk(data, offsets, length), batch, i, j):
                    if len(h):
                        parts.append((h, run_hash, ids[i + row].astype(np.int64), place, kind))
                        held += len(h)
                if held > rows_at_once:
                    yield flush(parts)
                    parts, held = [], 0
        if parts:
            yield flush(parts)

    return run


def removed_places(docs: DataFrame, length: int) -> DataFrame:
    """The rows of ``docs`` with two lists of packed starts and counts: ``done`` and ``places`` (null if empty), of windows that a document with a smaller doc_id has too.

    The steps are one plan.  Documents are dealt out by id once, and so are the
    lists of the second step: all columns pass through every use of them, so
    that Spark finds the exchanges equal and keeps one.
    """
    if length < FIRST_LEVEL:
        raise ValueError(f"windows have {FIRST_LEVEL} words at least")
    names = docs.columns
    id_at, text_at = names.index("doc_id"), names.index("text")
    lists_of = ("open", "evidence", "done", "places")
    # Inner joins leave out null ids by themselves; the outer one has to look the same.
    unnamed = docs.where("doc_id IS NULL").select("*", *[F.array().cast("array<long>").alias(x) for x in lists_of])
    docs = docs.where("doc_id IS NOT NULL")
    own = [docs[c] for c in names]

    by = Window.partitionBy("h")
    grams = docs.select("doc_id", "text").mapInArrow(_emit(1, length, 0, 1, 2), _ROWS).select("h", "doc", "place", "kind")
    grams = grams.withColumn("least", F.min("doc").over(by)).withColumn("most", F.max("doc").over(by)).withColumn("told", F.max((F.col("kind") == _EVIDENCE).cast("int")).over(by))
    grams = grams.where(f"kind <> {_EVIDENCE} AND (kind = {_SURE} OR told = 1 OR least < most)")
    marks = grams.groupBy("doc").agg(F.collect_list("place").alias("marks"))

    runs = docs.join(marks, docs["doc_id"] == marks["doc"]).select(*own, "marks").mapInArrow(_emit(2, length, id_at, text_at, len(names)), _ROWS)
    # The window over h comes first, so that its exchange does for the others.
    runs = runs.withColumn("least", F.min("doc").over(by)).withColumn("run_least", F.min("doc").over(Window.partitionBy("h", "run"))).withColumn("most", F.max("run_least").over(by))
    done = (F.col("kind") == _SURE) | (F.col("doc") > F.col("run_least"))
    state = F.when(done, "done").when(F.col("doc") > F.col("least"), "open").when(F.col("most") > F.col("least"), "evidence")
    runs = runs.select("doc", "place", state.alias("state")).where("state IS NOT NULL")
    lists = runs.groupBy("doc").agg(*[F.collect_list(F.when(F.col("state") == x, F.col("place"))).alias(x) for x in ("open", "evidence", "done")])

    told = docs.join(lists, docs["doc_id"] == lists["doc"]).select(*own, "open", "evidence", "done")
    windows = told.mapInArrow(_emit(3, length, id_at, text_at, len(names)), _ROWS)
    windows = windows.withColumn("least", F.min("doc").over(Window.partitionBy("h", "run"))).where(f"kind = {_SURE} OR (kind = {_NORMAL} AND doc > least)")
    places = windows.groupBy("doc").agg(F.collect_list("place").alias("places")).withColumnRenamed("doc", "doc_w")
    out = docs.join(lists, docs["doc_id"] == lists["doc"], "left").join(places, docs["doc_id"] == F.col("doc_w"), "left")
    return out.select(*own, *lists_of).unionByName(unnamed)


def substring_dedup(docs: DataFrame, length: int = 13) -> DataFrame:
    """The rows with ``text`` cut and with ``n_words`` and ``n_removed`` (both long).

    Words are runs of bytes other than space and 0x09 to 0x0D.  Each word is
    removed that lies in a window of ``length`` words which also starts in a
    document with a smaller doc_id; windows are judged on the input.  The words
    that stay are joined by one space.  A null text has no words and becomes the
    empty text; a row with a null doc_id is neither evidence nor changed but for
    the spaces between words.  Texts with the same doc_id are one document:
    they don't remove each other's windows.  Other columns are passed on;
    columns of the input with the names of the results or of the lists in between go.
    """
    docs = typed(docs.drop("n_words", "n_removed", "places", "open", "evidence", "done", "marks", "doc", "doc_w"))
    names = docs.columns
    text_at = names.index("text")
    joined = removed_places(docs, length)
    done_at, places_at = len(names) + 2, len(names) + 3

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, offsets in K.byte_chunks(batch.column(text_at)):
                chunk = _Chunk(data, offsets, length)
                edge = np.zeros(len(chunk.words) + 1, np.int64)
                for column in (done_at, places_at):
                    at, many, _ = chunk.given(*list_column(batch.column(column), i, j))
                    np.add.at(edge, at, 1)
                    np.add.at(edge, at + many - 1 + length, -1)
                gone = np.cumsum(edge[:-1]) > 0
                n_removed = np.diff(np.concatenate([[0], np.cumsum(gone)])[chunk.first])
                kept = np.flatnonzero(~gone)
                size = chunk.ends[kept] - chunk.starts[kept] + 1
                out = K.take_spans(np.append(data, np.uint8(32)), chunk.starts[kept], chunk.ends[kept] + 1)
                stop = np.cumsum(size)
                out[stop - 1] = 32
                bound = np.concatenate([[0], stop])[np.searchsorted(kept, chunk.first)]
                filled = np.diff(bound) > 0
                whole = np.delete(out, bound[1:][filled] - 1)
                ends = np.concatenate([[0], np.cumsum(np.diff(bound) - filled)])
                cols = list(batch.slice(i, j - i).columns[: len(names)])
                cols[text_at] = pa.Array.from_buffers(pa.string(), j - i, [None, pa.py_buffer(ends.astype(np.int32).tobytes()), pa.py_buffer(whole.tobytes())])
                yield pa.RecordBatch.from_arrays([*cols, pa.array(np.diff(chunk.first)), pa.array(n_removed)], [*names, "n_words", "n_removed"])

    return joined.mapInArrow(run, with_fields(docs.schema, "n_words long, n_removed long"))


def digest(docs: DataFrame) -> DataFrame:
    """The contract's columns."""
    out = substring_dedup(docs.select("doc_id", "text"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"))


#: DuckDB SQL of the digest over ``documents``.
SQL = """
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') AS words FROM documents),
g AS (SELECT doc_id, i, array_to_string(words[i : i + 12], ' ') AS win FROM w, LATERAL unnest(range(1, len(words) - 11)) AS u(i)),
m AS (SELECT win, min(doc_id) AS least FROM g GROUP BY win),
c AS (SELECT DISTINCT g.doc_id, g.i + o AS k FROM g JOIN m USING (win), range(13) AS t(o) WHERE least < g.doc_id),
x AS (SELECT w.doc_id, k, words[k] AS word FROM w, LATERAL unnest(range(1, len(words) + 1)) AS u(k)),
y AS (SELECT doc_id, string_agg(word, ' ' ORDER BY k) AS kept, count(*) AS n FROM x ANTI JOIN c USING (doc_id, k) GROUP BY doc_id)
SELECT w.doc_id, len(words)::BIGINT AS n_words, (len(words) - coalesce(n, 0))::BIGINT AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM w LEFT JOIN y USING (doc_id)
"""


def brute_force(rows: list[tuple[int, str | None]], length: int) -> list[tuple[int, int, int, str]]:
    """The digest of rows with distinct ids by plain comparison, for tests."""
    import re

    words = {d: re.findall(r"[^\x20\x09-\x0D]+", t or "") for d, t in rows}
    least: dict[tuple, int] = {}
    for d in sorted(words):
        for i in range(len(words[d]) - length + 1):
            least.setdefault(tuple(words[d][i : i + length]), d)
    out = []
    for d, w in words.items():
        gone = {k for i in range(len(w) - length + 1) if least[tuple(w[i : i + length])] < d for k in range(i, i + length)}
        kept = " ".join(x for k, x in enumerate(w) if k not in gone)
        out.append((d, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return out
