"""Removal of byte strings that occur elsewhere: bucket-pointer refinement of suffixes.

Suffixes are sorted only as far as ``length`` bytes, and only where they can
still share a bucket with another suffix.  A bucket identifier names the bytes
of a prefix; identifiers of longer prefixes are made from the identifiers at two
offsets, so they agree between tasks without a common table.

1. *Buckets of q-grams.*  Of the q-grams in a string of ``length`` bytes the one
   with the least identifier stands for it; equal strings have equal
   representatives.  A shuffle by identifier drops those that are alone.
2. *Runs.*  Neighbouring strings with the same representative are refined
   together: a bucket of a q-gram is sorted by the identifier of all bytes of a
   run.  Runs with company are repeated as a whole, and what they tell is reused:
   one run of each such bucket is the evidence for the next step.
3. *Parts.*  Runs that are alone, but whose q-gram is not, are cut into parts of
   PART strings, counted from the q-gram.  Their buckets are those of the bytes
   that all strings of a part have in common, nearly ``length`` of them, and are
   sorted by the identifier of all its bytes.  Parts alone in their bucket have
   no repeated string and go; parts with company are repeated as a whole.
4. *Strings.*  What is left are parts in which a repeated passage begins or
   ends.  They are taken apart; two identifiers of ``length`` bytes decide.

Each step is one shuffle, before which a task settles what it has twice itself,
so a bucket with a third of all suffixes costs a few rows for each task.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import kernels as K
from .common import typed
from .substring_dedup import MANY, START, TAG, least_positions, list_column, runs_of

_NORMAL, _EVIDENCE, _SURE = 0, 1, 2
PART = 16
_ROWS = "h long, run long, doc long, place long, kind int"
#: The first step only filters, so 48 bits of its identifiers do.
_FILTER_BITS = np.uint64(16)


def _refined(near: np.ndarray, far: np.ndarray) -> np.ndarray:
    """Identifiers of longer prefixes, from those at a start and at a later offset."""
    return K.mix64(near * np.uint64(0x9FB21C651E98DF25) + far)


class _Chunk:
    """Bytes of some rows with the runs of their strings."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, length: int):
        self.data, self.offsets, self.length = data, offsets, length
        self.part = min(PART, max(1, length // 4))
        q = max(1, length // 4)
        n = len(data)
        prefix = K.prefix_hash(data)
        at = np.arange(max(0, n - q + 1))
        self.gram = K.span_hash(prefix, at, at + q)
        self._prefix = prefix
        whole = K.span_hash(prefix, offsets[:-1], offsets[1:])
        self.tag = (whole & np.uint64(0xFFFF)).astype(np.int64)
        sizes = np.maximum(np.diff(offsets) - length + 1, 0)
        starts = K.ranges(offsets[:-1], sizes)
        row = np.repeat(np.arange(len(sizes)), sizes)
        stands = least_positions(self.gram, length - q + 1)[starts] if len(starts) else starts
        self.run_start, self.run_row, self.run_gram, self.run_size = runs_of(stands, starts, row)

    def string_ids(self, starts: np.ndarray, other: bool = False) -> np.ndarray:
        """Identifiers of ``length`` bytes, refined from those of half the length; ``other`` ones are made from other sums."""
        half = self.length // 2
        prefix = K.prefix_hash(self.data, 1) if other else self._prefix
        near = K.span_hash(prefix, starts, starts + half)
        far = K.span_hash(prefix, starts + half, starts + self.length)
        return _refined(near, far)

    def core_ids(self, grams: np.ndarray, numbers: np.ndarray) -> np.ndarray:
        """Identifiers of the bytes that all strings of parts have in common."""
        starts = grams - numbers * self.part
        return _refined(K.span_hash(self._prefix, starts, starts + self.length - self.part + 1), numbers.astype(np.uint64))

    def span_ids(self, starts: np.ndarray, sizes: np.ndarray, grams: np.ndarray) -> np.ndarray:
        """Identifiers of all bytes of runs or parts, and of where their q-gram lies."""
        return _refined(K.span_hash(self._prefix, starts, starts + sizes + self.length - 1), (grams - starts).astype(np.uint64))

    def parts(self, starts: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, ...]:
        """(index of the run, start, size, q-gram, number) of the parts of given runs; numbers count from the q-gram."""
        gram_of = np.zeros(len(self.data) + 1, np.int64)
        gram_of[self.run_start] = self.run_gram
        gram = gram_of[starts]
        part = self.part
        last, first = (gram - starts) // part, (gram - starts - sizes + 1) // part
        count = last - first + 1
        run = np.repeat(np.arange(len(starts)), count)
        number = K.ranges(first, count)
        a = np.maximum(gram[run] - number * part - (part - 1), starts[run])
        b = np.minimum(gram[run] - number * part, starts[run] + sizes[run] - 1)
        return run, a, b - a + 1, gram[run], number

    def places(self, starts: np.ndarray, rows: np.ndarray, many: np.ndarray) -> np.ndarray:
        return self.tag[rows] << TAG | (starts - self.offsets[rows]) << START | many

    def given(self, places: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts, counts and which of the places are of this text."""
        own = places >> TAG == self.tag[rows]
        places, rows = places[own], rows[own]
        return self.offsets[rows] + (places >> START & 0xFFFFFFFF), places & MANY, own


def _settle(h: np.ndarray, run: np.ndarray, doc: np.ndarray, place: np.ndarray, kind: np.ndarray) -> pa.RecordBatch:
    """Of (h, run) that a task has twice, its rows are sure, and one row of evidence goes on; the others go on as they are."""
    order = np.lexsort((run, h))
    h, run, doc, place, kind = (x[order] for x in (h, run, doc, place, kind))
    first = np.ones(len(h), bool)
    first[1:] = (h[1:] != h[:-1]) | (run[1:] != run[:-1])
    begin = np.flatnonzero(first)
    size = np.diff(np.append(begin, len(h)))
    twice = np.repeat(size > 1, size)
    told = np.flatnonzero(twice & (kind == _NORMAL))
    alone = np.flatnonzero(~twice)
    lone = begin[size > 1]
    scattered = K.mix64(h[told] ^ place[told].astype(np.uint64) ^ doc[told].astype(np.uint64) << np.uint64(20))
    at = np.concatenate([told, alone, lone])
    key = np.concatenate([scattered, h[alone], h[lone]])
    kinds = np.concatenate([np.full(len(told), _SURE), kind[alone], np.full(len(lone), _EVIDENCE)]).astype(np.int32)
    return pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(run[at].view(np.int64)), pa.array(doc[at]), pa.array(place[at]), pa.array(kinds)], ["h", "run", "doc", "place", "kind"])


def _emit(step: int, length: int):
    """Rows of the steps: 1 q-grams of (doc_id, text), 2 runs of (doc_id, text, grams), h being the q-gram, 3 parts of (doc_id, text, open, evidence, done), h being the bytes common to a part's strings, 4 strings of the same with the parts' lists."""
    rows_at_once = 3_000_000

    def of_chunk(chunk: _Chunk, batch: pa.RecordBatch, i: int, j: int) -> list[tuple[np.ndarray, ...]]:
        if step == 1:
            every = np.ones(len(chunk.run_gram), bool)
            every[1:] = chunk.run_gram[1:] != chunk.run_gram[:-1]
            runs = np.flatnonzero(every)
            rows, at = chunk.run_row[runs], chunk.run_gram[runs]
            # Two rows can't share a q-gram's position, so neighbours differ unless they are one run.
            return [(chunk.gram[at] >> _FILTER_BITS, np.zeros(len(at), np.uint64), rows, chunk.places(at, rows, np.zeros(len(at), np.int64)), np.zeros(len(at), np.int32))]
        places, rows = list_column(batch.column(2), i, j)
        if step == 2:
            at, _, _ = chunk.given(places, rows)
            seen = np.zeros(len(chunk.data), bool)
            seen[at] = True
            runs = np.flatnonzero(seen[chunk.run_gram]) if len(chunk.run_gram) else np.zeros(0, np.int64)
            rows = chunk.run_row[runs]
            ids = chunk.span_ids(chunk.run_start[runs], chunk.run_size[runs], chunk.run_gram[runs])
            return [(chunk.gram[chunk.run_gram[runs]], ids, rows, chunk.places(chunk.run_start[runs], rows, chunk.run_size[runs]), np.zeros(len(runs), np.int32))]
        out = []
        for column, kind in ((2, _NORMAL), (3, _EVIDENCE)):
            places, rows = list_column(batch.column(column), i, j)
            at, many, own = chunk.given(places, rows)
            if step == 3:
                run, starts, sizes, gram, number = chunk.parts(at, many)
                rows = rows[own][run]
                out.append((chunk.core_ids(gram, number), chunk.span_ids(starts, sizes, gram), rows, chunk.places(starts, rows, sizes), np.full(len(starts), kind, np.int32)))
                continue
            starts, rows = K.ranges(at, many), np.repeat(rows[own], many)
            if len(starts):
                out.append((chunk.string_ids(starts), chunk.string_ids(starts, True), rows, chunk.places(starts, rows, np.ones(len(starts), np.int64)), np.full(len(starts), kind, np.int32)))
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, held = [], 0
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            for i, j, data, offsets in K.byte_chunks(batch.column(1)):
                for h, run_id, rows, place, kind in of_chunk(_Chunk(data, offsets, length), batch, i, j):
                    if len(h):
                        parts.append((h, run_id, ids[i + rows].astype(np.int64), place, kind))
                        held += len(h)
                if held > rows_at_once:
                    yield _settle(*(np.concatenate(x) for x in zip(*parts)))
                    parts, held = [], 0
        if parts:
            yield _settle(*(np.concatenate(x) for x in zip(*parts)))

    return run


def _company(*by: str):
    return (F.col("kind") == _SURE) | (F.count(F.lit(1)).over(Window.partitionBy(*by)) > 1)


def removed_places(docs: DataFrame, length: int) -> DataFrame:
    """The rows (doc_id, text) with lists of packed starts and counts: ``done``, ``done_p`` and ``places`` (null if empty) of repeated strings.

    One plan; texts and the second step's lists are dealt out by id once.
    """
    lists_of = ("open", "evidence", "done", "open_p", "evidence_p", "done_p", "places")
    # Inner joins leave out null ids by themselves; the outer one has to look the same.
    unnamed = docs.where("doc_id IS NULL").select("*", *[F.array().cast("array<long>").alias(x) for x in lists_of])
    docs = docs.where("doc_id IS NOT NULL")
    own = [docs["doc_id"], docs["text"]]
    grams = docs.mapInArrow(_emit(1, length), _ROWS).select("h", "doc", "place", "kind")
    grams = grams.withColumn("company", _company("h")).where(f"company AND kind <> {_EVIDENCE}").groupBy("doc").agg(F.collect_list("place").alias("grams"))

    runs = docs.join(grams, docs["doc_id"] == grams["doc"]).select(*own, "grams").mapInArrow(_emit(2, length), _ROWS)
    lists = _lists(runs)
    told = docs.join(lists, docs["doc_id"] == lists["doc"]).select(*own, "open", "evidence", "done")
    parts = _lists(told.mapInArrow(_emit(3, length), _ROWS)).select(F.col("doc").alias("doc_p"), *[F.col(c).alias(f"{c}_p") for c in ("open", "evidence", "done")])
    told = docs.join(parts, docs["doc_id"] == parts["doc_p"]).select(*own, "open_p", "evidence_p", "done_p")
    strings = told.mapInArrow(_emit(4, length), _ROWS)
    strings = strings.withColumn("company", _company("h", "run")).where(f"company AND kind <> {_EVIDENCE}")
    places = strings.groupBy("doc").agg(F.collect_list("place").alias("places")).withColumnRenamed("doc", "doc_s")
    out = docs.join(lists, docs["doc_id"] == lists["doc"], "left").join(parts, docs["doc_id"] == parts["doc_p"], "left").join(places, docs["doc_id"] == F.col("doc_s"), "left")
    return out.select(*own, *lists_of).unionByName(unnamed)


def _lists(rows: DataFrame) -> DataFrame:
    """(doc, open, evidence, done) of runs or parts: those to be taken apart, those that others are held against, those that are repeated."""
    by = Window.partitionBy("h")
    # The window over h comes first, so that its exchange does for the others.
    rows = rows.withColumn("alone", F.count(F.lit(1)).over(by) == 1).withColumn("company", _company("h", "run"))
    rows = rows.withColumn("ask", (F.col("kind") == _NORMAL) & ~F.col("company"))
    rows = rows.withColumn("asked", F.max("ask").over(by))
    is_open = F.col("ask") & ~F.col("alone")
    evidence = F.col("asked") & ~F.col("ask") & (F.col("kind") != _SURE)
    done = F.col("company") & (F.col("kind") != _EVIDENCE)
    rows = rows.where(is_open | evidence | done)
    return rows.groupBy("doc").agg(*[F.collect_list(F.when(c, F.col("place"))).alias(n) for c, n in ((is_open, "open"), (evidence, "evidence"), (done, "done"))])


def suffix_dedup(docs: DataFrame, length: int = 200) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept) of every row, ``kept`` being binary.

    Each byte goes that lies in a string of ``length`` bytes which also starts
    anywhere else, be it in the same text; strings don't reach over texts and
    are judged on the input.  What stays may not be valid UTF-8.  A null text is
    empty.  Repeated rows are texts of their own, so they remove each other; a
    row with a null doc_id is neither changed nor evidence.  Other columns don't
    matter; no rows give no rows.
    """
    if length < 8:
        raise ValueError("strings have 8 bytes at least")
    texts = typed(docs.select("doc_id", "text"))
    joined = removed_places(texts, length)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, offsets in K.byte_chunks(batch.column(1)):
                whole = K.span_hash(K.prefix_hash(data), offsets[:-1], offsets[1:])
                edge = np.zeros(len(data) + 1, np.int32)
                for column in (4, 7, 8):
                    places, rows = list_column(batch.column(column), i, j)
                    own = places >> TAG == (whole & np.uint64(0xFFFF)).astype(np.int64)[rows]
                    places, rows = places[own], rows[own]
                    at, many = offsets[rows] + (places >> START & 0xFFFFFFFF), places & MANY
                    np.add.at(edge, at, 1)
                    np.add.at(edge, at + many - 1 + length, -1)
                gone = np.cumsum(edge[:-1]) > 0
                begins = gone.copy()
                begins[1:] &= ~gone[:-1]
                filled = offsets[:-1][np.diff(offsets) > 0]
                begins[filled] = gone[filled]
                removed = np.concatenate([[0], np.cumsum(gone)])[offsets]
                spans = np.concatenate([[0], np.cumsum(begins)])[offsets]
                kept = data[~gone]
                bound = offsets - removed
                stays = pa.Array.from_buffers(pa.binary(), j - i, [None, pa.py_buffer(bound.astype(np.int32).tobytes()), pa.py_buffer(kept.tobytes())])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.array(np.diff(offsets)), pa.array(np.diff(removed)), pa.array(np.diff(spans)), stays], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept"])

    return joined.mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary")


def digest(docs: DataFrame) -> DataFrame:
    """The contract's columns."""
    return suffix_dedup(docs).select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


def brute_force(rows: list[tuple[int, str | None]], length: int) -> list[tuple[int, int, int, int, str]]:
    """The digest of rows by plain counting, for tests."""
    from collections import Counter

    texts = [(d, (t or "").encode()) for d, t in rows]
    seen = Counter(b[i : i + length] for _, b in texts for i in range(len(b) - length + 1))
    out = []
    for d, b in texts:
        gone = bytearray(len(b))
        for i in range(len(b) - length + 1):
            if seen[b[i : i + length]] > 1:
                gone[i : i + length] = b"\x01" * length
        spans = sum(1 for i in range(len(b)) if gone[i] and not (i and gone[i - 1]))
        kept = bytes(x for x, g in zip(b, gone) if not g)
        out.append((d, len(b), sum(gone), spans, hashlib.sha256(kept).hexdigest()))
    return out
