"""Packing of documents into fixed windows with a controlled mixture of sources.

Deficit round-robin: in a block of documents each source has a queue.  Every
window gives each source its share of the window's tokens plus what it was owed
before; what a source can't deliver goes to the others and stays owed.  Debts go
on from window to window, and from block to block: a first pass counts the
tokens of each (block, source), and running sums over the blocks before, with
and without the source, give the debts with which a block starts, so blocks are
packed independently.

Documents are dealt to blocks by a hash of their id, so a source that has a
third of all rows is spread evenly.  The tokens left at a block's end are cut
into powers of two, which need no padding.
"""

from __future__ import annotations

import zlib
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import model_of
from .common import stash, text_column, tokenizer_json

WINDOW = 4096
#: Fixed value: the id that ends a document.
END_ID = 2
#: Tokens of a block, about.
BLOCK_TOKENS = 1 << 20
#: Blocks of a run, for running sums in two steps.
_RUN = 4096

_TOKENS = "doc_id long, source string, slot long, n long, ids binary"
_PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, source string"


def tokenized(docs: DataFrame, tokenizer_path: str | None = None) -> DataFrame:
    """(doc_id, source, slot, n, ids): little-endian 16-bit ids where the vocabulary allows, else 32-bit; slot tells equal rows apart."""
    content = docs.sparkSession.sparkContext.broadcast(tokenizer_json(tokenizer_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = model_of(content.value)
        kind = "<u2" if model.n_ids <= 1 << 16 else "<u4"
        for batch in batches:
            for first, ids, bounds in model.encode_rows(batch.column(1)):
                n = len(bounds) - 1
                with_end = np.insert(ids.astype(kind), bounds[1:], END_ID)
                cut = bounds + np.arange(n + 1)
                raw = with_end.tobytes()
                width = with_end.itemsize
                rows = [raw[a * width : b * width] for a, b in zip(cut.tolist(), cut[1:].tolist())]
                part = batch.slice(first, n)
                slot = [zlib.crc32(r) for r in rows]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(slot, pa.int64()), pa.array(np.diff(cut)), pa.array(rows, pa.binary())], ["doc_id", "source", "slot", "n", "ids"])

    source = F.col("source").cast("string") if "source" in docs.columns else F.lit("")
    return docs.select(F.col("doc_id").cast("long"), text_column(docs), F.coalesce(source, F.lit("")).alias("source")).mapInArrow(run, _TOKENS)


class _Packer:
    """Packs one block: fills windows from the queues of its sources."""

    def __init__(self, block: int, shares: dict[str, float], owed: dict[str, float], width: int):
        self.block, self.shares, self.width = block, shares, width
        self.owed = dict(owed)
        self.queues: dict[str, deque] = {}
        self.waiting: dict[str, int] = {}
        self.total = 0
        self.windows = 0
        self.rows: list[tuple] = []

    def add(self, source: str, doc_id: int | None, ids: np.ndarray) -> None:
        self.queues.setdefault(source, deque()).append([doc_id, ids, 0])
        self.waiting[source] = self.waiting.get(source, 0) + len(ids)
        self.total += len(ids)

    def _take(self, source: str, count: int, sequence: int, offset: int) -> int:
        queue = self.queues[source]
        done = 0
        while done < count:
            doc_id, ids, start = queue[0]
            length = min(len(ids) - start, count - done)
            crc = zlib.crc32(ids[start : start + length].astype("<u4").data)
            self.rows.append((doc_id, start, length, crc, len(ids), sequence, offset + done, source))
            done += length
            if start + length == len(ids):
                queue.popleft()
            else:
                queue[0][2] = start + length
        self.waiting[source] -= count
        self.total -= count
        return done

    def fill(self, size: int) -> None:
        """One sequence of ``size`` tokens."""
        sequence = self.block << 24 | self.windows
        self.windows += 1
        for s in self.shares:
            self.owed[s] = self.owed.get(s, 0.0) + size * self.shares[s]
        offset = 0
        ready = sorted((s for s, w in self.waiting.items() if w), key=lambda s: (-self.owed.get(s, 0.0), s))
        for s in ready:  # each source what it is owed
            count = min(int(self.owed.get(s, 0.0)), self.waiting[s], size - offset)
            if count > 0:
                offset += self._take(s, count, sequence, offset)
                self.owed[s] -= count
        for s in sorted(ready, key=lambda s: (-self.owed.get(s, 0.0), s)):  # and the rest in the order of debts
            count = min(self.waiting[s], size - offset)
            if count > 0:
                offset += self._take(s, count, sequence, offset)
                self.owed[s] = self.owed.get(s, 0.0) - count

    def finish(self) -> None:
        while self.total >= self.width:
            self.fill(self.width)
        while self.total:
            self.fill(1 << (self.total.bit_length() - 1))


def _pack(width: int, kind: str):
    def batch_of(rows: list[tuple]) -> pa.RecordBatch:
        cols = list(zip(*rows))
        kinds = [pa.int64()] * 7 + [pa.string()]
        return pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(cols, kinds)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "source"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer, block = None, None
        shares: dict[str, float] = {}
        owed: dict[str, float] = {}
        for batch in batches:
            cols = [batch.column(k) for k in range(7)]
            for r in range(batch.num_rows):
                b, is_doc, source = cols[0][r].as_py(), cols[1][r].as_py(), cols[2][r].as_py()
                if b != block:
                    if packer:
                        packer.finish()
                        if packer.rows:
                            yield batch_of(packer.rows)
                    packer, block, shares, owed = None, b, {}, {}
                if not is_doc:
                    shares[source], owed[source] = cols[5][r].as_py(), cols[6][r].as_py()
                    continue
                if packer is None:
                    packer = _Packer(b, shares, owed, width)
                packer.add(source, cols[3][r].as_py(), np.frombuffer(cols[4][r].as_buffer(), kind))
                while packer.total >= 64 * width:
                    packer.fill(width)
                if len(packer.rows) > 20_000:
                    yield batch_of(packer.rows)
                    packer.rows = []
        if packer:
            packer.finish()
            if packer.rows:
                yield batch_of(packer.rows)

    return run


def _sums_before(counts: DataFrame) -> DataFrame:
    """Adds to (block, source, n) the sum ``before`` of n over the source's smaller blocks, by runs of blocks and then within them."""
    counts = counts.withColumn("run", F.floor(F.col("block") / _RUN))
    runs = counts.groupBy("source", "run").agg(F.sum("n").alias("m"))
    earlier = Window.partitionBy("source").orderBy("run").rowsBetween(Window.unboundedPreceding, -1)
    runs = runs.select(F.col("source").alias("of"), "run", F.coalesce(F.sum("m").over(earlier), F.lit(0)).alias("base"))
    within = Window.partitionBy("source", "run").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.withColumn("inside", F.coalesce(F.sum("n").over(within), F.lit(0)))
    both = counts.join(runs.withColumnRenamed("run", "of_run"), F.col("source").eqNullSafe(F.col("of")) & (F.col("run") == F.col("of_run")))
    return both.select("block", "source", "n", (F.col("base") + F.col("inside")).alias("before"))


def pack(docs: DataFrame, width: int = WINDOW, target: dict[str, float] | None = None, tokenizer_path: str | None = None, block_tokens: int = BLOCK_TOKENS) -> DataFrame:
    """One row for each piece of a document in a sequence.

    ``target`` gives the share of tokens of each source; by default the shares
    that the input has.  Sources outside it fill what the others leave.  Every
    token is in one piece, whatever the target: when a source runs dry, others
    take its room.  A null text is empty and has the end id alone; a null source
    counts as the source ''; repeated rows are packed each; a null doc_id stays
    null.  Columns besides doc_id, text and source don't matter.  No rows give
    no rows.
    """
    if width & (width - 1) or width < 1:
        raise ValueError("windows have a power of two of tokens")
    if target is not None and (any(v < 0 for v in target.values()) or not sum(target.values())):
        raise ValueError("shares are not negative, and one is positive")
    spark = docs.sparkSession
    tokens = stash(tokenized(docs, tokenizer_path))
    total = tokens.agg(F.sum("n")).first()[0] or 0
    n_blocks = max(1, -(-total // block_tokens))
    block = F.pmod(F.xxhash64("doc_id", "slot"), F.lit(n_blocks))
    tokens = tokens.withColumn("block", block)

    counts = tokens.groupBy("block", "source").agg(F.sum("n").alias("n"))
    by_source = counts.groupBy("source").agg(F.sum("n").alias("n"))
    if target is None:
        shares = by_source.select("source", (F.col("n") / F.lit(float(max(total, 1)))).alias("share"))
    else:
        whole = sum(target.values())
        wanted = spark.createDataFrame([(s, v / whole) for s, v in target.items()], "source string, share double")
        shares = by_source.join(wanted, "source", "left").select("source", F.coalesce("share", F.lit(0.0)).alias("share"))
    # A source is owed its share of all tokens in the blocks before, those without it too, less what it had there.
    grid = _sums_before(counts.unionByName(counts.groupBy("block").agg(F.sum("n").alias("n")).withColumn("source", F.lit(None).cast("string"))))
    sizes = grid.where("source IS NULL").select("block", F.col("before").alias("size"))
    grid = grid.where("source IS NOT NULL").join(sizes, "block").join(shares, "source")
    debts = grid.select("block", "source", "share", (F.col("size") * F.col("share") - F.col("before")).alias("owed"))

    heads = debts.select("block", F.lit(False).alias("is_doc"), "source", F.lit(None).cast("long").alias("doc_id"), F.lit(None).cast("binary").alias("ids"), "share", "owed")
    bodies = tokens.select("block", F.lit(True).alias("is_doc"), "source", "doc_id", "ids", F.lit(None).cast("double").alias("share"), F.lit(None).cast("double").alias("owed"))
    rows = heads.unionByName(bodies).repartition("block").sortWithinPartitions("block", "is_doc", F.xxhash64("doc_id"), "doc_id", "ids")
    kind = "<u2" if model_of(tokenizer_json(tokenizer_path)).n_ids <= 1 << 16 else "<u4"
    return rows.mapInArrow(_pack(width, kind), _PIECES)

