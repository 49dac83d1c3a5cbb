"""Exact Jaccard join of word n-gram sets, down to components: a count-vector R-tree behind shared-key blocks.

1. Every document becomes a set of hashed shingles.  Copies (equal sets) are
   told by a 128-bit digest and joined at once.
2. Two sets that are similar enough share one of the first keys of each set in
   any fixed order of all shingles (prefix principle).  The order puts shingles
   of rare words first: a shingle's place is the sum of its words' levels, a
   word's level the logarithm of its count in a sketch of fixed size.  So texts
   that have nothing to do with each other seldom share a key.  Keys that are
   found in more than HEAVY documents by this order come last in a second one, so
   passages that many documents share seldom are keys.  Sketches only change the
   order, never the result.
3. The shingles of a document, hashed into groups and counted, are a point.  The
   sum of coordinate minima bounds the overlap of two points or boxes.  Within a
   key, every document is first held against the key's leader, a linear number
   of pairs.  This settles families of near copies.
4. What is left are pairs of different components that share a key and are near
   enough in size.  An R-tree over the points of a key prunes all that can't
   reach the threshold.  Points have about as many groups as shingles; in a tree
   all have those of its smallest set.  Keys with many documents are dealt out as
   blocks of bounded size.
5. Pairs that survive are verified on whole sets.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .common import connected, stash, text_column

SHINGLE = 5
#: Links need 100 * intersection >= PERCENT * union.
PERCENT = 75
#: Groups of a point: the power of two from the size of the set on, within these.  About one shingle a group tells unrelated texts apart.
LEAST_GROUPS, MOST_GROUPS = 256, 8192
_WIDE = 255
#: Cells of the sketch of word counts, and what a task's cell must exceed, in means, to be told.
SKETCH_BITS, SKETCH_TIMES = 18, 2
SKETCH_CELLS = 1 << SKETCH_BITS
#: Keys of more documents are put last, told by cells of their hashes, of which one in HEAVY_SHARE may be so.
HEAVY, HEAVY_BITS, HEAVY_SHARE = 16, 20, 8
#: Rows of a block in which points are compared; larger keys are dealt out.
BLOCK_ROWS = 1024
#: Up to this many documents are named to all tasks when their sets are fetched; more are joined.
BROADCAST_ROWS = 500_000


def shingle_sets(data: np.ndarray, offsets: np.ndarray, size: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of each row, one after another, and each row's offset."""
    h, bounds, _ = ranked_sets(*_words(data, offsets), None, size)
    return h, bounds


def _words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    low = K.LOWER[data]
    starts, ends, first = K.word_spans(low, offsets)
    return K.word_hash(low, starts, ends), first


def _small(numbers: np.ndarray) -> np.ndarray:
    """Numbers from 0 on as 16 bits where they fit: these are sorted in linear time."""
    return numbers.astype(np.uint16) if not len(numbers) or numbers.max() < 1 << 16 else numbers


def _cells(words: np.ndarray) -> np.ndarray:
    return (words >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)


def ranked_sets(words: np.ndarray, first: np.ndarray, levels: np.ndarray | None, size: int = SHINGLE) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """shingle_sets of hashed words, ``first`` telling each row's first, and each shingle's place in the order of all: the sum of its words' levels."""
    n_grams = max(0, len(words) - size + 1)
    at, row = K.gram_rows(first, size, n_grams)
    h = K.gram_hash(words, size)[at]
    place = None
    if levels is not None:
        total = np.concatenate([[0], np.cumsum(levels[_cells(words)].astype(np.int64))])
        place = (total[size:] - total[:-size])[at] if n_grams else np.zeros(0, np.int64)
    n_words = np.diff(first)
    short = np.flatnonzero((n_words > 0) & (n_words < size))
    if len(short):  # the whole sequence is the only shingle
        extra = np.array([_few(words[first[r] : first[r + 1]]) for r in short.tolist()], np.uint64)
        h, row = np.concatenate([h, extra]), np.concatenate([row, short])
        place = None if place is None else np.concatenate([place, np.zeros(len(short), np.int64)])
    order = np.argsort(h)
    order = order[np.argsort(_small(row[order]), kind="stable")]
    h, row = h[order], row[order]
    keep = np.ones(len(h), bool)
    keep[1:] = (h[1:] != h[:-1]) | (row[1:] != row[:-1])
    place = None if place is None else place[order][keep]
    h, row = h[keep], row[keep]
    return h, np.searchsorted(row, np.arange(len(first))), place


def _few(words: np.ndarray) -> int:
    return int(K.gram_hash(words, len(words))[0] ^ np.uint64(len(words)))


def _digests(h: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit digests of each set."""
    out = []
    for salt in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F):
        total = np.concatenate([[np.uint64(0)], np.cumsum(K.mix64(h + np.uint64(salt)))])
        out.append(K.mix64(total[bounds[1:]] - total[bounds[:-1]] + np.diff(bounds).astype(np.uint64)).view(np.int64))
    return out[0], out[1]


def count_vectors(h: np.ndarray, bounds: np.ndarray) -> list[bytes]:
    """For each row a byte for each hash group, its count; _WIDE stands for that or more."""
    out = []
    for a, b in zip(bounds.tolist(), bounds[1:].tolist()):
        groups = min(max(1 << max(b - a - 1, 0).bit_length(), LEAST_GROUPS), MOST_GROUPS)
        cell = (h[a:b] >> np.uint64(64 - groups.bit_length() + 1)).astype(np.int64)
        out.append(np.minimum(np.bincount(cell, minlength=groups), _WIDE).astype(np.uint8).tobytes())
    return out


def _counts(vector: bytes) -> np.ndarray:
    out = np.frombuffer(vector, np.uint8).astype(np.int64)
    if out.max(initial=0) == _WIDE:
        out[out == _WIDE] = 1 << 40
    return out


def _folded(vectors: np.ndarray, groups: int) -> np.ndarray:
    """The counts of coarser groups."""
    return vectors.reshape(*vectors.shape[:-1], groups, -1).sum(-1)


def overlap_bound(a: bytes, b: bytes) -> int:
    """The sum of coordinate minima, on the coarser of the two points' groups."""
    x, y = _counts(a), _counts(b)
    groups = min(len(x), len(y))
    return int(np.minimum(_folded(x, groups), _folded(y, groups)).sum())


def prefix_size(n: np.ndarray) -> np.ndarray:
    """How many first keys a set of n shingles needs so that no link is missed."""
    return np.where(n > 0, n - -(-n * PERCENT // 100) + 1, 0)


_INFO = "doc long, n long, f1 long, f2 long, vec binary, cell long, cell_count long"


def _info(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    sketch, total = np.zeros(SKETCH_CELLS, np.int64), 0
    names = ["doc", "n", "f1", "f2", "vec", "cell", "cell_count"]
    for batch in batches:
        for i, j, data, offsets in K.byte_chunks(batch.column(1)):
            words, first = _words(data, offsets)
            h, bounds, _ = ranked_sets(words, first, None)
            f1, f2 = _digests(h, bounds)
            vec = count_vectors(h, bounds)
            sketch += np.bincount(_cells(words), minlength=SKETCH_CELLS)
            total += len(words)
            none = pa.nulls(j - i, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.array(np.diff(bounds)), pa.array(f1), pa.array(f2), pa.array(vec, pa.binary()), none, none], names)
    often = np.flatnonzero(sketch > 8 + SKETCH_TIMES * total / SKETCH_CELLS)
    if len(often):
        none = pa.nulls(len(often), pa.int64())
        yield pa.RecordBatch.from_arrays([none, none, none, none, pa.nulls(len(often), pa.binary()), pa.array(often), pa.array(sketch[often])], names)


def _prefix_keys(levels, heavy=None):
    """Rows (key, doc): the first keys of each document; of equal sets in a task one document goes on."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        level_of, seen = levels.value, set()
        last = None if heavy is None else heavy.value.astype(np.int64) << 8
        for batch in batches:
            ids = batch.column(0)
            known = np.asarray(ids.is_valid())
            ids = np.asarray(ids.fill_null(0))
            for i, j, data, offsets in K.byte_chunks(batch.column(1)):
                h, bounds, place = ranked_sets(*_words(data, offsets), level_of)
                f1, f2 = _digests(h, bounds)
                n = np.diff(bounds)
                want = prefix_size(n)
                for r, f in enumerate(zip(f1.tolist(), f2.tolist())):
                    if f in seen or not known[i + r]:
                        want[r] = 0
                    else:
                        seen.add(f)
                row = np.repeat(np.arange(j - i), n)
                if last is not None:
                    place = np.minimum(place, 255) + last[(h >> np.uint64(64 - HEAVY_BITS)).astype(np.int64)]
                order = np.argsort(_small(place), kind="stable")
                order = order[np.argsort(_small(row[order]), kind="stable")]
                take = order[K.ranges(bounds[:-1], want)]
                yield pa.RecordBatch.from_arrays([pa.array(h[take].view(np.int64)), pa.array(ids[i + row[take]].astype(np.int64))], ["key", "doc"])

    return run


class CountVectorTree:
    """An R-tree over count vectors: boxes keep their upper corner and their smallest set size.

    Points are sorted into the tree from the top: a node is cut at the median of
    the set sizes if these differ by more than the threshold allows, else of the
    coordinate that spreads most.
    """

    LEAF = 24

    def __init__(self, sizes: np.ndarray, vectors: np.ndarray):
        self.sizes, self.vectors = sizes, vectors
        self.order = np.arange(len(sizes))
        #: (first, past last, left child, right child)
        self.nodes: list[tuple[int, int, int, int]] = []
        self.upper: list[np.ndarray] = []
        self.least: list[int] = []
        if len(sizes):
            self._build(0, len(sizes))

    def _build(self, a: int, b: int) -> int:
        own = self.order[a:b]
        me = len(self.nodes)
        self.nodes.append((a, b, -1, -1))
        self.upper.append(self.vectors[own].max(0))
        self.least.append(int(self.sizes[own].min()))
        if b - a > self.LEAF:
            by = self.sizes[own]
            if by.max() * PERCENT <= by.min() * 100:
                points = self.vectors[own]
                by = points[:, int(np.argmax(points.max(0) - points.min(0)))]
            self.order[a:b] = own[np.argsort(by, kind="stable")]
            mid = (a + b) // 2
            left, right = self._build(a, mid), self._build(mid, b)
            self.nodes[me] = (a, b, left, right)
        return me

    @staticmethod
    def reachable(overlap, size_a, size_b):
        """Whether an overlap of at most this much can make a link of sets of at least these sizes."""
        return overlap * (100 + PERCENT) >= (size_a + size_b) * PERCENT

    def pairs(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Index pairs of points, each once, whose overlap bound reaches the threshold."""
        todo = [(0, 0)] if self.nodes else []
        while todo:
            p, q = todo.pop()
            if p != q and not self.reachable(int(np.minimum(self.upper[p], self.upper[q]).sum()), self.least[p], self.least[q]):
                continue
            (a, b, left, right), (c, d, left_q, right_q) = self.nodes[p], self.nodes[q]
            if p == q and left >= 0:
                todo += [(left, left), (left, right), (right, right)]
            elif left >= 0 and (left_q < 0 or b - a >= d - c):
                todo += [(left, q), (right, q)]
            elif left_q >= 0:
                todo += [(p, left_q), (p, right_q)]
            else:
                x, y = self.order[a:b], self.order[c:d]
                over = np.minimum(self.vectors[x][:, None, :], self.vectors[y][None, :, :]).sum(2)
                good = self.reachable(over, self.sizes[x][:, None], self.sizes[y][None, :])
                i, j = np.nonzero(np.triu(good, 1) if p == q else good)
                if len(i):
                    yield x[i], y[j]


_PAIRS = "a long, b long"
#: A pair can only link in the same or in neighbouring size classes.
_CLASS_BASE = 1.005 * 100 / PERCENT


def _block_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Candidate pairs of rows (key, size_class, block, doc, own, n, comp, vec) that come sorted by block.

    Rows that aren't of the block's own size class only meet those that are, and rows of the key's home component only others.
    """
    held: pa.Table | None = None

    def blocks(table: pa.Table, at_end: bool) -> tuple[list[tuple[np.ndarray, np.ndarray]], pa.Table | None]:
        key = np.stack([table.column(c).to_numpy() for c in ("key", "size_class", "block")])
        change = np.flatnonzero((key[:, 1:] != key[:, :-1]).any(0)) + 1
        cut = [0, *change.tolist(), table.num_rows]
        rest = None
        if not at_end:
            rest = table.slice(cut[-2])
            cut = cut[:-1]
        found = []
        doc, n, comp, mine = (table.column(c).to_numpy() for c in ("doc", "n", "comp", "own"))
        vec = table.column("vec")
        for a, b in zip(cut, cut[1:]):
            comps = comp[a:b]
            if b - a < 2 or (comps == comps[0]).all() or not mine[a:b].any():
                continue
            raw = [_counts(v.as_py()) for v in vec.slice(a, b - a)]
            groups = min(map(len, raw))
            points = np.stack([np.minimum(_folded(x, groups), 1 << 20) for x in raw]).astype(np.int32)
            for x, y in CountVectorTree(n[a:b], points).pairs():
                keep = (comps[x] != comps[y]) & (mine[a:b][x] | mine[a:b][y])
                x, y = doc[a:b][x[keep]], doc[a:b][y[keep]]
                found.append((np.minimum(x, y), np.maximum(x, y)))
        return found, rest

    def out(found):
        if found:
            a, b = (np.concatenate(x) for x in zip(*found))
            pair = np.unique(np.stack([a, b], 1), axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(pair[:, 0].copy()), pa.array(pair[:, 1].copy())], ["a", "b"])

    for batch in batches:
        if not batch.num_rows:
            continue
        table = pa.Table.from_batches([batch])
        table = pa.concat_tables([held, table]) if held is not None else table
        found, held = blocks(table, False)
        yield from out(found)
    if held is not None:
        yield from out(blocks(held, True)[0])


def _bounded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows (a, b, n_a, n_b, vec_a, vec_b) the pairs whose overlap bound reaches the threshold."""
    for batch in batches:
        if not batch.num_rows:
            continue
        over = np.array([overlap_bound(x.as_py(), y.as_py()) for x, y in zip(batch.column(4), batch.column(5))], np.int64)
        good = CountVectorTree.reachable(over, batch.column(2).to_numpy(), batch.column(3).to_numpy())
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(good))


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, j, data, offsets in K.byte_chunks(batch.column(1)):
            h, bounds = shingle_sets(data, offsets)
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.array([h[a:b].tobytes() for a, b in zip(bounds, bounds[1:])], pa.binary())], ["doc", "grams"])


def _linked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows (a, b, grams_a, grams_b) those that link."""
    for batch in batches:
        good = []
        for x, y in zip(batch.column(2), batch.column(3)):
            x, y = np.frombuffer(x.as_py(), np.uint64), np.frombuffer(y.as_py(), np.uint64)
            both = len(np.intersect1d(x, y, assume_unique=True))
            good.append(100 * both >= PERCENT * (len(x) + len(y) - both))
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(good, pa.bool_()))


def _verified(texts: DataFrame, pairs: DataFrame) -> DataFrame:
    """The pairs (a, b) that link, by their whole sets."""
    wanted = stash(pairs.select(F.col("a").alias("doc")).union(pairs.select(F.col("b"))).distinct())
    if wanted.count() <= BROADCAST_ROWS:
        wanted = F.broadcast(wanted)
    named = texts.where("doc_id IS NOT NULL").withColumnRenamed("doc_id", "doc")
    sets = named.join(wanted, "doc", "left_semi").mapInArrow(_sets, "doc long, grams binary")
    left = sets.select(F.col("doc").alias("a"), F.col("grams").alias("grams_a"))
    right = sets.select(F.col("doc").alias("b"), F.col("grams").alias("grams_b"))
    both = pairs.join(left, "a").join(right, "b").select("a", "b", "grams_a", "grams_b")
    return both.mapInArrow(_linked, _PAIRS)


def _reached(pairs: DataFrame, named: DataFrame) -> DataFrame:
    """The pairs (a, b) whose sizes and count vectors leave a link possible; equal sets don't count."""

    def side(s: str) -> DataFrame:
        return named.select(F.col("doc").alias(s), *[F.col(c).alias(f"{c}_{s}") for c in ("n", "f1", "f2", "vec")])

    sizes = named.select("doc", "n")
    near = pairs.join(sizes.toDF("a", "n_x"), "a").join(sizes.toDF("b", "n_y"), "b")
    near = near.where(f"100 * least(n_x, n_y) >= {PERCENT} * greatest(n_x, n_y)").select("a", "b")
    both = near.join(side("a"), "a").join(side("b"), "b").where("f1_a <> f1_b OR f2_a <> f2_b")
    return both.select("a", "b", "n_a", "n_b", "vec_a", "vec_b").mapInArrow(_bounded, _PAIRS).distinct()


def ngram_components(docs: DataFrame) -> DataFrame:
    """(doc_id, n_shingles, component_id), one row for each input row.

    A document's set holds its distinct 5-word shingles after lower-casing A-Z;
    fewer words make one shingle, and no word (or a null text) an empty set that
    links with nothing.  Documents link when 100 * intersection >= 75 * union;
    component_id is the smallest doc_id that links reach.  Rows with the same
    doc_id are one node: a link of any of their texts counts.  A null doc_id has
    a null component.  Other columns don't matter; no rows give no rows.
    """
    spark = docs.sparkSession
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_column(docs).alias("text"))
    told = stash(texts.mapInArrow(_info, _INFO))
    info = told.where("cell IS NULL").drop("cell", "cell_count")

    # The sketch has SKETCH_CELLS cells whatever the input.
    cells = told.where("cell IS NOT NULL").groupBy("cell").agg(F.sum("cell_count").alias("c")).toPandas()
    level = np.zeros(SKETCH_CELLS, np.uint8)
    if len(cells):
        level[cells["cell"].to_numpy()] = np.log2(cells["c"].to_numpy()).astype(np.uint8)
    level = spark.sparkContext.broadcast(level)
    keys = texts.mapInArrow(_prefix_keys(level), "key long, doc long")
    often = keys.groupBy("key").count().where(F.col("count") > HEAVY)
    often = often.groupBy(F.shiftrightunsigned("key", 64 - HEAVY_BITS).alias("cell")).agg(F.max("count").alias("c")).toPandas()
    heavy = np.zeros(1 << HEAVY_BITS, np.uint8)
    if len(often):
        heavy[often["cell"].to_numpy()] = np.log2(often["c"].to_numpy()).astype(np.uint8)
        while (heavy > 0).sum() > len(heavy) // HEAVY_SHARE:
            heavy[heavy == heavy[heavy > 0].min()] = 0
    keys = texts.mapInArrow(_prefix_keys(level, spark.sparkContext.broadcast(heavy)), "key long, doc long")

    leaders = keys.groupBy("key").agg(F.min("doc").alias("lead"), F.max("doc").alias("top")).where("lead < top").drop("top")
    shared = stash(keys.join(leaders, "key").select("key", "doc", "lead"))
    named = info.where("n > 0 AND doc IS NOT NULL").dropDuplicates(["doc", "f1", "f2"])

    # Copies.
    copies = named.groupBy("f1", "f2").agg(F.min("doc").alias("b"), F.max("doc").alias("top")).where("b < top").drop("top")
    copies = named.select(F.col("doc").alias("a"), "f1", "f2").join(copies, ["f1", "f2"]).where("a > b").select("a", "b")

    # Each document against the leaders of its keys.
    led = shared.where("doc > lead").select(F.col("lead").alias("a"), F.col("doc").alias("b")).distinct()
    led = stash(_reached(led, named))
    links = stash(copies.union(_verified(texts, led)))
    parts = connected(links)

    # Pairs of different components that share a key.  Keys with the same documents are one.
    rows = shared.join(parts.withColumnRenamed("id", "doc"), "doc", "left").withColumn("comp", F.coalesce("component", "doc")).select("key", "doc", "lead", "comp")
    mixed = rows.groupBy("key").agg(
        F.count(F.lit(1)).alias("m"), F.min("comp").alias("low"), F.max("comp").alias("high"), F.sum(F.xxhash64("doc").cast("decimal(38,0)")).alias("s1"), F.sum(F.xxhash64(F.lit(7), "doc").cast("decimal(38,0)")).alias("s2")
    )
    mixed = mixed.where("low < high").groupBy("m", "s1", "s2").agg(F.min("key").alias("key")).select("key")
    rows = rows.join(mixed, "key").join(named.select("doc", "n"), "doc")
    # A row belongs to its size class, and is a guest in the class above.
    own = F.floor(F.log(F.col("n")) / math.log(_CLASS_BASE)).cast("int")
    rows = rows.withColumn("own_class", own).withColumn("size_class", F.explode(F.array(own, own + 1)))
    rows = stash(rows.select("key", "doc", "lead", "comp", "n", "size_class", (F.col("own_class") == F.col("size_class")).alias("own")))
    cells = rows.groupBy("key", "size_class").agg(F.count(F.lit(1)).alias("m"), F.min("comp").alias("low"), F.max("comp").alias("high"), F.max("own").alias("any"))
    cells = cells.where("any AND low < high").select("key", "size_class", F.ceil(F.col("m") / BLOCK_ROWS).cast("int").alias("parts"))
    # Rows of the leader's component are dealt out to blocks; others meet all blocks of their key and size.
    home = rows.where("doc = lead").select("key", F.col("comp").alias("home")).distinct()
    rows = rows.join(cells, ["key", "size_class"]).join(home, "key", "left")
    dealt = F.array(F.pmod(F.xxhash64(F.lit(3), "doc"), F.col("parts").cast("long")).cast("int"))
    rows = rows.withColumn("block", F.explode(F.when(F.col("comp") == F.col("home"), dealt).otherwise(F.sequence(F.lit(0), F.col("parts") - 1))))
    rows = rows.join(named.select("doc", "n", "vec"), ["doc", "n"]).select("key", "size_class", "block", "doc", "own", "n", "comp", "vec")
    near = rows.repartition("key", "size_class", "block").sortWithinPartitions("key", "size_class", "block").mapInArrow(_block_pairs, _PAIRS).distinct()
    near = stash(_reached(near.join(led, ["a", "b"], "left_anti"), named))
    links = links.union(_verified(texts, near))

    whole = connected(links)
    out = info.join(whole, info["doc"] == whole["id"], "left")
    return out.select(info["doc"].alias("doc_id"), info["n"].alias("n_shingles"), F.coalesce("component", info["doc"]).alias("component_id"))


def keep_representatives(docs: DataFrame) -> DataFrame:
    """The rows whose doc_id is the smallest of its component; of rows with that doc_id all stay, and so do null ids."""
    parts = ngram_components(docs).where("component_id < doc_id").select("doc_id").distinct()
    return docs.join(parts, "doc_id", "left_anti")


#: DuckDB SQL of the components over ``documents``.
SQL = """
WITH RECURSIVE w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS words FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(words[i : i + 4], ' ') AS g FROM w, LATERAL unnest(range(1, greatest(len(words) - 3, 2))) AS u(i) WHERE len(words) > 0),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM s x JOIN s y ON x.g = y.g AND x.doc_id <> y.doc_id GROUP BY ALL),
l AS (SELECT a, b FROM p JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * c >= 75 * (na.n + nb.n - c)),
r AS (SELECT a AS id, a AS to_id FROM l UNION SELECT r.id, l.b FROM r JOIN l ON r.to_id = l.a)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, least(d.doc_id, coalesce(c.m, d.doc_id)) AS component_id
FROM documents d LEFT JOIN n USING (doc_id) LEFT JOIN (SELECT id AS doc_id, min(to_id) AS m FROM r GROUP BY id) c USING (doc_id)
"""
