"""Vectorised byte kernels shared by the text operators (numpy and Arrow only).

All of them work on the UTF-8 buffer of an Arrow string column, so no Python
string is made for a row.  Rows are taken in chunks of about ``CHUNK_BYTES`` to
bound the memory of a task whatever the length of an Arrow batch.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

CHUNK_BYTES = 1 << 20

_BASE = np.uint64(0x9E3779B97F4A7C15)
_MASK = (1 << 64) - 1

#: True for the bytes that part words: space and 0x09 to 0x0D.
SEPARATOR = np.zeros(256, bool)
SEPARATOR[[0x20, *range(0x09, 0x0E)]] = True

#: ASCII lower case of a byte.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of unsigned 64-bit integers."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


#: Values of the bytes for two independent sums.
_BYTE_VALUE = [mix64(np.arange(1 + 256 * k, 257 + 256 * k, dtype=np.uint64) * _BASE) for k in range(2)]
_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers 0..n of an odd base modulo 2**64, and of its inverse."""
    if len(_powers[0]) <= n:
        size = max(n + 1, CHUNK_BYTES + 4096)
        inverse = pow(int(_BASE), -1, 1 << 64)
        for k, base in enumerate((int(_BASE), inverse)):
            steps = np.full(size, base & _MASK, np.uint64)
            steps[0] = 1
            _powers[k] = np.multiply.accumulate(steps)
    return _powers[0], _powers[1]


def prefix_hash(data: np.ndarray, salt: int = 0) -> np.ndarray:
    """Prefix sums from which ``span_hash`` gets the hash of any byte span; another ``salt`` gives others."""
    power, _ = power_tables(len(data))
    out = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_BYTE_VALUE[salt][data] * power[: len(data)], out=out[1:])
    return out


def span_hash(prefix: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of the spans, the same for equal bytes anywhere."""
    _, inverse = power_tables(len(prefix))
    return mix64((prefix[ends] - prefix[starts]) * inverse[starts] + (ends - starts).astype(np.uint64))


#: Up to this length the sums of span_hash tell all but freak spans apart; longer words are hashed whole.
LONG_WORD = 256


def word_hash(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, prefix: np.ndarray | None = None) -> np.ndarray:
    """64-bit hashes of words.  Sums modulo 2**64 are the same for certain long strings, so long words get a digest of their bytes."""
    out = span_hash(prefix_hash(data) if prefix is None else prefix, starts, ends)
    for i in np.flatnonzero(ends - starts > LONG_WORD).tolist():
        out[i] = int.from_bytes(hashlib.blake2b(data[starts[i] : ends[i]].tobytes(), digest_size=8).digest(), "little")
    return out


def utf8_rows(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and row offsets (from 0) of a string column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def row_chunks(offsets: np.ndarray, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of at most ``limit`` bytes, or of one longer row."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = int(np.searchsorted(offsets, offsets[i] + limit, "right")) - 1
        j = min(max(j, i + 1), n)
        yield i, j
        i = j


def byte_chunks(column: pa.Array, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, past last row, bytes, row offsets) of each chunk."""
    data, offsets = utf8_rows(column)
    for i, j in row_chunks(offsets, limit):
        yield i, j, data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]


def word_spans(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words, and for each row the index of its first word (one more at the end)."""
    inside = ~SEPARATOR[data]
    n = len(data)
    start = inside.copy()
    end = inside.copy()
    if n:
        start[1:] &= ~inside[:-1]
        end[:-1] &= ~inside[1:]
        at = offsets[:-1][np.diff(offsets) > 0]
        start[at] = inside[at]
        end[at[1:] - 1] = inside[at[1:] - 1]
    starts = np.flatnonzero(start)
    ends = np.flatnonzero(end) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def gram_hash(words: np.ndarray, size: int) -> np.ndarray:
    """Hashes of ``size`` consecutive word hashes, one for each start; rows aren't regarded."""
    n = len(words) - size + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = words[:n].copy()
    for k in range(1, size):
        out *= np.uint64(0xD6E8FEB86659FD93)
        out += words[k : n + k]
        out ^= out >> np.uint64(29)
    return mix64(out)


def gram_rows(first_word: np.ndarray, size: int, n_grams: int) -> tuple[np.ndarray, np.ndarray]:
    """Indices of the grams that lie in one row, and their rows."""
    counts = np.diff(first_word)
    row = np.repeat(np.arange(len(counts)), counts)[:n_grams]
    inside = np.arange(n_grams) + size <= first_word[1:][row] if n_grams else np.zeros(0, bool)
    index = np.flatnonzero(inside)
    return index, row[index]


def ranges(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """start, start + 1, ... of each range, one after another."""
    total = int(counts.sum())
    if not total:
        return np.zeros(0, np.int64)
    before = np.cumsum(counts) - counts
    return np.repeat(starts - before, counts) + np.arange(total)


def take_spans(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """The spans' bytes, one after another."""
    return data[ranges(starts, ends - starts)]
