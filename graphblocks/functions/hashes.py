"""Arithmetic hashes that Spark, DuckDB and numpy compute alike, and the tabular hashes."""

from __future__ import annotations

from functools import lru_cache, reduce

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

P = 2147483647
#: Multipliers of the portable hash.
_A, _B, _C, _D, _E, _F = 48271, 16807, 69621, 11, 40692, 12345


def mix(col: Column | str, seed: int = 0) -> Column:
    """0 .. P-1; a squared affine map, so another seed gives another order and not just a rotated one."""
    x = F.col(col) if isinstance(col, str) else col
    x = x.cast("long")
    h = (F.pmod(x, F.lit(P)) * _A + F.floor(x / P).cast("long") * _B + (seed % P) * _C + _D) % P
    return (h * h + h * _E + _F) % P


def mix_sql(expr: str, seed: int | str = 0) -> str:
    """The same as DuckDB SQL, for ids from 0 on."""
    h = f"((({expr}) % {P}) * {_A} + (({expr}) // {P}) * {_B} + (({seed}) % {P}) * {_C} + {_D}) % {P}"
    return f"((({h}) * ({h}) + ({h}) * {_E} + {_F}) % {P})"


def mix_np(x: np.ndarray | int, seed: int = 0) -> np.ndarray:
    x = np.asarray(x, np.int64)
    h = (x % P * _A + x // P * _B + seed % P * _C + _D) % P
    return (h * h + h * _E + _F) % P


@lru_cache(64)
def table(t: int, index: int, seed: int) -> np.ndarray:
    """2**t values of one chunk's table, made once and only read."""
    return mix_np(np.arange(1 << t), seed * 101 + index)


def _chunks(bits: int, low: int, t: int) -> int:
    return max(0, -(-(bits - low) // t))


def tabular_hash_np(x: np.ndarray, t: int = 10, bits: int = 30, seed: int = 0, low: int = 0) -> np.ndarray:
    """xor of a table value for each t-bit chunk; the ``low`` least bits pass through, which keeps neighbours together."""
    x = np.asarray(x, np.int64)
    out = x & ((1 << low) - 1)
    for i in range(_chunks(bits, low, t)):
        # Of values that meet the low bits only the upper bits count, so groups stay aligned.
        out ^= (table(t, i, seed)[(x >> (low + i * t)) & ((1 << t) - 1)] >> low) << low
    return out


def tabular_hash(col: Column | str, t: int = 10, bits: int = 30, seed: int = 0, low: int = 0) -> Column:
    x = (F.col(col) if isinstance(col, str) else col).cast("long")
    out = x.bitwiseAND(F.lit((1 << low) - 1))
    for i in range(_chunks(bits, low, t)):
        values = F.lit(((table(t, i, seed) >> low) << low).tolist())
        out = out.bitwiseXOR(F.get(values, F.shiftright(x, low + i * t).bitwiseAND(F.lit((1 << t) - 1)).cast("int")))
    return out


def tabular_hash_sql(expr: str, t: int = 10, bits: int = 30, seed: int = 0, low: int = 0) -> str:
    """As DuckDB SQL; table values are computed, not listed."""
    parts = [f"(({expr}) & {(1 << low) - 1})"]
    for i in range(_chunks(bits, low, t)):
        chunk = f"((({expr}) >> {low + i * t}) & {(1 << t) - 1})"
        parts.append(f"(({mix_sql(chunk, seed * 101 + i)} >> {low}) << {low})")
    return reduce(lambda a, b: f"xor({a}, {b})", parts)
