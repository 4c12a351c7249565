"""Random parameters that can be made again anywhere.

Two generators. `omega_slice` draws the columns of one block from a counter-based generator keyed by
(seed, block), so a task needs a few numbers of state instead of a matrix, and a retry or another
placement draws the same values. The portable one mixes (seed, row, place) in 31-bit arithmetic whose
products stay below 2^62, so NumPy, Spark SQL and DuckDB give the same integers.
"""

from __future__ import annotations

import math

import numpy as np

PRIME = (1 << 31) - 1
#: Multipliers of the mixing (fixed values).
BY_SEED, BY_ROW, BY_PLACE, FIRST, SECOND = 48271, 69621, 1103515245, 1343714438, 630360016
SHIFTS = (15, 13)


def generator(*key: int) -> np.random.Generator:
    return np.random.Generator(np.random.Philox(key=[int(k) & ((1 << 64) - 1) for k in (*key, 0)[:2]]))


def omega_slice(seed: int, block: int, d: int, width: int) -> np.ndarray:
    """d x width standard normals of one column block."""
    return generator(seed, block).standard_normal((d, width))


def portable_integer(seed: int, r, q) -> np.ndarray:
    """Integers in [0, PRIME) from (seed, r, q); r and q broadcast."""
    r, q = np.asarray(r, np.int64), np.asarray(q, np.int64)
    h = (seed * BY_SEED + r * BY_ROW + q * BY_PLACE) % PRIME
    h = ((h ^ (h >> SHIFTS[0])) * FIRST) % PRIME
    return ((h ^ (h >> SHIFTS[1])) * SECOND) % PRIME


def portable_uniform(seed: int, r, q) -> np.ndarray:
    return (portable_integer(seed, r, q) + 0.5) / PRIME


def portable_normal(seed: int, r, q) -> np.ndarray:
    """Standard normals: place q uses the uniforms 2q and 2q+1 of row r."""
    q = np.asarray(q, np.int64)
    u, v = portable_uniform(seed, r, 2 * q), portable_uniform(seed, r, 2 * q + 1)
    return np.sqrt(-2.0 * np.log(u)) * np.cos(2.0 * math.pi * v)


def portable_integer_sql(seed: int, r: str, q: str, dialect: str = "spark") -> str:
    """The same integers as a SQL expression; dialect is spark or duckdb."""

    def xor_shift(h: str, by: int) -> str:
        return f"(({h}) ^ shiftright({h}, {by}))" if dialect == "spark" else f"xor({h}, ({h}) >> {by})"

    h = f"(({seed * BY_SEED} + ({r}) * {BY_ROW} + ({q}) * CAST({BY_PLACE} AS BIGINT)) % {PRIME})"
    h = f"(({xor_shift(h, SHIFTS[0])} * CAST({FIRST} AS BIGINT)) % {PRIME})"
    return f"(({xor_shift(h, SHIFTS[1])} * CAST({SECOND} AS BIGINT)) % {PRIME})"


def portable_uniform_sql(seed: int, r: str, q: str, dialect: str = "spark") -> str:
    return f"(({portable_integer_sql(seed, r, q, dialect)} + 0.5e0) / {PRIME}e0)"


def portable_normal_sql(seed: int, r: str, q: str, dialect: str = "spark") -> str:
    u = portable_uniform_sql(seed, r, f"2 * ({q})", dialect)
    v = portable_uniform_sql(seed, r, f"2 * ({q}) + 1", dialect)
    return f"(sqrt(-2e0 * ln({u})) * cos({2.0 * math.pi!r}e0 * {v}))"
