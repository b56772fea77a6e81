"""Random numbers that are pure functions of (seed, k, id), the same in Spark SQL, in other SQL engines and in numpy.

Two lanes of modular quadratic mixing, with products below 2^62, give two uniforms; the Box-Muller form gives a normal.
No random matrix is ever stored, partitioning cannot change a value, and SQL can recompute any of them.  Ids congruent
modulo 2^31 - 1 share one lane; from 2^31 rows on, use the Philox generator of the coding operator instead.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

#: The lanes' primes, and the multipliers of the mixing rounds.
PRIMES = (2147483647, 2147483629)
MULTIPLIERS = (40692, 48271, 69621)
FIRST, SECOND = 1000003, 998244353
SEED_STEP, LANE_SEED = 7919, 104729


def lane_columns(name: str, k: str, ident: str, seed: int, lane: int) -> list[str]:
    """Select items, each using the ones before it, that end in the uniform `name`."""
    p = PRIMES[lane]
    a, b = (k, ident) if lane == 0 else (ident, k)
    shift = (seed + LANE_SEED * lane) * SEED_STEP + lane + 1
    items = [f"cast({a} as bigint) % {p} as {name}_a", f"cast({b} as bigint) % {p} as {name}_b"]
    items.append(f"({name}_a * {FIRST} % {p} + {name}_b * {SECOND} % {p} + {shift}) % {p} as {name}_h0")
    for i, q in enumerate(MULTIPLIERS):
        items.append(f"({name}_h{i} * {name}_h{i} % {p} + {name}_h{i} * {q} % {p} + 12345) % {p} as {name}_g{i}")
        items.append(f"({name}_g{i} * {q} + {name}_b) % {p} as {name}_h{i + 1}")
    return [*items, f"({name}_h{len(MULTIPLIERS)} + cast(0.5 as double)) / {p} as {name}"]


def _scratch(name: str) -> list[str]:
    rounds = range(len(MULTIPLIERS))
    return [f"{name}_a", f"{name}_b", f"{name}_h0", *(f"{name}_{x}" for i in rounds for x in (f"g{i}", f"h{i + 1}"))]


def uniform_columns(name: str, k: str, ident: str, seed: int) -> tuple[list[str], list[str]]:
    """(select items, helper columns to drop)."""
    return lane_columns(name, k, ident, seed, 0), _scratch(name)


def gauss_columns(name: str, k: str, ident: str, seed: int) -> tuple[list[str], list[str]]:
    u, v = f"{name}_u", f"{name}_v"
    items = lane_columns(u, k, ident, seed, 0) + lane_columns(v, k, ident, seed, 1)
    items.append(f"sqrt(-2 * ln({u})) * cos(2 * pi() * {v}) as {name}")
    return items, [*_scratch(u), *_scratch(v), u, v]


def with_uniform(df: DataFrame, name: str, k: str, ident: str, seed: int) -> DataFrame:
    items, extra = uniform_columns(name, k, ident, seed)
    return df.selectExpr("*", *items).drop(*extra)


def with_gauss(df: DataFrame, name: str, k: str, ident: str, seed: int) -> DataFrame:
    items, extra = gauss_columns(name, k, ident, seed)
    return df.selectExpr("*", *items).drop(*extra)


def sql_with(source: str, columns: tuple[list[str], list[str]]) -> str:
    """A SELECT over `source` that adds the columns, for engines with `exclude`."""
    items, extra = columns
    return f"select * exclude ({', '.join(extra)}) from (select *, {', '.join(items)} from {source})"


def _lane(k, ident, seed: int, lane: int) -> np.ndarray:
    p = PRIMES[lane]
    a, b = (k, ident) if lane == 0 else (ident, k)
    a, b = np.asarray(a, np.int64) % p, np.asarray(b, np.int64) % p
    h = (a * FIRST % p + b * SECOND % p + ((seed + LANE_SEED * lane) * SEED_STEP + lane + 1)) % p
    for q in MULTIPLIERS:
        g = (h * h % p + h * q % p + 12345) % p
        h = (g * q + b) % p
    return (h + 0.5) / p


def uniform(seed: int, k, ident) -> np.ndarray:
    """Broadcasts k against ident."""
    return _lane(k, ident, seed, 0)


def gauss(seed: int, k, ident) -> np.ndarray:
    return np.sqrt(-2 * np.log(_lane(k, ident, seed, 0))) * np.cos(2 * np.pi * _lane(k, ident, seed, 1))


def philox_gauss(seed: int, ids: np.ndarray, count: int) -> np.ndarray:
    """count x len(ids) normals, one counter-based stream for each id: ten times faster, no twin in SQL."""
    out = np.empty((count, len(ids)))
    for i, ident in enumerate(np.asarray(ids, np.int64).tolist()):
        out[:, i] = np.random.Generator(np.random.Philox(key=[seed, ident & (1 << 64) - 1])).standard_normal(count)
    return out
