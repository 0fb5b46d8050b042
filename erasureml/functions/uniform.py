"""Reproducible uniforms from integer arithmetic, the same in Spark, SQL and numpy.

A draw is a function of (t, worker, seed) alone, so a run can be replayed on any partitioning.
All products stay below 2^63 for t and worker up to 10^12.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

# The modulus 2^31-1 and the multipliers of the two congruential steps.
P, A_T, A_W, A_1, A_2, C_2 = 2147483647, 1000003, 8191, 48271, 69621, 12345


def uniform_sql(t: str, worker: str, seed: int) -> str:
    """The draw as SQL (Spark and DuckDB), in (0, 1)."""
    first = f"(((({A_T} * (({t}) % {P}) + {A_W} * (({worker}) % {P}) + {seed}) % {P}) * {A_1}) % {P})"
    return f"(((({A_2} * (({first} * {first}) % {P}) + {C_2}) % {P}) + 0.5) / {P}.0)".replace(".0)", "e0)")


def uniform(t: Column | str, worker: Column | str, seed: int) -> Column:
    t, worker = (F.col(x) if isinstance(x, str) else x for x in (t, worker))
    m = F.lit(P).cast("long")
    first = (A_T * (t.cast("long") % m) + A_W * (worker.cast("long") % m) + seed) % m * F.lit(A_1) % m
    return ((F.lit(A_2).cast("long") * (first * first % m) + C_2) % m + 0.5) / P


def uniform_np(t, worker, seed: int) -> np.ndarray:
    t, worker = np.broadcast_arrays(np.asarray(t, np.int64), np.asarray(worker, np.int64))
    first = (A_T * (t % P) + A_W * (worker % P) + seed) % P * A_1 % P
    return ((A_2 * (first * first % P) + C_2) % P + 0.5) / P


def counted_np(i, j, seed: int) -> np.ndarray:
    """Draws in (0, 1) from a 64-bit mixing of (i, j, seed): for random matrices, whose entries must not line up."""
    i, j = np.broadcast_arrays(np.asarray(i, np.uint64), np.asarray(j, np.uint64))
    with np.errstate(over="ignore"):
        z = np.full(i.shape, seed + 1, np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        for part in (i, j):
            z = z ^ (part + np.uint64(0x9E3779B97F4A7C15)) * np.uint64(0xD1342543DE82EF95)
            z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
            z = z ^ (z >> np.uint64(31))
    return ((z >> np.uint64(11)).astype(float) + 0.5) / (1 << 53)


def normal_np(i, j, seed: int) -> np.ndarray:
    """Box-Muller on two such draws."""
    return np.sqrt(-2 * np.log(counted_np(i, j, seed))) * np.cos(2 * np.pi * counted_np(i, j, seed + 500009))


def normal(t, worker, seed: int) -> Column:
    return F.sqrt(-2 * F.log(uniform(t, worker, seed))) * F.cos(2 * np.pi * uniform(t, worker, seed + 500009))


def ranked(n: int, seed: int) -> np.ndarray:
    """0..n-1 in a random order: by draw, then by number."""
    return np.lexsort((np.arange(n), uniform_np(np.arange(n), 0, seed)))
