"""Encoding matrices.  Every code has S'S = I (tight ones exactly, random ones in expectation); beta = N/n.

A code never needs to be sent: rows are a closed form of their numbers (random ones a counter-based draw), so any
task makes those it needs.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from erasureml.functions.transforms import fwht, haar as haar_transform
from erasureml.functions.uniform import counted_np, normal_np, ranked, uniform_np


SLAB_BYTES = 64 << 20


@dataclass(frozen=True)
class Code:
    """n source rows to N encoded rows. maker(i, j) gives entries; fast(X), if any, gives S X."""

    name: str
    n: int
    N: int
    maker: Callable[[np.ndarray, np.ndarray], np.ndarray]
    fast: Callable[[np.ndarray], np.ndarray] | None = field(default=None, repr=False)
    block: int = 1
    tight: bool = True
    copies: int = 1
    fast_t: Callable[[np.ndarray], np.ndarray] | None = field(default=None, repr=False)

    @property
    def beta(self) -> float:
        return self.N / self.n

    def rows(self, lo: int, hi: int) -> np.ndarray:
        return self.maker(np.arange(lo, hi)[:, None], np.arange(self.n)[None, :])

    def entry(self, i: int, j: int) -> float:
        return float(self.maker(np.array([[i]]), np.array([[j]]))[0, 0])

    def matrix(self) -> np.ndarray:
        return self.rows(0, self.N)

    def apply(self, x: np.ndarray) -> np.ndarray:
        """S x along the first axis; rows that x lacks are zero."""
        if len(x) < self.n:
            x = np.concatenate([x, np.zeros((self.n - len(x), *x.shape[1:]))])
        if self.fast:
            return self.fast(x)
        return np.concatenate([np.tensordot(self.rows(lo, hi), x, 1) for lo, hi in self._slabs()])

    def apply_t(self, z: np.ndarray) -> np.ndarray:
        """S'z; like `apply` it never holds more than SLAB_BYTES of S."""
        if self.fast_t:
            return self.fast_t(z)
        return sum(np.tensordot(self.rows(lo, hi).T, z[lo:hi], 1) for lo, hi in self._slabs())

    def _slabs(self) -> list[tuple[int, int]]:
        step = max(1, SLAB_BYTES // (8 * self.n))
        return [(lo, min(lo + step, self.N)) for lo in range(0, self.N, step)]

    def touched(self, present: np.ndarray) -> np.ndarray:
        """(N, ...) whether an encoded row has a term of a source row that is present: (n, ...)."""
        return np.concatenate([np.tensordot((self.rows(lo, hi) != 0).astype(float), present.astype(float), 1) > 0 for lo, hi in self._slabs()])

    def support(self, rows: np.ndarray) -> np.ndarray:
        """Source rows that these encoded rows touch."""
        return np.flatnonzero((self.maker(np.asarray(rows)[:, None], np.arange(self.n)[None, :]) != 0).any(0))

    def to_df(self, spark: SparkSession, m: int = 1, how: str = "scatter", seed: int = 1) -> DataFrame:
        """(enc_row, src_row, coef, worker) of the non-zero entries, made where they are used."""
        worker = assign(self, m, how, seed)

        def make(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for frame in frames:
                for i in frame["id"].to_numpy():
                    row = self.rows(i, i + 1)[0]
                    at = np.flatnonzero(row)
                    yield pd.DataFrame({"enc_row": np.full(len(at), i), "src_row": at, "coef": row[at], "worker": np.full(len(at), worker[i], np.int32)})

        return spark.range(self.N).mapInPandas(make, "enc_row long, src_row long, coef double, worker int")


def assign(code: Code, m: int, how: str = "scatter", seed: int = 1) -> np.ndarray:
    """The worker of every encoded row; all workers get the same number, up to one (blocks: whole blocks)."""
    i = np.arange(code.N)
    if how == "contiguous":
        return (i * m // code.N).astype(np.int32)
    if how == "round_robin":
        return (i % m).astype(np.int32)
    if how == "scatter":
        out = np.empty(code.N, np.int32)
        out[ranked(code.N, seed)] = i % m
        return out
    size = {"block": code.block, "half_block": max(1, code.block // 2)}.get(how)
    if size is None:
        raise ValueError(f"unknown assignment {how}")
    return (i // size * m // -(-code.N // size)).astype(np.int32)


def _sign(i: np.ndarray, j: np.ndarray) -> np.ndarray:
    return 1 - 2 * (np.bitwise_count(np.bitwise_and(i, j)).astype(np.int64) % 2)


def _power(n: float) -> int:
    return 1 << int(np.ceil(np.log2(n) - 1e-12)) if n > 1 else 1


def _spread(n: int, at: np.ndarray, size: int, signs: np.ndarray | None = None):
    """X to a taller array with its rows at `at`."""

    def put(x: np.ndarray) -> np.ndarray:
        out = np.zeros((size, *x.shape[1:]))
        out[at] = x if signs is None else x * signs.reshape(-1, *[1] * (x.ndim - 1))
        return out

    return put


def identity(n: int) -> Code:
    return Code("uncoded", n, n, lambda i, j: (i == j).astype(float), lambda x: np.array(x, float), fast_t=lambda z: np.array(z, float))


def replication(n: int, r: int = 2) -> Code:
    """r copies of every row, scaled to S'S = I; a receiver of several copies must drop all but one."""
    return Code("replication", n, r * n, lambda i, j: (i % n == j) / np.sqrt(r), lambda x: np.concatenate([x] * r) / np.sqrt(r), copies=r)


def hadamard(n: int, beta: float = 2, seed: int = 1, signs: bool = False) -> Code:
    """Columns of a Sylvester matrix of order the next power of two over beta n, chosen by draw; random signs on request."""
    size = _power(beta * n)
    at = np.sort(ranked(size, seed)[:n])
    sign = np.where(uniform_np(np.arange(n), 1, seed) < 0.5, -1.0, 1.0) if signs else np.ones(n)
    put = _spread(n, at, size, sign)

    def back(z: np.ndarray) -> np.ndarray:  # a Sylvester matrix is its own transpose
        return fwht(z)[at] * sign.reshape(-1, *[1] * (z.ndim - 1)) / np.sqrt(size)

    return Code("hadamard", n, size, lambda i, j: _sign(i, at[j]) * sign[j] / np.sqrt(size), lambda x: fwht(put(x)) / np.sqrt(size), fast_t=back)


def hadamard_full(size: int) -> Code:
    return Code("hadamard_full", size, size, lambda i, j: _sign(i, j) / np.sqrt(size), lambda x: fwht(x) / np.sqrt(size))


def hadamard_etf(s: int, parity: str = "odd") -> Code:
    """Order 4^s; the columns whose base-4 number has an odd (even) number of zero digits form an equiangular frame."""
    size = 4**s
    zeros = sum((np.arange(size) >> (2 * k) & 3) == 0 for k in range(s))
    at = np.flatnonzero(zeros % 2 == (parity == "odd"))
    put = _spread(len(at), at, size)
    return Code("hadamard_etf", len(at), size, lambda i, j: _sign(i, at[j]) / np.sqrt(size), lambda x: fwht(put(x)) / np.sqrt(size))


def paley(q: int) -> Code:
    """q a prime, 1 mod 4; N = q + 1, n = N / 2.

    A cosine and a sine column for each quadratic residue below q/2 over rows 1..q, row 0 is a border, and the last
    column joins the border to a constant.
    """
    if q % 4 != 1 or any(q % d == 0 for d in range(2, int(q**0.5) + 1)):
        raise ValueError("q must be a prime that is 1 modulo 4")
    residues = sorted({x * x % q for x in range(1, q)})
    half = np.array([a for a in residues if a < q - a])
    n = 2 * len(half) + 1

    def maker(i: np.ndarray, j: np.ndarray) -> np.ndarray:
        i, j = np.broadcast_arrays(i, j)
        angle = 2 * np.pi * half[np.minimum(j // 2, len(half) - 1)] * ((i - 1) % q) / q
        wave = np.where(j % 2 == 0, np.cos(angle), np.sin(angle)) * np.sqrt(2 / q)
        inner = np.where(i == 0, 0.0, wave)
        return np.where(j == n - 1, np.where(i == 0, np.sqrt(q), 1.0) / np.sqrt(2 * q), inner)

    return Code("paley", n, q + 1, maker)


def _incidence(name: str, blocks: np.ndarray, points: int, order: int) -> Code:
    """blocks: for every column the points (K of them) it joins; each incidence takes the next unused non-constant column
    of a Sylvester matrix of the order given, at the point's block of rows."""
    k = blocks.shape[1]
    used = np.zeros(points, np.int64)
    which = np.zeros_like(blocks)
    for c, pts in enumerate(blocks):
        for a, pt in enumerate(pts):
            used[pt] += 1
            which[c, a] = used[pt]

    def maker(i: np.ndarray, j: np.ndarray) -> np.ndarray:
        i, j = np.broadcast_arrays(i, j)
        point, inner = i // order, i % order
        out = np.zeros(i.shape)
        for a in range(k):
            out += np.where(blocks[j, a] == point, _sign(inner, which[j, a]), 0)
        return out / np.sqrt(k * order)

    return Code(name, len(blocks), points * order, maker, block=order)


def steiner(v: int) -> Code:
    """Pairs of v = 2^r points: n = v(v-1)/2, N = v^2."""
    if v & (v - 1) or v < 4:
        raise ValueError("v must be a power of two, at least 4")
    return _incidence("steiner", np.array([(a, b) for a in range(v) for b in range(a + 1, v)]), v, v)


def steiner_triples(h: int) -> Code:
    """Triples {x, y, x xor y} on 2^h - 1 points, with a Sylvester matrix of order 2^(h-1): larger beta."""
    points = (1 << h) - 1
    blocks = sorted({tuple(sorted((x, y, x ^ y))) for x in range(1, points + 1) for y in range(1, points + 1) if x != y})
    return _incidence("steiner_triples", np.array(blocks) - 1, points, 1 << (h - 1))


def _haar_entry(size: int) -> Callable[[np.ndarray, np.ndarray], np.ndarray]:
    r = size.bit_length() - 1

    def entry(i: np.ndarray, c: np.ndarray) -> np.ndarray:
        i, c = np.broadcast_arrays(i, c)
        level = np.floor(np.log2(np.maximum(i, 1))).astype(np.int64)
        inside = (c >> (r - level)) == i - (1 << level)
        bit = np.where(r - level - 1 >= 0, c >> np.maximum(r - level - 1, 0) & 1, 0)
        return np.where(i == 0, 2 ** (-r / 2), np.where(inside, 2.0 ** ((level - r) / 2) * (1 - 2 * bit), 0.0))

    return entry


def haar(n: int, beta: float = 2, seed: int = 1) -> Code:
    """Columns of an orthonormal Haar matrix, chosen by draw: each touches log2(N) + 1 rows."""
    size = _power(beta * n)
    at, entry = np.sort(ranked(size, seed)[:n]), _haar_entry(size)
    put = _spread(n, at, size)
    return Code("haar", n, size, lambda i, j: entry(i, at[j]), lambda x: haar_transform(put(x)))


def haar_full(size: int) -> Code:
    entry = _haar_entry(size)
    return Code("haar_full", size, size, entry, haar_transform)


def dft(n: int, beta: float = 2, seed: int = 1) -> Code:
    """Columns of the real form of a Fourier matrix (cosines and sines of every frequency), chosen by draw."""
    size = _power(beta * n)
    at = np.sort(ranked(size, seed)[:n])

    def maker(i: np.ndarray, j: np.ndarray) -> np.ndarray:
        i, c = np.broadcast_arrays(i, at[j])
        f = (i + 1) // 2
        edge = (i == 0) | (i == size - 1)
        wave = np.where(i % 2 == 1, np.cos(2 * np.pi * f * c / size), np.sin(2 * np.pi * f * c / size))
        return np.where(edge, np.cos(2 * np.pi * f * c / size), wave * np.sqrt(2)) / np.sqrt(size)

    put = _spread(n, at, size)

    def fast(x: np.ndarray) -> np.ndarray:
        z = np.fft.rfft(put(x), axis=0) / np.sqrt(size)
        out = np.zeros((size, *x.shape[1:]))
        out[0], out[-1] = z[0].real, z[-1].real
        out[1:-1:2], out[2:-1:2] = np.sqrt(2) * z[1:-1].real, -np.sqrt(2) * z[1:-1].imag
        return out

    return Code("dft", n, size, maker, fast)


def gaussian(n: int, beta: float = 2, seed: int = 1) -> Code:
    size = round(beta * n)
    return Code("gaussian", n, size, lambda i, j: normal_np(i, j, seed) / np.sqrt(size), tight=False)


def rademacher(n: int, beta: float = 2, seed: int = 1) -> Code:
    size = round(beta * n)
    return Code("rademacher", n, size, lambda i, j: np.where(counted_np(i, j, seed) < 0.5, -1.0, 1.0) / np.sqrt(size), tight=False)


def sketch(n: int, rows: int, seed: int = 1) -> Code:
    """Fewer rows than the source (beta < 1): a baseline that loses accuracy for good."""
    return Code("sketch", n, rows, lambda i, j: normal_np(i, j, seed) / np.sqrt(rows), tight=False)


def columns_of(code: Code, n: int, seed: int = 1) -> Code:
    """A code for n source rows from one for more, by a choice of columns; S'S = I is kept."""
    if n == code.n:
        return code
    at = np.sort(ranked(code.n, seed)[:n])
    put = _spread(n, at, code.n)
    return Code(code.name, n, code.N, lambda i, j: code.maker(i, at[j]), (lambda x: code.fast(put(x))) if code.fast else None, code.block, code.tight)


def padded(code: Code, n: int) -> Code:
    """A code for n source rows from one for more, the missing rows being zeros: the first n columns, S'S = I is kept."""
    if n > code.n:
        raise ValueError(f"{code.name} has {code.n} source rows")
    put = _spread(n, np.arange(n), code.n)
    return Code(code.name, n, code.N, code.maker, (lambda x: code.fast(put(x))) if code.fast else None, code.block, code.tight)


def fitted(make: Callable[[int, int], Code], n: int, pad: str = "subsample", seed: int = 1) -> Code:
    """The family's code for at least n rows brought to n: by a choice of columns ('subsample') or by zero rows ('zeros')."""
    whole = make(n, 1)
    return columns_of(whole, n, seed) if pad == "subsample" else padded(whole, n)


def _prime_over(n: int) -> int:
    q = 2 * n - 1
    while q % 4 != 1 or any(q % d == 0 for d in range(2, int(q**0.5) + 1)):
        q += 1
    return q


#: Codes of about twice the rows for any n, by the name of the scheme.
FAMILIES: dict[str, Callable[[int, int], Code]] = {
    "uncoded": lambda n, seed: identity(n),
    "replication": lambda n, seed: replication(n, 2),
    "gaussian": lambda n, seed: gaussian(n, 2, seed),
    "paley": lambda n, seed: columns_of(paley(_prime_over(n)), n, seed),
    "hadamard": lambda n, seed: hadamard(n, 2, seed),
    "hadamard_etf": lambda n, seed: columns_of(hadamard_etf(next(s for s in range(1, 12) if (4**s - 2**s) // 2 >= n)), n, seed),
    "steiner": lambda n, seed: columns_of(steiner(next(1 << r for r in range(2, 16) if (1 << r) * ((1 << r) - 1) // 2 >= n)), n, seed),
    "haar": lambda n, seed: haar(n, 2, seed),
    "dft": lambda n, seed: dft(n, 2, seed),
    "rademacher": lambda n, seed: rademacher(n, 2, seed),
}


@dataclass
class CodeBank:
    """Codes made once for n = step, 2 step, ... and cut to size by choosing columns."""

    kind: str
    step: int = 100
    max_n: int = 3500
    held: dict[int, Code] = field(default_factory=dict)

    def bucket(self, n: int) -> int:
        if n > self.max_n:
            raise ValueError(f"the bank ends at {self.max_n}")
        return -(-n // self.step) * self.step

    def get(self, n: int, seed: int = 1) -> Code:
        b = self.bucket(n)
        if b not in self.held:
            self.held[b] = FAMILIES[self.kind](b, 1)
        return columns_of(self.held[b], n, seed) if self.kind not in ("uncoded", "replication") else FAMILIES[self.kind](n, seed)
