"""Spectra of what is left of a code after erasures, frame measures, and the bounds that follow."""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from erasureml.operators.codes import Code, assign
from erasureml.functions.uniform import uniform_np


def subsets_of(m: int, k: int, how: str = "sample", count: int = 100, seed: int = 1) -> list[tuple[int, ...]]:
    """all: every k of m workers; sample: `count` of them by draw."""
    if how == "all":
        return list(itertools.combinations(range(m), k))
    return [tuple(sorted(np.argsort(uniform_np(s, np.arange(m), seed))[:k].tolist())) for s in range(count)]


def recorded_subsets(delays: DataFrame, k: int) -> dict[int, tuple[int, ...]]:
    """The workers that reply first in every round of a trace (a round's bits, on the driver); rounds with fewer replies keep those."""
    from erasureml.operators.stragglers import first_k

    out: dict[int, list[int]] = {}
    for r in first_k(delays, k).where("active").select("t", "worker").collect():
        out.setdefault(int(r["t"]), []).append(int(r["worker"]))
    return {t: tuple(sorted(a)) for t, a in sorted(out.items())}


def left_over(code: Code, worker: np.ndarray, subset: tuple[int, ...]) -> np.ndarray:
    s = code.maker(np.flatnonzero(np.isin(worker, subset))[:, None], np.arange(code.n)[None, :])
    return s.T @ s


def spectrum(spark: SparkSession, code: Code, m: int, k: int, *, how: str = "scatter", subsets: str | dict[int, tuple[int, ...]] = "sample", count: int = 50, seed: int = 1) -> DataFrame:
    """(subset, idx, eig) of S_A'S_A: subsets (given by number, or chosen) in parallel, every task makes its rows of S itself."""
    worker = assign(code, m, how, seed)
    by_number = subsets if isinstance(subsets, dict) else dict(enumerate(subsets_of(m, k, subsets, count, seed)))
    numbers, chosen = list(by_number), list(by_number.values())

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for i in frame["id"]:
                eig = np.linalg.eigvalsh(left_over(code, worker, chosen[i]))
                yield pd.DataFrame({"subset": np.full(len(eig), numbers[i]), "idx": np.arange(len(eig), dtype=np.int32), "eig": eig})

    return spark.range(0, len(chosen), 1, max(1, min(64, len(chosen)))).mapInPandas(run, "subset long, idx int, eig double")


def brip_epsilon(spark: SparkSession, code: Code, m: int, k: int, **kw) -> DataFrame:
    """(subset, lam_min, lam_max, eps) with eigenvalues over eta = k / m; eps is the larger distance from 1."""
    from pyspark.sql import functions as F

    eta = k / m
    eigs = spectrum(spark, code, m, k, **kw).groupBy("subset").agg((F.min("eig") / eta).alias("lam_min"), (F.max("eig") / eta).alias("lam_max"))
    return eigs.withColumn("eps", F.greatest(1 - F.col("lam_min"), F.col("lam_max") - 1))


def epsilon(code: Code, m: int, k: int, how: str = "scatter", subsets: str = "sample", count: int = 50, seed: int = 1) -> float:
    """The largest eps over the subsets, without Spark, for small codes."""
    worker, worst = assign(code, m, how, seed), 0.0
    for a in subsets_of(m, k, subsets, count, seed):
        e = np.linalg.eigvalsh(left_over(code, worker, a)) * m / k
        worst = max(worst, 1 - e[0], e[-1] - 1)
    return float(worst)


def bulk_ones(code: Code, m: int, k: int) -> int:
    """A tight code leaves at least this many eigenvalues at exactly 1 (before scaling by 1/eta)."""
    return max(0, int(np.floor(code.n * (1 - code.beta * (1 - k / m)) + 1e-9)))


def bulk_fraction(eigs: np.ndarray, eta: float, eps: float) -> float:
    e = np.asarray(eigs) / eta
    return float(((e > 1 - eps) & (e < 1 + eps)).mean())


def welch_bound(n: int, beta: float) -> float:
    return float(np.sqrt((beta - 1) / (n * beta - 1)))


def coherence(code: Code) -> float:
    """The largest inner product of two different rows scaled to length 1."""
    s = code.matrix()
    s = s / np.maximum(np.linalg.norm(s, axis=1, keepdims=True), 1e-300)
    g = np.abs(s @ s.T)
    np.fill_diagonal(g, 0)
    return float(g.max())


def is_etf(code: Code, tol: float = 1e-9) -> bool:
    return abs(coherence(code) - welch_bound(code.n, code.beta)) < tol


def frame_bounds(code: Code) -> tuple[float, float]:
    e = np.linalg.eigvalsh(code.matrix().T @ code.matrix()) * code.beta
    return float(e[0]), float(e[-1])


def gaussian_edges(beta: float, eta: float) -> tuple[float, float]:
    r = np.sqrt(1 / (beta * eta))
    return float((1 - r) ** 2), float((1 + r) ** 2)


def overlap_delta(code: Code, m: int, a: tuple[int, ...], b: tuple[int, ...], how: str = "scatter", seed: int = 1) -> float:
    """The smallest eigenvalue of what two rounds on end share, over its share of the workers."""
    both = tuple(set(a) & set(b))
    if not both:
        return 0.0
    return float(np.linalg.eigvalsh(left_over(code, assign(code, m, how, seed), both))[0] * m / len(both))


def overlap_thresholds(beta: float) -> dict[str, float]:
    """Shares of replies over which overlaps suffice: for any sets, and for independent random ones."""
    return {"worst": 0.5 + 1 / (2 * beta), "random": 1 / np.sqrt(beta)}


def support_overhead(code: Code, m: int, how: str = "contiguous", seed: int = 1) -> pd.DataFrame:
    """(worker, rows, ratio to n / m): the uncoded rows that each worker must hold."""
    worker = assign(code, m, how, seed)
    rows = [len(code.support(np.flatnonzero(worker == i))) for i in range(m)]
    return pd.DataFrame({"worker": np.arange(m), "rows": rows, "ratio": np.array(rows) * m / code.n})


def encoding_cost(code: Code, p: int) -> dict[str, float]:
    nnz = int((code.matrix() != 0).sum())
    flops = code.N * np.log2(code.N) * p if code.fast and code.name not in ("uncoded", "replication") else nnz * p
    return {"nnz": float(nnz), "flops": float(flops), "bytes": 8.0 * code.N * p, "factor": code.beta}


def exact_recovery_redundancy(lost: int) -> int:
    """Copies that codes which recover the whole gradient need, against a fixed beta here."""
    return lost + 1


# ---------------------------------------------------------------- bounds; NaN where their conditions fail


def bound_gd(t: int, f0: float, eps: float, step: float, mu: float, big: float, lam: float, zeta: float = 0.5) -> dict[str, float]:
    """Of the objective after t rounds over the optimum: a contraction to a neighbourhood of kappa^2 times the optimum."""
    kappa = (1 + eps) / (1 - eps)
    gamma = 1 - 4 * (mu * (1 - eps) + lam) * zeta * (1 - zeta) / (big * (1 + eps) + lam)
    if not 0 < kappa * gamma < 1:
        return {"rate": kappa * gamma, "first": float("nan"), "factor": float("nan")}
    return {"rate": kappa * gamma, "first": (kappa * gamma) ** t * f0, "factor": kappa**2 * (kappa - gamma) / (1 - kappa * gamma)}


def bound_prox(eps: float, t: int, step: float, distance: float) -> dict[str, float]:
    """Factor of the optimum and vanishing term of the running mean, and the growth a single step may show."""
    if eps >= 1 / 7:
        return {"mean_factor": float("nan"), "mean_term": float("nan"), "growth": (1 + 7 * eps) / (1 - 3 * eps) if eps < 1 / 3 else float("nan")}
    return {"mean_factor": (1 + 3 * eps) / (1 - 7 * eps), "mean_term": (1 + 7 * eps) / (1 - 7 * eps) * distance**2 / (2 * step * t), "growth": (1 + 7 * eps) / (1 - 3 * eps)}


def bound_bcd(t: int, gap0: float, step: float, smooth: float, eps: float, radius: float, nu: float | None = None) -> dict[str, float]:
    """Sublinear gap, or the linear rate under restricted strong convexity nu. radius: of the level set, an estimate."""
    if step >= 1 / (smooth * (1 + eps)):
        return {"sublinear": float("nan"), "rate": float("nan")}
    gain = step * (1 - smooth * (1 + eps) * step / 2) * (1 - eps)
    c = gain / radius**2
    return {"sublinear": 1 / (1 / gap0 + c * t), "rate": 1 - nu * gain if nu else float("nan")}


def inverse_hessian_extremes(eps: float, delta: float, mu: float, big: float, lam: float, p: int, memory: int) -> tuple[float, float]:
    """Bounds c1 <= eig(B^-1) <= c2 of the quasi-Newton matrix, from trace and determinant of its updates."""
    low, high = delta * mu + lam, (1 + eps) * big + lam
    upper_b = (memory + p) * high
    lower_det = low ** (p + memory) / upper_b**memory
    return 1 / upper_b, upper_b ** (p - 1) / lower_det


def bound_lbfgs(eps: float, c1: float, c2: float, mu: float, lam: float) -> float:
    """Contraction of one exact-step round (before the factor of the neighbourhood)."""
    return 1 - 4 * (mu * (1 - eps) + lam) * c1 * c2 / ((mu * (1 - eps) + lam) * (c1 + c2) ** 2)


def kantorovich(gram: np.ndarray, u: np.ndarray) -> tuple[float, float]:
    """cos of the angle between u and M u, and the lower bound 2 sqrt(kappa) / (kappa + 1) it never goes under."""
    e = np.linalg.eigvalsh(gram)
    kappa, v = e[-1] / e[0], gram @ u
    return float(u @ v / (np.linalg.norm(u) * np.linalg.norm(v))), float(2 * np.sqrt(kappa) / (kappa + 1))


def approximation_ratio(eps: float) -> float:
    """The erased problem's solution is at most this factor over the optimum: kappa^2 of the code."""
    return ((1 + eps) / (1 - eps)) ** 2
