"""Data-parallel solvers over the first replies of every round.

The problem is f(w) = |X w - y|^2 / (2 n) + lam h(w).  Each round sees the encoded sums of the active workers, scaled by
1 / (n eta) with eta = k / m; the regulariser is exact, on the driver.  The iterate is on the driver and is sent with
the round.  Traces carry the original objective when the original's sums are given.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pandas as pd

from erasureml.operators.partials import GramPartials


class UnsupportedLoss(ValueError):
    """Rows can be encoded for squared losses only."""


@dataclass
class Problem:
    """partials: of the encoded rows; n: original rows; original: their sums, for objectives (or None)."""

    partials: object
    n: int
    m: int
    p: int
    lam: float = 0.0
    original: GramPartials | None = None
    copies_of: np.ndarray | None = None  # replication: the part that each worker holds
    norm: float = 1.0  # squared norm by which the stored rows exceed S'S = I (copies stored unscaled: 1)

    def objective(self, w: np.ndarray, h: Callable[[np.ndarray], float] | None = None) -> float:
        if self.original is None:
            return float("nan")
        loss = self.original.gradients(w, np.ones(1, bool))[1][0] / (2 * self.n)
        return float(loss + self.lam * (h(w) if h else 0.5 * w @ w))

    def keep(self, live: np.ndarray, order: np.ndarray | None = None) -> tuple[np.ndarray, float]:
        """Which replies are used, and the factor that makes their sum stand for the whole.

        Of copies of a part the first is used, and the sum scaled by parts over distinct parts received.
        """
        if self.copies_of is None:
            return live, self.m / max(live.sum(), 1)
        used, seen = np.zeros_like(live), set()
        for i in np.flatnonzero(live) if order is None else [i for i in order if live[i]]:
            if self.copies_of[i] not in seen:
                seen.add(self.copies_of[i])
                used[i] = True
        return used, len(set(self.copies_of.tolist())) / max(len(seen), 1)


@dataclass
class RunResult:
    w: np.ndarray
    trace: pd.DataFrame
    active: np.ndarray
    warnings: list[str] = field(default_factory=list)


def _trace(objectives: list[float], clock: np.ndarray | None) -> pd.DataFrame:
    t = np.arange(len(objectives))
    f = np.array(objectives)
    return pd.DataFrame({"t": t, "objective": f, "running_mean": np.cumsum(f) / (t + 1), "clock": clock[: len(t)] if clock is not None else t.astype(float)})


def _warn(active: np.ndarray, m: int, beta: float) -> list[str]:
    return ["outside_brip: fewer replies than 1/beta of the workers"] if active.sum(1).min() < m / beta - 1e-9 else []


def largest_eigenvalue(gram: np.ndarray, rounds: int = 200) -> float:
    """By power iteration."""
    v = np.ones(len(gram)) / np.sqrt(len(gram))
    for _ in range(rounds):
        v = gram @ v
        v /= np.linalg.norm(v) or 1
    return float(v @ gram @ v)


def gradient_step(problem: Problem, eps: float = 0.3, zeta: float = 0.5) -> float:
    """2 zeta / (M (1 + eps) + lam), M the smoothness of the loss part."""
    return 2 * zeta / (largest_eigenvalue(problem.original.G[0]) / problem.n * (1 + eps) + problem.lam)


def gradient_descent(problem: Problem, active: np.ndarray, *, step: float, w0: np.ndarray | None = None, clock: np.ndarray | None = None, beta: float = 2, tol: float = 0.0) -> RunResult:
    w = np.zeros(problem.p) if w0 is None else w0.copy()
    seen = []
    for live in active:
        used, scale = problem.keep(live)
        g = problem.partials.gradients(w, used)[0].sum(0) * scale / problem.n + problem.lam * w
        w = w - step * g
        seen.append(problem.objective(w))
        if tol and np.linalg.norm(g) < tol:
            break
    return RunResult(w, _trace(seen, clock), active, _warn(active, problem.m, beta))


def proximal_gradient(problem: Problem, active: np.ndarray, prox: Callable[[np.ndarray, float], np.ndarray], h: Callable[[np.ndarray], float], *, step: float, clock: np.ndarray | None = None, beta: float = 2, w0: np.ndarray | None = None, record: Callable | None = None) -> RunResult:
    """w <- prox(w - step * gradient, step * lam); the whole prox point is taken."""
    w = np.zeros(problem.p) if w0 is None else w0.copy()
    seen, extra = [], []
    for live in active:
        used, scale = problem.keep(live)
        g = problem.partials.gradients(w, used)[0].sum(0) * scale / problem.n
        w = prox(w - step * g, step * problem.lam)
        seen.append(problem.objective(w, h))
        if record:
            extra.append(record(w))
    trace = _trace(seen, clock)
    if record:
        trace["measure"] = extra
    return RunResult(w, trace, active, _warn(active, problem.m, beta))


def rho_from_epsilon(eps: float) -> float:
    return (1 - eps) / (1 + eps)


def lbfgs(problem: Problem, active: np.ndarray, line: np.ndarray | None = None, *, memory: int = 10, rho: float = 0.9, init: str = "inverse", curvature: str = "overlap", w0: np.ndarray | None = None, clock: np.ndarray | None = None, beta: float = 2) -> RunResult:
    """Quasi-Newton steps whose curvature pairs come from workers that replied in two rounds on end.

    line: the second active sets, for the exact step length, for which a worker sends one number.  curvature 'naive'
    takes each round's own gradients (an ablation); init 'as_printed' takes the reciprocal first scale.
    """
    p, lam, n, m = problem.p, problem.lam, problem.n, problem.m
    line = active if line is None else line
    w = np.zeros(p) if w0 is None else w0.copy()
    pairs: list[tuple[np.ndarray, np.ndarray]] = []
    before: tuple | None = None
    seen = []
    for live, answer in zip(active, line, strict=True):
        used, scale = problem.keep(live)
        parts = problem.partials.gradients(w, used)[0]
        g = parts.sum(0) * scale / n + lam * w
        if before is not None:
            w_old, parts_old, used_old, g_old = before
            u = w - w_old
            both = used & used_old
            if curvature == "overlap":
                r = (parts - parts_old)[both].sum(0) * (m / max(both.sum(), 1) if problem.copies_of is None else scale) / n + lam * u
                ok = both.any()
            else:
                r, ok = g - g_old, True
            if ok and r @ u > 1e-12 * (u @ u):
                pairs = [*pairs, (u, r)][-memory:]
        d, alphas = g.copy(), []
        for u, r in reversed(pairs):
            a = (u @ d) / (r @ u)
            alphas.append(a)
            d = d - a * r
        if pairs:
            u, r = pairs[-1]
            d = d * ((r @ u) / (r @ r) if init == "inverse" else (r @ r) / (r @ u))
        for (u, r), a in zip(pairs, reversed(alphas), strict=True):
            d = d + u * (a - (r @ d) / (r @ u))
        d = -d
        used2, scale2 = problem.keep(answer)
        bend = problem.partials.curvature(d, used2).sum() * scale2 / n + lam * (d @ d)
        step = rho * -(d @ g) / bend if bend > 0 else 0.0
        before = (w, parts, used, g)
        w = w + step * d
        seen.append(problem.objective(w))
    return RunResult(w, _trace(seen, clock), active, _warn(active, m, beta))


# ---------------------------------------------------------------- proximal maps


def prox_l1(v: np.ndarray, tau: float) -> np.ndarray:
    return np.sign(v) * np.maximum(np.abs(v) - tau, 0)


def prox_l2sq(v: np.ndarray, tau: float) -> np.ndarray:
    return v / (1 + tau)


def prox_elastic(share: float) -> Callable[[np.ndarray, float], np.ndarray]:
    return lambda v, tau: prox_l1(v, share * tau) / (1 + (1 - share) * tau)


def prox_group(size: int) -> Callable[[np.ndarray, float], np.ndarray]:
    def prox(v: np.ndarray, tau: float) -> np.ndarray:
        g = v.reshape(-1, size)
        norm = np.linalg.norm(g, axis=1, keepdims=True)
        return (g * np.maximum(1 - tau / np.maximum(norm, 1e-300), 0)).ravel()

    return prox


def prox_l1sq(v: np.ndarray, tau: float) -> np.ndarray:
    """Of tau |v|_1^2: soft-thresholding at a level that the sorted magnitudes decide."""
    a = np.sort(np.abs(v))[::-1]
    level = 2 * tau * np.cumsum(a) / (1 + 2 * tau * np.arange(1, len(a) + 1))
    k = int((a > level).sum())
    return prox_l1(v, level[k - 1]) if k else np.zeros_like(v)


def project_box(lo: float, hi: float) -> Callable[[np.ndarray, float], np.ndarray]:
    return lambda v, tau: np.clip(v, lo, hi)


def project_nonneg(v: np.ndarray, tau: float) -> np.ndarray:
    return np.maximum(v, 0)


def project_l2ball(radius: float) -> Callable[[np.ndarray, float], np.ndarray]:
    return lambda v, tau: v * min(1.0, radius / max(np.linalg.norm(v), 1e-300))


# ---------------------------------------------------------------- exact solutions


def ridge_solution(original: GramPartials, n: int, lam: float) -> np.ndarray:
    return np.linalg.solve(original.G[0] / n + lam * np.eye(original.p), original.c[0] / n)


def lasso_solution(original: GramPartials, n: int, lam: float, rounds: int = 5000) -> np.ndarray:
    """By accelerated proximal steps on all data."""
    big = largest_eigenvalue(original.G[0]) / n * 1.01
    w = z = np.zeros(original.p)
    t = 1.0
    for _ in range(rounds):
        new = prox_l1(z - (original.G[0] @ z - original.c[0]) / n / big, lam / big)
        t_new = (1 + np.sqrt(1 + 4 * t * t)) / 2
        z = new + (t - 1) / t_new * (new - w)
        w, t = new, t_new
    return w
