"""Baselines beside plain codes: schemes by name, exact-recovery repetition, speculation, and coding combined with others."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from erasureml.functions.uniform import uniform
from erasureml.operators import blocks, codes, compare, encode, solvers
from erasureml.operators.partials import GramPartials, whole_gram


class WaitPolicy:
    """When a round ends: after k replies, a schedule of k by round, all within a deadline, or by overlap."""

    def __init__(self, kind: str, value) -> None:
        self.kind, self.value = kind, value

    @classmethod
    def fixed(cls, k: int) -> WaitPolicy:
        return cls("fixed", k)

    @classmethod
    def schedule(cls, ks: list[int]) -> WaitPolicy:
        return cls("schedule", ks)

    @classmethod
    def deadline(cls, seconds: float) -> WaitPolicy:
        return cls("deadline", seconds)

    @classmethod
    def overlap(cls, k: int, beta: float) -> WaitPolicy:
        return cls("overlap", (k, beta))

    def apply(self, delays: DataFrame) -> DataFrame:
        from erasureml.operators import stragglers

        if self.kind == "fixed":
            return stragglers.first_k(delays, self.value)
        if self.kind == "schedule":
            ks = F.array(*map(F.lit, self.value))
            return stragglers.first_k(delays, F.element_at(ks, F.least(F.col("t"), F.lit(len(self.value) - 1)) + 1))
        if self.kind == "deadline":
            return stragglers.within_deadline(delays, self.value)
        k, beta = self.value
        need = stragglers.adaptive_k(delays, k, beta)
        return stragglers.first_k(delays, 10**9).join(need, ["t", "phase"]).withColumn("active", F.col("rank") <= F.col("k"))


def exact_recovery(df: DataFrame, m: int, lost: int, p: int, lam: float) -> solvers.Problem:
    """Fractional repetition: groups of lost + 1 workers hold the same part, so any m - lost replies give the exact sum."""
    parts = m // (lost + 1)
    copy = F.explode(F.sequence(F.lit(0), F.lit(lost))).alias("copy")
    rows = df.select((F.col("row_id") % parts).cast("int").alias("part"), "x", "y", copy).select((F.col("copy") * parts + F.col("part")).cast("int").alias("worker"), "x", "y")
    n, original = df.count(), whole_gram(df, p)
    return solvers.Problem(GramPartials(rows, m, p), n, m, p, lam, original, np.arange(m) % parts)


def speculated(delays: DataFrame, quantile: float, seed: int, mean: float) -> DataFrame:
    """Replies when a second copy of every task that is late (over the quantile of its round) starts then; the first wins."""
    at = delays.groupBy("t", "phase").agg(F.percentile_approx("delay", quantile).alias("at"))
    again = -mean * F.log(uniform("t", "worker", seed + 77))
    late = delays.join(at, ["t", "phase"])
    return late.select("t", "phase", "worker", F.when(F.col("delay") > F.col("at"), F.least("delay", F.col("at") + again)).otherwise(F.col("delay")).alias("delay"))


def speculated_after(delays: DataFrame, replies: int, seed: int, mean: float) -> DataFrame:
    """`speculated`, second copies starting exactly at the given number of replies of a round."""
    from erasureml.operators.stragglers import first_k

    ranked = first_k(delays, replies)
    at = ranked.where(F.col("rank") == replies).select("t", "phase", F.col("delay").alias("at"))
    again = -mean * F.log(uniform("t", "worker", seed + 77))
    late = delays.join(at, ["t", "phase"])
    return late.select("t", "phase", "worker", F.when(F.col("delay") > F.col("at"), F.least("delay", F.col("at") + again)).otherwise(F.col("delay")).alias("delay"))


def coded_replication(df: DataFrame, code: codes.Code, m: int, p: int, lam: float, r: int = 2) -> solvers.Problem:
    """m / r encoded blocks, each on r workers; the first copy of a block counts."""
    blocks_ = m // r
    enc = encode.encode_rows(df, code, blocks_)
    copies = enc.select("worker", "x", "y", F.explode(F.sequence(F.lit(0), F.lit(r - 1))).alias("c")).select((F.col("c") * blocks_ + F.col("worker")).cast("int").alias("worker"), "x", "y")
    return solvers.Problem(GramPartials(copies, m, p), df.count(), m, p, lam, whole_gram(df, p), np.arange(m) % blocks_)


def run(scheme: str, df: DataFrame, active: np.ndarray, *, p: int, lam: float, algo: str = "gd", clock: np.ndarray | None = None, delays: np.ndarray | None = None) -> solvers.RunResult:
    """One scheme by name: uncoded, perfect, replication, exact_recovery:<lost>, coded:<code>, coded+replication:<code>,
    coded+async:<code>, sketch."""
    m = active.shape[1]
    kind, _, name = scheme.partition(":")
    if kind in ("uncoded", "replication"):
        problem, _ = compare.problem_of(df, kind, m, p, lam)
    elif kind == "perfect":
        problem, active = compare.problem_of(df, "uncoded", m, p, lam)[0], np.ones_like(active)
    elif kind == "exact_recovery":
        problem = exact_recovery(df, m, int(name), p, lam)
    elif kind == "coded+replication":
        problem = coded_replication(df, codes.FAMILIES[name](64, 1), m, p, lam)
    elif kind in ("coded", "coded+async"):
        problem, _ = compare.problem_of(df, name, m, p, lam)
    elif kind == "sketch":
        code = codes.sketch(64, 40)
        problem = solvers.Problem(GramPartials(encode.encode_rows(df, code, m), m, p), df.count(), m, p, lam, whole_gram(df, p))
    else:
        raise ValueError(f"unknown scheme {scheme}")
    step = solvers.gradient_step(problem)
    if kind == "coded+async":
        return blocks.async_gradient(problem, delays, step=step / m * 2, horizon=float(np.sort(delays.cumsum(0).ravel())[len(active) * 4]))
    if algo == "lbfgs":
        return solvers.lbfgs(problem, active, clock=clock)
    return solvers.gradient_descent(problem, active, step=step, clock=clock)


def row_encoded_loss(loss: str) -> None:
    """Rows can be encoded for squared losses only: others aren't a function of S X w."""
    if loss != "squared":
        raise solvers.UnsupportedLoss(loss)


def data_spectrum(df: DataFrame, p: int) -> dict[str, float]:
    """Extreme eigenvalues of X'X / n: the constants of steps and bounds."""
    gram = whole_gram(df, p)
    e = np.linalg.eigvalsh(gram.G[0]) / df.count()
    return {"low": float(e[0]), "high": float(e[-1])}
