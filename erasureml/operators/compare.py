"""Schemes side by side: the grids of the experiments, as one DataFrame of results."""

from __future__ import annotations

import concurrent.futures as cf

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from erasureml.operators import codes, encode, solvers
from erasureml.operators.partials import GramPartials, whole_gram
from erasureml.operators.stragglers import active_matrix, delays, first_copies, first_k, round_times


def problem_of(df: DataFrame, scheme: str, m: int, p: int, lam: float, group: int = 64, seed: int = 1, partials=GramPartials, original: GramPartials | None = None, n: int | None = None) -> tuple[solvers.Problem, float]:
    """The encoded problem of rows numbered from 0, and the code's beta. Groups of `group` rows share a code."""
    n = n or df.count()
    original = original or whole_gram(df, p)
    if scheme == "replication":
        return solvers.Problem(partials(encode.replicate(df, m), m, p), n, m, p, lam, original, np.arange(m) % (m // 2)), 2.0
    if scheme == "uncoded":
        code = codes.identity(max(group, m))
    elif scheme in ("hadamard_etf", "steiner"):
        code = {"hadamard_etf": lambda: codes.hadamard_etf(4 if group > 28 else 3), "steiner": lambda: codes.steiner(16 if group > 28 else 8)}[scheme]()
    else:
        code = codes.FAMILIES[scheme](group, seed)
    return solvers.Problem(partials(encode.encode_rows(df, code, m, seed=seed), m, p), n, m, p, lam, original), code.beta


def replies(spark: SparkSession, model, rounds: int, m: int, k: int, seed: int, phases: tuple[str, ...] = ("grad",)) -> tuple[dict[str, np.ndarray], np.ndarray]:
    """Active sets by phase and the clock of the rounds."""
    live = first_k(delays(spark, model, rounds, m, seed, phases), k)
    clock = np.array([r["clock"] for r in round_times(live).orderBy("t").select("clock").collect()])
    return {p: active_matrix(live, rounds, m, p) for p in phases}, clock


def grid(spark: SparkSession, df: DataFrame, p: int, lam: float, schemes: list[str], m: int, ks: list[int], model, rounds: int, algo: str = "lbfgs", trials: int = 1) -> DataFrame:
    """(scheme, m, k, trial, t, objective, clock) for ridge by `algo`."""
    original, n, out = whole_gram(df, p), df.count(), []
    for scheme in schemes:
        problem, beta = problem_of(df, scheme, m, p, lam, original=original, n=n)
        for k in ks:
            for trial in range(trials):
                active, clock = replies(spark, model, rounds, m, k, 1 + 101 * trial, ("grad", "line"))
                if algo == "lbfgs":
                    run = solvers.lbfgs(problem, active["grad"], active["line"], clock=clock, beta=beta)
                else:
                    run = solvers.gradient_descent(problem, active["grad"], step=solvers.gradient_step(problem), clock=clock, beta=beta)
                out.append(run.trace.assign(scheme=scheme, m=m, k=k, trial=trial))
    frame = pd.concat(out, ignore_index=True)[["scheme", "m", "k", "trial", "t", "objective", "clock"]]
    return spark.createDataFrame(frame)


def wall_clock_round(spark: SparkSession, answer, m: int, k: int, pool: int | None = None) -> dict[int, object]:
    """A real race: answer(i) runs worker i's job in its own thread; at k replies the other jobs are cancelled by tag."""
    sc, done = spark.sparkContext, {}

    def work(i: int):
        sc.addJobTag(f"erasure-{i}")
        try:
            return i, answer(i)
        finally:
            sc.removeJobTag(f"erasure-{i}")

    with cf.ThreadPoolExecutor(pool or m) as threads:
        for future in cf.as_completed([threads.submit(work, i) for i in range(m)]):
            if future.exception() is None and len(done) < k:
                i, value = future.result()
                done[i] = value
                if len(done) == k:
                    for j in set(range(m)) - set(done):
                        sc.cancelJobsWithTag(f"erasure-{j}")
    return done


__all__ = ["first_copies", "grid", "problem_of", "replies", "wall_clock_round"]
