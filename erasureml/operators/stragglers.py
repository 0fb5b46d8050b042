"""Delays, waiting rules and what follows from them: active sets, round times, participation."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from erasureml.functions.uniform import normal, uniform

Model = Callable[[Column, Column, int], Column]


def exponential(mean: float = 0.01) -> Model:
    return lambda t, i, seed: -mean * F.log(uniform(t, i, seed))


def mixture(weights: tuple[float, ...], means: tuple[float, ...], sds: tuple[float, ...]) -> Model:
    """Of normals; draws below zero count as zero."""

    def delay(t: Column, i: Column, seed: int) -> Column:
        u, z = uniform(t, i, seed + 7), normal(t, i, seed)
        out, total = None, 0.0
        for w, mu, sd in zip(weights, means, sds, strict=True):
            total += w
            value = F.greatest(F.lit(0.0), mu + sd * z)
            out = F.when(u < total, value) if out is None else out.when(u < total, value)
        return out.otherwise(F.greatest(F.lit(0.0), means[-1] + sds[-1] * z))

    return delay


# Fixed values of the experiments' mixtures: weights, means and standard deviations in seconds.
BIMODAL = mixture((0.5, 0.5), (0.5, 20.0), (0.2, 5.0))
TRIMODAL = mixture((0.8, 0.1, 0.1), (0.2, 0.6, 1.0), (0.1, 0.2, 0.4))


def background_power_law(exponent: float = 1.5, cap: int = 50, base: float = 0.1) -> Model:
    """Every worker keeps a number of background tasks, drawn once from a power law up to `cap`."""

    def delay(t: Column, i: Column, seed: int) -> Column:
        tasks = F.least(F.lit(cap), F.floor(F.pow(uniform(F.lit(0), i, seed + 3), F.lit(-1.0 / (exponent - 1.0)))))
        return base * (1 + tasks) * (0.9 + 0.2 * uniform(t, i, seed))

    return delay


def pareto(exponent: float = 1.1, scale: float = 0.1) -> Model:
    return lambda t, i, seed: scale * F.pow(uniform(t, i, seed), F.lit(-1.0 / exponent))


def never(model: Model, workers: list[int]) -> Model:
    """These workers never reply."""
    return lambda t, i, seed: F.when(i.isin(workers), F.lit(float("inf"))).otherwise(model(t, i, seed))


def delays(spark: SparkSession, model: Model, rounds: int, m: int, seed: int = 1, phases: tuple[str, ...] = ("grad",)) -> DataFrame:
    """(t, phase, worker, delay)."""
    grid = spark.range(rounds * m).select((F.col("id") / m).cast("int").alias("t"), (F.col("id") % m).cast("int").alias("worker"))
    out = None
    for k, phase in enumerate(phases):
        one = grid.select("t", F.lit(phase).alias("phase"), "worker", model(F.col("t"), F.col("worker"), seed + 1009 * k).alias("delay"))
        out = one if out is None else out.unionByName(one)
    return out


def delays_from_events(events: DataFrame, m: int) -> DataFrame:
    """A recorded trace: worker = user mod m, t = order of the event at the worker, delay = value."""
    w = Window.partitionBy("worker").orderBy("event_id")
    own = events.select("event_id", (F.col("user_id") % m).cast("int").alias("worker"), F.col("value").alias("delay"))
    return own.select((F.row_number().over(w) - 1).alias("t"), F.lit("grad").alias("phase"), "worker", "delay")


def loads_by_day(events: DataFrame, m: int) -> DataFrame:
    """(t, phase, worker, delay): the recorded days are the rounds, from 0 on; a worker (user mod m) takes as long as the values of its events
    add up to, in whole hundredths, so that sums are exact in any order.  A worker without events in a day has no reply."""
    own = events.select(F.unix_date(F.to_date("ts")).alias("day"), (F.col("user_id") % m).cast("int").alias("worker"), F.round(F.col("value") * 100).cast("long").alias("v"))
    days = own.groupBy("day", "worker").agg(F.sum("v").alias("delay"))
    return days.select((F.dense_rank().over(Window.orderBy("day")) - 1).alias("t"), F.lit("grad").alias("phase"), "worker", "delay")  # a row a day and worker


def first_k(delays_: DataFrame, k: int | Column) -> DataFrame:
    """With rank (ties by worker) and whether the reply is among the first k of its round and phase."""
    w = Window.partitionBy("t", "phase").orderBy("delay", "worker")
    return delays_.withColumn("rank", F.row_number().over(w)).withColumn("active", F.col("rank") <= k)


def within_deadline(delays_: DataFrame, seconds: float) -> DataFrame:
    w = Window.partitionBy("t", "phase").orderBy("delay", "worker")
    return delays_.withColumn("rank", F.row_number().over(w)).withColumn("active", F.col("delay") <= seconds)


def adaptive_k(delays_: DataFrame, k: int, beta: float) -> DataFrame:
    """(t, k): the fewest replies whose overlap with the round before exceeds m / beta workers, at least k.

    The round before is taken as its first k, so that rounds can be found all at once.
    """
    ranked = first_k(delays_, k)
    before = ranked.where("active").select((F.col("t") + 1).alias("t"), "phase", "worker", F.lit(1).alias("was"))
    w = Window.partitionBy("t", "phase").orderBy("rank")
    m = Window.partitionBy("t", "phase")
    seen = ranked.join(before, ["t", "phase", "worker"], "left").withColumn("overlap", F.sum(F.coalesce("was", F.lit(0))).over(w)).withColumn("m", F.count("*").over(m))
    need = F.min(F.when((F.col("overlap") > F.col("m") / beta) & (F.col("rank") >= k), F.col("rank")))
    found = seen.groupBy("t", "phase").agg(need.alias("need"), F.max("rank").alias("last"))
    return found.select("t", "phase", F.when(F.col("t") == 0, F.lit(k)).otherwise(F.coalesce("need", "last")).cast("int").alias("k"))


def adaptive_k_in_order(delays_: DataFrame, k: int, beta: float) -> list[tuple[int, int]]:
    """(t, k) like `adaptive_k`, but against the replies that the round before really used, round by round.

    How many replies a round needs is found for every number that the round before may have used (rounds x workers rows); the
    coordinator then follows the chain.
    """
    ranked = first_k(delays_.where(F.col("phase") == "grad"), k)
    m = ranked.agg(F.max("rank")).first()[0] or 0
    before = ranked.select((F.col("t") + 1).alias("t"), "worker", F.col("rank").alias("was_rank"))
    w = Window.partitionBy("t", "was").orderBy("rank")
    seen = ranked.join(before, ["t", "worker"], "left").withColumn("was", F.explode(F.sequence(F.lit(1), F.lit(m)))).withColumn("overlap", F.sum(F.coalesce((F.col("was_rank") <= F.col("was")).cast("int"), F.lit(0))).over(w))
    need = seen.groupBy("t", "was").agg(F.coalesce(F.min(F.when((F.col("overlap") > m / beta) & (F.col("rank") >= k), F.col("rank"))), F.lit(m)).alias("need"))
    table = {(r["t"], r["was"]): r["need"] for r in need.collect()}
    rounds = sorted(r["t"] for r in ranked.select("t").distinct().collect())
    out: list[tuple[int, int]] = []
    for t in rounds:
        out.append((int(t), int(table.get((t, out[-1][1]), m)) if out else k))
    return out


def first_copies(delays_: DataFrame, k: int, parts: int) -> DataFrame:
    """Of the first k replies the first of every part (worker mod parts); the others are dropped."""
    w = Window.partitionBy("t", "phase", "part").orderBy("delay", "worker")
    live = first_k(delays_, k).where("active").withColumn("part", F.col("worker") % parts)
    return live.withColumn("copy", F.row_number().over(w)).where("copy = 1").drop("copy")


def cover_times(delays_: DataFrame, parts: int) -> DataFrame:
    """(t, phase, round_time) when every part must have replied once: the slowest part's fastest copy."""
    fastest = delays_.groupBy("t", "phase", (F.col("worker") % parts).alias("part")).agg(F.min("delay").alias("fastest"))
    return fastest.groupBy("t", "phase").agg(F.max("fastest").alias("round_time"))


def round_times(active: DataFrame) -> DataFrame:
    """(t, round_time, clock): the last active reply of each phase, phases and rounds added up."""
    per = active.where("active").groupBy("t", "phase").agg(F.max("delay").alias("phase_time")).groupBy("t").agg(F.sum("phase_time").alias("round_time"))
    return per.withColumn("clock", F.sum("round_time").over(Window.orderBy("t").rowsBetween(Window.unboundedPreceding, 0)))


def participation(active: DataFrame) -> DataFrame:
    return active.groupBy("worker").agg(F.avg(F.col("active").cast("int")).alias("share"))


def active_matrix(active: DataFrame, rounds: int, m: int, phase: str = "grad") -> np.ndarray:
    """Rounds by workers, on the driver: the coordinator's own state, a bit for every reply."""
    out = np.zeros((rounds, m), bool)
    for r in active.where((F.col("phase") == phase) & F.col("active")).select("t", "worker").collect():
        if r["t"] < rounds:
            out[r["t"], r["worker"]] = True
    return out


def adversary(kind: str, m: int, k: int, rounds: int, score: Callable[[np.ndarray], float] | None = None, parts: int | None = None) -> np.ndarray:
    """Active sets chosen against the method.

    fixed: the same workers never reply; rotate: a window of losses moves on; kill_replicas: both copies of as many
    parts as can be are lost; greedy_worst: workers are erased one by one, each time the one that lowers `score` most.
    """
    out = np.ones((rounds, m), bool)
    lost = m - k
    if kind == "fixed":
        out[:, :lost] = False
    elif kind == "rotate":
        for t in range(rounds):
            out[t, (t * lost + np.arange(lost)) % m] = False
    elif kind == "kill_replicas":
        parts = parts or m // 2
        order = [i for part in range(parts) for i in range(part, m, parts)]
        out[:, order[:lost]] = False
    elif kind == "greedy_worst":
        live = np.ones(m, bool)
        for _ in range(lost):
            options = []
            for i in np.flatnonzero(live):
                live[i] = False
                options.append((score(live), i))
                live[i] = True
            live[min(options)[1]] = False
        out[:] = live
    else:
        raise ValueError(f"unknown adversary {kind}")
    return out
