"""Cost and accuracy measures as DataFrames."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from erasureml.functions.transforms import logloss
from erasureml.sources.fixtures import linear


def objective(df: DataFrame, w: np.ndarray, lam: float = 0.0) -> DataFrame:
    """Of the original rows: mean squared error over 2 and the ridge term."""
    r = linear("x", w) - F.col("y")
    return df.agg((F.avg(r * r) / 2 + 0.5 * lam * float(w @ w)).alias("objective"), F.count("*").alias("n"))


def classification(df: DataFrame, w: np.ndarray) -> DataFrame:
    """Error and mean logistic loss by split."""
    z = linear("x", w)
    return df.groupBy("is_test").agg(F.avg((F.col("y") * z <= 0).cast("int")).alias("error"), F.avg(logloss(F.col("y") * z)).alias("loss"), F.count("*").alias("n"))


def support_f1(true: DataFrame, found: DataFrame, tol: float = 0.0) -> DataFrame:
    """(feat, val) twice -> precision, recall and F1 of the non-zero coefficients."""
    both = true.select("feat", F.col("val").alias("a")).join(found.select("feat", F.col("val").alias("b")), "feat", "full_outer")
    is_a, is_b = (F.abs(F.coalesce(c, F.lit(0.0))) > tol for c in ("a", "b"))
    s = both.agg(F.sum((is_a & is_b).cast("long")).alias("tp"), F.sum((~is_a & is_b).cast("long")).alias("fp"), F.sum((is_a & ~is_b).cast("long")).alias("fn"))
    return s.select("tp", "fp", "fn", (F.col("tp") / (F.col("tp") + F.col("fp"))).alias("precision"), (F.col("tp") / (F.col("tp") + F.col("fn"))).alias("recall"), (2.0 * F.col("tp") / (2 * F.col("tp") + F.col("fp") + F.col("fn"))).alias("f1"))


def runtime_by_eta(delays: DataFrame, m: int) -> DataFrame:
    """(k, runtime) of all rounds when each waits for its first k replies: sums of order statistics."""
    w = Window.partitionBy("t", "phase").orderBy("delay", "worker")
    return delays.withColumn("k", F.row_number().over(w)).groupBy("k").agg(F.sum("delay").alias("runtime")).withColumn("eta", F.col("k") / m)


def speedup(runtimes: DataFrame) -> DataFrame:
    """Against waiting for all: the share of the runtime that is cut."""
    last = runtimes.orderBy(F.desc("k")).limit(1).select(F.col("runtime").alias("full"))
    return runtimes.crossJoin(F.broadcast(last)).select("k", "eta", "runtime", (1 - F.col("runtime") / F.col("full")).alias("cut"))


def async_events(delays: DataFrame, horizon: float) -> DataFrame:
    """(worker, t, time) of the updates that are done by the horizon: running sums of a worker's delays."""
    w = Window.partitionBy("worker").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    return delays.withColumn("time", F.sum("delay").over(w)).where(F.col("time") <= horizon).select("worker", "t", "time")


def shortest(delays: DataFrame, *own: str) -> float:
    """The time at which the first worker has used up its trace, the end of a run in which all go on."""
    return delays.groupBy(*own).agg(F.sum("delay").alias("total")).agg(F.min("total")).first()[0] or 0


def update_share(events: DataFrame, m: int) -> DataFrame:
    n = events.groupBy("worker").agg(F.count("*").alias("updates"))
    total = events.agg(F.count("*").alias("total"))
    return n.crossJoin(F.broadcast(total)).select("worker", "updates", (F.col("updates") / F.col("total")).alias("share"), F.lit(1.0 / m).alias("uniform"))


def staleness(events: DataFrame) -> DataFrame:
    """(worker, t, staleness): updates by others since the worker's own last one.

    A count of all updates before this one in time, less the same count at the last one; the order is total, as time
    is the axis of the whole run.
    """
    order = events.withColumn("k", F.row_number().over(Window.orderBy("time", "worker")))
    own = Window.partitionBy("worker").orderBy("t")
    return order.select("worker", "t", (F.col("k") - F.coalesce(F.lag("k").over(own), F.lit(0)) - 1).cast("long").alias("staleness"))


def communication(p: int, k: int, n: int, kind: str) -> int:
    """Numbers sent to the coordinator a round: gradients; with a line search a number more each; row sums for blocks."""
    return {"gd": p * k, "lbfgs": p * k + k, "prox": p * k, "bcd": n * k}[kind]


def trial_summary(traces: DataFrame) -> DataFrame:
    """Trials by scheme and round: mean, spread and quartiles of the objective."""
    return traces.groupBy("scheme", "t").agg(F.avg("objective").alias("mean"), F.stddev_samp("objective").alias("sd"), F.expr("percentile(objective, 0.25)").alias("q1"), F.expr("percentile(objective, 0.75)").alias("q3"), F.count("*").alias("trials"))


def async_replay(delays: DataFrame, horizon: float) -> DataFrame:
    """(run, worker, updates, stalest): asynchronous runs replayed event by event, a group a run, so that many go on at once.

    delays: (run, t, worker, delay). A run's events are rounds x workers: the state of one coordinator.
    """

    def replay(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["worker", "t"])
        done = frame.groupby("worker")["delay"].cumsum()
        live = frame.assign(done=done)[done <= horizon].sort_values(["done", "worker"]).reset_index(drop=True)
        last, updates, stalest = {}, {}, {}
        for k, worker in enumerate(live["worker"].tolist(), 1):
            stale = k - last.get(worker, 0) - 1
            last[worker], updates[worker], stalest[worker] = k, updates.get(worker, 0) + 1, max(stale, stalest.get(worker, 0))
        return pd.DataFrame({"run": [int(frame["run"].iloc[0])] * len(last), "worker": list(last), "updates": [updates[i] for i in last], "stalest": [stalest[i] for i in last]})

    return delays.groupBy("run").applyInPandas(replay, "run long, worker long, updates long, stalest long")
