"""Model parallelism: block coordinate descent on lifted features w = S'v, and its asynchronous baseline.

z = X w stays consistent because an erased worker keeps its block: v_i moves only when its reply is accepted.  So the
gradient of block i is S_i X' phi'(X S'v).  A round is one scan of the uncoded rows, which gives the objective and the
gradient at its start; S is applied to that one vector by the code's fast transform or in slabs, never as a whole.  Rows may
be dense (x) or sparse (idx, val), and one scan serves any number of iterates (schemes, or states that asynchronous workers
read).  `exchange_round` is the same round with columns split over workers: each sends its rows' sums, gets the others', and
answers with its block's gradient.  `BlockStates` is the workers' side of the protocol, in which a step is committed or
taken back one round later, when the coordinator's message says whether it was accepted.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from erasureml.operators.codes import Code, assign
from erasureml.operators.encode import stacked
from erasureml.operators.partials import _summed
from erasureml.operators.solvers import RunResult, _trace, _warn


@dataclass(frozen=True)
class Loss:
    """value and slope of phi at (z, y), and a bound of its second derivative."""

    value: Callable[[np.ndarray, np.ndarray], np.ndarray]
    slope: Callable[[np.ndarray, np.ndarray], np.ndarray]
    bend: float


LOGISTIC = Loss(lambda z, y: np.logaddexp(0, -y * z), lambda z, y: -y / (1 + np.exp(np.clip(y * z, -500, 500))), 0.25)
SQUARED = Loss(lambda z, y: 0.5 * (z - y) ** 2, lambda z, y: z - y, 1.0)
#: A hinge rounded off quadratically within one of the corner.
HINGE = Loss(lambda z, y: np.where(y * z >= 1, 0, np.where(y * z <= 0, 0.5 - y * z, 0.5 * (1 - y * z) ** 2)), lambda z, y: -y * np.clip(1 - y * z, 0, 1), 1.0)


class LocalGradient:
    """mean phi(X w) + lam/2 |w|^2 from arrays."""

    def __init__(self, x: np.ndarray, y: np.ndarray, loss: Loss, lam: float) -> None:
        self.x, self.y, self.loss, self.lam, self.n = x, y, loss, lam, len(y)

    def __call__(self, w: np.ndarray) -> tuple[float, np.ndarray]:
        z = self.x @ w
        return float(self.loss.value(z, self.y).mean() + 0.5 * self.lam * w @ w), self.x.T @ self.loss.slope(z, self.y) / self.n + self.lam * w

    def smoothness(self) -> float:
        return self.loss.bend * float(np.linalg.eigvalsh(self.x.T @ self.x)[-1]) / self.n + self.lam


class ScanGradient:
    """The same in one job over (x, y): every task sums value and slope, p + 1 numbers."""

    def __init__(self, df: DataFrame, p: int, loss: Loss, lam: float) -> None:
        self.df, self.p, self.loss, self.lam = df.select("x", "y"), p, loss, lam
        self.n = df.count()

    def __call__(self, w: np.ndarray) -> tuple[float, np.ndarray]:
        loss, p = self.loss, self.p

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            total = np.zeros(p + 1)
            for frame in frames:
                x, y = stacked(frame["x"]), frame["y"].to_numpy(float)
                z = x @ w
                total += np.append(x.T @ loss.slope(z, y), loss.value(z, y).sum())
            yield pd.DataFrame({"pos": np.arange(p + 1), "v": total})

        sums = self.df.mapInPandas(run, "pos int, v double").groupBy("pos").agg(F.sum("v").alias("v")).collect()
        v = np.zeros(p + 1)
        for r in sums:
            v[r["pos"]] = r["v"]
        return float(v[-1] / self.n + 0.5 * self.lam * w @ w), v[:-1] / self.n + self.lam * w


class SparseScan:
    """Objectives, gradients and error shares of many iterates in one job over (idx, val, y, is_test).

    A task adds up p numbers an iterate; tasks' sums are added over `tree` slots before the driver gets them.
    """

    def __init__(self, df: DataFrame, p: int, loss: Loss, lam: float, tree: int = 16) -> None:
        self.df, self.p, self.loss, self.lam, self.tree = df.select("idx", "val", "y", "is_test"), p, loss, lam, tree
        counts = {r["is_test"]: r["n"] for r in df.groupBy("is_test").agg(F.count("*").alias("n")).collect()}
        self.n, self.n_test = counts.get(False, 0), counts.get(True, 0)

    def smoothness(self) -> float:
        """A bound: the mean squared length of a row, times the loss's bend, plus lam."""
        square = self.df.where(~F.col("is_test")).agg(F.max(F.aggregate("val", F.lit(0.0), lambda a, v: a + v * v))).first()[0]
        return self.loss.bend * float(square or 0.0) + self.lam

    def __call__(self, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """w: (p, s) -> objectives (s,), gradients (p, s), shares of training and test rows with the wrong sign (2, s)."""
        loss, p, s, tree = self.loss, self.p, w.shape[1], self.tree

        def run(frames: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros((p + 3, s))
            for batch in frames:
                idx, val = batch.column(0), batch.column(1).flatten().to_numpy()
                row, at = np.repeat(np.arange(len(idx)), np.diff(idx.offsets.to_numpy())), idx.flatten().to_numpy()
                y, test = batch.column(2).to_numpy()[:, None], batch.column(3).to_numpy(zero_copy_only=False).astype(bool)
                z = np.zeros((len(idx), s))
                np.add.at(z, row, val[:, None] * w[at])
                slope = np.where(test[:, None], 0, loss.slope(z, y))
                np.add.at(total, at, val[:, None] * slope[row])
                wrong = z * y <= 0
                total[p] += np.where(test[:, None], 0, loss.value(z, y)).sum(0)
                total[p + 1] += (wrong & ~test[:, None]).sum(0)
                total[p + 2] += (wrong & test[:, None]).sum(0)
            slot = TaskContext.get().partitionId() % tree
            yield pa.RecordBatch.from_arrays([pa.array([slot], pa.int32()), pa.array([total.ravel()], pa.list_(pa.float64()))], ["worker", "sums"])

        got = sum(_summed(self.df.mapInArrow(run, "worker int, sums array<double>")).values()).reshape(p + 3, s)
        values = got[p] / max(self.n, 1) + 0.5 * self.lam * (w * w).sum(0)
        return values, got[:p] / max(self.n, 1) + self.lam * w, got[p + 1 :] / np.array([[max(self.n, 1)], [max(self.n_test, 1)]])


def block_steps(scheme: str, p: int, m: int, how: str = "scatter", seed: int = 1):
    """(number of coordinates, to w, step): v -> w, and (gradient of w, replies) -> move of v, of a scheme.

    replication: m / 2 parts of the features on two workers each; a part moves if any of its copies replies.
    """
    if scheme == "replication":
        part = np.arange(p) * (m // 2) // p
        return p, lambda v: v, lambda g, live: np.where(live[: m // 2 * 2].reshape(2, m // 2).any(0)[part], g, 0)
    from erasureml.operators.codes import FAMILIES

    code = FAMILIES[scheme](p, seed)
    worker = assign(code, m, how, seed)
    return code.N, code.apply_t, lambda g, live: np.where(live[worker], code.apply(g), 0)


def side_by_side(scan: SparseScan, schemes: dict[str, str], active: dict[str, np.ndarray], clocks: dict[str, np.ndarray], step: float) -> pd.DataFrame:
    """Block descent of several runs (name -> scheme) with one scan a round for all of them.

    active: (rounds, m) replies by run. Gives (name, t, clock, objective, train_error, test_error), t = 0 being the start.
    """
    names = list(schemes)
    rounds, m = active[names[0]].shape
    made = {n: block_steps(schemes[n], scan.p, m) for n in names}
    v = {n: np.zeros(made[n][0]) for n in names}
    rows = []
    for t in range(rounds + 1):
        value, g, wrong = scan(np.stack([made[n][1](v[n]) for n in names], 1))
        for j, n in enumerate(names):
            rows.append((n, t, float(clocks[n][t - 1]) if t else 0.0, float(value[j]), float(wrong[0, j]), float(wrong[1, j])))
            if t < rounds:
                v[n] = v[n] - step * made[n][2](g[:, j], active[n][t])
    return pd.DataFrame(rows, columns=["name", "t", "clock", "objective", "train_error", "test_error"])


def async_side(scan: SparseScan, delays: np.ndarray, step: float, horizon: float, looks: int = 8) -> tuple[pd.DataFrame, pd.DataFrame]:
    """Asynchronous block descent: (curve, events).  Nobody waits, so a scan serves all states read since the last one.

    delays: (updates, m). curve: (t, clock, objective, errors) at `looks` times; events: (time, worker, staleness).
    """
    m, p = delays.shape[1], scan.p
    part = np.arange(p) * m // p
    ends = np.cumsum(delays, 0)
    t, i = np.nonzero(ends <= horizon)
    order = np.lexsort((i, ends[t, i]))
    w = np.zeros(p)
    states: dict[int, np.ndarray] = {0: w}  # by the number of updates before it was read
    known: dict[int, np.ndarray] = {}
    read, at, rows, kept = [0] * m, [0] * m, [], [(0.0, w)]
    every = max(1, len(order) // looks)
    for k, (a, b) in enumerate(zip(t[order], i[order], strict=True)):
        if read[b] not in known:
            wanted = sorted({r for r in read if r not in known})
            _, g, _ = scan(np.stack([states[r] for r in wanted], 1))
            known |= dict(zip(wanted, g.T, strict=True))
        w = w - step * np.where(part == b, known[read[b]], 0)
        rows.append((float(ends[a, b]), int(b), k - at[b]))
        read[b], at[b] = k + 1, k + 1
        states[k + 1] = w
        for r in set(states) - set(read):
            states.pop(r), known.pop(r, None)
        if (k + 1) % every == 0:
            kept.append((float(ends[a, b]), w))
    value, _, wrong = scan(np.stack([x for _, x in kept], 1))
    curve = pd.DataFrame({"t": np.arange(len(kept)), "clock": [c for c, _ in kept], "objective": value, "train_error": wrong[0], "test_error": wrong[1]})
    return curve, pd.DataFrame(rows, columns=["time", "worker", "staleness"])


def exchange_round(blocks: DataFrame, labels: DataFrame, v: dict[int, np.ndarray], loss: Loss) -> DataFrame:
    """(worker, g): every worker's block gradient X_i' phi'(z), from blocks (row_id, worker, xblk) and labels (row_id, y).

    A worker sends u_i = X_i v_i, gets the sum of the others' (total less own), and adds its own again: n numbers a worker
    each way.  Blocks dealt by row_id meet their sums without another shuffle.
    """
    held = F.create_map(*(x for i, b in v.items() for x in (F.lit(i), F.array(*map(F.lit, b.tolist())))))
    own = F.aggregate(F.zip_with("xblk", held[F.col("worker")], lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    w = Window.partitionBy("row_id")
    sent = blocks.withColumn("u", own).withColumn("others", F.sum("u").over(w) - F.col("u"))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total: dict[int, np.ndarray] = {}
        for frame in frames:
            for i, part in frame.groupby("worker"):
                z = (part["others"] + part["u"]).to_numpy()
                g = stacked(part["xblk"]).T @ loss.slope(z, part["y"].to_numpy(float))
                total[int(i)] = total.get(int(i), 0) + g
        yield pd.DataFrame({"worker": np.array(list(total), np.int32), "sums": list(total.values())})

    answers = sent.join(labels, "row_id").select("worker", "xblk", "u", "others", "y").mapInPandas(run, "worker int, sums array<double>")
    sums = answers.select("worker", F.posexplode("sums").alias("pos", "g")).groupBy("worker", "pos").agg(F.sum("g").alias("g"))
    return sums.groupBy("worker").agg(F.transform(F.sort_array(F.collect_list(F.struct("pos", "g"))), lambda s: s["g"]).alias("g"))


class BlockStates:
    """The workers' blocks: a step is pending until the next round's message says whether its reply was in time."""

    def __init__(self, sizes: list[int]) -> None:
        self.v = [np.zeros(n) for n in sizes]
        self.pending: list[np.ndarray | None] = [None] * len(sizes)
        self.committed = [-1] * len(sizes)

    def hear(self, t: int, accepted: np.ndarray | None) -> None:
        """At the start of round t: the replies accepted in round t - 1; the others' steps are taken back."""
        for i, move in enumerate(self.pending):
            if move is not None and accepted is not None and accepted[i]:
                self.v[i], self.committed[i] = self.v[i] + move, t
            self.pending[i] = None

    def reply(self, gradients: dict[int, np.ndarray], step: float) -> None:
        for i, g in gradients.items():
            self.pending[i] = -step * g


def block_coordinate_descent(grad: Callable[[np.ndarray], tuple[float, np.ndarray]], code: Code, active: np.ndarray, *, step: float, how: str = "scatter", seed: int = 1, v0: np.ndarray | None = None, clock: np.ndarray | None = None) -> RunResult:
    """v_i <- v_i - step S_i g for the workers that reply; the others' blocks stay.  step < 1 / smoothness.

    grad is called once a round, and once more for the last objective.
    """
    m = active.shape[1]
    worker = assign(code, m, how, seed)
    v = np.zeros(code.N) if v0 is None else v0.copy()
    w = code.apply_t(v)
    g, seen = grad(w)[1], []
    for live in active:
        v = v - step * np.where(live[worker], code.apply(g), 0)
        w = code.apply_t(v)
        value, g = grad(w)
        seen.append(value)
    return RunResult(w, _trace(seen, clock), active, _warn(active, m, code.beta))


def replicated_block_descent(grad, p: int, active: np.ndarray, *, step: float, r: int = 2, clock: np.ndarray | None = None) -> RunResult:
    """m / r parts of the features on r workers each; a part moves once if any of its copies replies."""
    m = active.shape[1]
    parts = m // r
    part = np.arange(p) * parts // p
    w, seen = np.zeros(p), []
    g = grad(w)[1]
    for live in active:
        got = live.reshape(r, parts).any(0)
        w = w - step * np.where(got[part], g, 0)
        value, g = grad(w)
        seen.append(value)
    return RunResult(w, _trace(seen, clock), active, [])


def async_block_descent(grad, p: int, delays: np.ndarray, *, step: float, horizon: float) -> tuple[RunResult, pd.DataFrame]:
    """Every worker reads the state, works for its delay and applies its block; nobody waits.

    delays: (updates, m). Also gives the event table: time, worker, staleness (updates by others in between).
    """
    m = delays.shape[1]
    part = np.arange(p) * m // p
    ends = np.cumsum(delays, 0)
    t, i = np.nonzero(ends <= horizon)
    order = np.lexsort((i, ends[t, i]))
    w, seen, rows = np.zeros(p), [], []
    read, at = [grad(w)[1]] * m, [0] * m  # the gradient at the state that each worker read
    for k, (a, b) in enumerate(zip(t[order], i[order], strict=True)):
        w = w - step * np.where(part == b, read[b], 0)
        rows.append((float(ends[a, b]), int(b), k - at[b]))
        value, read[b] = grad(w)
        at[b] = k + 1
        seen.append(value)
    events = pd.DataFrame(rows, columns=["time", "worker", "staleness"])
    return RunResult(w, _trace(seen, events["time"].to_numpy()), np.zeros((0, m), bool)), events


def async_gradient(problem, delays: np.ndarray, *, step: float, horizon: float) -> RunResult:
    """The data-parallel form: a worker's stale partial gradient is applied when it comes."""
    m = delays.shape[1]
    ends = np.cumsum(delays, 0)
    t, i = np.nonzero(ends <= horizon)
    order = np.lexsort((i, ends[t, i]))
    w, seen, when = np.zeros(problem.p), [], []
    read = [w] * m
    for a, b in zip(t[order], i[order], strict=True):
        live = np.arange(m) == b
        w = w - step * (problem.partials.gradients(read[b], live)[0].sum(0) / problem.n + problem.lam / m * read[b])
        read[b] = w
        seen.append(problem.objective(w))
        when.append(ends[a, b])
    return RunResult(w, _trace(seen, np.array(when)), np.zeros((0, m), bool))


def with_bias(df: DataFrame) -> DataFrame:
    """A constant feature at the end."""
    return df.withColumn("x", F.concat("x", F.array(F.lit(1.0))))


def absorb_l2(df: DataFrame, lam: float, p: int, n: int) -> DataFrame:
    """(x, y) with p rows sqrt(n lam) e_j, y = 0, below: for the squared loss the L2 term becomes part of the mean over n rows,
    so that the objective stays a function of X w."""
    extra = df.sparkSession.range(p).select(F.transform(F.sequence(F.lit(0), F.lit(p - 1)), lambda j: F.when(j == F.col("id"), F.lit((n * lam) ** 0.5)).otherwise(F.lit(0.0))).alias("x"), F.lit(0.0).alias("y"))
    return df.select("x", "y").unionByName(extra)


def augmented(x: np.ndarray, lam: float) -> np.ndarray:
    """The L2 term as rows sqrt(2 lam) I below X, so that the objective stays a function of X w."""
    return np.concatenate([x, np.sqrt(2 * lam) * np.eye(x.shape[1])])


def logistic_solution(x: np.ndarray, y: np.ndarray, lam: float, rounds: int = 50) -> np.ndarray:
    """By Newton steps."""
    w = np.zeros(x.shape[1])
    for _ in range(rounds):
        s = 1 / (1 + np.exp(np.clip(y * (x @ w), -500, 500)))
        g = -x.T @ (y * s) / len(y) + lam * w
        w = w - np.linalg.solve((x.T * (s * (1 - s))) @ x / len(y) + lam * np.eye(len(w)), g)
    return w
