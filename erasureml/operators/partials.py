"""What the workers answer: partial gradients, losses and curvatures of encoded rows, by worker.

`ScanPartials` runs one job a round; the filter on worker is pushed to a layout by worker, so erased workers' files
are not read.  `GramPartials` reads the data once and keeps p x p sums for each worker on the driver: all rounds then cost
nothing, but only up to GRAM_BYTES, beyond which it refuses; `partials_of` chooses.  Both give the same numbers.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from erasureml.operators.encode import ALWAYS, group_of, stacked

SUMS = "worker int, sums array<double>"


def _summed(df: DataFrame, tree: int = 0, keep: int | None = None) -> dict[int, np.ndarray]:
    """Element-wise sums by worker: in tasks first, then by worker (and by worker mod tree, where the driver needs the total
    only; the worker `keep` stays by itself)."""

    def add(frame: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"worker": frame["worker"][:1].to_list(), "sums": [stacked(frame["sums"]).sum(0)]})

    key = F.when(F.col("worker") == (keep if keep is not None else -(1 << 30)), F.col("worker")).otherwise(F.col("worker") % tree).cast("int").alias("worker") if tree else F.col("worker")
    rows = df.select(key, "sums").groupBy("worker").applyInPandas(add, SUMS).collect()  # as many rows as logical workers
    return {r["worker"]: np.array(r["sums"]) for r in rows}


def _by_worker(frame: pd.DataFrame) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    for worker, own in frame.groupby("worker"):
        yield int(worker), stacked(own["x"]), own["y"].to_numpy(float)


def _accumulated(df: DataFrame, value) -> DataFrame:
    """value(x, y) summed by worker over a task; a task's state is one array a worker."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: dict[int, np.ndarray] = {}
        for frame in frames:
            for worker, x, y in _by_worker(frame):
                v = value(x, y)
                held[worker] = held[worker] + v if worker in held else v
        if held:
            yield pd.DataFrame({"worker": np.array(list(held), np.int32), "sums": list(held.values())})

    return df.select("worker", "x", "y").mapInPandas(run, SUMS)


class ScanPartials:
    """enc: (worker, x, y), best laid out by worker (encode.write_by_worker), so that erased workers' files aren't read."""

    def __init__(self, enc: DataFrame, m: int, p: int) -> None:
        self.enc, self.m, self.p = enc, m, p

    def _live(self, active: np.ndarray) -> DataFrame:
        return self.enc.where(F.col("worker").isin(np.flatnonzero(active).tolist()))

    def total(self, w: np.ndarray, active: np.ndarray, tree: int = 16) -> tuple[np.ndarray, float]:
        """The sum over active workers only: two levels of sums, so the driver gets `tree` rows whatever m is.

        Rows that are never erased count in full beside the others' sum times m / k, so that the total stands for all.
        """
        k, m = int(active.sum()), self.m

        def value(x: np.ndarray, y: np.ndarray) -> np.ndarray:
            r = x @ w - y
            return np.append(x.T @ r, r @ r)

        live = self.enc.where(F.col("worker").isin([ALWAYS, *np.flatnonzero(active).tolist()]))
        out = np.zeros(self.p + 1)
        for i, v in _summed(_accumulated(live, value), tree, keep=ALWAYS).items():
            out += v if i == ALWAYS else v * (m / max(k, 1))
        return out[:-1], float(out[-1])

    def gradients(self, w: np.ndarray, active: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(m, p) partial gradients E'(E w - e), zero where erased, and (m,) losses |E w - e|^2."""

        def value(x: np.ndarray, y: np.ndarray) -> np.ndarray:
            r = x @ w - y
            return np.append(x.T @ r, r @ r)

        g, loss = np.zeros((self.m, self.p)), np.zeros(self.m)
        for i, v in _summed(_accumulated(self._live(active), value)).items():
            g[i], loss[i] = v[:-1], v[-1]
        return g, loss

    def curvature(self, d: np.ndarray, active: np.ndarray) -> np.ndarray:
        """(m,) |E d|^2: a number a worker, not a vector."""
        out = np.zeros(self.m)
        for i, v in _summed(_accumulated(self._live(active), lambda x, y: np.array([((x @ d) ** 2).sum()]))).items():
            out[i] = v[0]
        return out


#: Bytes of sums by worker that a driver may hold.
GRAM_BYTES = 1 << 30


def partials_of(enc: DataFrame, m: int, p: int, gram_bytes: int = GRAM_BYTES):
    """Sums kept on the driver if they fit in gram_bytes, a scan a round beyond."""
    return GramPartials(enc, m, p) if 8 * m * (p * p + p + 1) <= gram_bytes else ScanPartials(enc, m, p)


class GramPartials:
    def __init__(self, enc: DataFrame, m: int, p: int) -> None:
        if 8 * m * (p * p + p + 1) > GRAM_BYTES:
            raise MemoryError(f"{m} workers' sums of {p} x {p} don't fit in GRAM_BYTES: use ScanPartials")
        self.m, self.p = m, p
        self.G, self.c, self.s = np.zeros((m, p, p)), np.zeros((m, p)), np.zeros(m)
        sums = _accumulated(enc, lambda x, y: np.concatenate([(x.T @ x).ravel(), x.T @ y, [y @ y]]))
        for i, v in _summed(sums).items():
            self.G[i], self.c[i], self.s[i] = v[: p * p].reshape(p, p), v[p * p : -1], v[-1]

    @classmethod
    def of(cls, blocks: list[tuple[np.ndarray, np.ndarray]]) -> GramPartials:
        """From arrays (E_i, e_i): for problems that fit in one task."""
        out = cls.__new__(cls)
        out.m, out.p = len(blocks), blocks[0][0].shape[1]
        out.G = np.stack([e.T @ e for e, _ in blocks])
        out.c = np.stack([e.T @ y for e, y in blocks])
        out.s = np.array([y @ y for _, y in blocks])
        return out

    def gradients(self, w: np.ndarray, active: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        gw = self.G @ w
        return (gw - self.c) * active[:, None], (gw @ w - 2 * self.c @ w + self.s) * active

    def curvature(self, d: np.ndarray, active: np.ndarray) -> np.ndarray:
        return (self.G @ d) @ d * active


class OnlinePartials:
    """The same answers from uncoded rows and a task's own rows of S: X'S'S(X w - y) by matrix-vector products only."""

    def __init__(self, support: DataFrame, code, m: int, p: int, how: str = "scatter", seed: int = 1) -> None:
        from erasureml.operators.codes import assign

        self.support, self.code, self.m, self.p = support, code, m, p
        self.worker = assign(code, m, how, seed)

    def gradients(self, w: np.ndarray, active: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        code, owner = self.code, self.worker

        def value(frame: pd.DataFrame) -> pd.DataFrame:
            worker, x, y = int(frame["worker"].iloc[0]), stacked(frame["x"]), frame["y"].to_numpy(float)
            s = code.maker(np.flatnonzero(owner == worker)[:, None], (frame["row_id"].to_numpy() % code.n)[None, :])
            r = s @ (x @ w - y)
            return pd.DataFrame({"worker": [worker], "sums": [np.append(x.T @ (s.T @ r), r @ r)]})

        live = self.support.where(F.col("worker").isin(np.flatnonzero(active).tolist()))
        parts = live.groupBy("worker", group_of(F.col("row_id"), code.n)).applyInPandas(lambda f: value(f), SUMS)
        g, loss = np.zeros((self.m, self.p)), np.zeros(self.m)
        for i, v in _summed(parts).items():
            g[i], loss[i] = v[:-1], v[-1]
        return g, loss


def whole_gram(df: DataFrame, p: int) -> GramPartials:
    """Of the original rows, as one worker: exact objectives and solutions."""
    return GramPartials(df.select(F.lit(0).cast("int").alias("worker"), "x", "y"), 1, p)
