"""Matrix factorisation by alternating ridge problems, coded where they are large.

A rating is x_user . y_item + u_user + v_item + b; every half epoch solves, for each user (item), a ridge problem of
dimension q = p + 1 on the ratings it has.  Ids with fewer than `threshold` ratings are solved exactly where their rows are;
larger ones go through quasi-Newton steps over m logical workers of which k reply.

Several schemes run side by side, and a half epoch is one job for all of them; where their factors are many, fewer run
at once.  An id's rows are taken in groups of `GROUP`, all encoded alike (S is block-diagonal): what the replies of a phase
add up to is x' M x with one GROUP x GROUP matrix M for all groups, so nothing is encoded and no worker's sums are made
(`Rows`).  An id with more than SPREAD ratings is dealt over several tasks, which send a q x q matrix for each worker
(`Sums`); these are added in two steps, so no id's ratings have to meet in one task.

Ratings are packed once for each side, by blocks of neighbouring ids.  An id's new factors leave its block with the names of
the other side's blocks that need them, and go there once in the next half epoch.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache, reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from erasureml.functions.uniform import uniform, uniform_np
from erasureml.operators.codes import Code, CodeBank, assign
from erasureml.operators.encode import stacked

GROUP, SPREAD, BATCH_BYTES, ROWS_BYTES, EVEN = 32, 1 << 14, 16 << 20, 4 << 20, 8  # EVEN: ids of up to so many groups are solved with those of as many
BLOCK, CHUNK, PIECE = 500_000, 1 << 17, 1 << 18  # ratings of a block, which a task holds with the factors they name, of a step in it, of a packed row
FACTOR_BYTES = 1 << 30  # of the factors of both sides; schemes beyond that take their turn
DELAY = 0.01
EXACT, COPIES = "exact", "replication"
_BANKS: dict[str, CodeBank] = {}


def code_of(scheme: str) -> Code:
    """The code of a scheme's groups, from a bank made once in a Python worker."""
    name = "uncoded" if scheme in (EXACT, COPIES) else scheme
    return _BANKS.setdefault(name, CodeBank(name, GROUP, GROUP)).get(GROUP)


def workers_of(scheme: str, m: int) -> int:
    """Different parts among m workers."""
    return 1 if scheme == EXACT else m // 2 if scheme == COPIES else m


def reply_delays(rounds: int, m: int, seed: int) -> np.ndarray:
    """(2 rounds, m) exponential delays: a row a phase (gradient, line search)."""
    return -DELAY * np.log(uniform_np(np.arange(2 * rounds)[:, None], np.arange(m)[None, :], seed))


def round_weights(scheme: str, m: int, k: int, delays: np.ndarray) -> np.ndarray:
    """(phases, parts): by how much each part's sum counts: k of m replies, of copies the first, scaled to stand for all."""
    rank = delays.argsort(1, kind="stable").argsort(1, kind="stable")
    live = rank < k
    if scheme == EXACT:
        return np.ones((len(delays), 1))
    if scheme == COPIES:
        parts = m // 2
        got = live[:, : 2 * parts].reshape(len(live), 2, parts).any(1)
        return got * (parts / np.maximum(got.sum(1, keepdims=True), 1))
    return live * (m / k)


def clock_of(scheme: str, m: int, k: int, delays: np.ndarray) -> float:
    """Seconds that the coordinator waits for replies in all phases."""
    return float(np.sort(delays, 1)[:, (m if scheme == EXACT else k) - 1].sum())


def quasi_newton(problem: Sums | Rows, lam: float, weights: np.ndarray, rounds: int, memory: int = 5, rho: float = 0.9) -> np.ndarray:
    """min |X w - y|^2 + lam |w|^2 for many ids at once.

    weights: those of the parts in the gradient phases, then in the line searches.
    Curvature pairs come from the parts that counted in two rounds on end.
    """
    w = np.zeros(problem.shape[::-1])  # an id a column: sums over an id's numbers then run along the ids
    at_w = problem.seen(w.T)
    pairs: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    scale = np.ones(w.shape[1])
    before = None
    for t in range(rounds):
        g = np.ascontiguousarray(problem.slope(weights[t], at_w).T)
        g += lam * w
        if before is not None:
            both = (weights[t] > 0) & (weights[t - 1] > 0)
            if both.any():
                u, at_u = before
                r = np.ascontiguousarray(problem.curve(both * (len(both) / both.sum()), at_u).T)
                r += lam * u
                ur, uu = _dots(u, r), _dots(u, u)
                ok = ur > 1e-12 * uu
                inverse = np.where(ok, 1 / np.where(ok, ur, 1), 0)
                pairs = [*pairs, (u, r, inverse)][-memory:]
                rr = _dots(r, r)
                scale = np.where(ok, ur / np.where(ok, rr, 1), scale)
        d, back = g.copy(), []
        for u, r, inverse in reversed(pairs):
            x = inverse * _dots(u, d)
            back.append(x)
            d -= x * r
        if pairs:
            d *= scale
        for (u, r, inverse), x in zip(pairs, reversed(back), strict=True):
            d += np.where(inverse > 0, x - inverse * _dots(r, d), 0) * u
        at_d = problem.seen(np.ascontiguousarray(d.T))
        bend = problem.bend(weights[rounds + t], at_d) + lam * _dots(d, d)
        step = -(rho * np.where(bend > 0, _dots(d, g) / np.where(bend > 0, bend, 1), 0))
        before = (step * d, problem.scaled(step, at_d))
        w, at_w = w + before[0], at_w + before[1]
    return np.ascontiguousarray(w.T)


def _dots(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.einsum("ji,ji->i", a, b)


class Sums:
    """Sums by part of many ids' problems: gram (ids, parts, q, q) and c (ids, parts, q)."""

    def __init__(self, gram: np.ndarray, c: np.ndarray) -> None:
        self.gram, self.c = gram, c

    @classmethod
    def of(cls, x: np.ndarray, y: np.ndarray, cuts: np.ndarray, scheme: str, m: int) -> Sums:
        """Of the rows between the cuts; groups of GROUP rows are encoded, all of them in one product."""
        sizes = np.diff(cuts)
        q, parts = x.shape[1], workers_of(scheme, m)
        z = np.column_stack([x, y])
        groups = -(-sizes // GROUP)
        first = np.cumsum(groups) - groups
        place = np.arange(len(z)) - np.repeat(cuts[:-1], sizes)
        full = np.zeros((GROUP, int(groups.sum()), q + 1))
        full[place % GROUP, np.repeat(first, sizes) + place // GROUP] = z
        if parts == 1:
            e, worker = full, np.zeros(GROUP, np.int64)
        else:
            code = code_of(scheme)
            e, worker = code.apply(full), assign(code, parts, "scatter", 1)
        gram, c = np.zeros((len(sizes), parts, q, q)), np.zeros((len(sizes), parts, q))
        for i in range(parts):
            own = e[worker == i].transpose(1, 0, 2)
            total = np.add.reduceat(own.transpose(0, 2, 1) @ own, first, axis=0)
            gram[:, i], c[:, i] = total[:, :q, :q], total[:, :q, q]
        return cls(gram, c)

    def packed(self) -> np.ndarray:
        return np.concatenate([self.gram.reshape(len(self.c), -1), self.c.reshape(len(self.c), -1)], 1)

    @classmethod
    def unpacked(cls, rows: np.ndarray, q: int) -> Sums:
        parts = rows.shape[1] // (q * q + q)
        return cls(rows[:, : parts * q * q].reshape(-1, parts, q, q), rows[:, parts * q * q :].reshape(-1, parts, q))

    def solved(self, lam: float, weights: np.ndarray | None, rounds: int) -> np.ndarray:
        if weights is None or self.c.shape[1] == 1:
            return ridge(self.gram.sum(1), self.c.sum(1), lam)
        return quasi_newton(self, lam, weights, rounds)

    @property
    def shape(self) -> tuple[int, int]:
        return len(self.c), self.c.shape[2]

    def seen(self, v: np.ndarray) -> np.ndarray:
        return v

    def scaled(self, step: np.ndarray, v: np.ndarray) -> np.ndarray:
        return step[:, None] * v

    def curve(self, a: np.ndarray, v: np.ndarray) -> np.ndarray:
        b, parts, q = self.c.shape
        return np.einsum("bij,bj->bi", (a @ self.gram.reshape(b, parts, q * q)).reshape(b, q, q), v)  # no copy of gram

    def slope(self, a: np.ndarray, v: np.ndarray) -> np.ndarray:
        return self.curve(a, v) - a @ self.c

    def bend(self, a: np.ndarray, v: np.ndarray) -> np.ndarray:
        return (self.curve(a, v) * v).sum(1)


class Rows:
    """Many ids' problems on their rows: x (groups, GROUP, q) and y (groups, GROUP), padded with zeros; ids lie between the cuts.

    A vector v of an id is seen as x v by groups, and replies with weights a act as the matrix M = sum of a_i S_i' S_i.
    Where all ids have as many groups, an id's rows are one matrix, and nothing is added up by id.
    """

    def __init__(self, x: np.ndarray, y: np.ndarray, cuts: np.ndarray, scheme: str, m: int) -> None:
        at, groups = padded_places(np.diff(cuts))
        full, goal = np.zeros((groups.sum() * GROUP, x.shape[1])), np.zeros(groups.sum() * GROUP)
        full[at], goal[at] = x[cuts[0] : cuts[-1]], y[cuts[0] : cuts[-1]]
        self._keep(full, goal, groups, scheme, m)

    @classmethod
    def padded(cls, x: np.ndarray, y: np.ndarray, groups: np.ndarray, scheme: str, m: int) -> Rows:
        """Of rows that lie at their `padded_places`, with zeros between."""
        self = cls.__new__(cls)
        self._keep(x, y, groups, scheme, m)
        return self

    def _keep(self, x: np.ndarray, y: np.ndarray, groups: np.ndarray, scheme: str, m: int) -> None:
        self.shape = n, q = len(groups), x.shape[1]
        self.x, self.y = x.reshape(-1, GROUP, q), y.reshape(-1, GROUP)
        self.even = bool(n) and bool((groups == groups[0]).all())
        self.by = self.x.reshape(n, -1, q) if self.even else self.x  # the matrices of an id's rows, or of its groups'
        if not self.even:
            self.first, self.of = np.cumsum(groups) - groups, np.repeat(np.arange(n), groups)
        self.scheme, self.parts = scheme, workers_of(scheme, m)

    def by_id(self, groups: np.ndarray) -> np.ndarray:
        return groups if self.even else np.add.reduceat(groups, self.first, axis=0)

    def seen(self, v: np.ndarray) -> np.ndarray:
        return np.matvec(self.by, v if self.even else v[self.of]).reshape(self.y.shape)

    def scaled(self, step: np.ndarray, v: np.ndarray) -> np.ndarray:
        each = v.reshape(self.by.shape[:2])
        return ((step if self.even else step[self.of])[:, None] * each).reshape(v.shape)

    def weighed(self, a: np.ndarray, v: np.ndarray) -> np.ndarray:
        mixed = _mixed(self.scheme, self.parts, a.astype(float).tobytes())
        return v @ mixed if mixed.ndim == 2 else v * mixed

    def back(self, v: np.ndarray) -> np.ndarray:
        return self.by_id(np.vecmat(v.reshape(self.by.shape[:2]), self.by))

    def curve(self, a: np.ndarray, v: np.ndarray) -> np.ndarray:
        return self.back(self.weighed(a, v))

    def slope(self, a: np.ndarray, v: np.ndarray) -> np.ndarray:
        return self.back(self.weighed(a, v - self.y))

    def bend(self, a: np.ndarray, v: np.ndarray) -> np.ndarray:
        each = self.by.shape[:2]
        return self.by_id(np.vecdot(self.weighed(a, v).reshape(each), v.reshape(each)))

    def solved(self, lam: float, weights: np.ndarray | None, rounds: int) -> np.ndarray:
        if weights is None or self.parts == 1:
            return ridge(self.by_id(self.by.transpose(0, 2, 1) @ self.by), self.back(self.y), lam)
        return quasi_newton(self, lam, weights, rounds)


def padded_places(sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(where the rows of ids with so many of them lie if each begins a new group, groups of each id)."""
    groups = -(-sizes // GROUP)
    shift = (np.cumsum(groups) - groups) * GROUP - (np.cumsum(sizes) - sizes)
    return np.arange(sizes.sum()) + np.repeat(shift, sizes), groups


@lru_cache(256)
def _mixed(scheme: str, parts: int, a: bytes) -> np.ndarray:
    """M of the replies' weights, or its diagonal if that is all there is."""
    code = code_of(scheme)
    s, worker = code.apply(np.eye(GROUP)), assign(code, parts, "scatter", 1)
    mixed = s.T @ (np.frombuffer(a)[worker][:, None] * s)
    return mixed if (mixed - np.diag(mixed.diagonal())).any() else mixed.diagonal().copy()


def ridge(gram: np.ndarray, c: np.ndarray, lam: float) -> np.ndarray:
    """(gram + lam) w = c for many ids.  Where factors have grown until lam is lost in rounding, a system can be singular: it is
    solved by its pseudoinverse then, and the others' solutions stay."""
    a = gram + lam * np.eye(c.shape[1])
    try:
        return np.linalg.solve(a, c[..., None])[..., 0]
    except np.linalg.LinAlgError:
        if len(a) > 1:
            half = len(a) // 2
            return np.concatenate([ridge(gram[:half], c[:half], lam), ridge(gram[half:], c[half:], lam)])
    if not np.isfinite(a).all():
        return np.full(c.shape, np.nan)
    return (np.linalg.pinv(a[0], rcond=1e-13, hermitian=True) @ c[0])[None]


def counted(ratings: DataFrame) -> DataFrame:
    """ratings with n_user and n_item, the training ratings of each id."""
    out = ratings
    for own in ("user", "item"):
        n = ratings.where(~F.col("is_test")).groupBy(own).agg(F.count("*").alias(f"n_{own}"))
        out = out.join(n, own, "left")
    return out


def with_hot(ratings: DataFrame, train: DataFrame, own: str, n: int, spread: int) -> tuple[DataFrame, bool]:
    """(ratings with n_own, null but for ids with more than `spread` training ratings; whether there are such ids).

    Ids are counted by hash first: only those of a bucket that has more can have more themselves.
    """
    bucket = F.pmod(F.xxhash64(own), F.lit(max(1024, 16 * n // spread)))
    heavy = train.groupBy(bucket.alias("bucket")).agg(F.count("*").alias("n")).where(F.col("n") > spread).select("bucket")
    if heavy.isEmpty():
        return ratings.withColumn(f"n_{own}", F.lit(None).cast("long")), False
    counts = train.withColumn("bucket", bucket).join(heavy, "bucket", "left_semi").groupBy(own).agg(F.count("*").alias(f"n_{own}")).where(F.col(f"n_{own}") > spread)
    return ratings.join(counts, own, "left"), not counts.isEmpty()


def blocks_of(ratings: DataFrame, own: str, n: int | None = None) -> list:
    """Where blocks of about BLOCK ratings begin, in the order of the ids: neighbours often share what they rated."""
    n = ratings.count() if n is None else n
    parts = max(-(-n // BLOCK), min(12, -(-n // 10_000)), 1)
    return sorted(set(ratings.approxQuantile(own, [k / parts for k in range(1, parts)], 0.2 / parts))) if parts > 1 else []


def _block(own: str, cuts: list) -> Column:
    """How many cuts are not above the id, found by halving."""

    def among(lo: int, hi: int) -> Column:
        mid = (lo + hi) // 2
        return F.lit(lo) if lo == hi else F.when(F.col(own) < cuts[mid], among(lo, mid)).otherwise(among(mid + 1, hi))

    return among(0, len(cuts))


def labels_of(spark: SparkSession, blocks: int) -> list[int]:
    """Numbers for the blocks that Spark deals evenly over its partitions; of many blocks, any numbers are."""
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    if blocks > 8 * parts:
        return list(range(blocks))
    number = F.col("id").cast("int")
    found: dict[int, list[int]] = {}
    for i, part in spark.range(64 * parts, numPartitions=1).select(number, F.pmod(F.hash(number), F.lit(parts))).collect():
        found.setdefault(part, []).append(i)
    return [found[b * parts // blocks if blocks < parts else b % parts].pop() for b in range(blocks)]


def _salt(own: str, by: str, spread: int) -> Column:
    n = F.col(f"n_{own}")  # null: not a hot id
    return F.when(n > spread, F.pmod(F.xxhash64(by), F.ceil(n / spread).cast("int"))).otherwise(0).cast("int")


def _place(own: str, by: str, cuts: list, spread: int, labels: list[int]) -> Column:
    """The block of a rating on a side: that of the id, of a hot id one of several."""
    at = ((_block(own, cuts) + _salt(own, by, spread)) % (len(cuts) + 1)).cast("int")
    return F.element_at(F.array(*map(F.lit, labels)), at + 1)


def packed(ratings: DataFrame, own: str, by: str, spread: int, block: Column, other: Column) -> DataFrame:
    """(block, piece, data): a side's ratings by block, in the order of its ids; other: the block of a rating on the other side.

    n_own may be null for ids whose ratings all lie in one block; they are counted there.
    """
    test = F.col("is_test") if "is_test" in ratings.columns else F.lit(False)
    rows = ratings.select(
        F.col(own).cast("long").alias("own"), F.col(by).cast("long").alias("by"), F.col("rating").cast("double").alias("rating"), test.alias("is_test"),
        F.col(f"n_{own}").cast("int").alias("n"), _salt(own, by, spread).alias("salt"), other.cast("int").alias("to"), block.cast("int").alias("block"),
    )

    def pack(rows: pa.Table) -> pa.Table:
        block, rows = rows["block"][:1], rows.drop_columns("block")
        rows = rows.take(pa.array(np.lexsort([rows[c].to_numpy() for c in ("by", "salt", "own")])))
        rows = rows.set_column(rows.schema.get_field_index("n"), "n", pa.array(_counts(rows), pa.int32()))
        data = []
        for lo in range(0, len(rows), PIECE):
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, rows.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
                out.write_table(rows.slice(lo, PIECE).combine_chunks())
            data.append(sink.getvalue().to_pybytes())
        return pa.table({"block": pa.array(block.to_pylist() * len(data), pa.int32()), "piece": pa.array(range(len(data)), pa.int32()), "data": pa.array(data, pa.binary())})

    return rows.groupBy("block").applyInArrow(pack, "block int, piece int, data binary")


def _counts(rows: pa.Table) -> np.ndarray:
    """n of every row of a block in the order of its ids: what is given, else the training ratings that its id has here."""
    own, train = rows["own"].to_numpy(), ~rows["is_test"].to_numpy()
    first = np.flatnonzero(np.diff(own, prepend=own[:1] - 1))
    here = np.repeat(np.add.reduceat(train.astype(np.int64), first), np.diff([*first, len(own)]))
    return np.where(rows["n"].is_null().to_numpy(), here, rows["n"].fill_null(0).to_numpy())


def _unpacked(mine: pa.Table) -> dict[str, np.ndarray]:
    pieces = [pa.ipc.open_stream(d.as_buffer()).read_all() for d in mine.sort_by("piece")["data"]]
    rows = pa.concat_tables(pieces)
    return {c: rows[c].to_numpy() for c in rows.column_names}


def _wide(factors: DataFrame, by: str) -> DataFrame:
    """(id, names, w): an id's factors and biases of all schemes side by side."""
    own = factors.groupBy(F.col(by).alias("id")).agg(F.sort_array(F.collect_list(F.struct("scheme", F.concat("f", F.array("bias")).alias("w")))).alias("all"))
    return own.select("id", F.col("all")["scheme"].alias("names"), F.flatten(F.col("all")["w"]).alias("w"))


def _long(wide: DataFrame, own: str, names: list[str], q: int) -> DataFrame:
    """(scheme, own, f, bias) of (id, w)."""
    each = wide.select("id", "w", F.posexplode(F.array(*map(F.lit, names))).alias("i", "scheme"))
    return each.select("scheme", F.col("id").alias(own), F.slice("w", F.col("i") * q + 1, F.lit(q - 1)).alias("f"), F.element_at("w", (F.col("i") + 1) * q).alias("bias"))


def _sent(rows: DataFrame, factors: DataFrame, by: str) -> DataFrame:
    """(to, id, names, w): every block's own copy of the factors that its rows name, one for all of them."""
    return rows.select(F.col("block").alias("to"), F.col(by).alias("id")).distinct().join(_wide(factors, by), "id").select("to", "id", "names", "w")


def _looked_up(sent: pa.Table, ids: np.ndarray, schemes: int, q: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(w by row of `sent` and scheme, the row of each id, whether there is one)."""
    if not len(sent):
        return np.zeros((1, schemes, q)), np.zeros(len(ids), np.int64), np.zeros(len(ids), bool)
    w = sent["w"].combine_chunks().flatten().to_numpy().reshape(len(sent), schemes, q)
    known = sent["id"].to_numpy()
    order = np.argsort(known, kind="stable")
    at = order[np.minimum(np.searchsorted(known[order], ids), len(known) - 1)]
    return w, at, known[at] == ids


def _batches(ids: np.ndarray, sizes: np.ndarray, room: int, each: bool) -> list[np.ndarray]:
    """ids in runs of at most `room` groups of their rows (each: of `room` ids), or of one id."""
    if not len(ids):
        return []
    before = np.arange(len(ids)) if each else np.cumsum(-(-sizes // GROUP))
    return np.split(ids, np.flatnonzero(np.diff(before // max(1, room))) + 1)


def _solved(blocks: DataFrame, sent: DataFrame | None, names: list[str], *, rank: int, lam: float, base: float, m: int, k: int, rounds: int, threshold: int, seed: int, spread: int, hot: bool, save=None, drop=None, start: int | None = None) -> DataFrame:
    """(id, w, home, other): every id's factors of all schemes, its blocks, and the other side's blocks that name it.

    blocks: as `packed` gives them; sent: (to, id, w), the other side's factors, or None for the `first_factors` of the seed `start`.
    hot: whether an id has more than `spread` ratings.
    """
    q, s = rank + 1, len(names)
    delays = reply_delays(rounds, m, seed)

    weights = {scheme: round_weights(scheme, m, k, delays) for scheme in names}

    def run(mine: pa.Table, sent: pa.Table | None = None) -> pa.Table:
        if not len(mine):
            return SOLVED.empty_table()
        block, rows = mine["block"][0].as_py(), _unpacked(mine)
        if sent is None:
            ids, w_of = np.unique(rows["by"], return_inverse=True)
            f = (uniform_np(ids[:, None], np.arange(rank)[None, :], start + 17) - 0.5) / np.sqrt(float(rank))
            w, found = np.repeat(np.column_stack([f, np.zeros(len(ids))])[:, None], s, axis=1), np.ones(len(w_of), bool)
        else:
            w, w_of, found = _looked_up(sent, rows["by"], s, q)
        first = np.concatenate([[0], np.flatnonzero((np.diff(rows["own"]) != 0) | (np.diff(rows["salt"]) != 0)) + 1])
        place = np.repeat(np.arange(len(first)), np.diff([*first, len(w_of)]))
        named = _distinct(place, rows["to"], len(first))  # by test ratings too: their errors need the factors
        kept = found & ~rows["is_test"]
        own, n, rating, at, place = (a[kept] for a in (rows["own"], rows["n"], rows["rating"], w_of, place))
        edges = np.concatenate([[0], np.flatnonzero(np.diff(place)) + 1, [len(own)]]) if len(own) else np.zeros(1, np.int64)
        place = place[edges[:-1]]

        def told(scheme: str | None, ids: np.ndarray, w: np.ndarray, place: np.ndarray) -> pa.Table:
            null = pa.nulls(len(ids), pa.list_(pa.float64()))
            return pa.Table.from_arrays([
                pa.array([scheme] * len(ids), pa.string()), pa.array(ids), lists(w) if scheme is None else null, null if scheme is None else lists(w),
                lists(np.full((len(ids), 1), block, np.int32)), named.take(pa.array(place)),
            ], schema=SOLVED)

        out, lo = [], 0
        while lo < len(edges) - 1:  # whole ids, CHUNK ratings or one id at a time
            hi = max(lo + 1, int(np.searchsorted(edges, edges[lo] + CHUNK, "right")) - 1)
            part, starts = slice(edges[lo], edges[hi]), edges[lo : hi + 1] - edges[lo]
            ids, sizes = own[part][starts[:-1]], n[part][starts[:-1]]
            done, sums = np.zeros((hi - lo, s, q)), []
            whole(w, at[part], rating[part] - base, sizes, starts, done)
            if (sizes > spread).any():
                for i, scheme in enumerate(names):
                    f = w[at[part], i]
                    sums += spread_out(scheme, np.column_stack([f[:, :rank], np.ones(len(f))]), rating[part] - f[:, rank] - base, sizes, starts)
            some = np.flatnonzero(sizes <= spread)
            out.append(told(None, ids[some], done[some].reshape(len(some), s * q), place[lo + some]))
            out += [told(scheme, ids[some], w, place[lo + some]) for scheme, some, w in sums]
            lo = hi
        rest = np.setdiff1d(np.flatnonzero(rows["n"][first] > spread), place)  # a hot id's blocks with test ratings only
        for scheme in names if len(rest) else []:
            for kind, some in ((EXACT, rest[rows["n"][first[rest]] < threshold]), (scheme, rest[rows["n"][first[rest]] >= threshold])):
                out.append(told(scheme, rows["own"][first[some]], np.zeros((len(some), workers_of(kind, m) * (q * q + q))), some))
        return pa.concat_tables([SOLVED.empty_table(), *out])

    def whole(w: np.ndarray, at: np.ndarray, goal: np.ndarray, n: np.ndarray, cuts: np.ndarray, done: np.ndarray) -> None:
        """Fill `done` for the ids whose ratings are all here; at: the rows of w that the ratings name, goal: the ratings over the base."""
        flat, held = w.reshape(-1, q), np.diff(cuts)
        kinds = np.where(n < threshold, 0, EVEN + 2) + np.minimum(-(-held // GROUP), EVEN + 1)
        for kind in np.unique(kinds[n <= spread]):
            own_ids = np.flatnonzero((kinds == kind) & (n <= spread))
            for ids in _batches(own_ids, held[own_ids], ROWS_BYTES // (8 * q * GROUP), False):
                places, groups = padded_places(held[ids])
                rows = np.arange(len(places)) + np.repeat(cuts[ids] - np.cumsum(held[ids]) + held[ids], held[ids])
                named, own_goal, pad = np.zeros(groups.sum() * GROUP, np.int64), np.zeros(groups.sum() * GROUP), np.ones(groups.sum() * GROUP, bool)
                named[places], own_goal[places], pad[places] = at[rows] * s, goal[rows], False
                ones, pad = (~pad).astype(float), np.flatnonzero(pad)
                for i, scheme in enumerate(names):
                    x = np.take(flat, named + i, axis=0)
                    x[pad] = 0
                    y = own_goal - x[:, rank]
                    x[:, rank] = ones
                    coded = None if kind <= EVEN + 1 or scheme == EXACT else scheme
                    done[ids, i] = Rows.padded(x, y, groups, coded or EXACT, m).solved(lam, coded and weights[coded], rounds)

    def spread_out(scheme: str, x: np.ndarray, y: np.ndarray, n: np.ndarray, cuts: np.ndarray) -> Iterator[tuple[str, np.ndarray, np.ndarray]]:
        """The sums of the ids whose ratings are not all here."""
        for kind, chosen in ((EXACT, n < threshold), (scheme, n >= threshold)):
            own_ids = np.flatnonzero(chosen & (n > spread))
            for at in _batches(own_ids, np.diff(cuts)[own_ids], BATCH_BYTES // (8 * q * q * workers_of(kind, m)), True):
                sizes = np.diff(cuts)[at]
                ends = np.concatenate([[0], np.cumsum(sizes)])
                rows = np.arange(ends[-1]) + np.repeat(cuts[at] - ends[:-1], sizes)
                yield scheme, at, Sums.of(x[rows], y[rows], ends, kind, m).packed()

    kept = "scheme string, id long, w array<double>, sums array<double>, home array<int>, other array<int>"
    out = blocks.groupBy("block").applyInArrow(lambda mine: run(mine), kept) if sent is None else blocks.groupBy("block").cogroup(sent.groupBy("to")).applyInArrow(run, kept)
    if not hot:
        return out.select("id", "w", "home", "other")
    out = save(out) if save else out
    added = _added(out, q, lam, rounds, weights)
    together = added.groupBy("id").agg(F.sort_array(F.collect_list(F.struct("scheme", "w"))).alias("all"), F.first("home").alias("home"), F.first("other").alias("other"))
    whole_ids = out.where("sums is null").select("id", "w", "home", "other").unionByName(together.select("id", F.flatten(F.col("all")["w"]).alias("w"), "home", "other"))
    if save:
        first, whole_ids = out, save(whole_ids)
        (drop or (lambda df: None))(first)
    return whole_ids


def _distinct(ids: np.ndarray, values: np.ndarray, n: int) -> pa.Array:
    """For the ids 0 to n - 1 the list of their different values."""
    low = int(values.min())
    span = int(values.max()) - low + 1
    both = np.unique(ids * span + (values - low))
    ends = np.concatenate([[0], np.cumsum(np.bincount(both // span, minlength=n))])
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(both % span + low, pa.int32()))


def _added(out: DataFrame, q: int, lam: float, rounds: int, weights: dict[str, np.ndarray]) -> DataFrame:
    """(scheme, id, w, home, other) of ids whose sums come from several tasks."""

    def union(lists: pd.Series) -> list[int]:
        return sorted({int(v) for some in lists for v in some})

    def add(frame: pd.DataFrame) -> pd.DataFrame:
        return frame[:1].assign(sums=[stacked(frame["sums"]).sum(0)], home=[union(frame["home"])], other=[union(frame["other"])])

    def solve(frame: pd.DataFrame) -> pd.DataFrame:
        scheme, sums = frame["scheme"].iloc[0], Sums.unpacked(stacked(frame["sums"]).sum(0)[None], q)
        w = sums.solved(lam, None if sums.c.shape[1] == 1 else weights[scheme], rounds)[0]
        return pd.DataFrame({"scheme": [scheme], "id": frame["id"][:1].to_list(), "w": [w], "home": [union(frame["home"])], "other": [union(frame["other"])]})

    several = out.where("sums is not null").select("scheme", "id", "sums", "home", "other").withColumn("slot", F.pmod(F.xxhash64("sums"), F.lit(64)).cast("int"))
    some = several.groupBy("scheme", "id", "slot").applyInPandas(add, "scheme string, id long, sums array<double>, home array<int>, other array<int>, slot int")
    return some.groupBy("scheme", "id").applyInPandas(solve, "scheme string, id long, w array<double>, home array<int>, other array<int>")


def half_epoch(ratings: DataFrame, other: DataFrame, own: str, by: str, *, rank: int, lam: float, base: float, m: int, k: int, rounds: int, threshold: int, seed: int, spread: int = SPREAD, cuts: list | None = None) -> DataFrame:
    """(scheme, own, f, bias) for every id with a rating, from the other side's factors (scheme, by, f, bias).

    ratings: (user, item, rating, n_user, n_item). `alternating` does many of these on ratings that it packs once.
    """
    cuts = blocks_of(ratings, own) if cuts is None else cuts
    names = sorted(r[0] for r in other.select("scheme").distinct().collect())
    block = _place(own, by, cuts, spread, labels_of(ratings.sparkSession, len(cuts) + 1))
    sent = _sent(ratings.withColumn("block", block), other, by)
    out = _solved(packed(ratings, own, by, spread, block, F.lit(0)), sent, names, rank=rank, lam=lam, base=base, m=m, k=k, rounds=rounds, threshold=threshold, seed=seed, spread=spread, hot=True)
    return _long(out, own, names, rank + 1)


SOLVED = pa.schema([("scheme", pa.string()), ("id", pa.int64()), ("w", pa.list_(pa.float64())), ("sums", pa.list_(pa.float64())), ("home", pa.list_(pa.int32())), ("other", pa.list_(pa.int32()))])


def lists(rows: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(rows) + 1, dtype=np.int32) * rows.shape[1]), pa.array(np.ascontiguousarray(rows).ravel()))


def predicted(ratings: DataFrame, users: DataFrame, items: DataFrame, base: float, schemes: list[str]) -> DataFrame:
    """ratings by scheme with guess; ids without factors count as zero."""
    u = users.select("scheme", "user", F.col("f").alias("uf"), F.col("bias").alias("ub"))
    v = items.select("scheme", "item", F.col("f").alias("vf"), F.col("bias").alias("vb"))
    dot = F.coalesce(F.aggregate(F.zip_with("uf", "vf", lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x), F.lit(0.0))
    each = ratings.withColumn("scheme", F.explode(F.array(*map(F.lit, schemes))))
    return each.join(u, ["scheme", "user"], "left").join(v, ["scheme", "item"], "left").withColumn("guess", dot + F.coalesce("ub", F.lit(0.0)) + F.coalesce("vb", F.lit(0.0)) + base)


def errors_by_block(blocks: DataFrame, users: DataFrame, items: DataFrame, base: float, names: list[str], q: int) -> dict[tuple[str, bool], float]:
    """{(scheme, is_test): root mean squared error}, like `rmse` of `predicted`, but by blocks of users: no rating meets its factors in a join."""

    def run(mine: pa.Table, sent: pa.Table) -> pa.Table:
        total: dict[tuple[str, bool], tuple[int, float]] = {}
        if len(mine):
            rows, is_user = _unpacked(mine), sent["of_user"].to_numpy() if len(sent) else np.zeros(0, bool)
            sides = [_looked_up(sent.filter(pa.array(of)), rows[name], len(names), q) for of, name in ((is_user, "own"), (~is_user, "by"))]
            for i, scheme in enumerate(names):
                for lo in range(0, len(rows["own"]), CHUNK):
                    part = slice(lo, lo + CHUNK)
                    u, v = (np.where(found[part, None], w[at[part], i], 0.0) for w, at, found in sides)
                    off = (rows["rating"][part] - (base + u[:, -1] + v[:, -1] + (u[:, :-1] * v[:, :-1]).sum(1))) ** 2
                    for kind in (False, True):
                        own = off[rows["is_test"][part] == kind]
                        n, sq = total.get((scheme, kind), (0, 0.0))
                        total[scheme, kind] = (n + len(own), sq + float(own.sum()))
        keys = list(total)
        return pa.table({"scheme": pa.array([a for a, _ in keys], pa.string()), "is_test": pa.array([b for _, b in keys], pa.bool_()), "n": pa.array([total[k][0] for k in keys], pa.int64()), "sq": pa.array([total[k][1] for k in keys], pa.float64())})

    sent = _dealt(users, "home").withColumn("of_user", F.lit(True)).union(_dealt(items, "other").withColumn("of_user", F.lit(False)))
    sums = blocks.groupBy("block").cogroup(sent.groupBy("to")).applyInArrow(run, "scheme string, is_test boolean, n long, sq double")
    return {(r["scheme"], r["is_test"]): (r["sq"] / r["n"]) ** 0.5 for r in sums.groupBy("scheme", "is_test").agg(F.sum("n").alias("n"), F.sum("sq").alias("sq")).where("n > 0").collect()}


def _dealt(factors: DataFrame, to: str) -> DataFrame:
    """(to, id, w): the factors for each block in the list `to`."""
    return factors.select(F.explode(to).alias("to"), "id", "w")


def rmse(predictions: DataFrame) -> DataFrame:
    return predictions.groupBy(*(c for c in ("scheme", "is_test") if c in predictions.columns)).agg(F.sqrt(F.avg(F.pow(F.col("rating") - F.col("guess"), 2))).alias("rmse"))


def _first(rank: int, seed: int) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(rank - 1)), lambda j: (uniform("item", j, seed + 17) - 0.5) / F.sqrt(F.lit(float(rank))))


def first_factors(items: DataFrame, rank: int, schemes: list[str], seed: int = 1) -> DataFrame:
    """(scheme, item, f, bias) to begin with."""
    return items.select("item").distinct().select(F.explode(F.array(*map(F.lit, schemes))).alias("scheme"), "item", _first(rank, seed).alias("f"), F.lit(0.0).alias("bias"))


def alternating(ratings: DataFrame, *, rank: int = 15, lam: float = 10.0, base: float = 3.0, epochs: int = 5, schemes: list[str] | str = "paley", m: int = 8, k: int = 4, rounds: int = 12, threshold: int = 500, seed: int = 1, save=None, each: bool = True, spread: int = SPREAD, drop=None) -> tuple[DataFrame, DataFrame, list[dict]]:
    """(users, items, trace of scheme, epoch, train and test error and clock). save cuts lineage after a half epoch.

    each: errors after every epoch, else after the last. drop: what to do with a saved table that is no longer needed.
    """
    schemes = [schemes] if isinstance(schemes, str) else list(schemes)
    save = save or (lambda df: df.persist())
    drop = drop or (lambda df: None)
    q = rank + 1
    given = save(ratings.select("user", "item", "rating", "is_test"))  # what makes them runs once, not again for each side
    train = given.where(~F.col("is_test"))
    n, n_users, n_items = train.agg(F.count("*"), F.approx_count_distinct("user"), F.approx_count_distinct("item")).first()
    ratings, many = given, {}
    for own in ("user", "item"):
        ratings, many[own] = with_hot(ratings, train, own, n, spread)
    cuts = {own: blocks_of(train, own, n) for own in ("user", "item")}
    place = {own: _place(own, by, cuts[own], spread, labels_of(ratings.sparkSession, len(cuts[own]) + 1)) for own, by in (("user", "item"), ("item", "user"))}
    blocks = {own: save(packed(ratings, own, by, spread, place[own], place[by])) for own, by in (("user", "item"), ("item", "user"))}
    drop(given)
    at_once = max(1, FACTOR_BYTES // (8 * q * max(1, n_users + n_items)))
    at_once = -(-len(schemes) // -(-len(schemes) // at_once))  # as many in each turn
    passes = [sorted(schemes)[lo : lo + at_once] for lo in range(0, len(schemes), at_once)]
    kw = {"rank": rank, "lam": lam, "base": base, "m": m, "k": k, "rounds": rounds, "threshold": threshold, "spread": spread, "save": save, "drop": drop}
    errors, last = {}, []

    def half(own: str, factors: DataFrame | None, names: list[str], half_seed: int) -> DataFrame:
        out = _solved(blocks[own], None if factors is None else _dealt(factors, "other"), names, seed=half_seed, start=seed, hot=many[own], **kw)
        return out if many[own] else save(out)

    for names in passes:
        users, items = None, None
        for epoch in range(epochs):
            if users is not None:
                drop(users)
            users = half("user", items, names, seed + 2 * epoch)
            if epoch:
                drop(items)
            items = half("item", users, names, seed + 2 * epoch + 1)
            if each or epoch == epochs - 1:
                errors[epoch] = errors.get(epoch, {}) | errors_by_block(blocks["user"], users, items, base, names, q)
        last.append((_long(users, "user", names, q), _long(items, "item", names, q)))
    clock, trace = dict.fromkeys(schemes, 0.0), []
    for epoch in range(epochs):
        for s in schemes:
            clock[s] += sum(clock_of(s, m, k, reply_delays(rounds, m, seed + 2 * epoch + half)) for half in (0, 1))
            if epoch in errors:
                trace.append({"scheme": s, "epoch": epoch, "train_rmse": errors[epoch].get((s, False)), "test_rmse": errors[epoch].get((s, True)), "clock": clock[s]})
    users, items = (reduce(DataFrame.unionByName, side) for side in zip(*last, strict=True))
    return users, items, trace
