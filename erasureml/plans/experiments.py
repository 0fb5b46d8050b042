"""Queries of the experiments' curves and of the methods' finer points, with SQL where it can follow.

Like in `workloads`, SQL is written from the definitions.  Solvers of few coefficients have recursive SQL over sums by worker.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from erasureml.functions.uniform import normal_np, uniform_np, uniform_sql
from erasureml.operators import baselines, blocks, codes, compare, encode, metrics, partials, solvers, spectrum, stragglers
from erasureml.plans import workloads as base
from erasureml.plans.workloads import CODE, KW, LAM, MW, PW, ROUNDS, SIGN, SMALL, r6, saved
from erasureml.sources import fixtures

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


COLS = [*(f"x{i}" for i in range(PW)), "y"]
SQUARES = [(i, j) for i in range(PW) for j in range(PW)]
GRAM = ", ".join(f"sum(x{i} * x{j}) AS g{i}{j}" for i, j in SQUARES) + ", " + ", ".join(f"sum(x{i} * y) AS c{i}" for i in range(PW)) + ", sum(y * y) AS s"
QUAD = " + ".join(f"o.g{i}{j} * w{i} * w{j}" for i, j in SQUARES) + " - 2 * (" + " + ".join(f"o.c{i} * w{i}" for i in range(PW)) + ") + o.s"
WORKERS = f"SELECT CAST(range // {MW} AS BIGINT) AS t, CAST(range % {MW} AS BIGINT) AS worker FROM range({ROUNDS * MW})"


def _first(seed: int, k: int) -> str:
    return f"SELECT t, worker FROM (SELECT *, row_number() OVER (PARTITION BY t ORDER BY -0.01e0 * ln({uniform_sql('t', 'worker', seed)}), worker) AS r FROM ({WORKERS})) WHERE r <= {k}"


def dot(a: str, b: str) -> str:
    return "(" + " + ".join(f"{a}{i} * {b}{i}" for i in range(PW)) + ")"


# ---------------------------------------------------------------- rounds over data


query("gd_ridge_scanned", base.ORACLES["gd_ridge_coded"])(lambda spark, sf: _scanned(spark, sf))


def _scanned(spark: SparkSession, sf: str) -> DataFrame:
    """The rounds of `gd_ridge_coded` with a Spark job each: encoded rows lie by worker, w goes out, erased workers' files aren't
    read, sums come back by two levels, late replies are never seen."""
    df = fixtures.dense_embeddings(spark, sf, PW)
    n, path = df.count(), base.shared(spark, "by_worker")
    encode.write_by_worker(encode.encode_rows(df, CODE(), MW), path)
    original = partials.whole_gram(df, PW)
    problem = solvers.Problem(None, n, MW, PW, LAM, original)
    active, _ = compare.replies(spark, stragglers.exponential(), ROUNDS, MW, KW, 1)
    w, rows = np.zeros(PW), []
    for t, live in enumerate(active["grad"]):
        here = encode.read_active(spark, path, np.flatnonzero(live).tolist())
        g, _ = partials.ScanPartials(here, MW, PW).total(w, live)
        w = w - base.STEP * (g / n + LAM * w)
        rows.append((t, *map(float, w), problem.objective(w)))
    frame = spark.createDataFrame(rows, "t long, " + ", ".join(f"w{i} double" for i in range(PW)) + ", objective double")
    return frame.select("t", *(r6(f"w{i}").alias(f"w{i}") for i in range(PW)), F.round("objective", 6).alias("objective"))


@query("gd_ridge_race")
def gd_ridge_race(spark: SparkSession, sf: str) -> DataFrame:
    """Rounds as real races: a job a worker in its own thread, the first 3 of 4 count, the last is cancelled by its tag."""
    m, k = 4, 3
    df = fixtures.dense_embeddings(spark, sf, PW)
    n, path = df.count(), base.shared(spark, "by_worker")
    encode.write_by_worker(encode.encode_rows(df, CODE(), m), path)
    original = partials.whole_gram(df, PW)
    problem = solvers.Problem(None, n, m, PW, LAM, original)
    w, rows = np.zeros(PW), []
    for t in range(3):

        def answer(i: int, w: np.ndarray = w) -> np.ndarray:
            return partials.ScanPartials(encode.read_active(spark, path, [i]), m, PW).gradients(w, np.arange(m) == i)[0][i]

        got = compare.wall_clock_round(spark, answer, m, k)
        w = w - base.STEP * (sum(got.values()) * m / len(got) / n + LAM * w)
        rows.append((t, len(got), problem.objective(w)))
    return spark.createDataFrame(rows, "t long, replies long, objective double")


def _lbfgs_sql() -> str:
    n = "(SELECT count(*) FROM embeddings)"
    sums = [f"g{i}{j}" for i, j in SQUARES] + [f"c{i}" for i in range(PW)]

    def total(of: str, name: str) -> str:
        return f"{name} AS (SELECT a.t, count(*) AS many, {', '.join(f'sum({x}) AS {x}' for x in sums)} FROM ({of}) a JOIN p ON a.worker = p.worker GROUP BY a.t)"

    def times(gram: str, v: str, i: int) -> str:
        return "(" + " + ".join(f"{gram}.g{i}{j} * {v}{j}" for j in range(PW)) + ")"

    rng = range(PW)
    one = "SELECT q.t, " + ", ".join(f"w.w{i}" for i in rng) + ", " + ", ".join(f"w.u{i}" for i in rng)
    one += ", " + ", ".join(f"({times('q', 'w.w', i)} - q.c{i}) * ({MW}e0 / {KW} / {n}) + {LAM} * w.w{i} AS g{i}" for i in rng)
    one += ", " + ", ".join(f"coalesce({times('b', 'w.u', i)} * ({MW}e0 / b.many / {n}) + {LAM} * w.u{i}, 0e0) AS r{i}" for i in rng)
    one += ", " + ", ".join(f"l.g{i}{j} AS l{i}{j}" for i, j in SQUARES) + " FROM w JOIN q ON q.t = w.t + 1 JOIN l ON l.t = q.t LEFT JOIN b ON b.t = q.t"
    two = f"SELECT *, CASE WHEN t = 0 THEN 0e0 ELSE {dot('u', 'g')} / {dot('r', 'u')} END AS a FROM ({one})"
    three = "SELECT *, " + ", ".join(f"CASE WHEN t = 0 THEN g{i} ELSE (g{i} - a * r{i}) * {dot('r', 'u')} / {dot('r', 'r')} END AS d{i}" for i in rng) + f" FROM ({two})"
    four = "SELECT * EXCLUDE (d0, d1, d2), " + ", ".join(f"-(CASE WHEN t = 0 THEN d{i} ELSE d{i} + u{i} * (a - {dot('r', 'd')} / {dot('r', 'u')}) END) AS d{i}" for i in rng) + f" FROM ({three})"
    bend = "(" + " + ".join(f"l{i}{j} * d{i} * d{j}" for i, j in SQUARES) + f") * ({MW}e0 / {KW} / {n}) + {LAM} * {dot('d', 'd')}"
    five = f"SELECT *, 0.9e0 * -{dot('d', 'g')} / ({bend}) AS step FROM ({four})"
    return f"""WITH RECURSIVE a AS ({_first(1, KW)}), z AS ({_first(1010, KW)}), e AS ({base._worker_rows('coded')}), p AS (SELECT worker, {GRAM} FROM e GROUP BY worker),
    {total('SELECT * FROM a', 'q')}, {total('SELECT * FROM z', 'l')}, {total('SELECT x.t, x.worker FROM a x JOIN a y ON x.worker = y.worker AND x.t = y.t + 1', 'b')},
    o AS (SELECT {GRAM} FROM ({base._rows_sql()})),
    w AS (SELECT CAST(-1 AS BIGINT) AS t, {', '.join(f'0e0 AS w{i}' for i in rng)}, {', '.join(f'0e0 AS u{i}' for i in rng)}
          UNION ALL SELECT t, {', '.join(f'w{i} + step * d{i} AS w{i}' for i in rng)}, {', '.join(f'step * d{i} AS u{i}' for i in rng)} FROM ({five}))
    SELECT t, round(({QUAD}) / (2 * {n}) + {LAM / 2} * {dot('w', 'w')}, 6) AS objective FROM w CROSS JOIN o WHERE t >= 0"""


@query("lbfgs_ridge_memory_1", _lbfgs_sql())
def lbfgs_ridge_memory_1(spark: SparkSession, sf: str) -> DataFrame:
    """Quasi-Newton steps with one curvature pair, overlaps, exact line search over second replies and back-off 0.9."""
    df = fixtures.dense_embeddings(spark, sf, PW)
    problem = solvers.Problem(partials.GramPartials(encode.encode_rows(df, CODE(), MW), MW, PW), df.count(), MW, PW, LAM, partials.whole_gram(df, PW))
    active, _ = compare.replies(spark, stragglers.exponential(), ROUNDS, MW, KW, 1, ("grad", "line"))
    run = solvers.lbfgs(problem, active["grad"], active["line"], memory=1)
    return spark.createDataFrame(run.trace[["t", "objective"]]).select("t", F.round("objective", 6).alias("objective"))


_PARTS = f"SELECT t, worker % 4 AS part FROM ({_first(1, KW)}) GROUP BY 1, 2"
_REPLICA_SQL = f"""WITH RECURSIVE e AS ({base._rows_sql()}), p AS (SELECT row_id % 4 AS part, {GRAM} FROM e GROUP BY 1), live AS ({_PARTS}),
    q AS (SELECT live.t, 4e0 / count(*) / (SELECT count(*) FROM embeddings) AS f, {', '.join(f'sum({x}) AS {x}' for x in [f'g{i}{j}' for i, j in SQUARES] + [f'c{i}' for i in range(PW)])} FROM live JOIN p ON p.part = live.part GROUP BY live.t),
    o AS (SELECT {GRAM} FROM e),
    w AS (SELECT CAST(-1 AS BIGINT) AS t, {', '.join(f'0e0 AS w{i}' for i in range(PW))}
          UNION ALL SELECT q.t, {', '.join(f"w.w{i} - {base.STEP}e0 * ((" + ' + '.join(f'q.g{i}{j} * w.w{j}' for j in range(PW)) + f" - q.c{i}) * q.f + {LAM} * w.w{i})" for i in range(PW))} FROM w JOIN q ON q.t = w.t + 1)
    SELECT t, round(({QUAD}) / (2 * (SELECT count(*) FROM embeddings)) + {LAM / 2} * {dot('w', 'w')}, 6) AS objective FROM w CROSS JOIN o WHERE t >= 0"""


@query("gd_ridge_first_copies", _REPLICA_SQL)
def gd_ridge_first_copies(spark: SparkSession, sf: str) -> DataFrame:
    """Replication: of a part's two copies the first that comes counts, and parts stand for those that lack both."""
    df = fixtures.dense_embeddings(spark, sf, PW)
    problem, _ = compare.problem_of(df, "replication", MW, PW, LAM)
    active, _ = compare.replies(spark, stragglers.exponential(), ROUNDS, MW, KW, 1)
    run = solvers.gradient_descent(problem, active["grad"], step=base.STEP)
    return spark.createDataFrame(run.trace[["t", "objective"]]).select("t", F.round("objective", 6).alias("objective"))


_W0 = base._W0
_ABSORBED = f"""WITH e AS ({base._worker_rows('coded')}), r AS (SELECT {', '.join(f"sum(x{i} * (" + ' + '.join(f'({w}) * x{j}' for j, w in enumerate(_W0)) + " - y)) AS g" + str(i) for i in range(PW))} FROM e WHERE worker NOT IN (1, 4))
SELECT {', '.join(f'round(g{i} * 8 / 6 + {0.7 * w!r}, 4) + 0e0 AS g{i}' for i, w in enumerate(_W0))} FROM r"""


@query("gradient_absorbed_ridge", _ABSORBED)
def gradient_absorbed_ridge(spark: SparkSession, sf: str) -> DataFrame:
    """The ridge term as rows below the data, which no erasure touches, beside encoded rows of which a quarter is erased."""
    both = encode.absorb_ridge(fixtures.dense_embeddings(spark, sf, PW), 0.7, PW)
    live = np.isin(np.arange(MW), [0, 2, 3, 5, 6, 7])
    g, _ = partials.ScanPartials(encode.encode_rows(both, CODE(), MW), MW, PW).total(np.array(_W0), live)
    return spark.createDataFrame([tuple(map(float, g))], ", ".join(f"g{i} double" for i in range(PW))).select(*((F.round(f"g{i}", 4) + 0.0).alias(f"g{i}") for i in range(PW)))


_NEED = f"""{base.DAYS}, n AS (SELECT max(rank) AS m FROM a), h AS (SELECT x.t, k.range AS was, x.rank AS r, m, sum(CASE WHEN y.rank <= k.range THEN 1 ELSE 0 END) OVER (PARTITION BY x.t, k.range ORDER BY x.rank) AS overlap
        FROM a x LEFT JOIN a y ON x.worker = y.worker AND x.t = y.t + 1 CROSS JOIN n CROSS JOIN range(1, {base.M + 1}) k WHERE k.range <= m),
    f AS (SELECT t, was, coalesce(min(CASE WHEN overlap > m / 2e0 AND r >= 9 THEN r END), max(m)) AS need FROM h GROUP BY 1, 2)"""


@query("adaptive_k_in_order", f"WITH RECURSIVE {_NEED}, k AS (SELECT CAST(0 AS BIGINT) AS t, CAST(9 AS BIGINT) AS k UNION ALL SELECT f.t, f.need FROM k JOIN f ON f.t = k.t + 1 AND f.was = least(k.k, (SELECT m FROM n))) SELECT t, k FROM k")
def adaptive_k_in_order(spark: SparkSession, sf: str) -> DataFrame:
    """The fewest replies that overlap enough with the replies that the round before really used; a round is a recorded day."""
    return spark.createDataFrame(stragglers.adaptive_k_in_order(base.days(spark, sf), 9, 2), "t long, k long").select("t", "k")


# ---------------------------------------------------------------- model parallelism

_C4 = codes.hadamard(4, 2, 1)
_V0 = [0.3, -0.2, 0.5, 0.1, -0.4, 0.2, 0.0, 0.6]
_S4 = np.array(_C4.matrix().tolist(), object)  # plain numbers, as SQL is made of them
_X4 = "SELECT vec_id AS row_id, " + ", ".join(f"8 * CAST(embedding[{k + 1}] AS DOUBLE) AS x{k}" for k in range(4)) + ", CASE WHEN label < 5 THEN 1e0 ELSE -1e0 END AS y FROM embeddings"
_M4, _T4, _K4, _STEP4 = 4, 6, 3, 0.4


def _four(spark: SparkSession, sf: str) -> DataFrame:
    x = F.transform(F.slice("embedding", 1, 4), lambda v: v.cast("double") * fixtures.SCALE)
    return fixtures.table(spark, sf, "embeddings").select(F.col("vec_id").alias("row_id"), x.alias("x"), F.when(F.col("label") < 5, 1.0).otherwise(-1.0).alias("y"))


def _bcd_sql() -> str:
    """v_i moves if its worker (i mod 4) replies: squared loss, lam in w."""
    names = [f"g{i}{j}" for i in range(4) for j in range(4)] + [f"c{i}" for i in range(4)]
    sums = ", ".join([f"sum(x{i} * x{j}) AS g{i}{j}" for i in range(4) for j in range(4)] + [f"sum(x{i} * y) AS c{i}" for i in range(4)] + ["sum(y * y) AS s"])
    w = [" + ".join(f"({_S4[a, i]!r}) * v{a}" for a in range(8)) for i in range(4)]
    grad = [f"(({' + '.join(f'o.g{i}{j} * w{j}' for j in range(4))} - o.c{i}) / n + {LAM} * w{i})" for i in range(4)]
    move = [f"v{a} - CASE WHEN l{a % 4} THEN {_STEP4}e0 * ({' + '.join(f'({_S4[a, i]!r}) * d{i}' for i in range(4))}) ELSE 0e0 END AS v{a}" for a in range(8)]
    grid = f"SELECT CAST(range // {_M4} AS BIGINT) AS t, CAST(range % {_M4} AS BIGINT) AS worker FROM range({_T4 * _M4})"
    live = f"SELECT t, {', '.join(f'bool_or(worker = {i} AND r <= {_K4}) AS l{i}' for i in range(4))} FROM (SELECT *, row_number() OVER (PARTITION BY t ORDER BY -0.01e0 * ln({uniform_sql('t', 'worker', 1)}), worker) AS r FROM ({grid})) GROUP BY t"
    quad = " + ".join(f"o.g{i}{j} * w{i} * w{j}" for i in range(4) for j in range(4)) + " - 2 * (" + " + ".join(f"o.c{i} * w{i}" for i in range(4)) + ") + o.s"
    at = f"SELECT v.*, {', '.join(f'{x} AS w{i}' for i, x in enumerate(w))} FROM v"
    assert names
    return f"""WITH RECURSIVE o AS (SELECT {sums}, count(*) AS n FROM ({_X4})), live AS ({live}),
    v AS (SELECT CAST(0 AS BIGINT) AS t, {', '.join(f'0e0 AS v{a}' for a in range(8))}
          UNION ALL SELECT t + 1, {', '.join(move)} FROM (SELECT x.*, l0, l1, l2, l3, {', '.join(f'{g} AS d{i}' for i, g in enumerate(grad))} FROM ({at}) x CROSS JOIN o JOIN live ON live.t = x.t))
    SELECT t, {', '.join(f'round(w{i}, 6) + 0e0 AS w{i}' for i in range(4))}, round(({quad}) / (2 * n) + {LAM / 2} * (w0 * w0 + w1 * w1 + w2 * w2 + w3 * w3), 6) AS objective FROM ({at}) CROSS JOIN o"""


def _lifted(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame, int]:
    df = _four(spark, sf)
    return saved(encode.encode_columns(df, _C4, _M4, "round_robin").repartition("row_id")), df.select("row_id", "y"), df.count()


@query("bcd_exchange_rounds", _bcd_sql())
def bcd_exchange_rounds(spark: SparkSession, sf: str) -> DataFrame:
    """Lifted blocks by worker, sums exchanged by row, steps committed one round later: t = 0 is the start."""
    lifted, labels, n = _lifted(spark, sf)
    worker = codes.assign(_C4, _M4, "round_robin")
    at = [np.flatnonzero(worker == i) for i in range(_M4)]
    active, _ = compare.replies(spark, stragglers.exponential(), _T4, _M4, _K4, 1)
    gram = partials.whole_gram(_four(spark, sf), 4)
    problem = solvers.Problem(None, n, _M4, 4, LAM, gram)
    states, told, rows = blocks.BlockStates([len(a) for a in at]), None, []
    for t in range(_T4 + 1):
        states.hear(t, told)
        v = np.zeros(8)
        for a, own in zip(at, states.v, strict=True):
            v[a] = own
        w = _C4.apply_t(v)
        rows.append((t, *map(float, w), problem.objective(w)))
        if t < _T4:
            ridge = LAM * _C4.apply(w)
            got = {r["worker"]: np.array(r["g"]) / n + ridge[at[r["worker"]]] for r in blocks.exchange_round(lifted, labels, dict(enumerate(states.v)), blocks.SQUARED).collect()}
            states.reply(got, _STEP4)
            told = active["grad"][t]
    frame = spark.createDataFrame(rows, "t long, w0 double, w1 double, w2 double, w3 double, objective double")
    return frame.select("t", *(r6(f"w{i}").alias(f"w{i}") for i in range(4)), F.round("objective", 6).alias("objective"))


_U4 = [" + ".join(f"({_V0[a]!r}) * (" + " + ".join(f"({_S4[a, j]!r}) * x{j}" for j in range(4)) + ")" for a in range(8))]


def _exchange_sql(slope: str) -> str:
    cells = " UNION ALL ".join(f"SELECT {a % 4} AS worker, {a // 4} AS pos, sum(({' + '.join(f'({_S4[a, j]!r}) * x{j}' for j in range(4))}) * slope) AS g FROM z" for a in range(8))
    return f"WITH z AS (SELECT *, {slope} AS slope FROM (SELECT *, {_U4[0]} AS z FROM ({_X4}))) SELECT CAST(worker AS BIGINT) AS worker, CAST(pos AS BIGINT) AS pos, round(g, 4) + 0e0 AS g FROM ({cells})"


def _exchanged(loss: blocks.Loss):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        lifted, labels, _ = _lifted(spark, sf)
        worker = codes.assign(_C4, _M4, "round_robin")
        v = {i: np.array(_V0)[worker == i] for i in range(_M4)}
        g = blocks.exchange_round(lifted, labels, v, loss).select(F.col("worker").cast("long").alias("worker"), F.posexplode("g").alias("pos", "g"))
        return g.select("worker", F.col("pos").cast("long").alias("pos"), (F.round("g", 4) + 0.0).alias("g"))

    return run


query("bcd_gradients_logistic", _exchange_sql("-y / (1 + exp(y * z))"))(_exchanged(blocks.LOGISTIC))
query("bcd_gradients_squared", _exchange_sql("z - y"))(_exchanged(blocks.SQUARED))
query("bcd_gradients_hinge", _exchange_sql("-y * least(1e0, greatest(0e0, 1 - y * z))"))(_exchanged(blocks.HINGE))


@query("bcd_monotone", "SELECT loss, code, true AS monotone FROM (VALUES ('hinge'), ('logistic'), ('squared')) l(loss) CROSS JOIN (VALUES ('hadamard'), ('steiner'), ('haar'), ('uncoded')) c(code)")
def bcd_monotone(spark: SparkSession, sf: str) -> DataFrame:
    """Whatever replies come, no round raises the objective, for every loss and code (step under 1 / smoothness)."""
    df, rows = saved(_four(spark, sf).select("x", "y")), []
    active, _ = compare.replies(spark, stragglers.exponential(), 5, 4, 2, 1)
    gram = partials.whole_gram(df, 4)
    n = df.count()
    for name, loss in (("hinge", blocks.HINGE), ("logistic", blocks.LOGISTIC), ("squared", blocks.SQUARED)):
        grad = blocks.ScanGradient(df, 4, loss, LAM)
        step = 0.95 / (loss.bend * solvers.largest_eigenvalue(gram.G[0]) / n + LAM)
        for code in ("hadamard", "steiner", "haar", "uncoded"):
            run = blocks.block_coordinate_descent(grad, codes.FAMILIES[code](4, 1), active["grad"], step=step)
            f = run.trace["objective"].to_numpy()
            rows.append((name, code, bool((np.diff(f) <= 1e-12).all())))
    return spark.createDataFrame(rows, "loss string, code string, monotone boolean")


def _sparse(spark: SparkSession, sf: str, p: int) -> DataFrame:
    """(idx, val, y, is_test): tf-idf of a random 69 % of features, hashed to p places, as sparse rows."""
    docs, labels = fixtures.table(spark, sf, "documents"), fixtures.table(spark, sf, "labels")
    return fixtures.sparse_rows(docs, labels, "toxic", p)


def _np_delays(model: str, rounds: int, m: int, seed: int) -> np.ndarray:
    """The delays of the models by numpy, of the same form as those of Spark."""
    t, i = np.arange(rounds)[:, None], np.arange(m)[None, :]
    u = uniform_np(t, i, seed)
    if model == "exponential":
        return -0.01 * np.log(u)
    z = normal_np(t, i, seed)
    if model == "powerlaw":
        tasks = np.minimum(50, np.floor(uniform_np(0, i, seed + 3) ** -2.0))
        return 0.1 * (1 + tasks) * (0.9 + 0.2 * u)
    pick = uniform_np(t, i, seed + 7)
    parts = ((0.5, 0.5, 0.2), (1.0, 20.0, 5.0)) if model == "bimodal" else ((0.8, 0.2, 0.1), (0.9, 0.6, 0.2), (1.0, 1.0, 0.4))
    out, before = np.zeros(pick.shape), 0.0
    for upto, mean, sd in parts:
        out = np.where((pick >= before) & (pick < upto), np.maximum(0.0, mean + sd * z), out)
        before = upto
    return out


def first_replies(delays: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(active, clock) of rounds that wait for k replies."""
    rank = delays.argsort(1, kind="stable").argsort(1, kind="stable")
    return rank < k, np.cumsum(np.sort(delays, 1)[:, k - 1])


def covering_replies(delays: np.ndarray, parts: int) -> tuple[np.ndarray, np.ndarray]:
    """(active, clock) of rounds that wait until every part (worker mod parts) has replied."""
    fastest = delays.reshape(len(delays), -1, parts).min(1)
    until = fastest.max(1)
    return delays <= until[:, None], np.cumsum(until)


def _curves(model: str, k: int):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        """Logistic error over the clock by scheme, 128 workers; one scan a round serves every scheme."""
        p, m, rounds = 1024, 128, 12
        scan = blocks.SparseScan(saved(_sparse(spark, sf, p)), p, blocks.LOGISTIC, 1e-4)
        step = 8.0
        d = _np_delays(model, rounds, m, 1)
        schemes = {"uncoded_all": "uncoded", "uncoded": "uncoded", "replication": "replication", "steiner": "steiner", "haar": "haar", "hadamard": "hadamard"}
        replies = {n: first_replies(d, m if n == "uncoded_all" else k) for n in schemes}
        curves = blocks.side_by_side(scan, schemes, {n: r[0] for n, r in replies.items()}, {n: r[1] for n, r in replies.items()}, step)
        horizon = float(replies["steiner"][1][-1])
        slow = d if model == "bimodal" else _np_delays(model, 8 * rounds, m, 1)
        asynchronous, _ = blocks.async_side(scan, slow, step / 2, min(horizon, float(np.sort(slow.cumsum(0).ravel())[4 * m - 1])))
        whole = pd.concat([curves, asynchronous.assign(name="asynchronous")], ignore_index=True)
        return spark.createDataFrame(whole[["name", "t", "clock", "objective", "train_error", "test_error"]])

    return run


query("logistic_curves_bimodal")(_curves("bimodal", 64))
query("logistic_curves_powerlaw")(_curves("powerlaw", 80))


@query("async_replay", f"""WITH d AS ({base.day_sql(more="CAST(user_id // 16 % 4 AS BIGINT) AS run,")}), h AS (SELECT min(total) AS horizon FROM (SELECT sum(delay) AS total FROM d GROUP BY run, worker)),
    e AS (SELECT *, sum(delay) OVER (PARTITION BY run, worker ORDER BY t) AS done FROM d), f AS (SELECT *, row_number() OVER (PARTITION BY run ORDER BY done, worker, t) AS k FROM e, h WHERE done <= horizon),
    g AS (SELECT run, worker, k - coalesce(lag(k) OVER (PARTITION BY run, worker ORDER BY t), 0) - 1 AS stale FROM f)
    SELECT run, worker, count(*) AS updates, CAST(max(stale) AS BIGINT) AS stalest FROM g GROUP BY 1, 2""")
def async_replay(spark: SparkSession, sf: str) -> DataFrame:
    """Asynchronous runs replayed side by side, a group a run: updates and the largest staleness of every worker.

    The users of events make four runs; a worker is as slow in a round as its recorded day, until the first trace of any run ends."""
    events = fixtures.table(spark, sf, "events").withColumn("run", F.pmod(F.floor(F.col("user_id") / 16), F.lit(4)))
    own = saved(stragglers.loads_by_day(events.withColumn("user_id", F.col("run") * base.M + F.col("user_id") % base.M), 4 * base.M))
    d = own.select(F.floor(F.col("worker") / base.M).alias("run"), "t", F.pmod("worker", F.lit(base.M)).alias("worker"), "delay")
    return metrics.async_replay(d, metrics.shortest(d, "run", "worker"))


# ---------------------------------------------------------------- curves of ridge and LASSO


@query("ridge_curves")
def ridge_curves(spark: SparkSession, sf: str) -> DataFrame:
    """More coefficients than rows (192 x 288), 32 workers, L-BFGS, 20 trials: mean and spread of the last objective over the
    optimum, share of runs over ten times it, and the runtime as a share of waiting for all, by scheme and k."""
    n, p, m, rounds, lam = 192, 288, 32, 20, 0.05
    df = saved(fixtures.gaussian_rows(spark, n, p))
    original, out = partials.whole_gram(df, p), []
    best = solvers.Problem(None, n, m, p, lam, original)
    optimum = best.objective(solvers.ridge_solution(original, n, lam))
    for scheme in ("uncoded", "replication", "hadamard"):
        problem, beta = compare.problem_of(df, scheme, m, p, lam, original=original, n=n)
        for k in (12, 20, 32):
            for trial in range(20 if k < m else 1):
                d = _np_delays("exponential", 2 * rounds, m, 1 + 101 * trial)
                live, _ = first_replies(d, k)
                clock = np.sort(d, 1)[:, k - 1].sum() / d.max(1).sum()
                with np.errstate(all="ignore"):
                    run = solvers.lbfgs(problem, live[:rounds], live[rounds:], beta=beta)
                f = float(run.trace["objective"].iloc[-1]) / optimum
                out.append((scheme, k, f if np.isfinite(f) else 1e12, float(clock)))
    t = spark.createDataFrame(out, "scheme string, k long, ratio double, clock double")
    return t.groupBy("scheme", "k").agg(F.count("*").alias("trials"), F.avg("ratio").alias("mean"), F.coalesce(F.stddev("ratio"), F.lit(0.0)).alias("sd"), F.max("ratio").alias("worst"), F.avg((F.col("ratio") > 10).cast("int")).alias("lost"), F.avg("clock").alias("clock"))


def _lasso(df: DataFrame, true: np.ndarray, lam: float, trials: int = 3) -> list[tuple]:
    """(scheme, k, trial, t, clock, f1, objective) every tenth round; replication waits for one copy of every part."""
    p, m, rounds = len(true), 32, 60
    original, n, out = partials.whole_gram(df, p), df.count(), []
    step = 0.9 / (solvers.largest_eigenvalue(original.G[0]) / n)
    for scheme, k in (("uncoded", 32), ("uncoded", 20), ("replication", 0), ("steiner", 20)):
        problem, beta = compare.problem_of(df, scheme, m, p, lam, original=original, n=n)

        def f1(w: np.ndarray) -> float:
            found = np.abs(w) > 1e-9
            return float(2 * (found & true).sum() / max(found.sum() + true.sum(), 1))

        for trial in range(trials):
            d = _np_delays("trimodal", rounds, m, 1 + 101 * trial)
            live, clock = covering_replies(d, m // 2) if scheme == "replication" else first_replies(d, k)
            run = solvers.proximal_gradient(problem, live, solvers.prox_l1, lambda v: float(np.abs(v).sum()), step=step / (1 if k == 32 or scheme == "replication" else 1.5), clock=clock, beta=beta, record=f1)
            out += [(scheme, k, trial, int(r.t), float(r.clock), float(r.measure), float(r.objective)) for r in run.trace[9::10].itertuples()]
    return out


_LASSO = "scheme string, k long, trial long, t long, clock double, f1 double, objective double"


@query("lasso_curves_generated")
def lasso_curves_generated(spark: SparkSession, sf: str) -> DataFrame:
    """Support recovery over the clock on normal rows (650 x 500, about 38 non-zeros), three trials."""
    p = 500
    df = saved(fixtures.gaussian_rows(spark, 650, p, noise=4.0, sparsity=0.076))
    return spark.createDataFrame(_lasso(df, fixtures.planted(p, 0.076) != 0, 0.3), _LASSO)


@query("lasso_curves_onehot")
def lasso_curves_onehot(spark: SparkSession, sf: str) -> DataFrame:
    """The same on the one-hot design of order lines (brand, type, size, flags), a tenth of whose features matter."""
    df, p = fixtures.onehot_lines(spark, sf)
    return spark.createDataFrame(_lasso(saved(df), fixtures.planted(p, 0.15) != 0, 0.002, 2), _LASSO)


# ---------------------------------------------------------------- codes

_TRIPLES = f"""WITH b AS (SELECT x, y, xor(x, y) AS z, row_number() OVER (ORDER BY x, y) - 1 AS j FROM (SELECT a.range AS x, c.range AS y FROM range(1, 8) a JOIN range(1, 8) c ON a.range < c.range) WHERE xor(x, y) > y),
    u AS (SELECT j, unnest([x, y, z]) - 1 AS pt FROM b), k AS (SELECT j, pt, row_number() OVER (PARTITION BY pt ORDER BY j) AS w FROM u)
    SELECT k.pt * 4 + r.range AS i, k.j, {SIGN.format(a='r.range', b='k.w')} / sqrt(12e0) AS v FROM k CROSS JOIN range(4) r"""
query("code_steiner_triples_gram", base._gram_sql(_TRIPLES, 28))(lambda spark, sf: base.gram_counts(spark, codes.steiner_triples(3)))

_SIGNED = f"SELECT i, j, v * CASE WHEN {uniform_sql('j', '1', 1)} < 0.5e0 THEN -1 ELSE 1 END AS v FROM ({base._HADAMARD})"
query("code_hadamard_signed_gram", base._gram_sql(_SIGNED, 16))(lambda spark, sf: base.gram_counts(spark, codes.hadamard(8, 2, 1, signs=True)))


def _split_sql(size: int) -> str:
    return f"SELECT how, worker, count(DISTINCT j) AS rows FROM (SELECT '{'block' if size == 8 else 'half_block'}' AS how, CAST(i // {size} * 16 // {64 // size} AS BIGINT) AS worker, j FROM ({base._STEINER})) GROUP BY 1, 2"


@query("code_half_blocks", f"{_split_sql(8)} UNION ALL {_split_sql(4)}")
def code_half_blocks(spark: SparkSession, sf: str) -> DataFrame:
    """Source rows that each of 16 workers must hold when Steiner blocks stay whole or are halved."""
    out = None
    for how in ("block", "half_block"):
        c = codes.steiner(8).to_df(spark, 16, how).groupBy(F.lit(how).alias("how"), F.col("worker").cast("long").alias("worker")).agg(F.countDistinct("src_row").alias("rows"))
        out = c if out is None else out.union(c)
    return out


_EMB = base._EMB
_ENERGY = f"(SELECT round(sum(x1 * x1 + x2 * x2), 4) FROM ({_EMB}))"


@query("code_padding_energy", f"SELECT pad, {_ENERGY} AS energy, CAST((n + 19) // 20 * 64 AS BIGINT) AS rows FROM (VALUES ('subsample'), ('zeros')) p(pad) CROSS JOIN (SELECT count(*) AS n FROM embeddings)")
def code_padding_energy(spark: SparkSession, sf: str) -> DataFrame:
    """A code of 28 source rows brought to 20 by choosing columns or by zero rows: lengths are kept, whatever the choice."""
    df, out = fixtures.dense_embeddings(spark, sf, 2), None
    for pad in ("subsample", "zeros"):
        code = codes.fitted(lambda n, seed: codes.hadamard_etf(3), 20, pad)
        e = encode.encode_rows(df, code, 8).agg(F.round(F.sum(F.aggregate("x", F.lit(0.0), lambda a, v: a + v * v)), 4).alias("energy"), F.count("*").alias("rows")).select(F.lit(pad).alias("pad"), "energy", "rows")
        out = e if out is None else out.union(e)
    return out


def _tight(name: str, entries: str) -> str:
    return f"SELECT '{name}' AS code, round(max(abs(g - CASE WHEN j = k THEN 1 ELSE 0 END)), 9) + 0e0 AS off FROM (SELECT a.j, b.j AS k, sum(a.v * b.v) AS g FROM ({entries}) a JOIN ({entries}) b ON a.i = b.i GROUP BY 1, 2)"


@query("code_frame_bounds", " UNION ALL ".join(_tight(n, sql) for n, (_, sql) in SMALL.items()))
def code_frame_bounds(spark: SparkSession, sf: str) -> DataFrame:
    """How far the frame bounds are from beta, that is the extreme eigenvalues of S'S from 1: nothing, for tight frames."""
    rows = [(name, max(abs(b / make().beta - 1) for b in spectrum.frame_bounds(make()))) for name, (make, _) in SMALL.items()]
    return spark.createDataFrame(rows, "code string, off double").select("code", (F.round("off", 9) + 0.0).alias("off"))


def _moments_sql(name: str, entries: str) -> str:
    own = f"SELECT e.*, e.i % 4 AS worker FROM ({entries}) e"
    return f"""SELECT '{name}' AS code, s AS lost, round(sum(CASE WHEN j = k THEN g ELSE 0 END), 6) AS first, round(sum(g * g), 6) AS second
    FROM (SELECT s.range AS s, a.j, b.j AS k, sum(a.v * b.v) AS g FROM ({own}) a JOIN ({own}) b ON a.i = b.i JOIN range(4) s ON a.worker <> s.range GROUP BY 1, 2, 3) GROUP BY s"""


@query("spectrum_moments", " UNION ALL ".join(_moments_sql(n, sql) for n, (_, sql) in SMALL.items()))
def spectrum_moments(spark: SparkSession, sf: str) -> DataFrame:
    """First and second moments of the eigenvalues of what is left when one of four workers is lost."""
    rows = []
    for name, (make, _) in SMALL.items():
        code = make()
        worker = codes.assign(code, 4, "round_robin")
        for lost in range(4):
            e = np.linalg.eigvalsh(spectrum.left_over(code, worker, tuple(i for i in range(4) if i != lost)))
            rows.append((name, lost, float(e.sum()), float((e * e).sum())))
    return spark.createDataFrame(rows, "code string, lost long, first double, second double").select("code", "lost", r6("first").alias("first"), r6("second").alias("second"))


@query("spectra_two_regimes")
def spectra_two_regimes(spark: SparkSession, sf: str) -> DataFrame:
    """Eigenvalues of what is left, in tenths of eta: few replies at redundancy 4 (3 of 8) and many at 2 (6 of 8), n = 96, with
    the share within half of 1."""
    out = None
    families = {
        "few": (3, {"hadamard": codes.hadamard(96, 4), "gaussian": codes.gaussian(96, 4), "haar": codes.haar(96, 4), "dft": codes.dft(96, 4), "steiner_triples": codes.columns_of(codes.steiner_triples(5), 96)}),
        "many": (6, {n: codes.FAMILIES[n](96, 1) for n in ("paley", "hadamard", "steiner", "gaussian", "haar")}),
    }
    for regime, (k, made) in families.items():
        for name, code in made.items():
            s = spectrum.spectrum(spark, code, 8, k, count=10).withColumn("x", F.col("eig") / (k / 8))
            h = s.groupBy(F.lit(regime).alias("regime"), F.lit(name).alias("code"), (F.floor(F.col("x") * 10) / 10).alias("bin")).agg(F.count("*").alias("n"), F.avg(F.col("x").between(0.5, 1.5).cast("int")).alias("within"))
            out = h if out is None else out.unionByName(h)
    return out


@query("erased_convexity", "SELECT code, true AS holds FROM (VALUES ('hadamard'), ('paley'), ('steiner')) c(code)")
def erased_convexity(spark: SparkSession, sf: str) -> DataFrame:
    """What is left after any erasure of 2 of 8 workers is as convex as (1 - eps) times the whole, eps being the code's."""
    df, p, rows = fixtures.dense_embeddings(spark, sf, 8), 8, []
    n, whole = df.count(), partials.whole_gram(df, 8)
    mu = float(np.linalg.eigvalsh(whole.G[0])[0]) / n
    for name in ("hadamard", "paley", "steiner"):
        code = codes.FAMILIES[name](28, 1)
        eps = spectrum.epsilon(code, 8, 6, subsets="all")
        g = partials.GramPartials(encode.encode_rows(df, code, 8), 8, p).G
        low = min(float(np.linalg.eigvalsh(g[list(a)].sum(0))[0]) / n / (6 / 8) for a in spectrum.subsets_of(8, 6, "all"))
        rows.append((name, bool(low + LAM >= (1 - min(eps, 1)) * (mu + LAM) - 1e-9)))
    return spark.createDataFrame(rows, "code string, holds boolean")


@query("bank_sizes", "SELECT n_ratings, CAST((n_ratings + 15) // 16 * 16 AS BIGINT) AS bucket, CAST(power(2, ceil(log2(2 * ((n_ratings + 15) // 16 * 16)))) AS BIGINT) AS rows, CAST(n_ratings AS DOUBLE) AS trace FROM (SELECT DISTINCT count(*) AS n_ratings FROM orders GROUP BY o_custkey)")
def bank_sizes(spark: SparkSession, sf: str) -> DataFrame:
    """What the bank gives for every number of orders that some customer has: bucket, encoded rows and trace of S'S."""
    n = fixtures.table(spark, sf, "orders").groupBy("o_custkey").agg(F.count("*").alias("n_ratings")).select("n_ratings").distinct()

    def look(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        bank = codes.CodeBank("hadamard", 16, 100_000)
        for frame in frames:
            made = [bank.get(int(k)) for k in frame["n_ratings"]]
            yield pd.DataFrame({"n_ratings": frame["n_ratings"], "bucket": [bank.bucket(int(k)) for k in frame["n_ratings"]], "rows": [c.N for c in made], "trace": [float((c.matrix() ** 2).sum()) for c in made]})

    return n.mapInPandas(look, "n_ratings long, bucket long, rows long, trace double").withColumn("trace", r6("trace"))


# ---------------------------------------------------------------- constants, measures, comparators

_G2 = f"SELECT sum(x1 * x1) / count(*) AS a, sum(x1 * x2) / count(*) AS b, sum(x2 * x2) / count(*) AS d FROM ({_EMB})"


@query("data_constants", f"SELECT round((a + d - sqrt((a - d) * (a - d) + 4 * b * b)) / 2, 6) AS low, round((a + d + sqrt((a - d) * (a - d) + 4 * b * b)) / 2, 6) AS high, round((a + d + sqrt((a - d) * (a - d) + 4 * b * b)) / 8, 6) AS logistic FROM ({_G2})")
def data_constants(spark: SparkSession, sf: str) -> DataFrame:
    """Strong convexity, smoothness of the squared loss and of the logistic one."""
    c = baselines.data_spectrum(fixtures.dense_embeddings(spark, sf, 2), 2)
    return spark.createDataFrame([(round(c["low"], 6), round(c["high"], 6), round(c["high"] * blocks.LOGISTIC.bend, 6))], "low double, high double, logistic double")


@query("bound_of_a_run", "SELECT CAST(range AS BIGINT) AS t, true AS holds FROM range(20)")
def bound_of_a_run(spark: SparkSession, sf: str) -> DataFrame:
    """Gradient descent with constants measured on the data and the code: no round is over the bound."""
    df, p, m, k = fixtures.dense_embeddings(spark, sf, 8, noise=4.0), 8, 8, 6
    problem, _ = compare.problem_of(df, "hadamard_etf", m, p, LAM, group=28)
    eps = spectrum.epsilon(codes.hadamard_etf(3), m, k, subsets="all")
    active, _ = compare.replies(spark, stragglers.exponential(), 20, m, k, 1)
    c, step = baselines.data_spectrum(df, p), solvers.gradient_step(problem, eps)
    run = solvers.gradient_descent(problem, active["grad"], step=step)
    best, f0 = problem.objective(solvers.ridge_solution(problem.original, problem.n, LAM)), problem.objective(np.zeros(p))
    kappa = (1 + eps) / max(1 - eps, 1e-9)
    rows = []
    for t, f in zip(run.trace["t"], run.trace["objective"], strict=True):
        rate = max(0.0, 1 - 0.5 * step * (1 - eps) * (c["low"] + LAM))
        rows.append((int(t), bool(f <= kappa**2 * (rate ** (t + 1) * f0 + best) + 1e-9)))
    return spark.createDataFrame(rows, "t long, holds boolean")


@query("storage_measured", f"SELECT code, CAST(n // rows * total + CASE WHEN n % rows > 0 THEN total ELSE 0 END AS BIGINT) AS stored, n FROM (SELECT count(*) AS n FROM embeddings) CROSS JOIN (VALUES ('hadamard_etf', 28, 64), ('steiner', 28, 64), ('haar', 8, 16)) c(code, rows, total)")
def storage_measured(spark: SparkSession, sf: str) -> DataFrame:
    """Encoded rows that are really made, against the rows of the table."""
    df, out = fixtures.dense_embeddings(spark, sf, 2), None
    for name in ("hadamard_etf", "steiner", "haar"):
        e = encode.encode_rows(df, SMALL[name][0](), 8).agg(F.count("*").alias("stored")).select(F.lit(name).alias("code"), "stored")
        out = e if out is None else out.union(e)
    return out.crossJoin(F.broadcast(df.agg(F.count("*").alias("n"))))


@query("communication_counted", f"SELECT CAST(range AS BIGINT) AS worker, CAST({PW + 1} AS BIGINT) AS numbers FROM range({MW}) WHERE range NOT IN (1, 4)")
def communication_counted(spark: SparkSession, sf: str) -> DataFrame:
    """The numbers that each active worker's answer holds in one round, counted in what is sent."""
    enc = encode.encode_rows(fixtures.dense_embeddings(spark, sf, PW), CODE(), MW).where(~F.col("worker").isin(1, 4))
    sums = partials._accumulated(enc, lambda x, y: np.append(x.T @ (x @ np.array(_W0) - y), ((x @ np.array(_W0) - y) ** 2).sum()))
    return sums.groupBy(F.col("worker").cast("long").alias("worker")).agg(F.max(F.size("sums")).cast("long").alias("numbers"))


@query("speculation_replayed", f"""WITH a AS (SELECT *, row_number() OVER (PARTITION BY t ORDER BY delay, worker) AS r FROM (SELECT t, worker, {base.DELAY_SQL['exponential']} AS delay FROM ({base.GRID}))),
    l AS (SELECT t, delay AS at FROM a WHERE r = 12), s AS (SELECT a.t, a.delay, CASE WHEN a.delay > l.at THEN least(a.delay, l.at - 0.01e0 * ln({uniform_sql('a.t', 'a.worker', 78)})) ELSE a.delay END AS again FROM a JOIN l ON a.t = l.t)
    SELECT t, round(max(delay), 6) AS plain, round(max(again), 6) AS speculated FROM s GROUP BY t""")
def speculation_replayed(spark: SparkSession, sf: str) -> DataFrame:
    """Rounds that wait for all, when a second copy of every task starts as three quarters have replied."""
    d = stragglers.delays(spark, stragglers.exponential(), base.T, base.M)
    s = baselines.speculated_after(d, 12, 1, 0.01)
    both = d.join(s.withColumnRenamed("delay", "again"), ["t", "phase", "worker"])
    return both.groupBy(F.col("t").cast("long").alias("t")).agg(F.round(F.max("delay"), 6).alias("plain"), F.round(F.max("again"), 6).alias("speculated"))


@query("task_delays_recorded")
def task_delays_recorded(spark: SparkSession, sf: str) -> DataFrame:
    """Seconds that every worker's part of a gradient takes here, recorded in its task, and the first 6 of 8 of every round."""
    enc = saved(encode.encode_rows(fixtures.dense_embeddings(spark, sf, PW), CODE(), MW).repartition(MW, "worker"))

    def round_of(t: int):
        def timed(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for frame in frames:
                for worker, own in frame.groupby("worker"):
                    began = time.perf_counter()
                    x = encode.stacked(own["x"])
                    g = x.T @ (x @ (np.array(_W0) / (t + 1)) - own["y"].to_numpy())
                    yield pd.DataFrame({"worker": [int(worker)], "delay": [time.perf_counter() - began + 0 * float(g.sum())]})

        return timed

    out = None
    for t in range(3):
        d = enc.select("worker", "x", "y").mapInPandas(round_of(t), "worker int, delay double").groupBy("worker").agg(F.sum("delay").alias("delay")).select(F.lit(t).alias("t"), F.lit("grad").alias("phase"), "worker", "delay")
        out = d if out is None else out.unionByName(d)
    return stragglers.first_k(saved(out), KW).select("t", "worker", "delay", "rank", "active")


_SOLVED = "g AS (SELECT sum(x1 * x1) / count(*) + 0.05e0 AS a, sum(x1 * x2) / count(*) AS b, sum(x2 * x2) / count(*) + 0.05e0 AS d, sum(x1 * y) / count(*) AS p, sum(x2 * y) / count(*) AS q FROM o)"
_P2 = fixtures.planted(2)
_ROWS2 = f"SELECT *, ({float(_P2[0])!r}) * x1 + ({float(_P2[1])!r}) * x2 + ({uniform_sql('row_id', '1', fixtures.NOISE_SEED)} - 0.5e0) * 2 AS y FROM ({_EMB})"


@query("library_ridge", f"WITH o AS ({_ROWS2}), {_SOLVED} SELECT CAST(floor(100 * (d * p - b * q) / (a * d - b * b) + 0.5) AS BIGINT) AS w0, CAST(floor(100 * (a * q - b * p) / (a * d - b * b) + 0.5) AS BIGINT) AS w1 FROM g")
def library_ridge(spark: SparkSession, sf: str) -> DataFrame:
    """Spark's own linear regression as a comparator: the ridge solution by normal equations, in hundredths."""
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.regression import LinearRegression

    df = fixtures.dense_embeddings(spark, sf, 2).select(array_to_vector("x").alias("features"), F.col("y").alias("label"))
    # the library scales the penalty with the label's deviation; undone by scaling the label to deviation 1
    sd = float(df.agg(F.stddev("label")).first()[0])
    model = LinearRegression(regParam=LAM, fitIntercept=False, standardization=False, solver="normal").fit(df.withColumn("label", F.col("label") / sd))
    return spark.createDataFrame([tuple(int(np.floor(100 * float(v) * sd + 0.5)) for v in model.coefficients)], "w0 long, w1 long")


@query("library_factorisation")
def library_factorisation(spark: SparkSession, sf: str) -> DataFrame:
    """Spark's own alternating least squares on the ratings less 3, rank 15."""
    from pyspark.ml.recommendation import ALS

    r = saved(fixtures.ratings_planted(spark, sf)).select(F.col("user").cast("int").alias("user"), F.col("item").cast("int").alias("item"), (F.col("rating") - 3).cast("float").alias("rating"), "is_test")
    model = ALS(rank=15, maxIter=5, regParam=0.5, userCol="user", itemCol="item", ratingCol="rating", coldStartStrategy="nan", seed=1).fit(r.where(~F.col("is_test")))
    guess = model.transform(r).withColumn("guess", F.when(F.isnan("prediction"), 0.0).otherwise(F.col("prediction")))
    return guess.groupBy("is_test").agg(F.sqrt(F.avg(F.pow(F.col("rating") - F.col("guess"), 2))).alias("rmse"))


@query("library_logistic")
def library_logistic(spark: SparkSession, sf: str) -> DataFrame:
    """Spark's own logistic regression on the sparse text features: error by split."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.linalg import Vectors, VectorUDT

    p = 1024
    vector = F.udf(lambda i, v: Vectors.sparse(p, sorted(zip(i, v, strict=True))), VectorUDT())
    df = saved(_sparse(spark, sf, p)).select(vector("idx", "val").alias("features"), (F.col("y") > 0).cast("double").alias("label"), "is_test")
    model = LogisticRegression(regParam=1e-4, fitIntercept=False, standardization=False, maxIter=50).fit(df.where(~F.col("is_test")))
    return model.transform(df).groupBy("is_test").agg(F.avg((F.col("prediction") != F.col("label")).cast("int")).alias("error"), F.count("*").alias("n"))


@query("udf_vec_sum", f"SELECT l, round(sum(x1), 4) + 0e0 AS s0, round(sum(x2), 4) + 0e0 AS s1 FROM (SELECT e.*, m.label AS l FROM ({_EMB}) e JOIN embeddings m ON m.vec_id = e.row_id) GROUP BY l")
def udf_vec_sum(spark: SparkSession, sf: str) -> DataFrame:
    """Element-wise sums of arrays by group, with the grouped aggregate."""
    from erasureml.functions.transforms import vec_sum

    df = fixtures.dense_embeddings(spark, sf, 2).join(fixtures.table(spark, sf, "embeddings").select(F.col("vec_id").alias("row_id"), F.col("label").alias("l")), "row_id")
    s = df.groupBy("l").agg(vec_sum()("x").alias("s"))
    return s.select("l", (F.round(F.col("s")[0], 4) + 0.0).alias("s0"), (F.round(F.col("s")[1], 4) + 0.0).alias("s1"))


@query("udf_gram", f"SELECT l, round(sum(x1 * x1), 4) AS a, round(sum(x1 * x2), 4) + 0e0 AS b, round(sum(x2 * x2), 4) AS d FROM (SELECT e.*, m.label AS l FROM ({_EMB}) e JOIN embeddings m ON m.vec_id = e.row_id) GROUP BY l")
def udf_gram(spark: SparkSession, sf: str) -> DataFrame:
    """Inner products of columns by group, with the grouped aggregate (row by row of the matrix)."""
    from erasureml.functions.transforms import gram

    df = fixtures.dense_embeddings(spark, sf, 2).join(fixtures.table(spark, sf, "embeddings").select(F.col("vec_id").alias("row_id"), F.col("label").alias("l")), "row_id")
    s = df.groupBy("l").agg(gram()("x").alias("s"))
    return s.select("l", F.round(F.col("s")[0], 4).alias("a"), (F.round(F.col("s")[1], 4) + 0.0).alias("b"), F.round(F.col("s")[3], 4).alias("d"))


@query("stream_late_replies", "SELECT CAST(dayofyear(ts) AS INTEGER) AS t, count(*) AS replies, CAST(greatest(0, count(*) - 4) AS BIGINT) AS late FROM events GROUP BY 1")
def stream_late_replies(spark: SparkSession, sf: str) -> DataFrame:
    """A stream of replies: how many come to each round, and how many are over the first four and dropped."""
    from erasureml.streaming import rounds

    return rounds.finished(rounds.late_replies(rounds.replies(rounds.source(spark, sf), 8), 4), "complete")
