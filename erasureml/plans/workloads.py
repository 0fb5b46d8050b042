"""Workload queries: codes, encodings, delays, solvers, factorisation and measures, with their SQL.

SQL here is written from the definitions, not from the DataFrame plans.  Values are rounded to 6 places, whole numbers
are BIGINT.  Iterative solvers of few coefficients have recursive SQL over sums by worker; the others are rows-only and
are held against numpy in the tests.
"""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from erasureml.functions.uniform import uniform, uniform_np, uniform_sql
from erasureml.operators import baselines, blocks, codes, compare, encode, factorization, metrics, partials, solvers, spectrum, stragglers
from erasureml.sources import fixtures
from erasureml.streaming.rounds import shared

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def r6(c: Column | str) -> Column:
    return F.round(c, 6) + 0.0


def saved(df: DataFrame) -> DataFrame:
    """A table in the shared folder, read again."""
    path = shared(df.sparkSession, "saved")
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def spooled(df: DataFrame) -> DataFrame:
    """`saved`, with the shuffle files of its plan cleared: Spark gives them up at the second of two collections a moment apart."""
    out = saved(df)
    for _ in range(2):
        time.sleep(0.2)
        df.sparkSession._jvm.System.gc()
    return out


def dropped(df: DataFrame) -> None:
    """Delete a table that `saved` wrote, and let Spark clear the shuffle files of plans that are gone."""
    jvm, conf = df.sparkSession._jvm, df.sparkSession._jsc.hadoopConfiguration()
    for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        at = jvm.org.apache.hadoop.fs.Path(path)
        if at.getName().startswith("saved-"):
            at.getFileSystem(conf).delete(at, True)
    jvm.System.gc()


# ---------------------------------------------------------------- codes


def gram_counts(spark: SparkSession, code: codes.Code) -> DataFrame:
    """How often which magnitude of inner product of two encoding rows occurs."""
    c = code.to_df(spark, 1, "contiguous")
    other = c.select(F.col("enc_row").alias("b"), "src_row", F.col("coef").alias("coef_b"))
    g = c.join(other, "src_row").groupBy("enc_row", "b").agg(F.abs(F.round(F.sum(F.col("coef") * F.col("coef_b")), 6)).alias("value"))
    out = g.groupBy((F.col("enc_row") == F.col("b")).alias("own"), "value").agg(F.count("*").alias("n"))
    total = F.when(F.col("own"), code.N).otherwise(code.N * (code.N - 1))
    missing = out.groupBy("own").agg(F.sum("n").alias("n")).select("own", F.lit(0.0).alias("value"), (total - F.col("n")).cast("long").alias("n")).where("n > 0")
    return out.unionByName(missing).groupBy("own", "value").agg(F.sum("n").alias("n"))


def _gram_sql(entries: str, size: int) -> str:
    """entries: SQL of (i, j, v), all pairs or the non-zero ones."""
    return f"""WITH e AS ({entries}), z AS (SELECT range AS i FROM range({size})),
    g AS (SELECT a.i AS i, b.i AS k, sum(a.v * b.v) AS v FROM e a JOIN e b ON a.j = b.j GROUP BY 1, 2),
    f AS (SELECT x.i = y.i AS own, abs(round(coalesce(g.v, 0), 6)) + 0e0 AS value FROM z x CROSS JOIN z y LEFT JOIN g ON g.i = x.i AND g.k = y.i)
    SELECT own, CAST(value AS DOUBLE) AS value, count(*) AS n FROM f GROUP BY 1, 2"""


def _chosen(size: int, n: int, seed: int) -> str:
    """SQL of (j, c): columns chosen by draw, in order."""
    return f"""SELECT row_number() OVER (ORDER BY c) - 1 AS j, c FROM (SELECT range AS c, row_number() OVER (ORDER BY {uniform_sql('range', '0', seed)}, range) AS k FROM range({size})) WHERE k <= {n}"""


SIGN = "(1 - 2 * (CAST(bit_count(CAST({a} AS BIGINT) & CAST({b} AS BIGINT)) AS BIGINT) % 2))"
_HADAMARD = f"SELECT r.range AS i, c.j, {SIGN.format(a='r.range', b='c.c')} / sqrt(16e0) AS v FROM range(16) r CROSS JOIN ({_chosen(16, 8, 1)}) c"
_ETF = f"""SELECT r.range AS i, c.range AS j, {SIGN.format(a='r.range', b='c.range')} / sqrt(64e0) AS v FROM range(64) r CROSS JOIN range(64) c
WHERE (CASE WHEN c.range % 4 = 0 THEN 1 ELSE 0 END + CASE WHEN c.range // 4 % 4 = 0 THEN 1 ELSE 0 END + CASE WHEN c.range // 16 = 0 THEN 1 ELSE 0 END) % 2 = 1"""
_STEINER = f"""SELECT p.pt * 8 + r.range AS i, p.j, {SIGN.format(a='r.range', b='p.w')} / sqrt(16e0) AS v
FROM (SELECT j, pt, row_number() OVER (PARTITION BY pt ORDER BY j) AS w FROM (
        SELECT j, unnest([a, b]) AS pt FROM (SELECT a.range AS a, b.range AS b, row_number() OVER (ORDER BY a.range, b.range) - 1 AS j
        FROM range(8) a JOIN range(8) b ON a.range < b.range))) p CROSS JOIN range(8) r"""
_HAAR = f"""SELECT i, j, CASE WHEN i = 0 THEN 0.25e0 WHEN (c >> (4 - l)) = i - (1 << l) THEN power(2e0, (l - 4) / 2e0) * (1 - 2 * ((c >> (3 - l)) & 1)) ELSE 0e0 END AS v
FROM (SELECT r.range AS i, c.j, c.c, CAST(floor(log2(greatest(r.range, 1))) AS BIGINT) AS l FROM range(16) r CROSS JOIN ({_chosen(16, 8, 1)}) c)"""
_PALEY = """WITH res AS (SELECT a, row_number() OVER (ORDER BY a) - 1 AS k FROM (SELECT DISTINCT x.range * x.range % 13 AS a FROM range(1, 13) x) WHERE a < 13 - a)
SELECT r.range AS i, 2 * k + s.range AS j, CASE WHEN r.range = 0 THEN 0e0 WHEN s.range = 0 THEN sqrt(2e0 / 13) * cos(2 * pi() * a * (r.range - 1) / 13) ELSE sqrt(2e0 / 13) * sin(2 * pi() * a * (r.range - 1) / 13) END AS v
FROM range(14) r CROSS JOIN res CROSS JOIN range(2) s
UNION ALL SELECT range, 6, CASE WHEN range = 0 THEN sqrt(13e0) ELSE 1e0 END / sqrt(26e0) FROM range(14)"""
SMALL = {
    "hadamard": (lambda: codes.hadamard(8, 2, 1), _HADAMARD), "hadamard_etf": (lambda: codes.hadamard_etf(3), _ETF), "steiner": (lambda: codes.steiner(8), _STEINER),
    "haar": (lambda: codes.haar(8, 2, 1), _HAAR), "paley": (lambda: codes.paley(13), _PALEY),
}
for _name, (_make, _sql) in SMALL.items():
    query(f"code_{_name}_gram", _gram_sql(_sql, _make().N))(lambda spark, sf, make=_make: gram_counts(spark, make()))


@query("code_welch_check")
def code_welch_check(spark: SparkSession, sf: str) -> DataFrame:
    rows = []
    for name, (make, _) in SMALL.items():
        c = make()
        rows.append((name, c.n, c.N, spectrum.coherence(c), spectrum.welch_bound(c.n, c.beta), spectrum.is_etf(c)))
    return spark.createDataFrame(rows, "code string, n long, rows long, coherence double, welch double, equiangular boolean")


for _name, _size in (("steiner", 64), ("haar", 16)):
    _sql = SMALL[_name][1]
    query(
        f"code_{_name}_support",
        f"WITH e AS ({_sql}) SELECT CAST(i * 4 // {_size} AS BIGINT) AS worker, count(DISTINCT j) AS rows FROM e WHERE v <> 0 GROUP BY 1",
    )(lambda spark, sf, make=SMALL[_name][0]: make().to_df(spark, 4, "contiguous").groupBy(F.col("worker").cast("long").alias("worker")).agg(F.countDistinct("src_row").alias("rows")))


@query("code_support_overhead")
def code_support_overhead(spark: SparkSession, sf: str) -> DataFrame:
    """Uncoded rows a worker must hold, over n/m, and the bounds: twice for pairs, beta log2 n for Haar."""
    rows = []
    for name, code, bound in (("steiner", codes.steiner(16), 2.0), ("haar", codes.haar(128, 2, 1), 2 * np.log2(128)), ("replication", codes.replication(128), 2.0), ("uncoded", codes.identity(128), 1.0)):
        for how in ("contiguous", "scatter"):
            rows += [(name, how, int(r.worker), int(r.rows), float(r.ratio), float(bound)) for r in spectrum.support_overhead(code, 8, how).itertuples()]
    return spark.createDataFrame(rows, "code string, how string, worker long, rows long, ratio double, bound double")


@query("code_replication_map", "SELECT CAST(w.range AS BIGINT) AS worker, CAST(w.range % 6 AS BIGINT) AS part, count(*) AS rows FROM range(12) w JOIN embeddings e ON e.vec_id % 6 = w.range % 6 GROUP BY 1, 2")
def code_replication_map(spark: SparkSession, sf: str) -> DataFrame:
    df = fixtures.dense_embeddings(spark, sf, 2)
    return encode.replicate(df, 12, 2).groupBy(F.col("worker").cast("long").alias("worker"), F.col("part").cast("long").alias("part")).agg(F.count("*").alias("rows"))


@query("code_assign_roundrobin", "SELECT CAST(range % 12 AS BIGINT) AS worker, count(*) AS rows FROM range(64) GROUP BY 1")
def code_assign_roundrobin(spark: SparkSession, sf: str) -> DataFrame:
    c = codes.steiner(8).to_df(spark, 12, "round_robin").select("enc_row", "worker").distinct()
    return c.groupBy(F.col("worker").cast("long").alias("worker")).agg(F.count("*").alias("rows"))


@query("code_bank_lookup", "SELECT n_ratings, count(*) AS users, CAST((n_ratings + 15) // 16 * 16 AS BIGINT) AS bucket FROM (SELECT o_custkey, count(*) AS n_ratings FROM orders GROUP BY 1) GROUP BY 1, 3")
def code_bank_lookup(spark: SparkSession, sf: str) -> DataFrame:
    n = fixtures.table(spark, sf, "orders").groupBy("o_custkey").agg(F.count("*").alias("n_ratings"))
    return n.groupBy("n_ratings").agg(F.count("*").alias("users")).withColumn("bucket", (F.ceil(F.col("n_ratings") / 16) * 16).cast("long"))


@query("code_encoding_cost")
def code_encoding_cost(spark: SparkSession, sf: str) -> DataFrame:
    """Non-zeros, operations, bytes and storage factor of every family by n."""
    rows = []
    for n in (32, 64, 128):
        for name, make in codes.FAMILIES.items():
            cost = spectrum.encoding_cost(make(n, 1), 64)
            rows.append((name, n, *map(float, cost.values())))
    return spark.createDataFrame(rows, "code string, n long, nnz double, flops double, bytes double, factor double")


# ---------------------------------------------------------------- encoding

_GROUPED = f"""WITH s AS ({{entries}}), o AS ({{rows}}),
e AS (SELECT o.row_id // {{n}} * {{N}} + s.i AS enc_row, {{sums}} FROM o JOIN s ON o.row_id % {{n}} = s.j GROUP BY 1)"""


@query(
    "encode_rows_hadamard_orders",
    _GROUPED.format(entries=_HADAMARD.replace("/ sqrt(16e0)", ""), n=8, N=16, sums="CAST(sum(s.v * f1) AS BIGINT) AS f1, CAST(sum(s.v * f2) AS BIGINT) AS f2, CAST(sum(s.v * f3) AS BIGINT) AS f3, CAST(sum(s.v * y) AS BIGINT) AS y",
        rows="SELECT o_orderkey AS row_id, CAST(substr(o_orderpriority, 1, 1) AS BIGINT) AS f1, month(o_orderdate) AS f2, o_custkey % 10 AS f3, CAST(round(o_totalprice * 100) AS BIGINT) AS y FROM orders")
    + " SELECT enc_row, f1, f2, f3, y FROM e",
)
def encode_rows_hadamard_orders(spark: SparkSession, sf: str) -> DataFrame:
    """Signed sums of whole numbers, exact in any order."""
    df = fixtures.int_orders(spark, sf).select("row_id", F.transform("f", lambda v: v.cast("double")).alias("x"), F.col("y").cast("double").alias("y"))
    e = encode.encode_rows(df, codes.hadamard(8, 2, 1), 8)
    whole = [F.round(F.col("x")[k] * 4).cast("long").alias(f"f{k + 1}") for k in range(3)]
    return e.select("enc_row", *whole, F.round(F.col("y") * 4).cast("long").alias("y"))


_EMB = "SELECT vec_id AS row_id, 8 * CAST(embedding[1] AS DOUBLE) AS x1, 8 * CAST(embedding[2] AS DOUBLE) AS x2 FROM embeddings"
for _name in ("steiner", "haar"):  # the SQL of pairs has their non-zero entries only, so no row where all terms are missing
    _c = SMALL[_name][0]()
    query(
        f"encode_rows_{_name}_embeddings",
        _GROUPED.format(entries=SMALL[_name][1], n=_c.n, N=_c.N, sums="sum(s.v * x1) AS x1, sum(s.v * x2) AS x2", rows=_EMB)
        + " SELECT CAST(enc_row AS BIGINT) AS enc_row, round(x1, 6) + 0e0 AS x1, round(x2, 6) + 0e0 AS x2 FROM e",
    )(lambda spark, sf, make=SMALL[_name][0], untouched=_name == "haar": encode.encode_rows(fixtures.dense_embeddings(spark, sf, 2), make(), 4, untouched=untouched).select("enc_row", r6(F.col("x")[0]).alias("x1"), r6(F.col("x")[1]).alias("x2")))


@query(
    "encode_cols_hadamard_embeddings",
    f"WITH s AS ({_HADAMARD}), x AS (SELECT vec_id AS row_id, unnest(range(8)) AS j, unnest(list_transform(embedding[1:8], lambda v: 8 * CAST(v AS DOUBLE))) AS v FROM embeddings) "
    "SELECT row_id, CAST(s.i % 4 AS BIGINT) AS worker, round(sum((x.v * s.v) * (x.v * s.v)), 6) + 0e0 AS diag, round(sum(x.v * s.v), 6) + 0e0 AS total FROM x JOIN s ON x.j = s.j GROUP BY 1, 2",
)
def encode_cols_hadamard_embeddings(spark: SparkSession, sf: str) -> DataFrame:
    """Sums over lifted feature blocks by row and worker."""
    df = fixtures.dense_embeddings(spark, sf, 8)
    e = encode.encode_columns(df, codes.hadamard(8, 2, 1), 4, "round_robin")
    s = codes.hadamard(8, 2, 1).to_df(spark, 4, "round_robin").select("worker", "src_row", F.col("coef") * F.col("coef")).toDF("worker", "src_row", "sq")
    diag = df.select("row_id", F.posexplode("x").alias("src_row", "v")).join(F.broadcast(s), "src_row").groupBy("row_id", "worker").agg(F.sum(F.col("v") * F.col("v") * F.col("sq")).alias("diag"))
    total = e.select("row_id", "worker", F.aggregate("xblk", F.lit(0.0), lambda a, v: a + v).alias("total"))
    return diag.join(total, ["row_id", "worker"]).select("row_id", F.col("worker").cast("long").alias("worker"), r6("diag").alias("diag"), r6("total").alias("total"))


@query("encode_energy_preserved", "SELECT round(sum(x1 * x1 + x2 * x2), 4) AS energy, count(*) AS rows FROM (" + _EMB + ")")
def encode_energy_preserved(spark: SparkSession, sf: str) -> DataFrame:
    """The squared length of encoded features is that of the rows: S'S = I, whatever the code."""
    df = fixtures.dense_embeddings(spark, sf, 2)
    e = encode.encode_rows(df, codes.hadamard_etf(3), 8)
    return e.agg(F.round(F.sum(F.aggregate("x", F.lit(0.0), lambda a, v: a + v * v)), 4).alias("energy")).crossJoin(F.broadcast(df.agg(F.count("*").alias("rows"))))


# ---------------------------------------------------------------- delays and waiting

T, M = 40, 16


def _u(seed: int) -> str:
    return uniform_sql("t", "worker", seed)


def _z(seed: int) -> str:
    return f"sqrt(-2 * ln({_u(seed)})) * cos(2 * pi() * {uniform_sql('t', 'worker', seed + 500009)})"


GRID = f"SELECT CAST(range // {M} AS BIGINT) AS t, CAST(range % {M} AS BIGINT) AS worker FROM range({T * M})"
DELAY_SQL = {
    "exponential": f"-0.01e0 * ln({_u(1)})",
    "bimodal": f"CASE WHEN {_u(8)} < 0.5e0 THEN greatest(0e0, 0.5e0 + 0.2e0 * ({_z(1)})) ELSE greatest(0e0, 20e0 + 5e0 * ({_z(1)})) END",
    "trimodal": f"CASE WHEN {_u(8)} < 0.8e0 THEN greatest(0e0, 0.2e0 + 0.1e0 * ({_z(1)})) WHEN {_u(8)} < 0.9e0 THEN greatest(0e0, 0.6e0 + 0.2e0 * ({_z(1)})) ELSE greatest(0e0, 1e0 + 0.4e0 * ({_z(1)})) END",
    "powerlaw": f"0.1e0 * (1 + least(50, floor(power({uniform_sql('0', 'worker', 4)}, -2e0)))) * (0.9e0 + 0.2e0 * {_u(1)})",
}
MODELS = {"exponential": stragglers.exponential(), "bimodal": stragglers.BIMODAL, "trimodal": stragglers.TRIMODAL, "powerlaw": stragglers.background_power_law()}
for _name, _sql in DELAY_SQL.items():
    query(f"delay_{_name}", f"SELECT t, worker, round({_sql}, 6) + 0e0 AS delay FROM ({GRID})")(
        lambda spark, sf, model=MODELS[_name]: stragglers.delays(spark, model, T, M).select(F.col("t").cast("long").alias("t"), F.col("worker").cast("long").alias("worker"), r6("delay").alias("delay"))
    )

TRACE = f"SELECT row_number() OVER (PARTITION BY user_id % {M} ORDER BY event_id) - 1 AS t, CAST(user_id % {M} AS BIGINT) AS worker, value AS delay FROM events"
D = f"d AS (SELECT t, worker, {DELAY_SQL['exponential']} AS delay FROM ({GRID})), a AS (SELECT *, row_number() OVER (PARTITION BY t ORDER BY delay, worker) AS rank FROM d)"


def day_sql(m: int = M, more: str = "") -> str:
    """SQL of (t, worker, delay) by recorded days, in hundredths; more: further keys."""
    return f"""SELECT CAST(dense_rank() OVER (ORDER BY day) - 1 AS BIGINT) AS t, * EXCLUDE (day) FROM (SELECT date_diff('day', DATE '1970-01-01', CAST(ts AS DATE)) AS day, CAST(user_id % {m} AS BIGINT) AS worker, {more}
    CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS delay FROM events GROUP BY ALL)"""


def days(spark: SparkSession, sf: str, m: int = M) -> DataFrame:
    return stragglers.loads_by_day(fixtures.table(spark, sf, "events"), m)


DAYS = f"d AS ({day_sql()}), a AS (SELECT *, row_number() OVER (PARTITION BY t ORDER BY delay, worker) AS rank FROM d)"


def _delays(spark: SparkSession) -> DataFrame:
    return stragglers.delays(spark, MODELS["exponential"], T, M)


def _long(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({n: F.col(n).cast("long") for n in names})


@query("delay_trace_events", f"SELECT t, worker, delay FROM ({TRACE})")
def delay_trace_events(spark: SparkSession, sf: str) -> DataFrame:
    return _long(stragglers.delays_from_events(fixtures.table(spark, sf, "events"), M), "t", "worker").select("t", "worker", "delay")


@query("first_k_active", f"WITH {D} SELECT t, worker, rank, rank <= 10 AS active FROM a")
def first_k_active(spark: SparkSession, sf: str) -> DataFrame:
    return _long(stragglers.first_k(_delays(spark), 10), "t", "worker", "rank").select("t", "worker", "rank", "active")


@query("active_overlap", f"WITH {DAYS}, k AS (SELECT t, worker FROM a WHERE rank <= 10) SELECT x.t, count(*) AS overlap FROM k x JOIN k y ON x.worker = y.worker AND x.t = y.t + 1 GROUP BY 1")
def active_overlap(spark: SparkSession, sf: str) -> DataFrame:
    a = stragglers.first_k(days(spark, sf), 10).where("active").select("t", "worker")
    return _long(a.join(a.select((F.col("t") + 1).alias("t"), "worker"), ["t", "worker"]).groupBy("t").agg(F.count("*").alias("overlap")), "t")


@query("active_complement", f"WITH {DAYS} SELECT t, worker FROM d EXCEPT SELECT t, worker FROM a WHERE rank <= 10")
def active_complement(spark: SparkSession, sf: str) -> DataFrame:
    d = days(spark, sf)
    return _long(d.select("t", "worker").exceptAll(stragglers.first_k(d, 10).where("active").select("t", "worker")), "t", "worker")


@query(
    "adaptive_k",
    f"WITH {DAYS}, o AS (SELECT a.t, a.rank, count(*) OVER (PARTITION BY a.t) AS m, sum(CASE WHEN p.worker IS NULL THEN 0 ELSE 1 END) OVER (PARTITION BY a.t ORDER BY a.rank) AS overlap FROM a LEFT JOIN a p ON p.t = a.t - 1 AND p.worker = a.worker AND p.rank <= 6) "
    f"SELECT t, CAST(CASE WHEN t = 0 THEN 6 ELSE coalesce(min(CASE WHEN overlap > m / 4e0 AND rank >= 6 THEN rank END), max(rank)) END AS BIGINT) AS k FROM o GROUP BY t",
)
def adaptive_k(spark: SparkSession, sf: str) -> DataFrame:
    return _long(stragglers.adaptive_k(days(spark, sf), 6, 4.0), "t", "k").select("t", "k")


@query("runtime_vs_eta", f"WITH {D} SELECT rank AS k, round(sum(delay), 6) AS runtime, rank / {M}e0 AS eta FROM a GROUP BY rank")
def runtime_vs_eta(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.runtime_by_eta(_delays(spark), M).select(F.col("k").cast("long").alias("k"), F.round("runtime", 6).alias("runtime"), "eta")


@query("runtime_vs_eta_events", f"WITH d AS ({TRACE}), a AS (SELECT *, row_number() OVER (PARTITION BY t ORDER BY delay, worker) AS rank FROM d) SELECT rank AS k, round(sum(delay), 4) AS runtime, rank / {M}e0 AS eta FROM a GROUP BY rank")
def runtime_vs_eta_events(spark: SparkSession, sf: str) -> DataFrame:
    d = stragglers.delays_from_events(fixtures.table(spark, sf, "events"), M)
    return metrics.runtime_by_eta(d, M).select(F.col("k").cast("long").alias("k"), F.round("runtime", 4).alias("runtime"), "eta")


@query("runtime_speedup", f"WITH {D}, r AS (SELECT rank AS k, sum(delay) AS runtime FROM a GROUP BY rank) SELECT k, round(1 - runtime / (SELECT max(runtime) FROM r), 6) + 0e0 AS cut FROM r")
def runtime_speedup(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.speedup(metrics.runtime_by_eta(_delays(spark), M)).select(F.col("k").cast("long").alias("k"), r6("cut").alias("cut"))


@query("virtual_clock", f"WITH {D}, r AS (SELECT t, max(delay) AS round_time FROM a WHERE rank <= 10 GROUP BY t) SELECT t, round(round_time, 6) AS round_time, round(sum(round_time) OVER (ORDER BY t), 6) AS clock FROM r")
def virtual_clock(spark: SparkSession, sf: str) -> DataFrame:
    c = stragglers.round_times(stragglers.first_k(_delays(spark), 10))
    return c.select(F.col("t").cast("long").alias("t"), F.round("round_time", 6).alias("round_time"), F.round("clock", 6).alias("clock"))


@query("participation_share", f"WITH {D} SELECT worker, round(avg(CASE WHEN rank <= 10 THEN 1e0 ELSE 0e0 END), 6) AS share FROM a GROUP BY worker")
def participation_share(spark: SparkSession, sf: str) -> DataFrame:
    return stragglers.participation(stragglers.first_k(_delays(spark), 10)).select(F.col("worker").cast("long").alias("worker"), F.round("share", 6).alias("share"))


# asynchronous runs over the recorded days, until the first worker's trace ends
_P = f"d AS ({day_sql()}), p AS (SELECT t, worker, sum(delay) OVER (PARTITION BY worker ORDER BY t) AS done FROM d), h AS (SELECT min(total) AS horizon FROM (SELECT sum(delay) AS total FROM d GROUP BY worker))"


@query("async_update_share", f"WITH {_P}, e AS (SELECT p.* FROM p, h WHERE done <= horizon) SELECT worker, count(*) AS updates, round(count(*) / (SELECT CAST(count(*) AS DOUBLE) FROM e), 6) AS share FROM e GROUP BY worker")
def async_update_share(spark: SparkSession, sf: str) -> DataFrame:
    d = saved(days(spark, sf))
    e = metrics.async_events(d, metrics.shortest(d, "worker"))
    return metrics.update_share(e, M).select(F.col("worker").cast("long").alias("worker"), "updates", F.round("share", 6).alias("share"))


@query("async_staleness", f"WITH {_P}, e AS (SELECT p.*, row_number() OVER (ORDER BY done, worker) AS k FROM p, h WHERE done <= horizon) SELECT worker, t, CAST(k - coalesce(lag(k) OVER (PARTITION BY worker ORDER BY t), 0) - 1 AS BIGINT) AS staleness FROM e")
def async_staleness(spark: SparkSession, sf: str) -> DataFrame:
    d = saved(days(spark, sf))
    return _long(metrics.staleness(metrics.async_events(d, metrics.shortest(d, "worker"))), "worker", "t")


@query("replica_first_copy", f"WITH {D}, c AS (SELECT t, worker % 8 AS part, worker, row_number() OVER (PARTITION BY t, worker % 8 ORDER BY delay, worker) AS copy FROM a WHERE rank <= 10) SELECT t, part, worker FROM c WHERE copy = 1")
def replica_first_copy(spark: SparkSession, sf: str) -> DataFrame:
    return _long(stragglers.first_copies(_delays(spark), 10, 8).select("t", "part", "worker"), "t", "part", "worker")


@query("replica_cover_time", f"WITH {D}, f AS (SELECT t, worker % 8 AS part, min(delay) AS m FROM d GROUP BY 1, 2) SELECT t, round(max(m), 6) AS round_time FROM f GROUP BY t")
def replica_cover_time(spark: SparkSession, sf: str) -> DataFrame:
    return stragglers.cover_times(_delays(spark), 8).select(F.col("t").cast("long").alias("t"), F.round("round_time", 6).alias("round_time"))


@query("deadline_wait", f"WITH {D} SELECT t, CAST(sum(CASE WHEN delay <= 0.02e0 THEN 1 ELSE 0 END) AS BIGINT) AS replies FROM d GROUP BY t")
def deadline_wait(spark: SparkSession, sf: str) -> DataFrame:
    a = stragglers.within_deadline(_delays(spark), 0.02)
    return a.groupBy(F.col("t").cast("long").alias("t")).agg(F.sum(F.col("active").cast("long")).alias("replies"))


# ---------------------------------------------------------------- ridge and LASSO with SQL

PW = 3  # coefficients of the problems that SQL follows
W_TRUE = fixtures.planted(PW)
LAM, ROUNDS, MW, KW = 0.05, 8, 8, 6
CODE = SMALL["hadamard_etf"][0]


def _rows_sql() -> str:
    x = ", ".join(f"8 * CAST(embedding[{k + 1}] AS DOUBLE) AS x{k}" for k in range(PW))
    y = " + ".join(f"({w!r}) * x{k}" for k, w in enumerate(W_TRUE.tolist()))
    return f"SELECT *, {y} + ({uniform_sql('row_id', '1', fixtures.NOISE_SEED)} - 0.5e0) * 2 AS y FROM (SELECT vec_id AS row_id, {x} FROM embeddings)"


def _worker_rows(scheme: str) -> str:
    """SQL of (worker, x0.., y): encoded or plain rows by worker."""
    cols = [*(f"x{k}" for k in range(PW)), "y"]
    if scheme == "uncoded":
        rank = f"SELECT range AS i, (row_number() OVER (ORDER BY {uniform_sql('range', '0', 1)}, range) - 1) % {MW} AS worker FROM range(64)"
        return f"SELECT a.worker, {', '.join('o.' + c for c in cols)} FROM ({_rows_sql()}) o JOIN ({rank}) a ON o.row_id % 64 = a.i"
    rank = f"SELECT range AS i, (row_number() OVER (ORDER BY {uniform_sql('range', '0', 1)}, range) - 1) % {MW} AS worker FROM range(64)"
    sums = ", ".join(f"sum(s.v * o.{c}) AS {c}" for c in cols)
    return f"SELECT a.worker, e.* EXCLUDE (i) FROM (SELECT o.row_id // 28 AS g, s.i, {sums} FROM ({_rows_sql()}) o JOIN ({_ETF_NUMBERED}) s ON o.row_id % 28 = s.j GROUP BY 1, 2) e JOIN ({rank}) a ON e.i = a.i"


_ETF_NUMBERED = f"SELECT i, dense_rank() OVER (ORDER BY j) - 1 AS j, v FROM ({_ETF})"


def _live_sql(k: int) -> str:
    return f"d AS (SELECT t, worker, {DELAY_SQL['exponential'].replace('-0.01e0', '-0.01e0')} AS delay FROM (SELECT CAST(range // {MW} AS BIGINT) AS t, CAST(range % {MW} AS BIGINT) AS worker FROM range({ROUNDS * MW}))), a AS (SELECT t, worker FROM (SELECT *, row_number() OVER (PARTITION BY t ORDER BY delay, worker) AS r FROM d) WHERE r <= {k})"


STEP = 0.3


def _solver_sql(scheme: str, k: int, lasso: bool) -> str:
    """Recursive rounds on sums over the active workers, which a join by round gives."""
    pairs = [(i, j) for i in range(PW) for j in range(PW)]
    g = ", ".join(f"sum(x{i} * x{j}) AS g{i}{j}" for i, j in pairs) + ", " + ", ".join(f"sum(x{i} * y) AS c{i}" for i in range(PW)) + ", sum(y * y) AS s"
    names = [f"g{i}{j}" for i, j in pairs] + [f"c{i}" for i in range(PW)]
    total = ", ".join(f"sum({x}) AS {x}" for x in names)
    scale = f"({MW} / {k}e0 / (SELECT count(*) FROM embeddings))"
    grad = [f"({' + '.join(f'q.g{i}{j} * w.w{j}' for j in range(PW))} - q.c{i}) * {scale}" for i in range(PW)]
    if lasso:
        new = [f"(w.w{i} - {STEP}e0 * {grad[i]})" for i in range(PW)]
        new = [f"sign({x}) * greatest(abs({x}) - {STEP * LAM!r}, 0e0)" for x in new]
        penalty = f"{LAM} * ({' + '.join(f'abs(w{i})' for i in range(PW))})"
    else:
        new = [f"w.w{i} - {STEP}e0 * ({grad[i]} + {LAM} * w.w{i})" for i in range(PW)]
        penalty = f"{LAM / 2} * ({' + '.join(f'w{i} * w{i}' for i in range(PW))})"
    quad = " + ".join(f"o.g{i}{j} * w{i} * w{j}" for i, j in pairs) + " - 2 * (" + " + ".join(f"o.c{i} * w{i}" for i in range(PW)) + ") + o.s"
    return f"""WITH RECURSIVE {_live_sql(k)}, e AS ({_worker_rows(scheme)}), p AS (SELECT worker, {g} FROM e GROUP BY worker),
    q AS (SELECT a.t, {total} FROM a JOIN p ON a.worker = p.worker GROUP BY a.t),
    o AS (SELECT {g} FROM ({_rows_sql()})),
    w AS (SELECT CAST(-1 AS BIGINT) AS t, {', '.join(f'0e0 AS w{i}' for i in range(PW))}
          UNION ALL SELECT q.t, {', '.join(f'{x} AS w{i}' for i, x in enumerate(new))} FROM w JOIN q ON q.t = w.t + 1)
    SELECT t, {', '.join(f'round(w{i}, 6) + 0e0 AS w{i}' for i in range(PW))}, round(({quad}) / (2 * (SELECT count(*) FROM embeddings)) + {penalty}, 6) AS objective FROM w CROSS JOIN o WHERE t >= 0"""


def _solver(scheme: str, k: int, lasso: bool):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        df = fixtures.dense_embeddings(spark, sf, PW)
        n, original = df.count(), partials.whole_gram(df, PW)
        code = codes.identity(64) if scheme == "uncoded" else CODE()
        problem = solvers.Problem(partials.GramPartials(encode.encode_rows(df, code, MW), MW, PW), n, MW, PW, LAM, original)
        active, _ = compare.replies(spark, MODELS["exponential"], ROUNDS, MW, k, 1)
        rows, w = [], np.zeros(PW)
        l1 = lambda v: float(np.abs(v).sum())
        for t in range(ROUNDS):
            live = active["grad"][t : t + 1]
            res = solvers.proximal_gradient(problem, live, solvers.prox_l1, l1, step=STEP, w0=w) if lasso else solvers.gradient_descent(problem, live, step=STEP, w0=w)
            w = res.w
            rows.append((t, *map(float, w), float(res.trace["objective"].iloc[0])))
        frame = spark.createDataFrame(rows, "t long, " + ", ".join(f"w{i} double" for i in range(PW)) + ", objective double")
        return frame.select("t", *(r6(f"w{i}").alias(f"w{i}") for i in range(PW)), F.round("objective", 6).alias("objective"))

    return run


for _name, _scheme, _k, _lasso in (("gd_ridge_uncoded", "uncoded", KW, False), ("gd_ridge_coded", "coded", KW, False), ("gd_ridge_perfect", "uncoded", MW, False), ("gd_ridge_coded_all", "coded", MW, False), ("ista_lasso_uncoded", "uncoded", KW, True), ("ista_lasso_coded", "coded", KW, True)):
    query(_name, _solver_sql(_scheme, _k, _lasso))(_solver(_scheme, _k, _lasso))


_W0 = [0.5, -0.25, 1.0]


def _gradient_sql(scheme: str, live: str) -> str:
    g = [f"sum(x{i} * ({' + '.join(f'({w}) * x{j}' for j, w in enumerate(_W0))} - y))" for i in range(PW)]
    return f"WITH e AS ({_worker_rows(scheme)}) SELECT worker, {', '.join(f'round({x}, 4) + 0e0 AS g{i}' for i, x in enumerate(g))} FROM e WHERE {live} GROUP BY worker"


def _gradients(scheme: str, live: list[int]):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        df = fixtures.dense_embeddings(spark, sf, PW)
        enc = encode.encode_rows(df, codes.identity(64) if scheme == "uncoded" else CODE(), MW)
        active = np.isin(np.arange(MW), live)
        g, _ = partials.ScanPartials(enc, MW, PW).gradients(np.array(_W0), active)
        out = spark.createDataFrame([(i, *map(float, g[i])) for i in live], "worker long, " + ", ".join(f"g{i} double" for i in range(PW)))
        return out.select("worker", *((F.round(f"g{i}", 4) + 0.0).alias(f"g{i}") for i in range(PW)))

    return run


query("gradient_partial_uncoded", _gradient_sql("uncoded", "true"))(_gradients("uncoded", list(range(MW))))
query("gradient_partial_coded", _gradient_sql("coded", "true"))(_gradients("coded", list(range(MW))))
query("gradient_erased", _gradient_sql("coded", "worker NOT IN (1, 4)"))(_gradients("coded", [0, 2, 3, 5, 6, 7]))


@query("online_equals_offline", "SELECT CAST(range AS BIGINT) AS worker, 0e0 AS difference FROM range(8)")
def online_equals_offline(spark: SparkSession, sf: str) -> DataFrame:
    """Gradients from uncoded support rows less those from encoded rows, by worker."""
    df, code = fixtures.dense_embeddings(spark, sf, PW), CODE()
    w, live = np.array(_W0), np.ones(MW, bool)
    off, _ = partials.ScanPartials(encode.encode_rows(df, code, MW), MW, PW).gradients(w, live)
    on, _ = partials.OnlinePartials(encode.support_rows(df, code, MW), code, MW, PW).gradients(w, live)
    return spark.createDataFrame([(i, round(float(np.abs(off[i] - on[i]).max()), 6) + 0.0) for i in range(MW)], "worker long, difference double")


@query("encode_join_equals_grouped", "SELECT CAST(range AS BIGINT) AS enc_row, 0e0 AS difference FROM range(64)")
def encode_join_equals_grouped(spark: SparkSession, sf: str) -> DataFrame:
    """The largest difference in any group, by row of the code; infinite where only one mode has a row or a worker."""
    df, code = fixtures.dense_embeddings(spark, sf, PW), CODE()
    a, b = (encode.encode_rows(df, code, MW, mode=m).select("worker", "enc_row", F.concat("x", F.array("y")).alias(m)) for m in ("join", "grouped"))
    diff = F.coalesce(F.array_max(F.zip_with("join", "grouped", lambda u, v: F.abs(u - v))), F.lit(float("inf")))
    return a.join(b, ["worker", "enc_row"], "full").groupBy((F.col("enc_row") % code.N).alias("enc_row")).agg((F.round(F.max(diff), 6) + 0.0).alias("difference"))


# ---------------------------------------------------------------- other solvers: rows only, held against numpy

SCHEMES = ("uncoded", "replication", "gaussian", "paley", "hadamard", "hadamard_etf", "steiner", "haar", "dft")


def _lbfgs(scheme: str):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        """Ridge on 16 coordinates, 12 of 16 replies."""
        df = fixtures.dense_embeddings(spark, sf, 16)
        return compare.grid(spark, df, 16, LAM, [scheme], 16, [12], stragglers.exponential(), 15)

    return run


for _scheme in SCHEMES:
    query(f"lbfgs_ridge_{_scheme}")(_lbfgs(_scheme))


@query("ridge_grid")
def ridge_grid(spark: SparkSession, sf: str) -> DataFrame:
    """Objective and clock of the last round by scheme and k, over trials."""
    df = fixtures.dense_embeddings(spark, sf, 16, noise=4.0)
    g = compare.grid(spark, df, 16, LAM, ["uncoded", "replication", "hadamard"], 16, [6, 12, 16], stragglers.exponential(), 12, trials=3)
    last = g.where(F.col("t") == 11)
    return last.groupBy("scheme", "m", "k").agg(F.avg("objective").alias("objective"), F.avg("clock").alias("clock"), F.count("*").alias("trials"))


@query("ridge_wide_generated")
def ridge_wide_generated(spark: SparkSession, sf: str) -> DataFrame:
    """More coefficients than rows: 192 normal rows by 288, so that only the ridge term bounds the curvature."""
    df = fixtures.gaussian_rows(spark, 192, 288)
    return compare.grid(spark, df, 288, LAM, ["uncoded", "hadamard"], 16, [6, 16], stragglers.exponential(), 10)


@query("gd_ridge_replication")
def gd_ridge_replication(spark: SparkSession, sf: str) -> DataFrame:
    df = fixtures.dense_embeddings(spark, sf, PW)
    return compare.grid(spark, df, PW, LAM, ["replication"], MW, [KW], stragglers.exponential(), ROUNDS, algo="gd")


@query("lbfgs_ablation")
def lbfgs_ablation(spark: SparkSession, sf: str) -> DataFrame:
    """Curvature from overlaps or from rounds on end, and both first scales, at few replies."""
    df = fixtures.dense_embeddings(spark, sf, 16, noise=4.0)
    problem, beta = compare.problem_of(df, "hadamard", 16, 16, LAM)
    active, _ = compare.replies(spark, stragglers.exponential(), 20, 16, 10, 1, ("grad", "line"))
    rows = []
    for curvature in ("overlap", "naive"):
        for init in ("inverse", "as_printed"):
            run = solvers.lbfgs(problem, active["grad"], active["line"], curvature=curvature, init=init, beta=beta)
            rows += [(curvature, init, int(t), float(f)) for t, f in zip(run.trace["t"], run.trace["objective"], strict=True)]
    return spark.createDataFrame(rows, "curvature string, init string, t long, objective double")


def adversary_rows(spark: SparkSession, sf: str, rounds: int = 60) -> pd.DataFrame:
    df = fixtures.dense_embeddings(spark, sf, 16, noise=4.0)
    original, n = partials.whole_gram(df, 16), df.count()
    best = None
    out = []
    for scheme in ("uncoded", "replication", "hadamard", "steiner"):
        problem, beta = compare.problem_of(df, scheme, 16, 16, LAM, original=original, n=n)
        best = best or problem.objective(solvers.ridge_solution(original, n, LAM))
        for kind in ("fixed", "rotate", "kill_replicas", "greedy_worst"):
            worst = lambda live, g=problem.partials.G: float(np.linalg.eigvalsh(g[live].sum(0))[0])
            active = stragglers.adversary(kind, 16, 12, rounds, worst)
            run = solvers.gradient_descent(problem, active, step=solvers.gradient_step(problem), beta=beta)
            out.append((scheme, kind, float(run.trace["objective"].iloc[-1] / best)))
    return pd.DataFrame(out, columns=["scheme", "adversary", "ratio"])


@query("adversarial_erasures")
def adversarial_erasures(spark: SparkSession, sf: str) -> DataFrame:
    """Final objective over the optimum when erasures are chosen against the method."""
    return spark.createDataFrame(adversary_rows(spark, sf))


def lasso_rows(spark: SparkSession, sf: str) -> pd.DataFrame:
    p = 64
    df = fixtures.dense_embeddings(spark, sf, p, noise=8.0, sparsity=0.12)
    true, original, n = fixtures.planted(p, 0.12) != 0, partials.whole_gram(df, p), df.count()
    step = 0.9 / (solvers.largest_eigenvalue(original.G[0]) / n)
    out = []
    for scheme, m, k in (("uncoded", 16, 16), ("uncoded", 16, 10), ("replication", 16, 10), ("steiner", 16, 10), ("hadamard", 16, 10)):
        problem, beta = compare.problem_of(df, scheme, m, p, 0.6, original=original, n=n)
        active, clock = compare.replies(spark, stragglers.TRIMODAL, 60, m, k, 1)

        def f1(w: np.ndarray) -> float:
            found = w != 0
            return float(2 * (found & true).sum() / max((found.sum() + true.sum()), 1))

        run = solvers.proximal_gradient(problem, active["grad"], solvers.prox_l1, lambda v: float(np.abs(v).sum()), step=step / (1.5 if scheme != "uncoded" else 1), clock=clock, beta=beta, record=f1)
        out.append(run.trace.assign(scheme=scheme, k=k))
    return pd.concat(out, ignore_index=True)[["scheme", "k", "t", "clock", "objective", "measure"]]


@query("ista_lasso_recovery")
def ista_lasso_recovery(spark: SparkSession, sf: str) -> DataFrame:
    """F1 of the support over the clock, under the trimodal delays."""
    return spark.createDataFrame(lasso_rows(spark, sf)).withColumnRenamed("measure", "f1")


@query("prox_variants")
def prox_variants(spark: SparkSession, sf: str) -> DataFrame:
    """Every regulariser and constraint on the same coded problem."""
    df = fixtures.dense_embeddings(spark, sf, 16)
    problem, _ = compare.problem_of(df, "hadamard", 16, 16, 0.2)
    active, _ = compare.replies(spark, stragglers.exponential(), 25, 16, 12, 1)
    forms = {
        "l1": (solvers.prox_l1, lambda v: np.abs(v).sum()), "l2": (solvers.prox_l2sq, lambda v: 0.5 * v @ v), "elastic": (solvers.prox_elastic(0.5), lambda v: 0.5 * np.abs(v).sum() + 0.25 * v @ v),
        "group": (solvers.prox_group(4), lambda v: np.linalg.norm(v.reshape(-1, 4), axis=1).sum()), "l1_squared": (solvers.prox_l1sq, lambda v: np.abs(v).sum() ** 2),
        "box": (solvers.project_box(-0.5, 0.5), lambda v: 0.0), "nonneg": (solvers.project_nonneg, lambda v: 0.0), "ball": (solvers.project_l2ball(1.0), lambda v: 0.0),
    }
    step, rows = solvers.gradient_step(problem), []
    for name, (prox, h) in forms.items():
        run = solvers.proximal_gradient(problem, active["grad"], prox, h, step=step)
        rows.append((name, float(run.trace["objective"].iloc[-1]), int((run.w != 0).sum()), float(np.linalg.norm(run.w)), float(run.w.min()), float(run.w.max())))
    return spark.createDataFrame(rows, "form string, objective double, nonzero long, length double, low double, high double")


# ---------------------------------------------------------------- logistic


def _toxic(spark: SparkSession, sf: str, p: int = 64) -> DataFrame:
    return fixtures.hashed_rows(fixtures.table(spark, sf, "documents"), fixtures.table(spark, sf, "labels"), "toxic", p)


def _bcd(scheme: str, k: int):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        """Toxic or not from 64 hashed tf-idf features under the bimodal delays."""
        p, lam, rounds, m = 64, 0.01, 20, 16
        df = saved(_toxic(spark, sf, p))
        grad = blocks.ScanGradient(df.where(~F.col("is_test")), p, blocks.LOGISTIC, lam)
        gram = partials.whole_gram(df.where(~F.col("is_test")).select("x", F.lit(0.0).alias("y")), p)
        step = 0.95 / (0.25 * solvers.largest_eigenvalue(gram.G[0]) / grad.n + lam)
        active, clock = compare.replies(spark, stragglers.BIMODAL, rounds, m, k, 1)
        if scheme == "replication":
            res = blocks.replicated_block_descent(grad, p, active["grad"], step=step, clock=clock)
        else:
            res = blocks.block_coordinate_descent(grad, codes.FAMILIES[scheme](p, 1), active["grad"], step=step, clock=clock)
        out = res.trace.assign(scheme=scheme, k=k)[["scheme", "k", "t", "objective", "clock"]]
        return spark.createDataFrame(out)

    return run


for _scheme, _k in (("uncoded", 16), ("uncoded", 8), ("replication", 8), ("steiner", 8), ("haar", 8), ("hadamard", 8)):
    query(f"bcd_logistic_{_scheme}_{_k}")(_bcd(_scheme, _k))


@query("bcd_logistic_error")
def bcd_logistic_error(spark: SparkSession, sf: str) -> DataFrame:
    """Train and test error of the coded solution."""
    p, lam = 64, 0.01
    df = saved(_toxic(spark, sf, p))
    grad = blocks.ScanGradient(df.where(~F.col("is_test")), p, blocks.LOGISTIC, lam)
    active, _ = compare.replies(spark, stragglers.background_power_law(), 20, 16, 10, 1)
    gram = partials.whole_gram(df.select("x", F.lit(0.0).alias("y")), p)
    res = blocks.block_coordinate_descent(grad, codes.FAMILIES["steiner"](p, 1), active["grad"], step=0.95 / (0.25 * solvers.largest_eigenvalue(gram.G[0]) / grad.n + lam))
    return metrics.classification(df, res.w)


@query("async_bcd_logistic")
def async_bcd_logistic(spark: SparkSession, sf: str) -> DataFrame:
    """Event by event under background loads: time, worker, staleness, objective."""
    p, lam, m = 16, 0.01, 8
    df = saved(_toxic(spark, sf, p))
    grad = blocks.ScanGradient(df.where(~F.col("is_test")), p, blocks.LOGISTIC, lam)
    d = stragglers.delays(spark, stragglers.background_power_law(), 6, m).toPandas().pivot(index="t", columns="worker", values="delay").to_numpy()
    res, events = blocks.async_block_descent(grad, p, d, step=1.0, horizon=float(np.sort(d.cumsum(0).ravel())[11]))
    return spark.createDataFrame(events.assign(objective=res.trace["objective"].to_numpy()))


@query(
    "residual_exchange",
    f"WITH s AS ({_HADAMARD}), x AS (SELECT vec_id AS row_id, unnest(range(8)) AS j, unnest(list_transform(embedding[1:8], lambda v: 8 * CAST(v AS DOUBLE))) AS v FROM embeddings), "
    "u AS (SELECT row_id, CAST(s.i % 4 AS BIGINT) AS worker, sum(x.v * s.v) AS u FROM x JOIN s ON x.j = s.j GROUP BY 1, 2) "
    "SELECT row_id, worker, round(sum(u) OVER (PARTITION BY row_id) - u, 6) + 0e0 AS others FROM u",
)
def residual_exchange(spark: SparkSession, sf: str) -> DataFrame:
    """What the coordinator sends to each worker: the row sums of all other blocks."""
    e = encode.encode_columns(fixtures.dense_embeddings(spark, sf, 8), codes.hadamard(8, 2, 1), 4, "round_robin")
    u = e.select("row_id", F.col("worker").cast("long").alias("worker"), F.aggregate("xblk", F.lit(0.0), lambda a, v: a + v).alias("u"))
    return u.select("row_id", "worker", r6(F.sum("u").over(Window.partitionBy("row_id")) - F.col("u")).alias("others"))


# ---------------------------------------------------------------- factorisation

_RATE = f"SELECT o_custkey AS \"user\", l_partkey AS item, avg(ceil(l_quantity / 10)) AS rating FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2"
_SPLIT = f"SELECT *, {uniform_sql(chr(34) + 'user' + chr(34), 'item', fixtures.SPLIT_SEED)} < 0.2e0 AS is_test FROM ({_RATE})"


@query("ratings_build", f'SELECT "user", item, round(rating, 6) AS rating FROM ({_RATE})')
def ratings_build(spark: SparkSession, sf: str) -> DataFrame:
    return fixtures.ratings(spark, sf).select("user", "item", F.round("rating", 6).alias("rating"))


@query("ratings_split", f"SELECT is_test, count(*) AS n, round(avg(rating), 6) AS mean FROM ({_SPLIT}) GROUP BY 1")
def ratings_split(spark: SparkSession, sf: str) -> DataFrame:
    return fixtures.ratings(spark, sf).groupBy("is_test").agg(F.count("*").alias("n"), F.round(F.avg("rating"), 6).alias("mean"))


@query("ratings_neighbours", f'SELECT "user", count(*) AS n, min(item) AS first, max(item) AS last FROM ({_SPLIT}) WHERE NOT is_test GROUP BY 1')
def ratings_neighbours(spark: SparkSession, sf: str) -> DataFrame:
    lists = fixtures.ratings(spark, sf).where(~F.col("is_test")).groupBy("user").agg(F.sort_array(F.collect_list("item")).alias("items"))
    return lists.select("user", F.size("items").cast("long").alias("n"), F.element_at("items", 1).alias("first"), F.element_at("items", -1).alias("last"))


@query("ratings_local_vs_coded", f'SELECT n < 24 AS local, count(*) AS users, CAST(sum(n) AS BIGINT) AS ratings FROM (SELECT "user", count(*) AS n FROM ({_SPLIT}) WHERE NOT is_test GROUP BY 1) GROUP BY 1')
def ratings_local_vs_coded(spark: SparkSession, sf: str) -> DataFrame:
    n = fixtures.ratings(spark, sf).where(~F.col("is_test")).groupBy("user").agg(F.count("*").alias("n"))
    return n.groupBy((F.col("n") < 24).alias("local")).agg(F.count("*").alias("users"), F.sum("n").alias("ratings"))


@query("rmse_constant_model", f"SELECT is_test, round(sqrt(avg((rating - 3) * (rating - 3))), 6) AS rmse FROM ({_SPLIT}) GROUP BY 1")
def rmse_constant_model(spark: SparkSession, sf: str) -> DataFrame:
    return factorization.rmse(fixtures.ratings(spark, sf).withColumn("guess", F.lit(3.0))).select("is_test", F.round("rmse", 6).alias("rmse"))


@query(
    "rmse_bias_model",
    f'WITH r AS ({_SPLIT}), b AS (SELECT "user" AS u, sum(rating - 3) / (10 + count(*)) AS bias FROM r WHERE NOT is_test GROUP BY 1) SELECT is_test, round(sqrt(avg(power(rating - 3 - coalesce(bias, 0), 2))), 6) AS rmse FROM r LEFT JOIN b ON r."user" = b.u GROUP BY 1',
)
def rmse_bias_model(spark: SparkSession, sf: str) -> DataFrame:
    """User biases only, shrunk by the ridge term: one exact half epoch without factors."""
    r = fixtures.ratings(spark, sf)
    b = r.where(~F.col("is_test")).groupBy("user").agg((F.sum(F.col("rating") - 3) / (10 + F.count("*"))).alias("bias"))
    guess = r.join(b, "user", "left").withColumn("guess", 3 + F.coalesce("bias", F.lit(0.0)))
    return factorization.rmse(guess).select("is_test", F.round("rmse", 6).alias("rmse"))


def _factorise(scheme: str, m: int, k: int):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        """Planted ratings, 2 epochs of rank 5; groups of 16 ratings and more are coded."""
        _, _, trace = factorization.alternating(fixtures.ratings_planted(spark, sf), rank=5, lam=2.0, epochs=2, schemes=scheme, m=m, k=k, threshold=16, rounds=8, save=spooled, drop=dropped)
        return spark.createDataFrame([(scheme, m, k, t["epoch"], t["train_rmse"], t["test_rmse"], t["clock"]) for t in trace], "scheme string, m long, k long, epoch long, train_rmse double, test_rmse double, clock double")

    return run


MF_SCHEMES = ["exact", "uncoded", "replication", "gaussian", "paley", "hadamard"]


def mf_table(spark: SparkSession, sf: str, m: int, k: int, raw: bool) -> DataFrame:
    """All schemes side by side at rank 15, lambda 10, base 3, 5 epochs; ids with 8 ratings or more are coded ('exact': none)."""
    r = fixtures.ratings(spark, sf) if raw else fixtures.ratings_planted(spark, sf)
    _, _, trace = factorization.alternating(r, schemes=MF_SCHEMES, m=m, k=k, threshold=8, rounds=8, save=spooled, drop=dropped, each=False)
    return spark.createDataFrame([(t["scheme"], m, m if t["scheme"] == "exact" else k, t["train_rmse"], t["test_rmse"], t["clock"]) for t in trace], "scheme string, m long, k long, train_rmse double, test_rmse double, clock double")


for _m, _k in ((8, 1), (8, 4), (8, 6), (24, 3), (24, 12)):
    query(f"mf_table_m{_m}_k{_k}")(lambda spark, sf, m=_m, k=_k: mf_table(spark, sf, m, k, False))
query("mf_table_raw_ratings")(lambda spark, sf: mf_table(spark, sf, 8, 4, True))


@query(
    "mf_exact_half_epoch",
    f"""WITH r AS ({_SPLIT}), t AS (SELECT "user", rating - 3 AS y, {uniform_sql("item", "0", 18)} - 0.5e0 AS f FROM r WHERE NOT is_test),
    g AS (SELECT "user", sum(f * f) + 10 AS a, sum(f) AS b, count(*) + 10e0 AS d, sum(f * y) AS p, sum(y) AS q FROM t GROUP BY 1)
    SELECT "user", round((d * p - b * q) / (a * d - b * b), 5) + 0e0 AS factor, round((a * q - b * p) / (a * d - b * b), 5) + 0e0 AS bias FROM g""",
)
def mf_exact_half_epoch(spark: SparkSession, sf: str) -> DataFrame:
    """One half epoch of rank 1 for the users, exactly: the 2 x 2 normal equations of every user."""
    r = factorization.counted(fixtures.ratings(spark, sf)).where(~F.col("is_test"))
    out = factorization.half_epoch(r, factorization.first_factors(r, 1, ["exact"]), "user", "item", rank=1, lam=10.0, base=3.0, m=8, k=8, rounds=4, threshold=8, seed=1)
    return out.select("user", (F.round(F.col("f")[0], 5) + 0.0).alias("factor"), (F.round("bias", 5) + 0.0).alias("bias"))


for _scheme in ("exact", "uncoded", "replication", "gaussian", "paley", "hadamard"):
    query(f"mf_altmin_{_scheme}")(_factorise(_scheme, 8, 8 if _scheme == "exact" else 4))


# ---------------------------------------------------------------- text features and measures

_TOK = "SELECT doc_id, token, count(*) AS tf FROM (SELECT doc_id, unnest(string_split_regex(lower(text), '[^a-z]+')) AS token FROM documents) WHERE length(token) > 0 GROUP BY 1, 2"


@query(
    "tfidf_documents",
    f"WITH t AS ({_TOK}), f AS (SELECT token, count(*) AS df FROM t GROUP BY 1 HAVING count(*) >= 2), n AS (SELECT count(*) AS docs FROM documents), "
    "r AS (SELECT doc_id, t.token, tf * ln((1 + docs) / (1e0 + df)) AS raw FROM t JOIN f ON t.token = f.token CROSS JOIN n), s AS (SELECT doc_id, sqrt(sum(raw * raw)) AS norm FROM r GROUP BY 1) "
    "SELECT r.doc_id, count(*) AS terms, round(sum(raw / norm), 5) AS total FROM r JOIN s ON r.doc_id = s.doc_id WHERE norm > 0 GROUP BY 1",
)
def tfidf_documents(spark: SparkSession, sf: str) -> DataFrame:
    return fixtures.tfidf(fixtures.table(spark, sf, "documents")).groupBy("doc_id").agg(F.count("*").alias("terms"), F.round(F.sum("val"), 5).alias("total"))


@query("tfidf_feature_subset", f"SELECT count(DISTINCT token) AS tokens, count(*) AS entries FROM ({_TOK}) WHERE {uniform_sql('ascii(token) * 1000 + length(token)', '2', fixtures.FEATURE_SEED)} < 0.69e0")
def tfidf_feature_subset(spark: SparkSession, sf: str) -> DataFrame:
    t = fixtures.tokens(fixtures.table(spark, sf, "documents")).where(uniform(F.ascii("token") * 1000 + F.length("token"), F.lit(2), fixtures.FEATURE_SEED) < 0.69)
    return t.agg(F.countDistinct("token").alias("tokens"), F.count("*").alias("entries"))


@query("tfidf_label_split", f"SELECT {uniform_sql('doc_id', '3', fixtures.SPLIT_SEED)} < 0.143e0 AS is_test, count(*) AS n, CAST(sum(toxic) AS BIGINT) AS toxic FROM labels GROUP BY 1")
def tfidf_label_split(spark: SparkSession, sf: str) -> DataFrame:
    labels = fixtures.table(spark, sf, "labels").withColumn("is_test", uniform("doc_id", F.lit(3), fixtures.SPLIT_SEED) < 0.143)
    return labels.groupBy("is_test").agg(F.count("*").alias("n"), F.sum("toxic").cast("long").alias("toxic"))


_R0 = " + ".join(f"({w}) * x{j}" for j, w in enumerate(_W0))


@query("objective_original", f"SELECT round(avg(power({_R0} - y, 2)) / 2 + {LAM / 2 * sum(w * w for w in _W0)!r}, 6) AS objective, count(*) AS n FROM ({_rows_sql()})")
def objective_original(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.objective(fixtures.dense_embeddings(spark, sf, PW), np.array(_W0), LAM).select(F.round("objective", 6).alias("objective"), "n")


@query("running_mean_objective", f"SELECT t, CAST(sum(CAST(round(objective * 1000000) AS BIGINT)) OVER (ORDER BY t ROWS UNBOUNDED PRECEDING) AS BIGINT) AS millionths, count(*) OVER (ORDER BY t ROWS UNBOUNDED PRECEDING) AS rounds FROM ({_solver_sql('coded', KW, False)})")
def running_mean_objective(spark: SparkSession, sf: str) -> DataFrame:
    """The sum of all rounds' objectives so far, in whole millionths, and their number: its ratio is the running mean."""
    t, w = QUERIES["gd_ridge_coded"](spark, sf), Window.orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    return t.select("t", F.sum(F.round(F.col("objective") * 1000000).cast("long")).over(w).alias("millionths"), F.count("*").over(w).alias("rounds"))


@query(
    "support_f1",
    "WITH a AS (SELECT range AS feat, " + uniform_sql("range", "1", fixtures.PLANT_SEED) + " < 0.12e0 AS is_a, " + uniform_sql("range", "5", 3) + " < 0.2e0 AS is_b FROM range(64)), "
    "s AS (SELECT sum(CASE WHEN is_a AND (is_b OR feat % 2 = 0) THEN 1 ELSE 0 END) AS tp, sum(CASE WHEN NOT is_a AND is_b THEN 1 ELSE 0 END) AS fp, sum(CASE WHEN is_a AND NOT (is_b OR feat % 2 = 0) THEN 1 ELSE 0 END) AS fn FROM a) "
    "SELECT CAST(tp AS BIGINT) AS tp, CAST(fp AS BIGINT) AS fp, CAST(fn AS BIGINT) AS fn, round(2e0 * tp / (2 * tp + fp + fn), 6) AS f1 FROM s",
)
def support_f1(spark: SparkSession, sf: str) -> DataFrame:
    j = spark.range(64).select(F.col("id").alias("feat"))
    true = j.where(uniform("feat", F.lit(1), fixtures.PLANT_SEED) < 0.12).withColumn("val", F.lit(1.0))
    found = j.where((uniform("feat", F.lit(5), 3) < 0.2) | ((uniform("feat", F.lit(1), fixtures.PLANT_SEED) < 0.12) & (F.col("feat") % 2 == 0))).withColumn("val", F.lit(0.5))
    return metrics.support_f1(true, found).select("tp", "fp", "fn", F.round("f1", 6).alias("f1"))


@query("classification_error", f"SELECT is_test, round(avg(CASE WHEN y * z <= 0 THEN 1e0 ELSE 0e0 END), 6) AS error, count(*) AS n FROM (SELECT row_id % 5 = 0 AS is_test, CASE WHEN y > 0 THEN 1e0 ELSE -1e0 END AS y, {_R0} AS z FROM ({_rows_sql()})) GROUP BY 1")
def classification_error(spark: SparkSession, sf: str) -> DataFrame:
    df = fixtures.dense_embeddings(spark, sf, PW).select("row_id", "x", F.when(F.col("y") > 0, 1.0).otherwise(-1.0).alias("y"), (F.col("row_id") % 5 == 0).alias("is_test"))
    return metrics.classification(df, np.array(_W0)).select("is_test", F.round("error", 6).alias("error"), "n")


@query("trial_summary", f"WITH x AS (SELECT CASE WHEN worker < 8 THEN 'a' ELSE 'b' END AS scheme, t, {DELAY_SQL['exponential']} AS v FROM ({GRID})) SELECT scheme, t, round(avg(v), 6) AS mean, round(stddev_samp(v), 6) AS sd, count(*) AS trials FROM x GROUP BY 1, 2")
def trial_summary(spark: SparkSession, sf: str) -> DataFrame:
    d = _delays(spark).select(F.when(F.col("worker") < 8, "a").otherwise("b").alias("scheme"), F.col("t").cast("long").alias("t"), F.col("delay").alias("objective"))
    return metrics.trial_summary(d).select("scheme", "t", F.round("mean", 6).alias("mean"), F.round("sd", 6).alias("sd"), "trials")


# ---------------------------------------------------------------- spectra and bounds


@query("brip_spectrum")
def brip_spectrum(spark: SparkSession, sf: str) -> DataFrame:
    """Histograms of what the first replies of the recorded days leave of five codes: few replies at high redundancy, many at moderate."""
    out, d = None, saved(days(spark, sf, 8))
    left = {k: spectrum.recorded_subsets(d, k) for k in (4, 7)}
    for name in ("paley", "hadamard_etf", "steiner", "gaussian", "haar"):
        code = codes.FAMILIES[name](28, 1)
        for m, k in ((8, 4), (8, 7)):
            s = spectrum.spectrum(spark, code, m, k, subsets=left[k]).select(F.lit(name).alias("code"), F.lit(k).cast("long").alias("k"), (F.floor(F.col("eig") / (k / m) * 10) / 10).alias("bin"))
            h = s.groupBy("code", "k", "bin").agg(F.count("*").alias("n"))
            out = h if out is None else out.unionByName(h)
    return out


@query("brip_epsilon")
def brip_epsilon(spark: SparkSession, sf: str) -> DataFrame:
    """By recorded day: what the first 6 of 8 workers leave of the code."""
    return spectrum.brip_epsilon(spark, codes.hadamard_etf(3), 8, 6, subsets=spectrum.recorded_subsets(days(spark, sf, 8), 6))


@query("brip_trace", f"SELECT t AS subset, 28e0 * least(6, count(*)) / 8 AS trace FROM ({day_sql(8)}) GROUP BY t")
def brip_trace(spark: SparkSession, sf: str) -> DataFrame:
    """The sum of the eigenvalues is the number of rows left times their squared length: 6/8 of n = 28 if 6 of 8 workers reply that day."""
    left = spectrum.recorded_subsets(days(spark, sf, 8), 6)
    return spectrum.spectrum(spark, codes.hadamard_etf(3), 8, 6, subsets=left).groupBy("subset").agg(F.round(F.sum("eig"), 6).alias("trace"))


@query("bulk_ones")
def bulk_ones(spark: SparkSession, sf: str) -> DataFrame:
    """Eigenvalues at exactly one, and the least number that tight codes keep there."""
    out = None
    for name in ("paley", "hadamard_etf", "steiner", "haar", "gaussian"):
        code = codes.FAMILIES[name](28, 1)
        s = spectrum.spectrum(spark, code, 8, 7, count=8).groupBy("subset").agg(F.sum((F.abs(F.col("eig") - 1) < 1e-9).cast("long")).alias("ones"))
        one = s.select(F.lit(name).alias("code"), "subset", "ones", F.lit(spectrum.bulk_ones(code, 8, 7) if code.tight else 0).cast("long").alias("least"))
        out = one if out is None else out.unionByName(one)
    return out


@query("gaussian_edges")
def gaussian_edges(spark: SparkSession, sf: str) -> DataFrame:
    code = codes.gaussian(128, 2, 1)
    low, high = spectrum.gaussian_edges(2, 0.75)
    return spectrum.brip_epsilon(spark, code, 16, 12, count=12).select("subset", "lam_min", "lam_max", F.lit(low).alias("edge_low"), F.lit(high).alias("edge_high"))


@query("bounds")
def bounds(spark: SparkSession, sf: str) -> DataFrame:
    """What the theory allows at several eps for the ridge problem of the embeddings: rates and factors, NaN where a condition fails."""
    p, rounds, delta = 4, 50, 0.5
    df, w = fixtures.dense_embeddings(spark, sf, p), fixtures.planted(p)
    mu, big = baselines.data_spectrum(df, p).values()
    f0, far = df.agg(F.avg(F.col("y") * F.col("y")) / 2).first()[0], float(np.linalg.norm(w))
    step, rows = 0.8 / big, []
    for eps in (0.01, 0.05, 0.1, 0.2, 0.5):
        gd = spectrum.bound_gd(rounds, f0, eps, step, mu, big, LAM)
        prox = spectrum.bound_prox(eps, rounds, step, far)
        bcd = spectrum.bound_bcd(rounds, f0, step, big, eps, far, mu)
        c1, c2 = spectrum.inverse_hessian_extremes(eps, delta, mu, big, LAM, p, 2)
        rows.append((eps, gd["rate"], gd["factor"], prox["mean_factor"], prox["growth"], bcd["sublinear"], bcd["rate"], spectrum.bound_lbfgs(eps, c1, c2, mu, LAM), spectrum.approximation_ratio(eps), solvers.rho_from_epsilon(eps)))
    return spark.createDataFrame([tuple(map(float, r)) for r in rows], "eps double, gd_rate double, gd_factor double, prox_factor double, prox_growth double, bcd_gap double, bcd_rate double, lbfgs_rate double, solution_factor double, rho double")


@query("overlap_condition")
def overlap_condition(spark: SparkSession, sf: str) -> DataFrame:
    """The curvature that two rounds on end share, by k."""
    code, rows = codes.hadamard_etf(3), []
    for k in range(8, 17):
        sets = spectrum.subsets_of(16, k, "sample", 21, 5)
        rows += [(k, i, len(set(a) & set(b)), spectrum.overlap_delta(code, 16, a, b)) for i, (a, b) in enumerate(zip(sets, sets[1:], strict=False))]
    return spark.createDataFrame(rows, "k long, pair long, overlap long, delta double")


@query("exact_recovery_redundancy")
def exact_recovery_redundancy(spark: SparkSession, sf: str) -> DataFrame:
    """Storage of codes that recover the gradient exactly against a fixed factor of two, by stragglers."""
    return spark.createDataFrame([(r, spectrum.exact_recovery_redundancy(r), 2) for r in range(8)], "stragglers long, exact long, fixed long")


@query("communication_per_round")
def communication_per_round(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame([(kind, k, metrics.communication(64, k, 2000, kind)) for kind in ("gd", "lbfgs", "prox", "bcd") for k in (4, 8, 12, 16)], "kind string, k long, numbers long")


# ---------------------------------------------------------------- further baselines and rules

_BASELINES = ("uncoded", "perfect", "replication", "exact_recovery:1", "exact_recovery:3", "coded:hadamard", "coded:steiner", "coded+replication:hadamard", "coded+async:hadamard", "sketch")


@query("baseline_schemes")
def baseline_schemes(spark: SparkSession, sf: str) -> DataFrame:
    """The last objective of 30 gradient rounds, 12 of 16 replies, over the optimum."""
    df, p, m = fixtures.dense_embeddings(spark, sf, 8, noise=4.0), 8, 16
    active, clock = compare.replies(spark, stragglers.exponential(), 30, m, 12, 1)
    d = stragglers.delays(spark, stragglers.exponential(), 30, m).toPandas().pivot(index="t", columns="worker", values="delay").to_numpy()
    original, n = partials.whole_gram(df, p), df.count()
    w = solvers.ridge_solution(original, n, LAM)
    best = solvers.Problem(None, n, m, p, LAM, original).objective(w)
    rows = []
    for scheme in _BASELINES:
        run = baselines.run(scheme, df, active["grad"], p=p, lam=LAM, clock=clock, delays=d)
        rows.append((scheme, float(run.trace["objective"].iloc[-1] / best)))
    return spark.createDataFrame(rows, "scheme string, ratio double")


@query("speculation_runtime", f"WITH d AS (SELECT t, worker, {DELAY_SQL['exponential']} AS delay FROM ({GRID})) SELECT t, round(max(delay), 6) AS plain FROM d GROUP BY t")
def speculation_plain(spark: SparkSession, sf: str) -> DataFrame:
    """Rounds that wait for all: the figure that speculation improves."""
    return _delays(spark).groupBy(F.col("t").cast("long").alias("t")).agg(F.round(F.max("delay"), 6).alias("plain"))


@query("speculation_gain")
def speculation_gain(spark: SparkSession, sf: str) -> DataFrame:
    d = _delays(spark)
    s = baselines.speculated(d, 0.75, 1, 0.01)
    plain, fast = (x.groupBy("t").agg(F.max("delay").alias(n)) for x, n in ((d, "plain"), (s, "speculated")))
    return plain.join(fast, "t")


@query("wait_schedule", f"WITH {D} SELECT t, CAST(sum(CASE WHEN rank <= CASE WHEN t = 0 THEN 4 WHEN t = 1 THEN 8 ELSE 12 END THEN 1 ELSE 0 END) AS BIGINT) AS replies FROM a GROUP BY t")
def wait_schedule(spark: SparkSession, sf: str) -> DataFrame:
    a = baselines.WaitPolicy.schedule([4, 8, 12]).apply(_delays(spark))
    return a.groupBy(F.col("t").cast("long").alias("t")).agg(F.sum(F.col("active").cast("long")).alias("replies"))


@query("adversary_never_replies", f"WITH d AS (SELECT t, worker, CASE WHEN worker IN (2, 9) THEN 1e300 ELSE delay END AS delay FROM ({day_sql()})), a AS (SELECT *, row_number() OVER (PARTITION BY t ORDER BY delay, worker) AS rank FROM d) SELECT worker, CAST(sum(CASE WHEN rank <= 14 THEN 1 ELSE 0 END) AS BIGINT) AS rounds FROM a GROUP BY worker")
def adversary_never_replies(spark: SparkSession, sf: str) -> DataFrame:
    never = stragglers.never(lambda t, i, seed: F.col("delay"), [2, 9])
    return stragglers.first_k(days(spark, sf).withColumn("delay", never(F.col("t"), F.col("worker"), 1)), 14).groupBy(F.col("worker").cast("long").alias("worker")).agg(F.sum(F.col("active").cast("long")).alias("rounds"))


@query("encoding_amortisation")
def encoding_amortisation(spark: SparkSession, sf: str) -> DataFrame:
    """Seconds to encode, kept, against seconds of a scan round on the result, by code."""
    import time

    df, rows = fixtures.dense_embeddings(spark, sf, 16), []
    for name in ("uncoded", "hadamard", "steiner", "haar"):
        code = codes.identity(64) if name == "uncoded" else codes.FAMILIES[name](64, 1)
        began = time.time()
        enc = saved(encode.encode_rows(df, code, MW))
        encoded = time.time()
        partials.ScanPartials(enc, MW, 16).gradients(np.zeros(16), np.ones(MW, bool))
        rows.append((name, encoded - began, time.time() - encoded))
    return spark.createDataFrame(rows, "code string, encode_seconds double, round_seconds double")


@query("storage_modes", "SELECT s.range AS extra, CAST(n AS BIGINT) AS source_rows, CAST(n * 2 AS BIGINT) AS stored, CAST(CASE WHEN s.range = 0 THEN 8 ELSE 16 END AS BIGINT) AS workers, n * 2e0 / CASE WHEN s.range = 0 THEN 8 ELSE 16 END AS rows_a_worker FROM range(2) s CROSS JOIN (SELECT count(*) AS n FROM embeddings)")
def storage_modes(spark: SparkSession, sf: str) -> DataFrame:
    """Redundancy of two as more rows a worker, or as twice the workers with as many rows as before."""
    n = fixtures.table(spark, sf, "embeddings").agg(F.count("*").alias("n"))
    workers = F.when(F.col("id") == 0, 8).otherwise(16)
    return spark.range(2).crossJoin(F.broadcast(n)).select(F.col("id").alias("extra"), F.col("n").alias("source_rows"), (F.col("n") * 2).alias("stored"), workers.cast("long").alias("workers"), (F.col("n") * 2.0 / workers).alias("rows_a_worker"))


@query("data_spectrum")
def data_spectrum(spark: SparkSession, sf: str) -> DataFrame:
    rows = [(p, *baselines.data_spectrum(fixtures.dense_embeddings(spark, sf, p), p).values()) for p in (4, 16, 64)]
    return spark.createDataFrame(rows, "p long, low double, high double")


# ---------------------------------------------------------------- layout


@query("layout_pruned_by_worker", f"SELECT worker, count(*) AS rows FROM (SELECT (row_number() OVER (ORDER BY {uniform_sql('range', '0', 1)}, range) - 1) % 8 AS worker FROM range(64)) CROSS JOIN (SELECT DISTINCT vec_id // 28 AS g FROM embeddings) WHERE worker IN (0, 3, 5) GROUP BY 1")
def layout_pruned_by_worker(spark: SparkSession, sf: str) -> DataFrame:
    """Encoded rows laid out by worker; three workers are read, the other folders are not."""
    path = shared(spark, "layout")
    encode.write_by_worker(encode.encode_rows(fixtures.dense_embeddings(spark, sf, 4), CODE(), 8), path)
    return encode.read_active(spark, path, [0, 3, 5]).groupBy(F.col("worker").cast("long").alias("worker")).agg(F.count("*").alias("rows"))


@query("absorbed_ridge_rows", "SELECT count(*) + 3 AS rows, round(sum(x0 * x0) + 0.05e0, 5) AS first FROM (" + _rows_sql() + ")")
def absorbed_ridge_rows(spark: SparkSession, sf: str) -> DataFrame:
    df = encode.absorb_ridge(fixtures.dense_embeddings(spark, sf, PW), LAM, PW)
    return df.agg(F.count("*").alias("rows"), F.round(F.sum(F.col("x")[0] * F.col("x")[0]), 5).alias("first"))


__all__ = ["ORACLES", "QUERIES", "adversary_rows", "lasso_rows", "uniform_np"]
