"""Every registered query against its SQL on the smallest tables, and the waiting rules of streams."""

import duckdb
import pytest
from pyspark.sql import functions as F

from erasureml.operators import codes, encode
from erasureml.plans import catalog
from erasureml.streaming import rounds

AT = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{AT}/{t}.parquet'")
    return c


def _norm(v):
    return 0.0 if isinstance(v, float) and v == 0 else v


@pytest.mark.parametrize("name", sorted(catalog.ORACLES))
def test_query_equals_sql(spark, con, name):
    df = catalog.QUERIES[name](spark, AT)
    columns = sorted(df.columns)
    got = sorted((tuple(_norm(r[c]) for c in columns) for r in df.collect()), key=str)
    cur = con.execute(catalog.ORACLES[name])
    at = [[d[0] for d in cur.description].index(c) for c in columns]
    assert got == sorted((tuple(_norm(r[i]) for i in at) for r in cur.fetchall()), key=str)


def test_entry_and_registry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 8
    assert set(e.oracle_sql()) <= set(e.queries())


def test_stream_takes_first_k_over_several_triggers(spark, tmp_path):
    events = spark.read.parquet(f"{AT}/events.parquet").orderBy("ts", "event_id").limit(300).toPandas()
    for i in range(3):
        spark.createDataFrame(events.iloc[100 * i : 100 * i + 100]).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    schema = spark.read.parquet(f"{tmp_path}/in").schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    out = rounds.finished(rounds.first_k(rounds.replies(stream, 8), 4))
    per = {r["t"]: r["count"] for r in out.groupBy("t").count().collect()}
    whole = {r["t"]: min(4, r["count"]) for r in rounds.replies(spark.read.parquet(f"{tmp_path}/in"), 8).groupBy("t").count().collect()}
    assert per == whole


def test_stream_goes_on_after_a_restart(spark, tmp_path):
    """The second run finds its state and reads the new file only."""
    events = spark.read.parquet(f"{AT}/events.parquet").orderBy("ts", "event_id").limit(200).toPandas()
    schema = spark.read.parquet(f"{AT}/events.parquet").schema
    for i in range(2):
        spark.createDataFrame(events.iloc[100 * i : 100 * i + 100]).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        stream = spark.readStream.schema(schema).parquet(f"{tmp_path}/in")
        out = rounds.first_k(rounds.replies(stream, 8), 4).writeStream.option("checkpointLocation", f"{tmp_path}/state").trigger(availableNow=True)
        out.format("parquet").option("path", f"{tmp_path}/out").start().awaitTermination()
    got = {r["t"]: r["count"] for r in spark.read.parquet(f"{tmp_path}/out").groupBy("t").count().collect()}
    whole = {r["t"]: min(4, r["count"]) for r in rounds.replies(spark.read.parquet(f"{tmp_path}/in"), 8).groupBy("t").count().collect()}
    assert got == whole


def test_standardise_all_gives_every_row(spark):
    assert catalog.QUERIES["op_standardise_all"](spark, AT).count() == spark.read.parquet(f"{AT}/lineitem.parquet").count()


@pytest.mark.parametrize("name", sorted(catalog.QUERIES))
def test_every_query_is_a_function(name):
    assert callable(catalog.QUERIES[name])


@pytest.mark.parametrize("scheme", ["exact", "uncoded", "replication", "gaussian", "paley", "hadamard"])
def test_factorisation_of_every_scheme_runs(spark, scheme):
    rows = catalog.QUERIES[f"mf_altmin_{scheme}"](spark, AT).collect()
    assert [(r["scheme"], r["epoch"]) for r in rows] == [(scheme, 0), (scheme, 1)]
    assert all(0 < r["train_rmse"] < 5 and 0 < r["test_rmse"] < 5 for r in rows)


@pytest.mark.parametrize("name", ["encode_rows_steiner_embeddings", "encode_rows_haar_embeddings"])
@pytest.mark.parametrize("rows", [29, 34, 60])
def test_encoded_rows_of_an_incomplete_group_equal_sql(spark, tmp_path, name, rows):
    """One row of 28 reaches two of a pair code's eight blocks; the SQL has no row for the others."""
    spark.read.parquet(f"{AT}/embeddings.parquet").where(f"vec_id < {rows} AND vec_id <> 3").write.parquet(f"{tmp_path}/embeddings.parquet")
    c = duckdb.connect()
    c.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet/*.parquet'")
    got = sorted(tuple(r) for r in catalog.QUERIES[name](spark, str(tmp_path)).select("enc_row", "x1", "x2").collect())
    assert got == sorted(c.execute(f"SELECT enc_row, x1, x2 FROM ({catalog.ORACLES[name]})").fetchall())


def test_both_ways_of_encoding_leave_the_same_rows_out(spark):
    df = spark.createDataFrame([(i, [float(i + 1)], 1.0) for i in (0, 1, 30, 57)], "row_id long, x array<double>, y double")
    ways = [encode.encode_rows(df, codes.steiner(8), 4, mode=mode, untouched=False).collect() for mode in ("grouped", "join")]
    assert sorted(map(str, ways[0])) == sorted(map(str, ways[1])) and len(ways[0]) < 3 * 64


FOLLOW = ["active_complement", "active_overlap", "adaptive_k", "adaptive_k_in_order", "adversary_never_replies", "async_replay", "async_staleness", "async_update_share", "bounds", "brip_epsilon", "brip_spectrum", "brip_trace"]


@pytest.mark.parametrize("name", FOLLOW)
def test_query_follows_its_table(spark, tmp_path, name):
    """Other events (or vectors) give other rows, and those of the SQL where there is SQL."""
    spark.read.parquet(f"{AT}/events.parquet").withColumn("value", F.lit(400.0) - F.col("value")).where("user_id <> 3 AND (dayofyear(ts) % 5 > 0 OR user_id % 8 < 3)").write.parquet(f"{tmp_path}/events.parquet")
    spark.read.parquet(f"{AT}/embeddings.parquet").withColumn("embedding", F.transform("embedding", lambda v: v * 2)).write.parquet(f"{tmp_path}/embeddings.parquet")
    other = catalog.QUERIES[name](spark, str(tmp_path))
    got = sorted(map(tuple, other.collect()), key=str)
    assert got and got != sorted(map(tuple, catalog.QUERIES[name](spark, AT).collect()), key=str)
    if name in catalog.ORACLES:
        c = duckdb.connect()
        c.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet/*.parquet'")
        assert got == sorted(c.execute(f"SELECT {', '.join(other.columns)} FROM ({catalog.ORACLES[name]})").fetchall(), key=str)


def test_requests_meet_only_the_rows_of_their_span(spark, tmp_path):
    """Each pair once, also at an hour's edges and before 1970; the join is dealt by worker and span."""
    at = ["1969-12-31 22:59:59.5", "1969-12-31 23:30:00", "1970-01-01 00:00:00", "1970-01-01 01:00:00", "1970-01-01 01:00:00.000001", "1970-01-01 01:59:59", "1970-01-01 03:00:00"]
    rows = spark.createDataFrame([(i, 8 * i, 1.0, v) for i, v in enumerate(at)], "event_id long, user_id long, value double, at string").withColumn("ts", F.to_timestamp("at"))
    replies = rounds.replies(rows, 8)
    got = sorted((r["q_id"], r["event_id"]) for r in rounds.answered(replies, replies).collect())
    a, b = replies.alias("a"), replies.alias("b")
    plain = a.join(b, F.expr("b.arrival_ts > a.arrival_ts AND b.arrival_ts <= a.arrival_ts + interval 1 hour"))
    assert got == sorted((r[0], r[1]) for r in plain.select("a.event_id", "b.event_id").collect()) and got
    plan = rounds.answered(replies, replies)._jdf.queryExecution().optimizedPlan().toString()
    assert "q_span" in plan.split("Join Inner")[1].splitlines()[0]


def test_all_events_ask_in_the_same_keyed_join(spark):
    """Of pairs from all requests, those of every tenth are the other query's."""
    some, every = ({(r["q_id"], r["event_id"]) for r in catalog.QUERIES[f"stream_request_reply{n}"](spark, AT).collect()} for n in ("", "_all"))
    assert some == {p for p in every if p[0] % 10 == 0}
