"""Streaming queries over `events`, with the SQL of what they add up to once all input is read."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erasureml.sources.fixtures import table
from erasureml.streaming import rounds

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
M = 8


def stream(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[f"stream_{name}"] = f
        if sql:
            ORACLES[f"stream_{name}"] = sql
        return f

    return keep


def _replies(spark: SparkSession, sf: str) -> DataFrame:
    return rounds.replies(rounds.source(spark, sf), M)


_R = f"r AS (SELECT CAST(dayofyear(ts) AS BIGINT) AS t, CAST(user_id % {M} AS BIGINT) AS worker, ts, event_id, value FROM events)"


@stream("first_k", f"WITH {_R} SELECT t, worker, event_id FROM (SELECT *, row_number() OVER (PARTITION BY t ORDER BY ts, event_id) AS k FROM r) WHERE k <= 5")
def first_k(spark, sf):
    """In one trigger; over several, replies count in the order in which files come."""
    out = rounds.finished(rounds.first_k(_replies(spark, sf), 5))
    return out.select(F.col("t").cast("long").alias("t"), F.col("worker").cast("long").alias("worker"), "event_id")


@stream("participation", f"WITH {_R} SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS start, worker, count(*) AS n FROM r GROUP BY 1, 2")
def participation(spark, sf):
    out = rounds.finished(rounds.participation(_replies(spark, sf)), "complete")
    return out.select("start", F.col("worker").cast("long").alias("worker"), "n")


@stream("round_times")
def round_times(spark, sf):
    return rounds.finished(rounds.round_times(_replies(spark, sf)), "complete")


@stream("idle_spells", f"WITH {_R}, g AS (SELECT *, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER w < 7200000000 THEN 0 ELSE 1 END AS new FROM r WINDOW w AS (PARTITION BY worker ORDER BY ts, event_id)), s AS (SELECT *, sum(new) OVER (PARTITION BY worker ORDER BY ts, event_id) AS k FROM g) SELECT worker, count(*) AS n FROM s GROUP BY worker, k")
def idle_spells(spark, sf):
    out = rounds.finished(rounds.idle_spells(_replies(spark, sf)), "complete")
    return out.select(F.col("worker").cast("long").alias("worker"), "n")


@stream("replica_dedupe", f"WITH {_R} SELECT DISTINCT t, worker % 4 AS part FROM r")
def replica_dedupe(spark, sf):
    return rounds.finished(rounds.deduplicated(_replies(spark, sf), 4)).select(F.col("t").cast("long").alias("t"), F.col("part").cast("long").alias("part"))


@stream("request_reply", f"WITH {_R} SELECT a.event_id AS q_id, b.event_id AS event_id FROM r a JOIN r b ON a.worker = b.worker AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_id % 10 = 0")
def request_reply(spark, sf):
    """Every tenth event asks, as in its SQL; in `request_reply_all` all do."""
    asked = _replies(spark, sf).where("event_id % 10 = 0")
    return rounds.finished(rounds.answered(asked, _replies(spark, sf))).select("q_id", "event_id")


@stream("request_reply_all", f"WITH {_R} SELECT a.event_id AS q_id, b.event_id AS event_id FROM r a JOIN r b ON a.worker = b.worker AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def request_reply_all(spark, sf):
    return rounds.finished(rounds.answered(_replies(spark, sf), _replies(spark, sf))).select("q_id", "event_id")


@stream("enriched", f"SELECT s_name AS name, count(*) AS n FROM events JOIN supplier ON user_id % {M} = s_suppkey GROUP BY 1")
def enriched(spark, sf):
    s = table(spark, sf, "supplier").select(F.col("s_suppkey").cast("int").alias("worker"), F.col("s_name").alias("name"))
    return rounds.finished(rounds.enriched(_replies(spark, sf), s).groupBy("name").agg(F.count("*").alias("n")), "complete")


@stream("online_steps", "SELECT count(*) AS replies, round(sum(value), 4) AS total FROM events")
def online_steps(spark, sf):
    """A step a micro-batch; here the step adds up, so that the whole is known."""
    seen = rounds.online_steps(_replies(spark, sf), lambda df, i: df.agg(F.count("*").alias("n"), F.sum("payload").alias("v")).first())
    return spark.createDataFrame([(sum(r["n"] for r in seen), float(sum(r["v"] or 0 for r in seen)))], "replies long, total double").select("replies", F.round("total", 4).alias("total"))
