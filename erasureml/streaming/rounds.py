"""Waiting rules over a stream of replies.

Replies are (t, worker, arrival_ts, payload). All functions take and return DataFrames, streaming or not; `finished`
runs a stream over what is there and gives its result as a table in the shared folder.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def shared(spark: SparkSession, name: str) -> str:
    """A new path in the checkpoint folder that the session names.  Without one, a temporary folder that goes with the process
    if Spark runs in one JVM; on a cluster that would be the driver's own disk, so there it is an error."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not (sc.master == "local" or sc.master.startswith("local[")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        if not named:
            named = tempfile.mkdtemp(prefix="ckpt")
            atexit.register(shutil.rmtree, named, True)
        sc.setCheckpointDir(named)
    return f"{sc.getCheckpointDir()}/{name}-{uuid.uuid4().hex}"


def replies(events: DataFrame, m: int) -> DataFrame:
    """Every worker's events as replies to rounds of a day each."""
    return events.select(F.dayofyear("ts").alias("t"), (F.col("user_id") % m).cast("int").alias("worker"), F.col("ts").cast("timestamp").alias("arrival_ts"), "event_id", F.col("value").alias("payload"))


def source(spark: SparkSession, sf_dir: str, files_a_batch: int = 1) -> DataFrame:
    """The table as a stream, a file a trigger. A pattern names it, as Spark takes a single file by a pattern only."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_a_batch).parquet(f"{sf_dir}/events.parque[t]")


def first_k(stream: DataFrame, k: int) -> DataFrame:
    """The first k replies of every round; its state is a count, so a closed round costs a number."""

    def accept(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        count = state.get[0] if state.exists else 0
        frame = pd.concat(list(frames), ignore_index=True).sort_values(["arrival_ts", "event_id"])
        taken = frame.head(max(0, k - count))
        state.update((count + len(taken),))
        yield taken[["t", "worker", "event_id", "payload"]]

    return stream.groupBy("t").applyInPandasWithState(accept, "t int, worker int, event_id long, payload double", "count int", "append", "NoTimeout")


def late_replies(stream: DataFrame, k: int) -> DataFrame:
    """(t, replies, late): how many replies come to a round and how many of them are over its first k, which drops them."""
    return stream.groupBy("t").agg(F.count("*").alias("replies")).withColumn("late", F.greatest(F.lit(0), F.col("replies") - k).cast("long"))


def participation(stream: DataFrame, width: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Replies by worker and hour; later ones than the watermark are dropped."""
    return stream.withWatermark("arrival_ts", late).groupBy(F.window("arrival_ts", width).alias("w"), "worker").agg(F.count("*").alias("n")).select(F.unix_timestamp("w.start").alias("start"), "worker", "n")


def round_times(stream: DataFrame, width: str = "6 hours", slide: str = "1 hour") -> DataFrame:
    """Sliding mean and largest payload."""
    own = stream.withWatermark("arrival_ts", "2 hours").groupBy(F.window("arrival_ts", width, slide).alias("w"))
    return own.agg(F.count("*").alias("n"), F.max("payload").alias("slowest"), F.percentile_approx("payload", 0.5).alias("middle")).select(F.unix_timestamp("w.start").alias("start"), "n", "slowest", "middle")


def idle_spells(stream: DataFrame, gap: str = "2 hours") -> DataFrame:
    own = stream.withWatermark("arrival_ts", "2 hours").groupBy("worker", F.session_window("arrival_ts", gap).alias("w"))
    return own.agg(F.count("*").alias("n")).select("worker", F.unix_timestamp("w.start").alias("start"), F.unix_timestamp("w.end").alias("stop"), "n")


def deduplicated(stream: DataFrame, parts: int) -> DataFrame:
    """The first copy of every part and round."""
    part = stream.withColumn("part", F.col("worker") % parts).withWatermark("arrival_ts", "40 days")
    return part.dropDuplicatesWithinWatermark(["t", "part"]).select("t", "part")


def answered(requests: DataFrame, stream: DataFrame, within: str = "1 hour") -> DataFrame:
    """Replies joined to the requests of the hour before them.

    A request is looked for in the one or two spans of that length that its replies can lie in, a reply lies in one: a row meets
    its own span's rows in the state, not all that its worker ever had, and spans are dealt over tasks.
    """
    width = pd.Timedelta(within).value // 1000
    span = "unix_micros({}) div " + str(width)
    q = requests.select(F.col("worker").alias("q_worker"), F.col("arrival_ts").alias("asked"), F.col("event_id").alias("q_id")).withWatermark("asked", "2 hours")
    q = q.withColumn("q_span", F.explode(F.expr(f"sequence({span.format('asked')}, {span.format(f'(asked + interval {within})')})")))
    r = stream.withWatermark("arrival_ts", "2 hours").withColumn("span", F.expr(span.format("arrival_ts")))
    on = (F.col("q_worker") == F.col("worker")) & (F.col("q_span") == F.col("span")) & (F.col("arrival_ts") > F.col("asked")) & (F.col("arrival_ts") <= F.col("asked") + F.expr(f"interval {within}"))
    return q.join(r, on).select("q_id", "event_id", "worker")


def enriched(stream: DataFrame, static: DataFrame) -> DataFrame:
    """Replies with facts about their worker; the static side is broadcast only if Spark finds it small."""
    return stream.join(static, "worker")


def finished(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run until all input is read; complete and update results replace the table, by batch."""
    spark = stream.sparkSession
    out, checkpoint = shared(spark, "stream"), shared(spark, "stream-checkpoint")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").option("path", out).start()
    else:
        query = writer.foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(out)).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def online_steps(stream: DataFrame, step) -> list:
    """One step of a solver for each micro-batch; step(batch) sees its accepted replies."""
    seen: list = []
    checkpoint = shared(stream.sparkSession, "steps-checkpoint")
    stream.writeStream.option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(lambda df, i: seen.append(step(df, i))).start().awaitTermination()
    return seen
