"""Tables, and fixtures derived from them by arithmetic, so that Spark and SQL agree on every value."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from erasureml.functions.uniform import normal, uniform, uniform_np

SCALE = 8.0
PLANT_SEED, NOISE_SEED, SPLIT_SEED, FEATURE_SEED = 11, 23, 31, 47


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def planted(p: int, sparsity: float = 1.0, scale: float = 2.0) -> np.ndarray:
    """Coefficients in (-scale, scale); a share of them non-zero."""
    j = np.arange(p)
    w = (uniform_np(j, 0, PLANT_SEED) - 0.5) * 2 * scale
    return np.where(uniform_np(j, 1, PLANT_SEED) < sparsity, w, 0.0)


def linear(x: Column | str, w: np.ndarray) -> Column:
    return F.aggregate(F.zip_with(x, F.array(*map(F.lit, w.tolist())), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)


def dense_embeddings(spark: SparkSession, sf_dir: str, p: int = 64, noise: float = 1.0, sparsity: float = 1.0) -> DataFrame:
    """(row_id, x, y): the first p coordinates times 8 (about unit variance), y = x.w + uniform noise."""
    w = planted(p, sparsity)
    x = F.transform(F.slice("embedding", 1, p), lambda v: v.cast("double") * SCALE)
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_id"), x.alias("x")).withColumn("y", linear("x", w) + (uniform("row_id", F.lit(1), NOISE_SEED) - 0.5) * 2 * noise)


def int_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(row_id, f ARRAY<LONG>, y LONG): whole numbers only, so that encoded sums are exact."""
    f = [F.substring("o_orderpriority", 1, 1).cast("long"), F.month("o_orderdate").cast("long"), F.col("o_custkey") % 10]
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("row_id"), F.array(*f).alias("f"), F.round(F.col("o_totalprice") * 100).cast("long").alias("y"))


def gaussian_rows(spark: SparkSession, n: int, p: int, noise: float = 1.0, sparsity: float = 1.0, parts: int = 8) -> DataFrame:
    """Standard normal (row_id, x, y) made in the JVM from row and column numbers."""
    w = planted(p, sparsity)
    x = F.transform(F.sequence(F.lit(0), F.lit(p - 1)), lambda j: normal("id", j, 101))
    rows = spark.range(0, n, 1, parts).select(F.col("id").alias("row_id"), x.alias("x"))
    return rows.withColumn("y", linear("x", w) + noise * normal("row_id", F.lit(p + 1), 103))


def ratings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user, item, rating 1..5, is_test): customer by part, quantity in tens, the mean of repeats; a fifth is test."""
    lines, orders = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders")
    joined = lines.select("l_orderkey", "l_partkey", "l_quantity").join(orders.select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    mean = joined.groupBy(F.col("o_custkey").alias("user"), F.col("l_partkey").alias("item")).agg(F.avg(F.ceil(F.col("l_quantity") / 10)).alias("rating"))
    return mean.withColumn("is_test", uniform("user", F.col("item"), SPLIT_SEED) < 0.2)


def ratings_planted(spark: SparkSession, sf_dir: str, rank: int = 3) -> DataFrame:
    """The same pairs with ratings of low rank and biases, clipped to 1..5."""
    score = F.lit(3.0) + (uniform("user", F.lit(900), 7) - 0.5) * 2 + (uniform("item", F.lit(901), 7) - 0.5) * 2
    for k in range(rank):
        score = score + (uniform("user", F.lit(k), 5) - 0.5) * (uniform("item", F.lit(k + 50), 5) - 0.5) * 4
    return ratings(spark, sf_dir).withColumn("rating", F.least(F.lit(5.0), F.greatest(F.lit(1.0), score)))


def tokens(docs: DataFrame, key: str = "doc_id") -> DataFrame:
    """(doc_id, token, tf) of lower-case words."""
    words = F.filter(F.split(F.lower("text"), r"[^a-z]+"), lambda w: F.length(w) > 0)
    return docs.select(key, F.explode(words).alias("token")).groupBy(key, "token").agg(F.count("*").alias("tf"))


def tfidf(docs: DataFrame, min_df: int = 2, key: str = "doc_id") -> DataFrame:
    """(doc_id, token, val): tf * ln((1 + N) / (1 + df)), each document scaled to length 1."""
    tf = tokens(docs, key)
    df = tf.groupBy("token").agg(F.count("*").alias("df")).where(F.col("df") >= min_df)
    n = docs.agg(F.count("*").alias("docs"))
    raw = tf.join(df, "token").crossJoin(F.broadcast(n)).withColumn("raw", F.col("tf") * F.log((1.0 + F.col("docs")) / (1.0 + F.col("df"))))
    norm = raw.groupBy(key).agg(F.sqrt(F.sum(F.col("raw") * F.col("raw"))).alias("norm"))
    return raw.join(norm, key).where("norm > 0").select(key, "token", (F.col("raw") / F.col("norm")).alias("val"))


def hashed_rows(docs: DataFrame, labels: DataFrame, target: str, p: int = 256, kept: float = 0.69) -> DataFrame:
    """(row_id, x dense of p hashed features, y = -1 or 1, is_test): a subset of tokens, tf-idf, summed by hash."""
    val = tfidf(docs.join(labels.select("doc_id"), "doc_id", "left_semi")).withColumn("h", feature_key("token")).where(uniform("h", F.lit(2), FEATURE_SEED) < kept)
    sums = val.groupBy("doc_id", (F.col("h") % p).cast("int").alias("feat")).agg(F.sum("val").alias("val"))
    x = sums.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("feat", "val"))).alias("m"))
    dense = F.transform(F.sequence(F.lit(0), F.lit(p - 1)), lambda j: F.coalesce(F.element_at("m", j), F.lit(0.0)))
    y = F.when(F.col(target) > 0, 1.0).otherwise(-1.0)
    return x.join(labels, "doc_id").select(F.col("doc_id").alias("row_id"), dense.alias("x"), y.alias("y"), (uniform("doc_id", F.lit(3), SPLIT_SEED) < 0.143).alias("is_test"))


def feature_key(token: Column | str) -> Column:
    """A number of a token's letters, which SQL can follow."""
    return F.aggregate(F.transform(F.split(token, ""), lambda c: F.ascii(c).cast("long")), F.lit(7).cast("long"), lambda s, c: (s * 31 + c) % 2147483647)


def sparse_rows(docs: DataFrame, labels: DataFrame, target: str, p: int, kept: float = 0.69) -> DataFrame:
    """(row_id, idx, val, y = -1 or 1, is_test): tf-idf of a random share of the features, hashed to p places, as sparse rows."""
    val = tfidf(docs.join(labels.select("doc_id"), "doc_id", "left_semi")).withColumn("h", feature_key("token")).where(uniform("h", F.lit(2), FEATURE_SEED) < kept)
    sums = val.groupBy("doc_id", (F.col("h") % p).cast("int").alias("feat")).agg(F.sum("val").alias("v"))
    rows = sums.groupBy("doc_id").agg(F.sort_array(F.collect_list(F.struct("feat", "v"))).alias("m"))
    idx, values = F.transform("m", lambda s: s["feat"]), F.transform("m", lambda s: s["v"])
    y = F.when(F.col(target) > 0, 1.0).otherwise(-1.0)
    test = (uniform("doc_id", F.lit(3), SPLIT_SEED) < 0.143).alias("is_test")
    return rows.join(labels, "doc_id").select(F.col("doc_id").alias("row_id"), idx.alias("idx"), values.alias("val"), y.alias("y"), test)


def onehot_lines(spark: SparkSession, sf_dir: str, noise: float = 0.5) -> tuple[DataFrame, int]:
    """((row_id, x, y), p): brand, type, size and flags of order lines as indicators, y planted; row_id counts the rows.

    The categories are those of the tables; there are as many of them as the table `part` is designed with.
    """
    from erasureml.operators.encode import numbered

    lines = table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "part"), F.col("l_partkey") == F.col("p_partkey"))
    names = ("p_brand", "p_type", "p_size", "l_returnflag", "l_linestatus")
    seen = {c: [r[0] for r in table(spark, sf_dir, "part" if c[0] == "p" else "lineitem").select(c).distinct().orderBy(c).collect()] for c in names}

    def marks(c: str) -> Column:
        return F.transform(F.array(*map(F.lit, seen[c])), lambda v: F.when(F.col(c) == v, 1.0).otherwise(0.0))

    parts = [marks(c) for c in names]
    p = sum(map(len, seen.values()))
    rows = numbered(lines.select(F.concat(*parts).alias("x")))
    return rows.withColumn("y", linear("x", planted(p, 0.15)) + (uniform("row_id", F.lit(1), NOISE_SEED) - 0.5) * 2 * noise).select("row_id", "x", "y"), p
