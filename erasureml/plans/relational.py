"""The relational surface that users of the solvers need, each operator on a given table, with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from erasureml.functions.transforms import dot, register, soft_threshold
from erasureml.functions.uniform import uniform, uniform_sql
from erasureml.sources.fixtures import table
from erasureml.streaming.rounds import shared

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def op(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[f"op_{name}"] = f
        if sql:
            ORACLES[f"op_{name}"] = sql
        return f

    return keep


def t(spark: SparkSession, sf: str, *names: str) -> list[DataFrame]:
    return [table(spark, sf, n) for n in names]


def long(c) -> F.Column:
    return (F.col(c) if isinstance(c, str) else c).cast("long")


# ---------------------------------------------------------------- sources and sinks

ALL = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@op("scan_all_tables", " UNION ALL ".join(f"SELECT '{n}' AS name, count(*) AS rows FROM {n}" for n in ALL))
def scan_all_tables(spark, sf):
    out = None
    for n in ALL:
        one = table(spark, sf, n).agg(F.count("*").alias("rows")).select(F.lit(n).alias("name"), "rows")
        out = one if out is None else out.unionByName(one)
    return out


@op("scan_pushdown", "SELECT count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem WHERE l_quantity >= 40 AND l_returnflag = 'R'")
def scan_pushdown(spark, sf):
    """Two of eleven columns are read and both filters reach the scan."""
    (li,) = t(spark, sf, "lineitem")
    return li.where((F.col("l_quantity") >= 40) & (F.col("l_returnflag") == "R")).agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"))


@op("partitioned_layout", "SELECT CAST(user_id % 8 AS BIGINT) AS worker, count(*) AS n FROM events WHERE user_id % 8 IN (1, 5) GROUP BY 1")
def partitioned_layout(spark, sf):
    path = shared(spark, "layout")
    table(spark, sf, "events").withColumn("worker", F.col("user_id") % 8).repartition("worker").write.partitionBy("worker").parquet(path)
    return spark.read.parquet(path).where(F.col("worker").isin(1, 5)).groupBy(long("worker").alias("worker")).agg(F.count("*").alias("n"))


@op("bucketed_join", "SELECT o_orderstatus AS status, count(*) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def bucketed_join(spark, sf):
    """Both sides bucketed and sorted on the key: the join has no exchange."""
    import uuid

    o, li = t(spark, sf, "orders", "lineitem")
    names = []
    for df, key in ((o.select("o_orderkey", "o_orderstatus"), "o_orderkey"), (li.select("l_orderkey", "l_partkey"), "l_orderkey")):
        names.append(f"bucketed_{uuid.uuid4().hex}")
        df.repartition(8, key).write.bucketBy(8, key).sortBy(key).format("parquet").saveAsTable(names[-1])
    a, b = (spark.table(n) for n in names)
    return a.join(b, a["o_orderkey"] == b["l_orderkey"]).groupBy(F.col("o_orderstatus").alias("status")).agg(F.count("*").alias("lines"))


def _round_trip(kind: str, **options):
    def run(spark, sf):
        path, (c,) = shared(spark, kind), t(spark, sf, "customer")
        df = c.select("c_custkey", "c_name", "c_nationkey", "c_mktsegment")
        df.write.options(**options).format(kind).save(path)
        return spark.read.schema(df.schema).options(**options).format(kind).load(path).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.sum("c_custkey").alias("keys"))

    return run


for _k, _o in (("csv", {"header": "true"}), ("json", {}), ("orc", {})):
    op(f"{_k}_round_trip", "SELECT c_mktsegment, count(*) AS n, CAST(sum(c_custkey) AS BIGINT) AS keys FROM customer GROUP BY 1")(_round_trip(_k, **_o))


@op("generator_source", "SELECT CAST(range % 7 AS BIGINT) AS r, count(*) AS n, CAST(sum(range) AS BIGINT) AS s FROM range(10000) GROUP BY 1")
def generator_source(spark, sf):
    return spark.range(0, 10000, 1, 8).groupBy((F.col("id") % 7).alias("r")).agg(F.count("*").alias("n"), F.sum("id").alias("s"))


@op("file_metadata")
def file_metadata(spark, sf):
    """Which worker's files a pruned read touched."""
    path = shared(spark, "meta")
    table(spark, sf, "events").withColumn("worker", F.col("user_id") % 4).repartition("worker").write.partitionBy("worker").parquet(path)
    read = spark.read.parquet(path).where("worker IN (0, 2)").select("worker", F.regexp_extract("_metadata.file_path", "worker=([0-9]+)", 1).alias("folder"))
    return read.groupBy("worker", "folder").agg(F.count("*").alias("n"))


# ---------------------------------------------------------------- projections and filters


@op("computed_columns", "SELECT l_orderkey, l_linenumber, l_partkey, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 4) AS charge FROM lineitem WHERE l_tax > 0.07")
def computed_columns(spark, sf):
    (li,) = t(spark, sf, "lineitem")
    return li.where("l_tax > 0.07").select("l_orderkey", "l_linenumber", "l_partkey", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax")), 4).alias("charge"))


@op("in_set_filter", "SELECT event_type, count(*) AS n FROM events WHERE user_id % 16 IN (0, 3, 7, 9) GROUP BY 1")
def in_set_filter(spark, sf):
    return table(spark, sf, "events").where((F.col("user_id") % 16).isin(0, 3, 7, 9)).groupBy("event_type").agg(F.count("*").alias("n"))


@op("predicates", "SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_totalprice BETWEEN 50000 AND 150000 AND o_custkey IS NOT NULL AND o_orderpriority LIKE '%I%' AND regexp_matches(o_orderstatus, '^[OF]$') GROUP BY 1")
def predicates(spark, sf):
    (o,) = t(spark, sf, "orders")
    return o.where(F.col("o_totalprice").between(50000, 150000) & F.col("o_custkey").isNotNull() & F.col("o_orderpriority").like("%I%") & F.col("o_orderstatus").rlike("^[OF]$")).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@op("hash_split", f"SELECT {uniform_sql('o_orderkey', '0', 31)} < 0.2e0 AS is_test, count(*) AS n, CAST(sum(o_orderkey) AS BIGINT) AS keys FROM orders GROUP BY 1")
def hash_split(spark, sf):
    return table(spark, sf, "orders").groupBy((uniform("o_orderkey", F.lit(0), 31) < 0.2).alias("is_test")).agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("keys"))


@op("conditional_value", "SELECT CAST(sum(CASE WHEN l_returnflag = 'A' THEN 1 WHEN l_linestatus = 'O' THEN -1 ELSE 0 END) AS BIGINT) AS balance FROM lineitem")
def conditional_value(spark, sf):
    return table(spark, sf, "lineitem").agg(F.sum(F.when(F.col("l_returnflag") == "A", 1).when(F.col("l_linestatus") == "O", -1).otherwise(0)).alias("balance"))


@op("bernoulli_sample")
def bernoulli_sample(spark, sf):
    return table(spark, sf, "lineitem").sample(0.1, 7).agg(F.count("*").alias("n"))


@op("stratified_sample")
def stratified_sample(spark, sf):
    return table(spark, sf, "orders").sampleBy("o_orderstatus", {"O": 0.1, "F": 0.5}, 3).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


# ---------------------------------------------------------------- joins


def _equi(hint: str):
    def run(spark, sf):
        o, li = t(spark, sf, "orders", "lineitem")
        return li.select("l_orderkey", "l_quantity").join(o.select("o_orderkey", "o_orderpriority").hint(hint), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("q"))

    return run


for _h in ("shuffle_hash", "merge"):
    op(f"join_{_h}", "SELECT o_orderpriority, count(*) AS n, sum(l_quantity) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")(_equi(_h))


@op("join_broadcast", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def join_broadcast(spark, sf):
    """nation has 25 rows whatever the scale."""
    c, n = t(spark, sf, "customer", "nation")
    return c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


@op("join_semi", "SELECT lang, count(*) AS n FROM documents WHERE doc_id IN (SELECT doc_id FROM labels) GROUP BY 1")
def join_semi(spark, sf):
    d, la = t(spark, sf, "documents", "labels")
    return d.join(la, "doc_id", "left_semi").groupBy("lang").agg(F.count("*").alias("n"))


@op("join_anti", "SELECT lang, count(*) AS n FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels) GROUP BY 1")
def join_anti(spark, sf):
    d, la = t(spark, sf, "documents", "labels")
    return d.join(la, "doc_id", "left_anti").groupBy("lang").agg(F.count("*").alias("n"))


@op("join_full_outer", "SELECT CAST(coalesce(a.k, b.k) AS BIGINT) AS k, coalesce(x, 0) AS x, coalesce(y, 0) AS y FROM (SELECT c_nationkey AS k, count(*) AS x FROM customer WHERE c_acctbal > 9000 GROUP BY 1) a FULL OUTER JOIN (SELECT s_nationkey AS k, count(*) AS y FROM supplier GROUP BY 1) b ON a.k = b.k")
def join_full_outer(spark, sf):
    c, s = t(spark, sf, "customer", "supplier")
    a = c.where("c_acctbal > 9000").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("x"))
    b = s.groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("y"))
    return a.join(b, "k", "full_outer").select(long("k").alias("k"), F.coalesce("x", F.lit(0)).cast("long").alias("x"), F.coalesce("y", F.lit(0)).cast("long").alias("y"))


@op("join_left_default", "SELECT c_custkey, coalesce(n, 0) AS n FROM customer LEFT JOIN (SELECT o_custkey, count(*) AS n FROM orders WHERE o_orderstatus = 'P' GROUP BY 1) ON c_custkey = o_custkey")
def join_left_default(spark, sf):
    c, o = t(spark, sf, "customer", "orders")
    n = o.where("o_orderstatus = 'P'").groupBy("o_custkey").agg(F.count("*").alias("n"))
    return c.join(n, F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


@op("cross_small", "SELECT a.r_name AS a, b.r_name AS b FROM region a CROSS JOIN region b WHERE a.r_regionkey < b.r_regionkey")
def cross_small(spark, sf):
    """Five rows by five: pairs of encoding vectors are formed so, for codes of a fixed order."""
    (r,) = t(spark, sf, "region")
    a, b = r.select(F.col("r_regionkey").alias("i"), F.col("r_name").alias("a")), r.select(F.col("r_regionkey").alias("j"), F.col("r_name").alias("b"))
    return a.crossJoin(F.broadcast(b)).where("i < j").select("a", "b")


@op("theta_join", "SELECT p_brand, count(*) AS n FROM part JOIN (VALUES (1, 10), (40, 45)) v(lo, hi) ON p_size BETWEEN lo AND hi GROUP BY 1")
def theta_join(spark, sf):
    v = spark.createDataFrame([(1, 10), (40, 45)], "lo int, hi int")
    return table(spark, sf, "part").join(F.broadcast(v), F.col("p_size").between(F.col("lo"), F.col("hi"))).groupBy("p_brand").agg(F.count("*").alias("n"))


ASOF = "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN value END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS state FROM events"


@op("asof_join", ASOF)
def asof_join(spark, sf):
    """The newest purchase before each event of a user: a union in time order, so one sort by user."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return table(spark, sf, "events").select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("value")), ignorenulls=True).over(w).alias("state"))


@op("interval_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR")
def interval_join(spark, sf):
    """Equal users, and a time bucket of the interval's length: a row meets two buckets, not all of its user's."""
    e = table(spark, sf, "events").select("event_id", "user_id", "ts")
    width = 6 * 3600
    a = e.select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("ta"), F.explode(F.array(F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / width), F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / width) + 1)).alias("bucket"))
    b = e.select(F.col("event_id").alias("b"), "user_id", "ts", F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / width).alias("bucket"))
    on = (F.col("u") == F.col("user_id")) & (a["bucket"] == b["bucket"]) & (F.col("ts") > F.col("ta")) & (F.col("ts") <= F.col("ta") + F.expr("interval 6 hours"))
    return a.join(b, on).select("a", "b")


@op("star_join", "SELECT r_name, p_brand, round(sum(l_extendedprice), 2) AS price FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON l_partkey = p_partkey GROUP BY 1, 2")
def star_join(spark, sf):
    li, o, c, n, r, p = t(spark, sf, "lineitem", "orders", "customer", "nation", "region", "part")
    j = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).join(p, F.col("l_partkey") == F.col("p_partkey"))
    return j.groupBy("r_name", "p_brand").agg(F.round(F.sum("l_extendedprice"), 2).alias("price"))


@op("self_join_previous", "WITH d AS (SELECT DISTINCT user_id, CAST(dayofyear(ts) AS BIGINT) AS day FROM events) SELECT a.day, count(*) AS n FROM d a JOIN d b ON a.user_id = b.user_id AND a.day = b.day + 1 GROUP BY 1")
def self_join_previous(spark, sf):
    d = table(spark, sf, "events").select("user_id", F.dayofyear("ts").cast("long").alias("day")).distinct()
    return d.join(d.withColumn("day", F.col("day") + 1), ["user_id", "day"]).groupBy("day").agg(F.count("*").alias("n"))


@op("salted_join", "SELECT source, count(*) AS n, sum(length(text)) AS chars FROM documents JOIN (SELECT DISTINCT source AS s FROM documents) ON source = s GROUP BY 1")
def salted_join(spark, sf):
    """A hot source is spread over 8 salts, and its partner row is repeated for each."""
    d = table(spark, sf, "documents").select("source", F.length("text").cast("long").alias("len"), (F.col("doc_id") % 8).cast("int").alias("salt"))
    s = d.select("source").distinct().select("source", F.explode(F.sequence(F.lit(0), F.lit(7))).alias("salt"))
    part = d.join(s, ["source", "salt"]).groupBy("source", "salt").agg(F.count("*").alias("n"), F.sum("len").alias("chars"))
    return part.groupBy("source").agg(F.sum("n").alias("n"), F.sum("chars").cast("decimal(38,0)").alias("chars"))


ORACLES["op_salted_join"] = ORACLES["op_salted_join"].replace("sum(length(text)) AS chars", "CAST(sum(length(text)) AS BIGINT) AS chars")
_salted = QUERIES["op_salted_join"]
QUERIES["op_salted_join"] = lambda spark, sf: _salted(spark, sf).withColumn("chars", F.col("chars").cast("long"))


# ---------------------------------------------------------------- aggregations


@op("group_sum", "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS q, round(avg(l_discount), 8) AS d FROM lineitem GROUP BY 1, 2")
def group_sum(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("q"), F.round(F.avg("l_discount"), 8).alias("d"))


@op("vector_sum", "SELECT CAST(label AS BIGINT) AS label, CAST(pos AS BIGINT) AS pos, round(sum(v), 4) + 0e0 AS v FROM (SELECT label, unnest(range(64)) AS pos, unnest(list_transform(embedding, lambda x: CAST(x AS DOUBLE))) AS v FROM embeddings) GROUP BY 1, 2")
def vector_sum(spark, sf):
    return table(spark, sf, "embeddings").select("label", F.posexplode("embedding").alias("pos", "v")).groupBy(long("label").alias("label"), long("pos").alias("pos")).agg((F.round(F.sum(F.col("v").cast("double")), 4) + 0.0).alias("v"))


@op("gram_matrix", "WITH x AS (SELECT vec_id, unnest(range(8)) AS i, unnest(list_transform(embedding[1:8], lambda x: CAST(x AS DOUBLE))) AS v FROM embeddings) SELECT CAST(a.i AS BIGINT) AS i, CAST(b.i AS BIGINT) AS j, round(sum(a.v * b.v), 5) + 0e0 AS g FROM x a JOIN x b ON a.vec_id = b.vec_id GROUP BY 1, 2")
def gram_matrix(spark, sf):
    """Pairs inside a row, by nested transforms: no join."""
    x = table(spark, sf, "embeddings").select(F.transform(F.slice("embedding", 1, 8), lambda v: v.cast("double")).alias("x"))
    pairs = x.select("x", F.posexplode("x").alias("i", "a")).select("i", "a", F.posexplode("x").alias("j", "b"))
    return pairs.groupBy(long("i").alias("i"), long("j").alias("j")).agg((F.round(F.sum(F.col("a") * F.col("b")), 5) + 0.0).alias("g"))


@op("tree_sum", "SELECT round(sum(value), 4) AS total, count(*) AS n FROM events")
def tree_sum(spark, sf):
    part = table(spark, sf, "events").groupBy((F.col("user_id") % 4).alias("node")).agg(F.sum("value").alias("v"), F.count("*").alias("n"))
    return part.agg(F.round(F.sum("v"), 4).alias("total"), F.sum("n").alias("n"))


@op("count_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def count_distinct(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@op("approx_distinct")
def approx_distinct(spark, sf):
    return table(spark, sf, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


for _kind, _sql in (("cube", "CUBE (l_returnflag, l_linestatus)"), ("rollup", "ROLLUP (l_returnflag, l_linestatus)")):
    op(_kind, f"SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY {_sql}")(
        lambda spark, sf, kind=_kind: getattr(table(spark, sf, "lineitem"), kind)("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))
    )


@op("grouping_sets", "SELECT event_type, CAST(user_id % 4 AS BIGINT) AS w, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type), (user_id % 4), ())")
def grouping_sets(spark, sf):
    e = table(spark, sf, "events").select("event_type", (F.col("user_id") % 4).alias("w"))
    return e.groupingSets([[F.col("event_type")], [F.col("w")], []], "event_type", "w").agg(F.count("*").alias("n"))


@op("pivot", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY 1")
def pivot(spark, sf):
    p = table(spark, sf, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1)))
    return p.select("o_orderpriority", *(F.coalesce(s, F.lit(0)).cast("long").alias(s.lower()) for s in ("F", "O", "P")))


@op("min_by", "SELECT user_id, arg_min(event_id, (ts, event_id)) AS first, arg_max(event_id, (ts, event_id)) AS last FROM events GROUP BY 1")
def min_by(spark, sf):
    key = F.struct("ts", "event_id")
    return table(spark, sf, "events").groupBy("user_id").agg(F.min_by("event_id", key).alias("first"), F.max_by("event_id", key).alias("last"))


@op("statistics", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS middle, round(stddev_samp(value), 6) AS sd, round(corr(value, user_id), 6) AS c, round(regr_slope(value, user_id), 8) AS slope FROM events GROUP BY 1")
def statistics(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(F.round(F.expr("percentile(value, 0.5)"), 6).alias("middle"), F.round(F.stddev_samp("value"), 6).alias("sd"), F.round(F.corr("value", "user_id"), 6).alias("c"), F.round(F.regr_slope("value", "user_id"), 8).alias("slope"))


@op("collect_map", "SELECT o_custkey, array_to_string(list(o_orderkey ORDER BY o_orderkey), ',') AS orders FROM orders GROUP BY 1")
def collect_map(spark, sf):
    return table(spark, sf, "orders").groupBy("o_custkey").agg(F.array_join(F.sort_array(F.collect_list("o_orderkey")), ",").alias("orders"))


@op("histogram", "SELECT CAST(floor(value / 25) AS BIGINT) AS bin, count(*) AS n FROM events GROUP BY 1")
def histogram(spark, sf):
    return table(spark, sf, "events").groupBy(long(F.floor(F.col("value") / 25)).alias("bin")).agg(F.count("*").alias("n"))


@op("having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) >= 12")
def having(spark, sf):
    return table(spark, sf, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).where("n >= 12")


@op("bool_agg", "SELECT user_id, bool_and(value > 1) AS all_over, bool_or(event_type = 'purchase') AS bought FROM events GROUP BY 1")
def bool_agg(spark, sf):
    return table(spark, sf, "events").groupBy("user_id").agg(F.bool_and(F.col("value") > 1).alias("all_over"), F.bool_or(F.col("event_type") == "purchase").alias("bought"))


# ---------------------------------------------------------------- windows



def by_user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


OVER = "OVER (PARTITION BY user_id ORDER BY ts, event_id"


def _events(spark, sf):
    return table(spark, sf, "events")


@op("window_first_k", f"SELECT user_id, event_id FROM (SELECT *, row_number() {OVER}) AS r FROM events) WHERE r <= 3")
def window_first_k(spark, sf):
    return _events(spark, sf).withColumn("r", F.row_number().over(by_user())).where("r <= 3").select("user_id", "event_id")


RANK = "OVER (PARTITION BY event_type ORDER BY value, event_id)"


@op("window_ranks", f"SELECT event_id, rank() {RANK} AS r, dense_rank() {RANK} AS d, ntile(4) {RANK} AS q, round(percent_rank() {RANK}, 6) AS p, round(cume_dist() {RANK}, 6) AS c FROM events")
def window_ranks(spark, sf):
    w = Window.partitionBy("event_type").orderBy("value", "event_id")
    return _events(spark, sf).select("event_id", long(F.rank().over(w)).alias("r"), long(F.dense_rank().over(w)).alias("d"), long(F.ntile(4).over(w)).alias("q"), F.round(F.percent_rank().over(w), 6).alias("p"), F.round(F.cume_dist().over(w), 6).alias("c"))


@op("window_running", f"SELECT event_id, round(sum(value) {OVER} ROWS UNBOUNDED PRECEDING), 5) AS clock, CAST(floor(avg(value) {OVER} ROWS UNBOUNDED PRECEDING) * 1000 + 1e-6) AS BIGINT) AS mean FROM events")
def window_running(spark, sf):
    w = by_user().rowsBetween(Window.unboundedPreceding, 0)
    return _events(spark, sf).select("event_id", F.round(F.sum("value").over(w), 5).alias("clock"), F.floor(F.avg("value").over(w) * 1000 + 1e-6).alias("mean"))


@op("window_lag_lead", f"SELECT event_id, lag(event_id) {OVER}) AS before, lead(event_id) {OVER}) AS after FROM events")
def window_lag_lead(spark, sf):
    return _events(spark, sf).select("event_id", F.lag("event_id").over(by_user()).alias("before"), F.lead("event_id").over(by_user()).alias("after"))


@op("window_moving", f"SELECT event_id, round(avg(value) {OVER} ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 5) AS smooth FROM events")
def window_moving(spark, sf):
    return _events(spark, sf).select("event_id", F.round(F.avg("value").over(by_user().rowsBetween(-4, 0)), 5).alias("smooth"))


@op("window_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS day FROM events")
def window_range(spark, sf):
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-86_400_000_000, 0)
    return _events(spark, sf).select("event_id", F.count("*").over(w).alias("day"))


@op("window_values", f"SELECT event_id, first_value(value) {OVER}) AS f, nth_value(value, 3) {OVER}) AS n, last_value(CASE WHEN value > 60 THEN value END IGNORE NULLS) {OVER}) AS l FROM events")
def window_values(spark, sf):
    return _events(spark, sf).select("event_id", F.first("value").over(by_user()).alias("f"), F.nth_value("value", 3).over(by_user()).alias("n"), F.last(F.when(F.col("value") > 60, F.col("value")), ignorenulls=True).over(by_user()).alias("l"))


@op("window_total_less_own", "SELECT event_id, count(*) OVER (PARTITION BY user_id) - 1 AS others, round(sum(value) OVER (PARTITION BY user_id) - value, 4) + 0e0 AS rest FROM events")
def window_total_less_own(spark, sf):
    w = Window.partitionBy("user_id")
    return _events(spark, sf).select("event_id", (F.count("*").over(w) - 1).alias("others"), (F.round(F.sum("value").over(w) - F.col("value"), 4) + 0.0).alias("rest"))


@op("window_sessions", f"SELECT user_id, count(*) AS sessions FROM (SELECT user_id, epoch_us(ts) - lag(epoch_us(ts)) {OVER}) AS gap FROM events) WHERE gap IS NULL OR gap > 7200000000 GROUP BY 1")
def window_sessions(spark, sf):
    gap = F.unix_micros(F.col("ts").cast("timestamp")) - F.lag(F.unix_micros(F.col("ts").cast("timestamp"))).over(by_user())
    return _events(spark, sf).select("user_id", gap.alias("gap")).where("gap IS NULL OR gap > 7200000000").groupBy("user_id").agg(F.count("*").alias("sessions"))


# ---------------------------------------------------------------- sort, limit, sets


@op("sort_limit", "SELECT l_orderkey, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_partkey, l_linenumber LIMIT 50")
def sort_limit(spark, sf):
    return table(spark, sf, "lineitem").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_partkey", "l_linenumber").limit(50).select("l_orderkey", "l_extendedprice")


@op("sort_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice, o_orderkey LIMIT 20 OFFSET 30")
def sort_offset(spark, sf):
    return table(spark, sf, "orders").orderBy("o_totalprice", "o_orderkey").offset(30).limit(20).select("o_orderkey")


@op("topk_per_group", "SELECT o_orderstatus, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 5")
def topk_per_group(spark, sf):
    w = Window.partitionBy("o_orderstatus").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, sf, "orders").withColumn("r", F.row_number().over(w)).where("r <= 5").select("o_orderstatus", "o_orderkey")


def _two(spark, sf):
    e = _events(spark, sf)
    return e.where("event_type = 'click'").select("user_id"), e.where("event_type = 'purchase'").select("user_id")


C, B = "SELECT user_id FROM events WHERE event_type = 'click'", "SELECT user_id FROM events WHERE event_type = 'purchase'"
for _n, _s, _f in (("intersect", "INTERSECT", "intersect"), ("intersect_all", "INTERSECT ALL", "intersectAll"), ("except", "EXCEPT", "subtract"), ("except_all", "EXCEPT ALL", "exceptAll"), ("union_all", "UNION ALL", "unionAll")):
    op(_n, f"{C} {_s} {B}")(lambda spark, sf, f=_f: (lambda a, b: getattr(a, f)(b))(*_two(spark, sf)))


@op("union_by_name", "SELECT s_suppkey AS key, s_acctbal AS bal, NULL AS segment FROM supplier UNION ALL SELECT c_custkey, c_acctbal, c_mktsegment FROM customer")
def union_by_name(spark, sf):
    s, c = t(spark, sf, "supplier", "customer")
    return s.select(F.col("s_suppkey").alias("key"), F.col("s_acctbal").alias("bal")).unionByName(c.select(F.col("c_acctbal").alias("bal"), F.col("c_mktsegment").alias("segment"), F.col("c_custkey").alias("key")), allowMissingColumns=True)


@op("distinct", "SELECT DISTINCT user_id, event_type FROM events")
def distinct(spark, sf):
    return _events(spark, sf).dropDuplicates(["user_id", "event_type"]).select("user_id", "event_type")


# ---------------------------------------------------------------- functions


@op("bit_functions", "SELECT CAST(a.range AS BIGINT) AS i, CAST(sum((1 - 2 * (CAST(bit_count(a.range & b.range) AS BIGINT) % 2)) * (b.range + 1)) AS BIGINT) AS v FROM range(32) a CROSS JOIN range(32) b GROUP BY 1")
def bit_functions(spark, sf):
    """The Sylvester transform of 1..32, as signs from bit counts."""
    b = F.sequence(F.lit(0).cast("long"), F.lit(31).cast("long"))
    return spark.range(32).select(F.col("id").alias("i"), F.aggregate(F.transform(b, lambda j: (1 - 2 * (F.bit_count(F.col("id").bitwiseAND(j)) % 2)) * (j + 1)), F.lit(0).cast("long"), lambda s, v: s + v).alias("v"))


@op("residues", "SELECT CAST(range AS BIGINT) AS a, range IN (SELECT x.range * x.range % 29 FROM range(1, 29) x) AS residue FROM range(1, 29)")
def residues(spark, sf):
    squares = spark.range(1, 29).select((F.col("id") * F.col("id") % 29).alias("a")).distinct().withColumn("residue", F.lit(True))
    return spark.range(1, 29).select(F.col("id").alias("a")).join(F.broadcast(squares), "a", "left").select("a", F.coalesce("residue", F.lit(False)).alias("residue"))


@op("math_functions", "SELECT event_id, round(ln(1 + value), 6) AS l, round(exp(-value / 50), 6) AS e, round(sqrt(value), 6) AS r, round(greatest(-value, 0e0) + ln(1 + exp(-abs(value))), 8) + 0e0 AS loss, round(sign(value - 50) * greatest(abs(value - 50) - 10, 0e0), 6) + 0e0 AS soft FROM events")
def math_functions(spark, sf):
    v = F.col("value")
    return _events(spark, sf).select("event_id", F.round(F.log1p("value"), 6).alias("l"), F.round(F.exp(-v / 50), 6).alias("e"), F.round(F.sqrt("value"), 6).alias("r"), (F.round(F.greatest(-v, F.lit(0.0)) + F.log1p(F.exp(-F.abs(v))), 8) + 0.0).alias("loss"), (F.round(soft_threshold(v - 50, 10.0), 6) + 0.0).alias("soft"))


@op("array_functions", "SELECT vec_id, round(list_dot_product(CAST(embedding[1:16] AS DOUBLE[]), CAST(embedding[17:32] AS DOUBLE[])), 6) + 0e0 AS d, CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS positive FROM embeddings")
def array_functions(spark, sf):
    e = table(spark, sf, "embeddings").withColumn("x", F.transform("embedding", lambda v: v.cast("double")))
    return e.select("vec_id", (F.round(dot(F.slice("x", 1, 16), F.slice("x", 17, 16)), 6) + 0.0).alias("d"), long(F.size(F.filter("embedding", lambda v: v > 0))).alias("positive"))


@op("map_functions", "SELECT o_custkey, CAST(count(DISTINCT o_orderpriority) AS BIGINT) AS kinds, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY 1")
def map_functions(spark, sf):
    n = table(spark, sf, "orders").groupBy("o_custkey", "o_orderpriority").agg(F.count("*").alias("n"))
    m = n.groupBy("o_custkey").agg(F.map_from_entries(F.collect_list(F.struct("o_orderpriority", "n"))).alias("m"))
    return m.select("o_custkey", long(F.size(F.map_keys("m"))).alias("kinds"), F.aggregate(F.map_values(F.transform_values("m", lambda k, v: v)), F.lit(0).cast("long"), lambda s, v: s + v).alias("n"))


@op("json_functions", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def json_functions(spark, sf):
    return _events(spark, sf).select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@op("string_functions", "SELECT page_id, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS n, CAST(len(regexp_extract_all(html, '<p>')) AS BIGINT) AS paragraphs, upper(substr(url, 1, 12)) AS head FROM pages")
def string_functions(spark, sf):
    return table(spark, sf, "pages").select("page_id", long(F.length(F.regexp_replace("html", "<[^>]*>", ""))).alias("n"), long(F.size(F.regexp_extract_all("html", F.lit("<p>"), F.lit(0)))).alias("paragraphs"), F.upper(F.substring("url", 1, 12)).alias("head"))


@op("date_functions", "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*) AS n, CAST(sum(datediff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE))) AS BIGINT) AS days FROM orders GROUP BY 1")
def date_functions(spark, sf):
    o = table(spark, sf, "orders").select(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("month"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("d"))
    return o.groupBy("month").agg(F.count("*").alias("n"), F.sum("d").alias("days"))


@op("casts", "SELECT CAST(count(TRY_CAST(substr(o_orderpriority, 1, 1) AS INTEGER)) AS BIGINT) AS digits, CAST(count(nullif(o_orderstatus, 'O')) AS BIGINT) AS others FROM orders")
def casts(spark, sf):
    return table(spark, sf, "orders").agg(F.count(F.expr("try_cast(substring(o_orderpriority, 1, 1) as int)")).alias("digits"), F.count(F.nullif("o_orderstatus", F.lit("O"))).alias("others"))


@op("standardise", "SELECT l_orderkey, l_partkey, l_linenumber, round((l_quantity - (SELECT avg(l_quantity) FROM lineitem)) / (SELECT stddev_samp(l_quantity) FROM lineitem), 6) + 0e0 AS z FROM lineitem WHERE l_orderkey < 500")
def standardise(spark, sf):
    """Orders under 500 only, as in its SQL; `standardise_all` gives every row."""
    return standardise_all(spark, sf).where("l_orderkey < 500")


@op("standardise_all", "SELECT l_orderkey, l_partkey, l_linenumber, round((l_quantity - (SELECT avg(l_quantity) FROM lineitem)) / (SELECT stddev_samp(l_quantity) FROM lineitem), 6) + 0e0 AS z FROM lineitem")
def standardise_all(spark, sf):
    (li,) = t(spark, sf, "lineitem")
    s = li.agg(F.avg("l_quantity").alias("mean"), F.stddev_samp("l_quantity").alias("sd"))
    return li.crossJoin(F.broadcast(s)).select("l_orderkey", "l_partkey", "l_linenumber", (F.round((F.col("l_quantity") - F.col("mean")) / F.col("sd"), 6) + 0.0).alias("z"))


@op("one_hot", "SELECT p_type, CAST(sum(CASE WHEN p_brand = 'Brand#11' THEN 1 ELSE 0 END) AS BIGINT) AS b11, CAST(sum(CASE WHEN p_size > 25 THEN 1 ELSE 0 END) AS BIGINT) AS large FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def one_hot(spark, sf):
    li, p = t(spark, sf, "lineitem", "part")
    return li.select("l_partkey").join(p, F.col("l_partkey") == F.col("p_partkey")).groupBy("p_type").agg(F.sum((F.col("p_brand") == "Brand#11").cast("long")).alias("b11"), F.sum((F.col("p_size") > 25).cast("long")).alias("large"))


@op("hashing_trick", "SELECT CAST((ascii(p_brand) * 31 + length(p_name) * 7 + p_size) % 16 AS BIGINT) AS slot, count(*) AS n FROM part GROUP BY 1")
def hashing_trick(spark, sf):
    return table(spark, sf, "part").groupBy(long((F.ascii("p_brand") * 31 + F.length("p_name") * 7 + F.col("p_size")) % 16).alias("slot")).agg(F.count("*").alias("n"))


# ---------------------------------------------------------------- registered functions


@op("udf_fwht", "WITH x AS (SELECT vec_id, unnest(range(16)) AS j, unnest(embedding[1:16]) AS v FROM embeddings) SELECT vec_id, round(sum(CAST(v AS DOUBLE) * (1 - 2 * (CAST(bit_count(5 & j) AS BIGINT) % 2))), 5) + 0e0 AS fifth FROM x GROUP BY 1")
def udf_fwht(spark, sf):
    """The fast transform as a vectorised SQL function."""
    register(spark)
    e = table(spark, sf, "embeddings").select("vec_id", F.transform(F.slice("embedding", 1, 16), lambda v: v.cast("double")).alias("x"))
    return e.select("vec_id", (F.round(F.element_at(F.expr("erasure_fwht(x)"), 6), 5) + 0.0).alias("fifth"))


@op("udtf_hadamard_rows", "SELECT CAST(a.range AS BIGINT) AS enc_row, CAST(count(*) AS BIGINT) AS n, round(sum(CASE WHEN CAST(bit_count(a.range & b.range) AS BIGINT) % 2 = 0 THEN 0.25e0 ELSE -0.25e0 END), 6) + 0e0 AS s FROM range(16) a CROSS JOIN range(16) b GROUP BY 1")
def udtf_hadamard_rows(spark, sf):
    register(spark)
    return spark.sql("SELECT enc_row, count(*) AS n, round(sum(coef), 6) + 0D AS s FROM hadamard_rows(16) GROUP BY 1")


@op("udtf_code_tables")
def udtf_code_tables(spark, sf):
    register(spark)
    return spark.sql("SELECT 'steiner' AS code, count(*) AS n FROM steiner_rows(8) UNION ALL SELECT 'paley', count(*) FROM paley_rows(13) UNION ALL SELECT 'haar', count(*) FROM haar_rows(16)")

