"""Registered queries of the operators around the methods, each with a DuckDB twin."""

from __future__ import annotations


from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from levcut.operators import relational as ops
from levcut.sources import tables as t
from levcut.streaming import events as stream

QUERIES: dict = {}
ORACLES: dict = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


@query("SELECT n_name, count(DISTINCT c_custkey) AS customers, count(o_orderkey) AS orders, round(sum(o_totalprice::DECIMAL(18, 2))::DOUBLE, 2) AS total FROM nation JOIN customer ON n_nationkey = c_nationkey LEFT JOIN orders ON o_custkey = c_custkey GROUP BY n_name")
def join_and_aggregate(spark: SparkSession, d: str) -> DataFrame:
    c = t.load(spark, d, "customer").join(F.broadcast(t.load(spark, d, "nation")), F.col("n_nationkey") == F.col("c_nationkey"))
    o = t.load(spark, d, "orders")
    return c.join(o, F.col("o_custkey") == F.col("c_custkey"), "left").groupBy("n_name").agg(
        F.countDistinct("c_custkey").alias("customers"), F.count("o_orderkey").alias("orders"),
        F.round(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("double"), 2).alias("total"),
    )


@query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def join_anti(spark: SparkSession, d: str) -> DataFrame:
    return t.load(spark, d, "customer").join(t.load(spark, d, "orders"), F.col("o_custkey") == F.col("c_custkey"), "left_anti").select("c_custkey")


@query("SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 49)")
def join_semi(spark: SparkSession, d: str) -> DataFrame:
    lines = t.load(spark, d, "lineitem").filter("l_quantity > 49")
    return t.load(spark, d, "part").join(lines, F.col("l_partkey") == F.col("p_partkey"), "left_semi").select("p_partkey")


@query("SELECT band, count(*) AS n FROM events JOIN (SELECT i AS band, i * 10.0 AS lo, i * 10.0 + 10.0 AS hi FROM range(0, 60) r(i)) ON value >= lo AND value < hi GROUP BY band")
def join_range(spark: SparkSession, d: str) -> DataFrame:
    bands = spark.range(60).select(F.col("id").alias("band"), (F.col("id") * 10.0).alias("lo"), (F.col("id") * 10.0 + 10.0).alias("hi"))
    return ops.range_join(t.load(spark, d, "events").select("value"), "value", F.broadcast(bands), "lo", "hi", 10.0).groupBy("band").agg(F.count("*").alias("n"))


@query("""WITH p AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase'),
v AS (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'view' GROUP BY ALL)
SELECT p.event_id, v.value AS last_view FROM p ASOF LEFT JOIN v ON p.user_id = v.user_id AND p.ts >= v.ts""")
def join_as_of(spark: SparkSession, d: str) -> DataFrame:
    e = t.load(spark, d, "events")
    views = e.filter("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("value").alias("value"))
    return ops.as_of(e.filter("event_type = 'purchase'").select("event_id", "user_id", "ts"), views, "user_id", "ts", "value", "last_view").select("event_id", "last_view")


@query("""SELECT a.event_id AS view_id, b.event_id AS click_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR
WHERE a.event_type = 'view' AND b.event_type = 'click'""")
def join_interval(spark: SparkSession, d: str) -> DataFrame:
    e = t.load(spark, d, "events")
    a = e.filter("event_type = 'view'").select(F.col("event_id").alias("view_id"), "user_id", F.col("ts").alias("t1"))
    b = e.filter("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", F.col("ts").alias("t2"))
    return ops.interval_join(a, b, "user_id", "t1", "t2", 3600).select("view_id", "click_id")


@query("SELECT l_partkey AS k, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY l_partkey")
def join_salted(spark: SparkSession, d: str) -> DataFrame:
    part = t.load(spark, d, "part").select(F.col("p_partkey").alias("k"))
    lines = t.load(spark, d, "lineitem").select(F.col("l_partkey").alias("k"), "l_orderkey")
    return ops.salted_join(lines, part, "k", "l_orderkey").groupBy("k").agg(F.count("*").alias("n"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, grouping(l_returnflag) * 2 + grouping(l_linestatus) AS level FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def aggregate_cube(spark: SparkSession, d: str) -> DataFrame:
    return t.load(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.grouping_id().alias("level"))


@query("SELECT user_id, count(*) FILTER (event_type = 'view') AS views, count(*) FILTER (event_type = 'click') AS clicks FROM events GROUP BY user_id")
def aggregate_pivot(spark: SparkSession, d: str) -> DataFrame:
    p = t.load(spark, d, "events").groupBy("user_id").pivot("event_type", ["view", "click"]).count()
    return p.select("user_id", F.coalesce("view", F.lit(0)).alias("views"), F.coalesce("click", F.lit(0)).alias("clicks"))


@query("SELECT round(corr(l_quantity, l_extendedprice), 6) AS corr, round(regr_slope(l_extendedprice, l_quantity), 6) AS slope, round(stddev_samp(l_quantity), 6) AS sd FROM lineitem")
def aggregate_statistics(spark: SparkSession, d: str) -> DataFrame:
    e = t.load(spark, d, "lineitem")
    return e.agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("corr"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 6).alias("slope"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"))


@query("SELECT p_brand, p_partkey, r::INT AS place FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) WHERE r <= 3")
def window_top_per_group(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return t.load(spark, d, "part").select("p_brand", "p_partkey", F.row_number().over(w).alias("place")).filter("place <= 3")


@query("SELECT o_orderkey, date_diff('day', lag(o_orderdate) OVER w, o_orderdate)::INT AS gap FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def window_gaps(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return t.load(spark, d, "orders").select("o_orderkey", F.datediff("o_orderdate", F.lag("o_orderdate").over(w)).alias("gap"))


@query("SELECT o_orderkey, sum(1) OVER (ORDER BY o_orderdate, o_orderkey)::BIGINT AS place, round(sum(o_totalprice::DECIMAL(18, 2)) OVER (ORDER BY o_orderdate, o_orderkey)::DOUBLE, 2) AS running FROM orders")
def prefix_sum_orders(spark: SparkSession, d: str) -> DataFrame:
    o = t.load(spark, d, "orders").select("o_orderkey", "o_orderdate", F.round(F.col("o_totalprice") * 100).alias("cents"))
    out = ops.prefix_sum(o, [F.col("o_orderdate"), F.col("o_orderkey")], "cents", "running", "place")
    return out.select("o_orderkey", F.col("place").cast("long").alias("place"), F.round(F.col("running") / 100, 2).alias("running"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 100")
def top_orders(spark: SparkSession, d: str) -> DataFrame:
    return t.load(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(100).select("o_orderkey", "o_totalprice")


@query("(SELECT l_partkey AS k FROM lineitem WHERE l_quantity > 45 INTERSECT SELECT l_partkey FROM lineitem WHERE l_discount > 0.08) EXCEPT SELECT p_partkey FROM part WHERE p_size > 40")
def set_operations(spark: SparkSession, d: str) -> DataFrame:
    e = t.load(spark, d, "lineitem")
    a = e.filter("l_quantity > 45").select(F.col("l_partkey").alias("k")).intersect(e.filter("l_discount > 0.08").select("l_partkey"))
    return a.subtract(t.load(spark, d, "part").filter("p_size > 40").select("p_partkey"))


@query("SELECT lang, count(*) AS n, sum(len(regexp_extract_all(lower(text), '([a-z]+)', 1)))::BIGINT AS tokens FROM documents GROUP BY lang")
def text_tokens(spark: SparkSession, d: str) -> DataFrame:
    words = F.size(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"), F.lit(1)))
    return t.load(spark, d, "documents").groupBy("lang").agg(F.count("*").alias("n"), F.sum(words.cast("long")).alias("tokens"))


@query("SELECT vec_id, round(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]), 4) AS norm FROM embeddings")
def array_norms(spark: SparkSession, d: str) -> DataFrame:
    e = F.col("embedding").cast("array<double>")
    return t.load(spark, d, "embeddings").select("vec_id", F.round(F.aggregate(F.zip_with(e, e, lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x), 4).alias("norm"))


@query("SELECT (props->>'$.k')::INT AS k, count(*) AS n FROM events GROUP BY ALL")
def json_fields(spark: SparkSession, d: str) -> DataFrame:
    return t.load(spark, d, "events").groupBy(F.from_json("props", "k int")["k"].alias("k")).agg(F.count("*").alias("n"))


@query("SELECT date_trunc('hour', ts) AS start, count(*) AS n, round(sum(value), 4) AS sx FROM events GROUP BY ALL")
def window_tumbling(spark: SparkSession, d: str) -> DataFrame:
    e = t.load(spark, d, "events")
    w = F.window("ts", "1 hour")
    return e.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("sx")).select(F.col("w.start").alias("start"), "n", "sx")


@query("SELECT date_trunc('hour', ts) AS start, count(*) AS n, round(sum(value), 4) AS sx FROM events GROUP BY ALL")
def stream_window_moments(spark: SparkSession, d: str) -> DataFrame:
    """The stream's windows, drained once, equal the batch windows."""
    events = stream.source(spark, d, glob="events.parquet")
    name = "levcut_window_moments"
    out = stream.run_once(stream.window_moments(events), name, "complete")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "n", F.round("sx", 4).alias("sx"))


@query("SELECT r_regionkey, r_name FROM region")
def round_trip_csv(spark: SparkSession, d: str) -> DataFrame:
    from levcut.runtime import checkpoint_folder

    path = f"{checkpoint_folder(spark)}/region-{abs(hash(d)) % 10**8}.csv"
    t.save(t.load(spark, d, "region"), path, "csv")
    return spark.read.schema("r_regionkey int, r_name string").option("header", "true").csv(path)
