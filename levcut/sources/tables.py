"""Matrices and graphs from the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levcut.functions.portable import key60


#: A word of any script, the same in Java's and DuckDB's expressions.
WORD = r"[\p{L}\p{M}\p{N}_]+"


def load(spark: SparkSession, folder: str, name: str, fmt: str = "parquet", schema: str | None = None) -> DataFrame:
    """A table of the folder; text formats need a declared schema."""
    if fmt == "parquet":
        return spark.read.parquet(f"{folder}/{name}.parquet")
    if schema is None:
        raise ValueError("text formats need a declared schema")
    return spark.read.schema(schema).format(fmt).option("header", "true").load(f"{folder}/{name}.{fmt}")


def save(df: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = ()) -> None:
    df.write.mode("overwrite").partitionBy(*partition_by).format(fmt).option("header", "true").save(path)


def save_bucketed(df: DataFrame, name: str, buckets: int, column: str) -> None:
    """A table whose later joins on the column need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, column).sortBy(column).saveAsTable(name)


def design_events(spark: SparkSession, d: str) -> DataFrame:
    """event_id, one, value, hour and the response y from the JSON props."""
    k = F.from_json("props", "k int")["k"].cast("double")
    hour = F.hour("ts").cast("double")
    rows = load(spark, d, "events").select(F.col("event_id").alias("id"), F.lit(1.0).alias("one"), "value", hour.alias("hour"), k.alias("y"))
    return rows.filter("value is not null and hour is not null and y is not null")


def design_lineitem(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "lineitem").select(
        (F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("id"),
        F.lit(1.0).alias("one"),
        F.col("l_quantity").alias("quantity"),
        (F.col("l_discount") + F.lit(0.0)).alias("discount"),
        F.col("l_tax").alias("tax"),
        F.col("l_extendedprice").alias("y"),
    )


def tokens(spark: SparkSession, d: str) -> DataFrame:
    """doc_id, lang, term: one row an occurrence of a lower-cased word, of letters, marks, digits and _ of any script."""
    words = F.regexp_extract_all(F.lower("text"), F.lit(f"({WORD})"), F.lit(1))
    return load(spark, d, "documents").select("doc_id", "lang", F.explode(words).alias("term"))


def term_counts(spark: SparkSession, d: str) -> DataFrame:
    return tokens(spark, d).groupBy(F.col("doc_id").alias("row_id"), F.col("term").alias("col_id")).agg(F.count("*").cast("double").alias("value"))


def term_binary(spark: SparkSession, d: str, least: int = 5) -> DataFrame:
    """Presence of terms that at least ``least`` documents hold."""
    counts = term_counts(spark, d).select("row_id", "col_id", F.lit(1.0).alias("value"))
    known = counts.groupBy("col_id").agg(F.count("*").alias("df")).filter(F.col("df") >= least)
    return counts.join(known.select("col_id"), "col_id", "left_semi").select("row_id", "col_id", "value")


def doc_labels(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "documents").select(F.col("doc_id").alias("row_id"), F.col("lang").alias("label"))


def bought(spark: SparkSession, d: str) -> DataFrame:
    """custkey, orderkey, partkey, suppkey, price, orderdate of every line."""
    lines = load(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_extendedprice")
    orders = load(spark, d, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))


def customer_part(spark: SparkSession, d: str) -> DataFrame:
    return bought(spark, d).groupBy(F.col("o_custkey").alias("row_id"), F.col("l_partkey").alias("col_id")).agg(F.count("*").cast("double").alias("value"))


def customer_brand(spark: SparkSession, d: str) -> DataFrame:
    part = load(spark, d, "part").select("p_partkey", "p_brand")
    rows = bought(spark, d).join(part, F.col("l_partkey") == F.col("p_partkey"))
    return rows.groupBy(F.col("o_custkey").alias("row_id"), F.col("p_brand").alias("col_id")).agg(F.count("*").cast("double").alias("value"))


def embedding_matrix(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "embeddings").select(
        F.col("vec_id").alias("row_id"), F.posexplode(F.col("embedding").cast("array<double>")).alias("col_id", "value")
    )


def pairs(df: DataFrame, left, right, weight=None) -> DataFrame:
    """Bipartite edges: left ids become even, right ids odd; src < dst."""
    w = F.count("*").cast("double") if weight is None else F.sum(weight).cast("double")
    a, b = left * 2, right * 2 + 1
    return df.groupBy(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst")).agg(w.alias("w"))


def g_order_part(spark: SparkSession, d: str, days: int | None = None) -> DataFrame:
    """Orders and their parts; the first ``days`` days of orders if given."""
    rows = bought(spark, d)
    if days is not None:
        first = load(spark, d, "orders").agg(F.min("o_orderdate").alias("first_"))
        rows = rows.crossJoin(F.broadcast(first)).filter(F.col("o_orderdate") < F.col("first_") + F.expr(f"INTERVAL {days} DAYS"))
    # Lines lie by order since the join, so pairs are told apart without another shuffle.
    a, b = F.col("l_orderkey") * 2, F.col("l_partkey") * 2 + 1
    return rows.select("l_orderkey", "l_partkey").distinct().select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst"), F.lit(1.0).alias("w"))


def g_part_supplier(spark: SparkSession, d: str) -> DataFrame:
    return pairs(load(spark, d, "lineitem"), F.col("l_partkey"), F.col("l_suppkey")).withColumn("w", F.lit(1.0))


def g_customer_order(spark: SparkSession, d: str) -> DataFrame:
    return pairs(load(spark, d, "orders"), F.col("o_custkey"), F.col("o_orderkey")).withColumn("w", F.lit(1.0))


def g_bids(spark: SparkSession, d: str) -> DataFrame:
    """Customers as advertisers, parts as phrases, money as weight."""
    return pairs(bought(spark, d), F.col("o_custkey"), F.col("l_partkey"), F.col("l_extendedprice").cast("decimal(18,2)"))


def g_doc_term(spark: SparkSession, d: str) -> DataFrame:
    # A document's words are told apart before they are rows; one shuffle takes rows of equal doc_id.
    terms = F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(f"({WORD})"), F.lit(1))))
    rows = load(spark, d, "documents").select((F.col("doc_id") * 2).alias("a"), terms.alias("term")).withColumn("b", key60(F.col("term")) * 2 + 1)
    return rows.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).distinct().withColumn("w", F.lit(1.0))


def g_segment_priority(spark: SparkSession, d: str) -> DataFrame:
    """Ten nodes: market segments 0-4, order priorities 5-9, orders as weight."""
    segment, priority = _codes(load(spark, d, "customer"), "c_mktsegment", 0), _codes(load(spark, d, "orders"), "o_orderpriority", 5)
    rows = load(spark, d, "orders").join(load(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    rows = rows.join(F.broadcast(segment), "c_mktsegment").join(F.broadcast(priority), "o_orderpriority")
    return rows.groupBy(F.col("c_mktsegment_code").alias("src"), F.col("o_orderpriority_code").alias("dst")).agg(F.count("*").cast("double").alias("w"))


def _codes(df: DataFrame, column: str, base: int) -> DataFrame:
    """Dense codes of a column with few values."""
    from pyspark.sql import Window

    order = Window.orderBy(column)
    return df.select(column).distinct().withColumn(f"{column}_code", F.row_number().over(order) - 1 + base)


def g_pages(spark: SparkSession, d: str) -> DataFrame:
    links = F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1))))
    rows = load(spark, d, "pages").select("page_id", links.alias("href"))
    return pairs(rows, F.col("page_id"), key60(F.col("href"))).withColumn("w", F.lit(1.0))


def g_turns(spark: SparkSession, d: str) -> DataFrame:
    """Paths: each turn of a conversation to the next."""
    turn = load(spark, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("src")).distinct()
    nxt = turn.select(F.col("src").alias("dst"))
    return turn.join(nxt, F.col("dst") == F.col("src") + 1).select("src", "dst", F.lit(1.0).alias("w"))


def g_copurchase(spark: SparkSession, d: str) -> DataFrame:
    """Parts bought in the same order; w counts orders. An order of n parts gives n (n - 1) / 2 pairs, which are what is asked for."""
    items = load(spark, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    other = items.select(F.col("l_orderkey"), F.col("l_partkey").alias("dst"))
    joined = items.join(other, "l_orderkey").filter("l_partkey < dst")
    return joined.groupBy(F.col("l_partkey").alias("src"), "dst").agg(F.count("*").cast("double").alias("w"))


def baskets(spark: SparkSession, d: str) -> DataFrame:
    rows = load(spark, d, "lineitem").select(F.col("l_orderkey").alias("basket"), F.col("l_partkey").alias("item"))
    return rows.distinct()
