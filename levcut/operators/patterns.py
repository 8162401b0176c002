"""Records and generative views: itemsets and rules, unseen cells of a mean model."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def item_pairs(baskets: DataFrame, least: int) -> DataFrame:
    """a, b, n: pairs of frequent items in a basket; infrequent items go first."""
    frequent = baskets.groupBy("item").agg(F.count("*").alias("c")).filter(F.col("c") >= least).select("item")
    kept = baskets.join(frequent, "item", "left_semi")
    other = kept.select("basket", F.col("item").alias("b"))
    return kept.join(other, "basket").filter("item < b").groupBy(F.col("item").alias("a"), "b").agg(F.count("*").alias("n")).filter(F.col("n") >= least)


def rules(baskets: DataFrame, least: int) -> DataFrame:
    """lhs, rhs, support, confidence, lift of one-to-one rules, both ways."""
    total = baskets.select("basket").distinct().count()
    pairs = item_pairs(baskets, least)
    both = pairs.select(F.col("a").alias("lhs"), F.col("b").alias("rhs"), "n").unionByName(pairs.select(F.col("b").alias("lhs"), F.col("a").alias("rhs"), "n"))
    one = baskets.groupBy("item").agg(F.count("*").alias("c"))
    scored = both.join(one.select(F.col("item").alias("lhs"), F.col("c").alias("cl")), "lhs").join(one.select(F.col("item").alias("rhs"), F.col("c").alias("cr")), "rhs")
    return scored.select(
        "lhs", "rhs", (F.col("n") / total).alias("support"), (F.col("n") / F.col("cl")).alias("confidence"),
        (F.col("n") * float(total) / (F.col("cl") * F.col("cr"))).alias("lift"),
    )


def itemsets(baskets: DataFrame, min_support: float, most: int = 3) -> DataFrame:
    """Frequent itemsets of any size by pattern growth."""
    from pyspark.ml.fpm import FPGrowth

    grouped = baskets.groupBy("basket").agg(F.collect_set("item").alias("items"))
    return FPGrowth(itemsCol="items", minSupport=min_support).fit(grouped).freqItemsets.filter(F.size("items") <= most)


def timed_rule(events: DataFrame, first: str, second: str, low: int, high: int) -> DataFrame:
    """Within an hour band: how often users with one event type also have the other."""
    band = events.filter(F.hour("ts").between(low, high - 1))
    users = band.groupBy("user_id").agg(F.max((F.col("event_type") == first).cast("int")).alias("a"), F.max((F.col("event_type") == second).cast("int")).alias("b"))
    return users.agg(
        F.sum("a").alias("with_first"), F.sum(F.col("a") * F.col("b")).alias("with_both"), F.try_divide(F.sum(F.col("a") * F.col("b")), F.sum("a")).alias("confidence")
    )


def fit_mean(events: DataFrame, dims: tuple[str, ...], hit: str) -> tuple[DataFrame, dict[str, DataFrame]]:
    """Smoothed log odds of a hit overall and along each dimension, with binomial variance."""

    def odds(hits, n):
        return F.log((hits + 0.5) / (n - hits + 0.5))

    base = events.agg(F.sum(hit).alias("hits"), F.count("*").alias("n")).select(odds(F.col("hits"), F.col("n")).alias("base"))
    parts = {}
    for d in dims:
        g = events.groupBy(d).agg(F.sum(hit).alias("hits"), F.count("*").alias("n"))
        rate = F.col("hits") / F.col("n")
        parts[d] = g.select(d, odds(F.col("hits"), F.col("n")).alias(f"odds_{d}"), (rate * (1 - rate) / F.col("n")).alias(f"var_{d}"))
    return base, parts


def predict_unseen(events: DataFrame, dims: tuple[str, ...], hit: str) -> DataFrame:
    """A probability for every cell of the dimensions, seen or not: additive log odds.

    The product of the dimensions' distinct values must be small; each side is one
    row a value.
    """
    base, parts = fit_mean(events, dims, hit)
    cells = base
    logit = F.col("base")
    for d in dims:
        cells = cells.crossJoin(F.broadcast(parts[d]))
        logit = logit + F.col(f"odds_{d}") - F.col("base")
    return cells.select(*dims, (1 / (1 + F.exp(-logit))).alias("prob"))
