"""Random draws of columns or rows by given probabilities, with rescaling."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from levcut.functions.portable import u01
from levcut.operators.relational import as_of, prefix_sum


def draws_for(k: int, eps: float, kappa: float = 1.0) -> int:
    """Columns for a relative error of eps: order k log k over eps squared."""
    return max(k, math.ceil(kappa * k * math.log(max(2, k)) / eps**2))


def draw(p: DataFrame, c: int, scheme: str = "with_replacement", seed: int = 0, key: str = "col_id") -> DataFrame:
    """key, p, draws, scale. p sums to 1.

    with_replacement: c draws from hashes of 0..c-1; equal ones are one row with
    their count, scaled by sqrt(draws / (c p)). bernoulli: kept with min(1, c p), scaled
    by its inverse root. exponential_keys: exactly c without replacement, by the
    smallest -ln(u)/p.
    """
    live = p.filter("p > 0")
    if scheme == "bernoulli":
        q = F.least(F.lit(1.0), F.lit(float(c)) * F.col("p"))
        return live.filter(u01(key, seed) < q).select(key, "p", F.lit(1).alias("draws"), (1 / F.sqrt(q)).alias("scale"))
    if scheme == "exponential_keys":
        order = -F.log(F.greatest(u01(key, seed), F.lit(2.0**-33))) / F.col("p")
        best = live.withColumn("order_", order).orderBy("order_", key).limit(c)
        return best.select(key, "p", F.lit(1).alias("draws"), (1 / F.sqrt(F.least(F.lit(1.0), F.lit(float(c)) * F.col("p")))).alias("scale"))
    if scheme != "with_replacement":
        raise ValueError(scheme)
    # Intervals of the distribution: each begins where the one before ends. A draw
    # lies in the range of rows that the ends of ranges tell, and there in the last
    # interval that begins at or before it; no interval is met by other draws.
    live = live.select(key, "p")
    summed = prefix_sum(live, [F.col(key)], "p", "high", part="range_")
    inside = Window.partitionBy("range_").orderBy(key)
    ends = sorted((r["range_"], r["high"]) for r in summed.groupBy("range_").agg(F.max("high").alias("high")).collect())
    starts = dict(zip([x for x, _ in ends], [0.0, *(h for _, h in ends[:-1])], strict=True))
    begun = F.create_map(*[F.lit(y) for x in starts.items() for y in x]) if starts else F.lit(None)
    low = F.coalesce(F.lag("high").over(inside), begun[F.col("range_")])
    intervals = summed.withColumn("low_", low).select("range_", F.col("low_").alias("at_"), F.struct(key, "p").alias("hit_"))
    total = ends[-1][1] if ends else 0.0
    at = p.sparkSession.range(c).select((u01("id", seed) * F.lit(total * (1 - 1e-12))).alias("at_"))
    later = F.array(*[F.struct(F.lit(h).alias("h"), F.lit(x).alias("x")) for x, h in ends])
    draws = at.withColumn("range_", F.filter(later, lambda e: e["h"] > F.col("at_"))[0]["x"]) if ends else at.withColumn("range_", F.lit(0))
    met = as_of(draws, intervals, "range_", "at_", "hit_", "won_")
    folded = met.groupBy(F.col(f"won_.{key}").alias(key), F.col("won_.p").alias("p")).agg(F.count("*").cast("int").alias("draws"))
    return folded.withColumn("scale", F.sqrt(F.col("draws") / (F.lit(float(c)) * F.col("p"))))


def by_norm(a: DataFrame) -> DataFrame:
    """col_id, score, p proportional to squared column norms (additive-error sampling)."""
    norms = a.groupBy("col_id").agg(F.sum(F.col("value") * F.col("value")).alias("score"))
    total = norms.agg(F.sum("score").alias("t")).first()["t"]
    return norms.withColumn("p", F.col("score") / float(total or 1.0))


def uniform(a: DataFrame) -> DataFrame:
    ids = a.select("col_id").distinct()
    return ids.select("col_id", F.lit(1.0).alias("score"), F.lit(1.0 / max(1, ids.count())).alias("p"))
