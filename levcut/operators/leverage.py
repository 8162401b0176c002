"""Leverage scores of columns, probabilities, and what they tell about a matrix."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from levcut.functions.portable import entropy_term
from levcut.operators import svd
from levcut.operators.relational import prefix_sum


def _squares(columns: Sequence[str]) -> Column:
    out = F.lit(0.0)
    for c in columns:
        out = out + F.col(c) * F.col(c)
    return out


def columns(v: DataFrame, k: int | None = None, probs: str = "basis", a: DataFrame | None = None) -> DataFrame:
    """col_id, score, p: squared row norms of the basis over k, a map.

    two_term averages these with the share of each column in the residual.
    """
    cols = [c for c in v.columns if c != "col_id"][:k]
    scored = v.select("col_id", _squares(cols).alias("score"))
    scored = scored.withColumn("p", F.col("score") / float(max(1, len(cols))))
    if probs == "basis":
        return scored
    if probs != "two_term" or a is None:
        raise ValueError(probs)
    # |A_j - (A_k)_j|^2 = |A_j|^2 - |(A v) v_j|^2; A_k needs one further pass.
    u = svd.multiply(a, v, "col_id", "row_id", cols, "y")
    g = svd.inner(u, svd.names(len(cols), "y"))
    norms = a.groupBy("col_id").agg(F.sum(F.col("value") * F.col("value")).alias("s"))
    kept = F.lit(0.0)
    for i, x in enumerate(cols):
        for j, y in enumerate(cols):
            kept = kept + F.col(x) * F.col(y) * F.lit(float(g[i, j]))
    rest = v.join(norms, "col_id").select("col_id", F.greatest(F.lit(0.0), F.col("s") - kept).alias("rest"))
    total = rest.agg(F.sum("rest").alias("t")).first()["t"]
    share = F.col("rest") / float(total) if total > 1e-12 else F.col("p")
    return scored.join(rest, "col_id").select("col_id", "score", ((F.col("p") + share) / 2).alias("p"))


def rows(a: DataFrame, k: int, found: svd.Svd | None = None) -> DataFrame:
    """row_id, score, p: of the left vectors, which one more product gives."""
    found = found or svd.topk(a, k)
    u = svd.left(a, found)
    cols = [c for c in u.columns if c != "row_id"]
    return u.select("row_id", _squares(cols).alias("score"), (_squares(cols) / float(max(1, len(cols)))).alias("p"))


def by_rank(v: DataFrame) -> DataFrame:
    """Scores for every rank up to k from one pass: col_id, rank, score."""
    cols = [c for c in v.columns if c != "col_id"]
    prefixes = F.array(*[F.struct(F.lit(i + 1).alias("rank"), _squares(cols[: i + 1]).alias("score")) for i in range(len(cols))])
    return v.select("col_id", F.explode(prefixes).alias("x")).select("col_id", "x.rank", "x.score")


def columns_approx(a: DataFrame, k: int, seed: int = 0, power: int = 1) -> DataFrame:
    """Scores from a rough basis: one range-finder pass or a few."""
    return columns(svd.basis(a, k, seed, power))


def projector_diag(v: DataFrame, seed: int = 1) -> DataFrame:
    """Diagonal of the projector after a random rotation of the basis: equal to the scores."""
    cols = [c for c in v.columns if c != "col_id"]
    q, _ = np.linalg.qr(np.random.default_rng(seed).normal(size=(len(cols), len(cols))))
    return columns(svd.rotate(v, "col_id", cols, q, cols))


def flag(scores: DataFrame, k: int, factor: float = 2.0) -> DataFrame:
    """Columns whose score exceeds factor times the average k/n."""
    n = scores.count()
    return scores.filter(F.col("score") > factor * k / max(1, n))


def coherence(scores: DataFrame, k: int) -> float:
    row = scores.agg(F.max("score").alias("top"), F.count("*").alias("n")).first()
    return row["top"] * row["n"] / k


def cumulative(scores: DataFrame, key: str = "col_id", top: int | None = None) -> DataFrame:
    """t, score, cum: running sum of the largest scores; ties by id."""
    order = [F.col("score").desc(), F.col(key)]
    if top is not None:
        best = scores.orderBy(*order).limit(top)
        w = Window.orderBy(*order)
        return best.select(key, "score", F.row_number().over(w).alias("t"), F.sum("score").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("cum"))
    return prefix_sum(scores.select(key, "score"), order, "score", "cum", "t")


def signature(scores: DataFrame, k: int) -> DataFrame:
    """One row on non-uniformity: largest over average, share of the top hundredth, effective count, flagged."""
    n = scores.count()
    cut = F.col("score") > 2.0 * k / max(1, n)
    edge = scores.approxQuantile("score", [0.99], 0.001)[0] if n else 0.0
    return scores.agg(
        F.count("*").alias("n"),
        (F.max("score") / F.avg("score")).alias("max_over_mean"),
        (F.sum(F.when(F.col("score") >= edge, F.col("score")).otherwise(0.0)) / F.sum("score")).alias("top_share"),
        (F.sum("score") ** 2 / F.sum(F.col("score") ** 2)).alias("effective"),
        F.sum(cut.cast("long")).alias("flagged"),
    )


def information_gain(a: DataFrame, labels: DataFrame) -> DataFrame:
    """col_id, df, gain: bits that presence of the column tells about the label."""
    sizes = {r["label"]: r["count"] for r in labels.groupBy("label").count().collect()}
    m = float(sum(sizes.values()))
    classes = sorted(sizes)
    joined = a.filter("value != 0").select("row_id", "col_id").join(labels, "row_id")
    counts = joined.groupBy("col_id").agg(
        F.count("*").cast("double").alias("df"), *[F.sum((F.col("label") == c).cast("double")).alias(f"n{i}") for i, c in enumerate(classes)]
    )
    prior = sum(-n / m * np.log2(n / m) for n in sizes.values())
    inside, outside = F.lit(0.0), F.lit(0.0)
    for i, c in enumerate(classes):
        inside = inside + entropy_term(F.col(f"n{i}"), F.col("df"))
        outside = outside + entropy_term(F.lit(float(sizes[c])) - F.col(f"n{i}"), F.lit(m) - F.col("df"))
    share = F.col("df") / F.lit(m)
    rest = F.when(F.col("df") < F.lit(m), (1 - share) * outside).otherwise(0.0)
    return counts.select("col_id", "df", (F.lit(float(prior)) - share * inside - rest).alias("gain"))


def mutual_information(a: DataFrame, labels: DataFrame, bins: int = 4) -> DataFrame:
    """col_id, mi: the same for values in equal-count bins, absent entries a bin of their own."""
    sizes = labels.groupBy("label").agg(F.count("*").alias("n_label"))
    m = labels.count()
    cuts = a.groupBy("col_id").agg(F.percentile_approx("value", [i / bins for i in range(1, bins)]).alias("cuts"))
    binned = a.join(cuts, "col_id").join(labels, "row_id").select("col_id", "label", F.size(F.filter("cuts", lambda c: c < F.col("value"))).alias("bin"))
    cells = binned.groupBy("col_id", "bin", "label").agg(F.count("*").alias("n"))
    seen = cells.groupBy("col_id", "label").agg(F.sum("n").alias("seen"))
    every = cells.select("col_id").distinct().crossJoin(F.broadcast(sizes))
    absent = every.join(seen, ["col_id", "label"], "left").select(
        "col_id", F.lit(-1).alias("bin"), "label", (F.col("n_label") - F.coalesce("seen", F.lit(0))).alias("n")
    )
    full = cells.unionByName(absent).filter("n > 0")
    by_bin = full.groupBy("col_id", "bin").agg(F.sum("n").alias("n_bin"))
    rows_ = full.join(by_bin, ["col_id", "bin"]).join(F.broadcast(sizes), "label")
    term = F.col("n") / float(m) * F.log2(F.col("n") * float(m) / (F.col("n_bin") * F.col("n_label")))
    return rows_.groupBy("col_id").agg(F.sum(term).alias("mi"))


def vs_information_gain(a: DataFrame, labels: DataFrame, ks: Sequence[int]) -> DataFrame:
    """k, pearson, spearman of scores with information gain, for each rank.

    A rank k is one key: all of its columns are put in order by one task, which
    holds a score and a gain of each and spills what it can't, so all ranks take
    one job where running sums over ranges would take some jobs each.
    """
    found = svd.topk(a, max(ks))
    scores = by_rank(found.v).filter(F.col("rank").isin(*ks)).join(information_gain(a, labels), "col_id").select("rank", "score", "gain")
    by = Window.partitionBy("rank")
    placed = scores.withColumn("rs", F.rank().over(by.orderBy("score"))).withColumn("rg", F.rank().over(by.orderBy("gain")))
    known = placed.groupBy("rank").agg(F.corr("score", "gain").alias("pearson"), F.corr(F.col("rs").cast("double"), F.col("rg").cast("double")).alias("spearman"))
    asked = a.sparkSession.createDataFrame([(k,) for k in ks], "k int")
    return asked.join(known, asked["k"] == known["rank"], "left").select("k", "pearson", "spearman")
