"""Global spectral partitioning by distributed power iteration, and bounds."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levcut.functions.portable import u01
from levcut.operators import graph
from levcut.runtime import cut_lineage


def fiedler(edges: DataFrame, rounds: int = 60, tol: float = 1e-7, seed: int = 0, every: int = 5) -> tuple[DataFrame, float]:
    """node, value of the second eigenvector of the normalized Laplacian over
    root degrees, and its Rayleigh quotient (an upper estimate of lambda_2).

    One round is a join of the edges with the vector and a sum by node, on the
    lazy walk; the trivial vector is taken out each time. The graph must be
    connected.
    """
    deg = cut_lineage(graph.degrees(edges).select("node", "vol"))
    total = deg.agg(F.sum("vol").alias("v")).first()["v"]
    # Loops of half weight make the walk lazy, so a round reads the vector once.
    out = graph.both_ways(edges).join(deg.withColumnRenamed("node", "src"), "src").select("src", "dst", (F.col("w") / F.col("vol") / 2).alias("c"), "vol")
    steps = cut_lineage(out.unionByName(deg.select(F.col("node").alias("src"), F.col("node").alias("dst"), F.lit(0.5).alias("c"), "vol")))
    x = cut_lineage(deg.select("node", "vol", (u01("node", seed) - 0.5).alias("x")))
    last = quotient = math.inf
    for i in range(rounds):
        # x is in the scale v / sqrt(d): the walk is an average over neighbours.
        pulled = steps.join(x.select(F.col("node").alias("dst"), "x"), "dst")
        x = pulled.groupBy(F.col("src").alias("node")).agg(F.max("vol").alias("vol"), F.sum(F.col("c") * F.col("x")).alias("x"))
        if i % every == every - 1 or i == rounds - 1:
            x = cut_lineage(x)
            stats = x.agg(F.sum(F.col("vol") * F.col("x")).alias("m"), F.sum(F.col("vol") * F.col("x") ** 2).alias("s")).first()
            mean = stats["m"] / total
            norm = math.sqrt(max(stats["s"] - total * mean * mean, 1e-300))
            x = x.select("node", "vol", ((F.col("x") - mean) / norm).alias("x"))
            quotient = rayleigh(edges, x)
            if abs(last - quotient) <= tol * max(quotient, 1e-12):
                break
            last = quotient
    return cut_lineage(x.select("node", F.col("x").alias("value"))), quotient


def rayleigh(edges: DataFrame, x: DataFrame) -> float:
    """Sum of w (x_i - x_j)^2 over edges; x has unit degree-weighted norm and zero mean."""
    a = x.select(F.col("node").alias("src"), F.col("x").alias("xa"))
    b = x.select(F.col("node").alias("dst"), F.col("x").alias("xb"))
    return edges.join(a, "src").join(b, "dst").agg(F.sum(F.col("w") * (F.col("xa") - F.col("xb")) ** 2).alias("r")).first()["r"]


def sweep(edges: DataFrame, vector: DataFrame) -> DataFrame:
    """Every prefix's cut in the order of the vector."""
    return graph.sweep_all(edges, vector)


def balanced(swept: DataFrame, total_volume: float, beta: float) -> DataFrame:
    """The best prefix with both sides at least beta of the volume."""
    share = F.least(F.col("vol"), F.lit(total_volume) - F.col("vol")) / total_volume
    return graph.best_prefix(swept.filter(share >= beta))


def residual(edges: DataFrame, x: DataFrame, quotient: float) -> float:
    """How far x is from an eigenvector: the normalized Laplacian has an eigenvalue within this of the quotient.

    x: node, value of unit degree-weighted norm.
    """
    deg = graph.degrees(edges).select("node", "vol")
    near = x.select(F.col("node").alias("dst"), F.col("value").alias("other"))
    pulled = graph.both_ways(edges).join(near, "dst").groupBy(F.col("src").alias("node")).agg(F.sum(F.col("w") * F.col("other")).alias("s"))
    gap = F.col("value") - F.col("s") / F.col("vol") - quotient * F.col("value")
    return math.sqrt(x.join(deg, "node").join(pulled, "node").agg(F.sum(F.col("vol") * gap * gap).alias("r")).first()["r"])


def lower_bound(edges: DataFrame, rounds: int = 120) -> float:
    """Half of the least value that the eigenvalue next to the quotient can have.

    Every set's conductance is at least half of the second eigenvalue. The
    quotient itself is an upper estimate of it, so the residual is taken off; what
    is left is a bound if the iteration has met the second eigenvalue, not a later one.
    """
    x, quotient = fiedler(edges, rounds)
    return max(0.0, quotient - residual(edges, x, quotient)) / 2


def embed(edges: DataFrame, k: int, rounds: int = 30) -> DataFrame:
    """node, v0..: k leading vectors of the symmetric normalized adjacency, by block iteration."""
    from levcut.operators import svd

    deg = graph.degrees(edges).select("node", F.sqrt("vol").alias("s"))
    scaled = (
        graph.both_ways(edges)
        .join(deg.withColumnRenamed("node", "src").withColumnRenamed("s", "s1"), "src")
        .join(deg.withColumnRenamed("node", "dst").withColumnRenamed("s", "s2"), "dst")
        .select(F.col("src").alias("row_id"), F.col("dst").alias("col_id"), (F.col("w") / F.col("s1") / F.col("s2")).alias("value"))
    )
    own = deg.select(F.col("node").alias("row_id"), F.col("node").alias("col_id"), F.lit(1.0).alias("value"))
    lazy = cut_lineage(scaled.unionByName(own))
    found = svd.topk(lazy, k, "subspace", power=max(2, rounds // 4))
    return found.v.withColumnRenamed("col_id", "node")


def kmeans(embedded: DataFrame, groups: int, seed: int = 1) -> DataFrame:
    """node, part: k-means on rows of the embedding scaled to unit length."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import Normalizer, VectorAssembler

    cols = [c for c in embedded.columns if c != "node"]
    rows = Normalizer(inputCol="raw", outputCol="features").transform(VectorAssembler(inputCols=cols, outputCol="raw").transform(embedded))
    model = KMeans(k=groups, seed=seed).fit(rows)
    return model.transform(rows).select("node", F.col("prediction").cast("long").alias("part"))
