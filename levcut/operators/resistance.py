"""Leverage of edges: effective resistance, exact and by random projections."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levcut.functions.portable import u01
from levcut.operators import graph
from levcut.operators.small import NODES, SmallGraph
from levcut.runtime import cut_lineage


def exact(edges: DataFrame) -> DataFrame:
    """src, dst, r, leverage = w r, from the pseudo-inverse of the Laplacian on the driver."""
    g = SmallGraph.of(edges)
    r = g.resistance()
    rows = [(int(g.ids[i]), int(g.ids[j]), float(x), float(w * x)) for (i, j, w), x in zip(g.edges(), r, strict=True)]
    return edges.sparkSession.createDataFrame(rows, "src long, dst long, r double, leverage double")


def scores(edges: DataFrame, count: int = 16, rounds: int = 40, tol: float = 1e-3) -> DataFrame:
    """exact() where the driver can hold the graph, else the sketch with its bridges put at 1."""
    from levcut.operators import probes

    if graph.degrees(edges).limit(NODES + 1).count() <= NODES:
        return exact(edges)
    rough = sketch(edges, count, rounds, tol)
    alone = probes.bridges(edges).withColumn("bridge_", F.lit(True))
    sure = F.coalesce("bridge_", F.lit(False))
    joined = rough.join(edges.select("src", "dst", "w"), ["src", "dst"]).join(alone, ["src", "dst"], "left")
    return joined.select("src", "dst", F.when(sure, 1 / F.col("w")).otherwise(F.col("r")).alias("r"), F.when(sure, 1.0).otherwise(F.least("leverage", F.lit(1.0))).alias("leverage"))


def sketch(edges: DataFrame, count: int = 24, rounds: int = 60, tol: float = 1e-6, seed: int = 5) -> DataFrame:
    """src, dst, r, leverage from ``count`` random signs per edge.

    For each sign vector a Laplacian system is solved by conjugate gradients with
    all right sides as wide columns: one join and one aggregate a round.
    """
    cols = [f"c{i}" for i in range(count)]
    key = F.concat_ws("-", "src", "dst")
    signs = [(F.when(u01(key, seed * 1000 + i) < 0.5, -1.0).otherwise(1.0) * F.sqrt("w") / math.sqrt(count)).alias(c) for i, c in enumerate(cols)]
    marked = edges.select("src", "dst", *signs)
    minus = marked.select(F.col("dst").alias("node"), *[(-F.col(c)).alias(c) for c in cols])
    b = marked.select(F.col("src").alias("node"), *cols).unionByName(minus).groupBy("node").agg(*[F.sum(c).alias(c) for c in cols])
    deg = graph.degrees(edges).select("node", "vol")
    both = cut_lineage(graph.both_ways(edges))
    state = cut_lineage(
        b.join(deg, "node").select(
            "node", "vol", *[F.lit(0.0).alias(f"x{i}") for i in range(count)], *[F.col(c).alias(f"r{i}") for i, c in enumerate(cols)],
            *[(F.col(c) / F.col("vol")).alias(f"p{i}") for i, c in enumerate(cols)],
        )
    )
    rz = _dots(state, [F.col(f"r{i}") * F.col(f"r{i}") / F.col("vol") for i in range(count)])
    first = rz.copy()
    for _ in range(rounds):
        pulled = both.join(state.select(F.col("node").alias("dst"), *[f"p{i}" for i in range(count)]), "dst").groupBy(F.col("src").alias("node")).agg(
            *[F.sum(F.col("w") * F.col(f"p{i}")).alias(f"s{i}") for i in range(count)]
        )
        ap = state.join(pulled, "node")
        lap = [F.col("vol") * F.col(f"p{i}") - F.col(f"s{i}") for i in range(count)]
        ap = cut_lineage(ap.select("node", "vol", *[f"{t}{i}" for t in "xrp" for i in range(count)], *[v.alias(f"q{i}") for i, v in enumerate(lap)]))
        step = rz / np.maximum(_dots(ap, [F.col(f"p{i}") * F.col(f"q{i}") for i in range(count)]), 1e-300)
        moved = ap.select(
            "node", "vol",
            *[(F.col(f"x{i}") + float(step[i]) * F.col(f"p{i}")).alias(f"x{i}") for i in range(count)],
            *[(F.col(f"r{i}") - float(step[i]) * F.col(f"q{i}")).alias(f"r{i}") for i in range(count)],
            *[f"p{i}" for i in range(count)],
        )
        new = _dots(moved, [F.col(f"r{i}") * F.col(f"r{i}") / F.col("vol") for i in range(count)])
        state = moved.select(
            "node", "vol", *[f"x{i}" for i in range(count)], *[f"r{i}" for i in range(count)],
            *[(F.col(f"r{i}") / F.col("vol") + float(new[i] / max(rz[i], 1e-300)) * F.col(f"p{i}")).alias(f"p{i}") for i in range(count)],
        )
        rz = new
        if (rz <= tol * tol * np.maximum(first, 1e-300)).all():
            break
    a = state.select(F.col("node").alias("src"), *[F.col(f"x{i}").alias(f"a{i}") for i in range(count)])
    z = state.select(F.col("node").alias("dst"), *[F.col(f"x{i}").alias(f"b{i}") for i in range(count)])
    gap = F.lit(0.0)
    for i in range(count):
        gap = gap + (F.col(f"a{i}") - F.col(f"b{i}")) ** 2
    return edges.join(a, "src").join(z, "dst").select("src", "dst", gap.alias("r"), (F.col("w") * gap).alias("leverage"))


def _dots(df: DataFrame, terms: list) -> np.ndarray:
    return np.array(list(df.agg(*[F.sum(t).alias(f"d{i}") for i, t in enumerate(terms)]).first()), float)


def check(edges: DataFrame, scores: DataFrame) -> DataFrame:
    """Foster's sum: leverages add up to nodes less components."""
    n = graph.degrees(edges).count()
    parts = graph.components(edges).select("component").distinct().count()
    return scores.agg(F.sum("leverage").alias("total"), F.lit(float(n - parts)).alias("expected"), F.max("leverage").alias("largest"))


def correlates(edges: DataFrame, scores: DataFrame) -> DataFrame:
    """Correlation of edge leverage with the product and the sum of end degrees; null where either is constant."""
    d = graph.degrees(edges).select("node", "deg")
    rows = scores.join(d.select(F.col("node").alias("src"), F.col("deg").alias("d1")), "src").join(d.select(F.col("node").alias("dst"), F.col("deg").alias("d2")), "dst")

    def corr(x, y):
        return F.try_divide(F.covar_pop(x, y), F.stddev_pop(x) * F.stddev_pop(y))

    h, product, total = F.col("leverage"), (F.col("d1") * F.col("d2")).cast("double"), (F.col("d1") + F.col("d2")).cast("double")
    return rows.agg(corr(h, product).alias("with_product"), corr(h, total).alias("with_sum"))
