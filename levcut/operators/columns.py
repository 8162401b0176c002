"""Column subset selection: two stages, its baselines, errors and sweeps."""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levcut.operators import leverage, qr, sample, svd
from levcut.operators.relational import ranks
from levcut.runtime import bounded


def _factor(v: DataFrame, ids: Sequence | None = None, most: int = 200_000) -> tuple[list, np.ndarray]:
    """Column ids and the k x c matrix of their basis rows, on the driver."""
    cols = [c for c in v.columns if c != "col_id"]
    frame = v if ids is None else v.filter(F.col("col_id").isin(list(ids)))
    rows = sorted(bounded(frame, most), key=lambda r: r["col_id"])
    return [r["col_id"] for r in rows], np.array([[r[c] for c in cols] for r in rows]).reshape(len(rows), len(cols)).T


def two_stage(
    a: DataFrame, k: int, c: int | None = None, rule: str = "low_rr", scheme: str = "with_replacement", seed: int = 0,
    probs: str = "basis", found: svd.Svd | None = None, tries: int = 5, axis: str = "columns",
) -> list:
    """Exactly k column ids (axis="rows": row ids, of the transpose): c columns of the top-k basis are drawn by leverage and
    rescaled, and a deterministic rule picks k of them.

    Both stages look at the basis, never at A. A draw with fewer than k distinct
    columns is repeated with the next seed, at last filled up by leverage.
    """
    if axis == "rows":
        return two_stage(svd.transpose(a), k, c, rule, scheme, seed, probs, found, tries)
    found = found or svd.topk(a, k)
    p = leverage.columns(found.v, k, probs, a).cache()
    c = c or max(k, math.ceil(2 * k * math.log(max(2, k)) + k))
    drawn = []
    for attempt in range(tries):
        drawn = sorted(sample.draw(p, c, scheme, seed + attempt).collect(), key=lambda r: r["col_id"])
        if len(drawn) >= min(k, found.k):
            break
    scale = {r["col_id"]: r["scale"] for r in drawn}
    if len(scale) < found.k:
        best = p.orderBy(F.desc("p"), "col_id").limit(found.k).collect()
        scale |= {r["col_id"]: 1.0 for r in best if r["col_id"] not in scale}
    p.unpersist()
    ids, mat = _factor(found.v.select("col_id", *svd.names(min(k, found.k))), list(scale))
    picked = qr.select(mat * np.array([scale[i] for i in ids]), min(k, found.k), rule)
    return [ids[i] for i in picked]


def columns_of(a: DataFrame, ids: Sequence) -> DataFrame:
    """The chosen columns of A: a broadcast semi-join of k ids."""
    kind = a.schema["col_id"].dataType.simpleString()
    keys = a.sparkSession.createDataFrame([(i,) for i in ids], f"col_id {kind}")
    return a.join(F.broadcast(keys), "col_id", "left_semi")


def qr_on_basis(a: DataFrame, k: int, rule: str = "pivot", found: svd.Svd | None = None) -> list:
    """No random stage: the rule on the whole k x n basis."""
    found = found or svd.topk(a, k)
    ids, mat = _factor(found.v.select("col_id", *svd.names(min(k, found.k))))
    return [ids[i] for i in qr.select(mat, min(k, found.k), rule)]


def qr_on_matrix(a: DataFrame, k: int, rule: str = "pivot", known: tuple[list, np.ndarray] | None = None) -> list:
    """The conventional baseline: the rule on A itself, through its Gram matrix."""
    ids, g = known or svd.gram(a)
    return [ids[i] for i in qr.select(_root(g), k, rule)]


def _root(g: np.ndarray) -> np.ndarray:
    """R with R'R = G: columns with the lengths and angles of A's."""
    values, vectors = np.linalg.eigh(g)
    return np.sqrt(np.maximum(values, 0))[:, None] * vectors.T


def naive_hybrid(a: DataFrame, k: int, c: int, rule: str = "pivot", seed: int = 0, found: svd.Svd | None = None) -> list:
    """Draws columns of A by leverage and runs the rule on those columns of A."""
    found = found or svd.topk(a, k)
    p = leverage.columns(found.v)
    ids = [r["col_id"] for r in sample.draw(p, c, "exponential_keys", seed).collect()]
    if found.gram is not None:
        every, full = found.gram
        order = sorted(ids)
        at = [every.index(i) for i in order]
        g = full[np.ix_(at, at)]
    else:
        order, g = svd.gram(columns_of(a, ids))
    return [order[i] for i in qr.select(_root(g), min(k, len(order)), rule)]


def top_loading(v: DataFrame, k: int) -> list:
    """For each leading vector the column with the largest loading; one pass."""
    row = v.agg(*[F.max_by("col_id", F.struct(F.abs(c), F.lit(0))).alias(c) for c in svd.names(k)]).first()
    return [row[c] for c in svd.names(k)]


def residual(
    a: DataFrame, ids: Sequence, norm: str = "fro", rank: int | None = None, mode: str = "best_in_span", known: tuple[list, np.ndarray] | None = None
) -> float:
    """Error of projecting A on the span of the chosen columns.

    With rank: onto the best rank-k part inside the span (best_in_span), or onto
    the span of the best rank-k part of C (truncate_c). known: the Gram matrix of
    A, of which everything here is a block; without it A is multiplied.
    """
    ids = list(dict.fromkeys(ids))
    if known is not None:
        order, full = known
        at = [order.index(i) for i in ids]
        g, whole = full[np.ix_(at, at)], full[:, at]
    else:
        kind = a.schema["col_id"].dataType.simpleString()
        at = F.broadcast(a.sparkSession.createDataFrame([(c, i) for i, c in enumerate(ids)], f"col_id {kind}, at_ int"))
        stems = svd.names(len(ids), "c")
        c = a.join(at, "col_id").groupBy("row_id").agg(*[F.sum(F.when(F.col("at_") == i, F.col("value")).otherwise(0.0)).alias(n) for i, n in enumerate(stems)])
        g = svd.inner(c, stems)
        w = svd.multiply(a, c, "row_id", "col_id", stems, "w")
    values, vectors = np.linalg.eigh(g)
    live = values > max(values.max(), 0) * 1e-11
    if rank is not None and mode == "truncate_c":
        live &= np.arange(len(values)) >= len(values) - rank
    half = vectors[:, live] / np.sqrt(values[live])
    products = whole.T @ whole if known is not None else svd.inner(w, svd.names(len(ids), "w"))
    m = half.T @ products @ half
    if norm == "fro":
        kept = np.sort(np.linalg.eigvalsh(m))[::-1][: rank if rank is not None else len(m)]
        total = float(np.trace(full)) if known is not None else svd.squared_norm(a)
        return float(np.sqrt(max(0.0, total - kept.sum())))
    if known is None:
        order, full = svd.gram(a)
        rows = {r["col_id"]: [r[n] for n in svd.names(len(ids), "w")] for r in bounded(w, svd.GRAM_COLUMNS)}
        whole = np.array([rows.get(x, [0.0] * len(ids)) for x in order])
    wm = whole @ half
    if rank is not None and mode == "best_in_span":
        u = np.linalg.eigh(m)[1][:, ::-1][:, :rank]
        wm = wm @ u
    return float(np.sqrt(max(0.0, np.linalg.eigvalsh(full - wm @ wm.T).max())))


def best_columns(a: DataFrame, k: int, most: int = 2_000_000) -> DataFrame:
    """Exhaustive: error and ids of every set of k columns, few columns only.

    Sets are numbered and dealt over tasks; each is scored from the Gram matrix.
    """
    ids, g = svd.gram(a, 64)
    n, count = len(ids), math.comb(len(ids), k)
    if count > most:
        raise ValueError(f"{count} sets")
    spark = a.sparkSession
    shared = spark.sparkContext.broadcast((g, g @ g, float(np.trace(g))))

    def unrank(number: int) -> list[int]:
        out, low = [], 0
        for left in range(k, 0, -1):
            while (block := math.comb(n - low - 1, left - 1)) <= number:
                number -= block
                low += 1
            out.append(low)
            low += 1
        return out

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        g_, gg, total = shared.value
        for frame in frames:
            rows = []
            for number in frame["id"]:
                s = unrank(int(number))
                # |A|^2 - tr((C'C)^+ C'A A'C), and C'A A'C is a block of the squared Gram matrix.
                error = total - np.trace(np.linalg.pinv(g_[np.ix_(s, s)], hermitian=True) @ gg[np.ix_(s, s)])
                rows.append((float(np.sqrt(max(0.0, error))), [str(ids[i]) for i in s]))
            yield pd.DataFrame(rows, columns=["error", "col_ids"])

    return spark.range(count).mapInPandas(run, "error double, col_ids array<string>")


def relative_error(
    a: DataFrame, k: int, eps: float, seed: int = 0, scheme: str = "with_replacement", probs: DataFrame | None = None, known: tuple[list, np.ndarray] | None = None
) -> tuple[list, float]:
    """More than k columns by leverage: ids and the error of the best rank-k part in their span."""
    if probs is None:
        found = svd.topk(a, k)
        probs, known = leverage.columns(found.v), known or found.gram
    p = probs
    ids = [r["col_id"] for r in sample.draw(p, sample.draws_for(k, eps), scheme, seed).collect()]
    return ids, residual(a, ids, rank=k, known=known)


def best_of(a: DataFrame, k: int, eps: float, repeats: int, seed: int = 0) -> tuple[list, float, list[float]]:
    """Repeats draws over one basis and keeps the least error."""
    found = svd.topk(a, k)
    p = leverage.columns(found.v).cache()
    tried = [relative_error(a, k, eps, seed + i, probs=p, known=found.gram) for i in range(repeats)]
    p.unpersist()
    ids, error = min(tried, key=lambda x: x[1])
    return ids, error, [e for _, e in tried]


def coverage(p: DataFrame, v: DataFrame, k: int, cs: Sequence[int], repeats: int, seed: int = 0) -> DataFrame:
    """Share of draws of c columns that still have rank k."""
    out = []
    for c in cs:
        full = 0
        for r in range(repeats):
            ids = [x["col_id"] for x in sample.draw(p, c, "with_replacement", seed + r).collect()]
            _, mat = _factor(v, ids)
            full += int(np.linalg.matrix_rank(mat, tol=1e-6) >= k)
        out.append((c, full / repeats))
    return v.sparkSession.createDataFrame(out, "c int, share double")


def sweep_c(a: DataFrame, k: int, cs: Sequence[int], seeds: Sequence[int], rule: str = "low_rr") -> DataFrame:
    """c, seed, error, ratio to the best rank-k error; the basis is computed once."""
    found = svd.topk(a, k)
    optimum = found.tail()
    rows = []
    for c in cs:
        for seed in seeds:
            error = residual(a, two_stage(a, k, c, rule, seed=seed, found=found), known=found.gram)
            rows.append((c, seed, error, error / optimum if optimum else 1.0))
    return a.sparkSession.createDataFrame(rows, "c int, seed int, error double, ratio double")


def sweep_k(a: DataFrame, ks: Sequence[int], rule: str = "low_rr", seed: int = 0) -> DataFrame:
    """k, error, optimum: rank as a choice of model; prefixes of one basis are reused."""
    found = svd.topk(a, max(ks))
    rows = []
    for k in ks:
        part = svd.Svd(found.v.select("col_id", *svd.names(k)), found.sigma[:k], found.total, found.gram)
        rows.append((k, residual(a, two_stage(a, k, rule=rule, seed=seed, found=part), known=found.gram), part.tail()))
    return a.sparkSession.createDataFrame(rows, "k int, error double, optimum double")


def compare_rules(a: DataFrame, k: int, rules: Sequence[str] = qr.RULES, seeds: Sequence[int] = (0, 1, 2)) -> DataFrame:
    """method, rule, error (least over seeds), ratio: with and without the random stage."""
    found = svd.topk(a, k)
    optimum = found.tail() or 1.0
    rows = []
    for rule in rules:
        error = lambda ids: residual(a, ids, known=found.gram)
        rows.append(("matrix", rule, error(qr_on_matrix(a, k, rule, found.gram))))
        rows.append(("basis", rule, error(qr_on_basis(a, k, rule, found))))
        rows.append(("two_stage", rule, min(error(two_stage(a, k, None, rule, seed=s, found=found)) for s in seeds)))
        rows.append(("naive_hybrid", rule, min(error(naive_hybrid(a, k, 4 * k, rule, s, found)) for s in seeds)))
    return a.sparkSession.createDataFrame([(m, r, e, e / optimum) for m, r, e in rows], "method string, rule string, error double, ratio double")


def bounds(k: int, n: int) -> dict[str, float]:
    """Factors over the best rank-k error that the literature proves; 1 for hidden constants."""
    log = math.log(max(2, k))
    return {
        "two_stage_spectral": k**0.75 * math.sqrt(log) * n**0.5,
        "two_stage_fro": k * math.sqrt(log),
        "exact_fro": math.sqrt(k + 1),
        "pivot_spectral": math.sqrt(k * (n - k) + 1),
        "exhaustive_fro_over_spectral": math.sqrt((k + 1) * (n - k)),
    }


def reconstruct(a: DataFrame, ids: Sequence) -> DataFrame:
    """row_id, col_id, value of C C^+ A for the columns that were not chosen."""
    kind = a.schema["col_id"].dataType.simpleString()
    stems = svd.names(len(ids), "c")
    at = F.broadcast(a.sparkSession.createDataFrame([(c, i) for i, c in enumerate(ids)], f"col_id {kind}, at_ int"))
    c = a.join(at, "col_id").groupBy("row_id").agg(*[F.sum(F.when(F.col("at_") == i, F.col("value")).otherwise(0.0)).alias(n) for i, n in enumerate(stems)])
    inverse = np.linalg.pinv(svd.inner(c, stems), hermitian=True)
    w = svd.multiply(a, c, "row_id", "col_id", stems, "w")
    x = svd.rotate(w, "col_id", svd.names(len(ids), "w"), inverse, svd.names(len(ids), "x"))
    unseen = x.join(at.select("col_id"), "col_id", "left_anti")
    value = F.lit(0.0)
    for s, t in zip(stems, svd.names(len(ids), "x"), strict=True):
        value = value + F.col(s) * F.col(t)
    entries = a.join(at.select("col_id"), "col_id", "left_anti").select("row_id", "col_id", F.col("value").alias("truth"))
    return entries.join(c, "row_id").join(unseen, "col_id").select("row_id", "col_id", "truth", value.alias("value"))


def classify(a: DataFrame, ids: Sequence, labels: DataFrame, seed: int = 3) -> float:
    """Accuracy on held-out rows of the nearest class mean over the chosen columns."""
    chosen = columns_of(a, ids)
    from levcut.functions.portable import u01

    parts = labels.withColumn("test_", u01("row_id", seed) < 0.25)
    sizes = parts.filter("not test_").groupBy("label").agg(F.count("*").alias("n_"))
    sums = chosen.join(parts.filter("not test_"), "row_id").groupBy("label", "col_id").agg(F.sum("value").alias("s_"))
    means = sums.join(F.broadcast(sizes), "label").select("label", "col_id", (F.col("s_") / F.col("n_")).alias("mean_"))
    norms = means.groupBy("label").agg(F.sum(F.col("mean_") ** 2).alias("norm_"))
    test = parts.filter("test_").select("row_id", F.col("label").alias("truth_"))
    cross = chosen.join(test, "row_id").join(F.broadcast(means), "col_id").groupBy("row_id", "label").agg(F.sum(F.col("value") * F.col("mean_")).alias("dot_"))
    every = test.crossJoin(F.broadcast(norms)).join(cross, ["row_id", "label"], "left")
    gap = F.col("norm_") - 2 * F.coalesce("dot_", F.lit(0.0))
    best = every.groupBy("row_id", "truth_").agg(F.min_by("label", F.struct(gap, "label")).alias("guess_"))
    return best.agg(F.avg((F.col("guess_") == F.col("truth_")).cast("double")).alias("x")).first()["x"]


def cluster(a: DataFrame, ids: Sequence, groups: int, seed: int = 1) -> DataFrame:
    """row_id, part: k-means of the rows over the chosen columns alone."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    stems = svd.names(len(ids), "c")
    at = {i: n for i, n in zip(ids, stems, strict=True)}
    wide = columns_of(a, ids).groupBy("row_id").agg(*[F.sum(F.when(F.col("col_id") == i, F.col("value")).otherwise(0.0)).alias(n) for i, n in at.items()])
    every = a.select("row_id").distinct().join(wide, "row_id", "left").fillna(0.0, stems)
    rows = VectorAssembler(inputCols=stems, outputCol="features").transform(every)
    return KMeans(k=groups, seed=seed).fit(rows).transform(rows).select("row_id", F.col("prediction").cast("long").alias("part"))


def transfer(a1: DataFrame, a2: DataFrame, k: int, seed: int = 0) -> DataFrame:
    """Columns chosen on one population, judged on another: error and own optimum."""
    ids = two_stage(a1, k, seed=seed)
    rows = []
    for name, a in (("own", a1), ("other", a2)):
        found = svd.topk(a, k)
        rows.append((name, residual(a, ids, known=found.gram), found.tail()))
    return a1.sparkSession.createDataFrame(rows, "population string, error double, optimum double")


def success(errors: Sequence[float], optimum: float, eps: float) -> float:
    """Share of repeats within (1 + eps) of the optimum."""
    return sum(e <= (1 + eps) * optimum for e in errors) / max(1, len(errors))


def rank_correlation(df: DataFrame, x: str, y: str) -> float:
    """Spearman's over all rows of a frame with one row a column of A."""
    ranked = ranks(ranks(df, x, "rx_"), y, "ry_")
    return ranked.agg(F.corr("rx_", "ry_").alias("r")).first()["r"]
