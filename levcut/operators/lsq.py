"""Least squares: exact, sampled by leverage, sketched; leverage diagnostics."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

import levcut.runtime  # noqa: F401
from levcut.functions.portable import u01


class Moments:
    """Sufficient statistics of a design: count, A'A, A'b, b'b."""

    def __init__(self, m: float, ata: np.ndarray, atb: np.ndarray, btb: float):
        self.m, self.ata, self.atb, self.btb = m, ata, atb, btb

    def __sub__(self, other: Moments) -> Moments:
        return Moments(self.m - other.m, self.ata - other.ata, self.atb - other.atb, self.btb - other.btb)


def moment_columns(xs: Sequence[str], y: str | None, weight: Column | None = None, prefix: str = "") -> list[Column]:
    """All sums of products, for one aggregate."""
    w = F.lit(1.0) if weight is None else weight
    names = [*xs, *([y] if y else [])]
    out = [F.sum(w).alias(f"{prefix}m")]
    for i, a in enumerate(names):
        out += [F.sum(w * F.col(a) * F.col(b)).alias(f"{prefix}s_{i}_{j}") for j, b in enumerate(names) if j >= i]
    return out


def _moments(row, n: int, with_y: bool, prefix: str = "") -> Moments:
    size = n + with_y
    full = np.zeros((size, size))
    for i in range(size):
        for j in range(i, size):
            full[i, j] = full[j, i] = row[f"{prefix}s_{i}_{j}"] or 0.0
    return Moments(row[f"{prefix}m"] or 0.0, full[:n, :n], full[:n, n] if with_y else np.zeros(n), full[n, n] if with_y else 0.0)


def moments(df: DataFrame, xs: Sequence[str], y: str | None = None, weight: Column | None = None) -> Moments:
    """One scan, one row to the driver."""
    return _moments(df.agg(*moment_columns(xs, y, weight)).first(), len(xs), y is not None)


def inverse_factor(ata: np.ndarray) -> np.ndarray:
    """W with W'A'A W = I on the row space: scores are squared norms of a W.

    Columns are scaled to unit norm first; directions below rounding are left
    out, so a rank-deficient design has scores that sum to its rank.
    """
    scale = np.sqrt(np.maximum(np.diag(ata), 0))
    scale[scale == 0] = 1
    values, vectors = np.linalg.eigh(ata / np.outer(scale, scale))
    live = values > values.max(initial=0) * 1e-12
    return (vectors[:, live] / np.sqrt(values[live])) / scale[:, None]


def tall_skinny_r(df: DataFrame, names: Sequence[str]) -> np.ndarray:
    """R of the QR factorization, from one R a partition; no squared condition."""
    width = len(names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        r = np.zeros((0, width))
        for batch in batches:
            block = np.stack([c.to_numpy(zero_copy_only=False) for c in batch.columns], 1) if batch.num_rows else np.zeros((0, width))
            r = np.linalg.qr(np.concatenate([r, block]), mode="r")
        yield pa.RecordBatch.from_arrays([pa.array(list(r), pa.list_(pa.float64()))], names=["r"])

    rows = df.select(*[F.col(c).cast("double") for c in names]).mapInArrow(run, "r array<double>").collect()
    stacked = np.array([x["r"] for x in rows]).reshape(-1, width)
    return np.linalg.qr(stacked, mode="r")


def solve(df: DataFrame, y: str, xs: Sequence[str], method: str = "cholesky", weight: Column | None = None) -> np.ndarray:
    """Coefficients of the least-squares fit."""
    if method == "qr":
        frame = df if weight is None else df.select(*[(F.sqrt(weight) * F.col(c)).alias(c) for c in [*xs, y]])
        r = tall_skinny_r(frame, [*xs, y])
        n = len(xs)
        return np.linalg.lstsq(r[:n, :n], r[:n, n], rcond=None)[0]
    found = moments(df, xs, y, weight)
    return solve_moments(found, method)


def solve_moments(found: Moments, method: str = "cholesky") -> np.ndarray:
    scale = np.sqrt(np.maximum(np.diag(found.ata), 0))
    scale[scale == 0] = 1
    g, rhs = found.ata / np.outer(scale, scale), found.atb / scale
    if method == "cholesky":
        try:
            lower = np.linalg.cholesky(g)
            return np.linalg.solve(lower.T, np.linalg.solve(lower, rhs)) / scale
        except np.linalg.LinAlgError:
            pass
    return np.linalg.pinv(g, rcond=1e-12, hermitian=True) @ rhs / scale


def linear(xs: Sequence[str], coefficients: np.ndarray) -> Column:
    out = F.lit(0.0)
    for name, c in zip(xs, coefficients, strict=True):
        out = out + F.col(name) * F.lit(float(c))
    return out


def score_column(xs: Sequence[str], w: np.ndarray) -> Column:
    """Squared norm of a W, as one expression over wide columns."""
    out = F.lit(0.0)
    for j in range(w.shape[1]):
        part = linear(xs, w[:, j])
        out = out + part * part
    return out


def leverage(df: DataFrame, xs: Sequence[str], name: str = "h") -> DataFrame:
    """The rows with their diagonal entry of the hat matrix: one scan, then a map."""
    return df.withColumn(name, score_column(xs, inverse_factor(moments(df, xs).ata)))


def influence(df: DataFrame, xs: Sequence[str], key: str, pairs: DataFrame) -> DataFrame:
    """Off-diagonal entries of the hat matrix for the pairs (i, j) asked for."""
    inv = np.linalg.pinv(moments(df, xs).ata, hermitian=True)
    left = df.select(F.col(key).alias("i"), *[F.col(x).alias(f"a_{x}") for x in xs])
    right = df.select(F.col(key).alias("j"), *[F.col(x).alias(f"b_{x}") for x in xs])
    value = F.lit(0.0)
    for p, a in enumerate(xs):
        for q, b in enumerate(xs):
            value = value + F.col(f"a_{a}") * F.col(f"b_{b}") * F.lit(float(inv[p, q]))
    return pairs.join(left, "i").join(right, "j").select("i", "j", value.alias("h"))


def flag(df: DataFrame, xs: Sequence[str], factor: float = 2.0) -> DataFrame:
    """Rows whose leverage exceeds factor times the average n/m."""
    found = moments(df, xs)
    w = inverse_factor(found.ata)
    limit = factor * w.shape[1] / found.m if found.m else 0.0
    return df.withColumn("h", score_column(xs, w)).filter(F.col("h") > F.lit(limit))


def fit_diagnostics(df: DataFrame, y: str, xs: Sequence[str], method: str = "cholesky") -> DataFrame:
    """fitted, residual, h for every row."""
    found = moments(df, xs, y)
    beta = solve_moments(found, method)
    return df.withColumns(
        {"fitted": linear(xs, beta), "residual": F.col(y) - linear(xs, beta), "h": score_column(xs, inverse_factor(found.ata))}
    )


def assumptions(df: DataFrame, y: str, xs: Sequence[str], order: str, bins: int = 10) -> DataFrame:
    """Are the assumptions plausible: decile, n, mean, variance of the residuals by equal parts of the fit.

    A last row, decile -1, has the number of neighbours in order, their
    correlation as mean, and the skewness of all residuals as variance.
    """
    from levcut.operators.relational import prefix_sum

    rows = fit_diagnostics(df, y, xs).select(F.col(order).alias("at_"), "fitted", "residual", F.lit(1.0).alias("one_"))
    m = rows.count()
    ranked = prefix_sum(rows, [F.col("fitted"), F.col("at_")], "one_", "sum_", "place_")
    part = F.floor((F.col("place_") - 1) * bins / m).cast("long")
    by_part = ranked.groupBy(part.alias("decile")).agg(F.count("*").alias("n"), F.avg("residual").alias("mean"), F.var_pop("residual").alias("variance"))
    # Neighbours meet by their place, so no task needs all rows in order.
    placed = prefix_sum(rows, [F.col("at_")], "one_", "sum_", "place_").select("place_", "residual")
    after = placed.select((F.col("place_") + 1).alias("place_"), F.col("residual").alias("before_"))
    lag = placed.join(after, "place_").agg(F.lit(-1).cast("long").alias("decile"), F.count("*").alias("n"), F.corr("residual", "before_").alias("mean"))
    return by_part.unionByName(lag.crossJoin(rows.agg(F.skewness("residual").alias("variance"))))


def delete_effect(df: DataFrame, y: str, xs: Sequence[str], factor: float = 2.0) -> tuple[np.ndarray, np.ndarray, int]:
    """Coefficients with all rows and without the flagged ones; one further scan."""
    whole = moments(df, xs, y)
    w = inverse_factor(whole.ata)
    scored = df.withColumn("h_", score_column(xs, w))
    out = moments(scored.filter(F.col("h_") > factor * w.shape[1] / whole.m), xs, y)
    return solve_moments(whole), solve_moments(whole - out), int(out.m)


def sample_size(n: int, eps: float) -> int:
    """Rows that leverage sampling keeps for a relative error of eps."""
    return int(np.ceil(n * np.log(max(2, n)) / eps**2))


def sampled(df: DataFrame, y: str, xs: Sequence[str], r: int, key: str, seed: int, probs: str = "leverage", method: str = "cholesky") -> np.ndarray:
    """Solve on rows kept with probability min(1, r p), reweighted by its inverse.

    probs: leverage, or uniform as the control. Rows are drawn by a hash of
    their key, so the sample is a filter and needs no shuffle.
    """
    found = moments(df, xs)
    w = inverse_factor(found.ata)
    p = score_column(xs, w) / F.lit(float(w.shape[1])) if probs == "leverage" else F.lit(1.0 / found.m)
    keep = F.least(F.lit(1.0), F.lit(float(r)) * p)
    rows = df.withColumn("keep_", keep).filter(u01(key, seed) < F.col("keep_"))
    return solve(rows, y, xs, method, weight=1.0 / F.col("keep_"))


def errors(df: DataFrame, y: str, xs: Sequence[str], exact: np.ndarray, approximate: np.ndarray) -> tuple[float, float]:
    """Residual ratio and relative error of the coefficients."""
    a, b = F.col(y) - linear(xs, exact), F.col(y) - linear(xs, approximate)
    row = df.agg(F.sum(a * a).alias("a"), F.sum(b * b).alias("b")).first()
    return float(np.sqrt(row["b"] / row["a"])), float(np.linalg.norm(exact - approximate) / np.linalg.norm(exact))


def leverage_approx(df: DataFrame, xs: Sequence[str], key: str, buckets: int, seed: int = 3, kind: str = "countsketch") -> DataFrame:
    """Scores from a sketch of the rows instead of A'A.

    countsketch adds each row, with a random sign, to one bucket; the R factor
    of the bucket sums stands in for that of A.
    """
    sign = F.when(u01(key, seed) < 0.5, -1.0).otherwise(1.0)
    bucket = F.floor(u01(key, seed + 1) * buckets)
    sums = df.groupBy(bucket.alias("bucket_")).agg(*[F.sum(sign * F.col(x)).alias(x) for x in xs]).select(*xs).collect()
    sketch = np.array([list(r) for r in sums])
    return df.withColumn("h_approx", score_column(xs, inverse_factor(sketch.T @ sketch)))


def regularized(df: DataFrame, y: str, xs: Sequence[str], l1: float = 0.0, l2: float = 0.0, rounds: int = 500) -> np.ndarray:
    """Penalized fit: closed form for l2, coordinate descent on moments for l1.

    The loss is half the mean squared residual.
    """
    found = moments(df, xs, y)
    g, b = found.ata / found.m, found.atb / found.m
    n = len(xs)
    if not l1:
        return np.linalg.solve(g + l2 * np.eye(n), b)
    x = np.zeros(n)
    for _ in range(rounds):
        before = x.copy()
        for j in range(n):
            rest = b[j] - g[j] @ x + g[j, j] * x[j]
            x[j] = np.sign(rest) * max(0.0, abs(rest) - l1) / (g[j, j] + l2)
        if np.abs(x - before).max() < 1e-12:
            break
    return x


def boosted(df: DataFrame, y: str, xs: Sequence[str], iterations: Sequence[int], pace: float = 0.5) -> dict[int, tuple[np.ndarray, float]]:
    """Early stopping: gradient steps on the moments, (coefficients, mean squared residual) after each count."""
    found = moments(df, xs, y)
    scale = np.sqrt(np.diag(found.ata) / found.m)
    g, b = found.ata / found.m / np.outer(scale, scale), found.atb / found.m / scale
    step = pace / np.linalg.eigvalsh(g).max()
    x, out = np.zeros(len(xs)), {}
    for i in range(1, max(iterations) + 1):
        x = x - step * (g @ x - b)
        if i in iterations:
            out[i] = (x / scale, float(x @ g @ x - 2 * x @ b + found.btb / found.m))
    return out
