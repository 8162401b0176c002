"""Best rank-k subspaces of a sparse matrix in (row_id, col_id, value) form."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levcut.functions.portable import u01
from levcut.runtime import bounded, cut_lineage, release, ship
from levcut.schema import COO, require

#: Columns up to which the Gram matrix is formed and its eigenvectors taken.
GRAM_COLUMNS = 1024
#: Entries of a factor of the columns that every task holds at a time, and entries of one that the driver holds.
HELD_ENTRIES = 4_000_000
DRIVER_ENTRIES = 16_000_000


@dataclass
class Svd:
    v: DataFrame  # col_id, v0..
    sigma: np.ndarray
    total: float  # squared Frobenius norm
    gram: tuple[list, np.ndarray] | None = None  # where it was formed

    @property
    def k(self) -> int:
        return len(self.sigma)

    def tail(self, k: int | None = None) -> float:
        """Frobenius error of the best approximation of rank k."""
        return float(np.sqrt(max(0.0, self.total - (self.sigma[: self.k if k is None else k] ** 2).sum())))


def names(k: int, stem: str = "v") -> list[str]:
    return [f"{stem}{i}" for i in range(k)]


def transpose(a: DataFrame) -> DataFrame:
    return require(a, COO).select(F.col("col_id").alias("row_id"), F.col("row_id").alias("col_id"), "value")


def squared_norm(a: DataFrame) -> float:
    return a.agg(F.sum(F.col("value") * F.col("value")).alias("s")).first()["s"] or 0.0


def gram(a: DataFrame, most: int = GRAM_COLUMNS) -> tuple[list, np.ndarray]:
    """Column ids in order, and A'A on the driver; columns must be few.

    Rows are brought together once; a task adds up the products of its rows in a
    matrix of its own, so a long row costs its length and no pairs are shuffled.
    """
    ids = sorted(r["col_id"] for r in bounded(a.select("col_id").distinct(), most))
    n = len(ids)
    kind = a.schema["col_id"].dataType.simpleString()
    at = F.broadcast(a.sparkSession.createDataFrame([(c, i) for i, c in enumerate(ids)], f"col_id {kind}, at_ int"))

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g = np.zeros((n, n))
        rest: list[np.ndarray] = [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]

        def add(row: np.ndarray, col: np.ndarray, value: np.ndarray) -> None:
            starts = np.flatnonzero(np.diff(row, prepend=row[0] - 1)) if len(row) else np.zeros(0, int)
            for low in range(0, len(starts), 2048):
                first, last = starts[low], starts[low + 2048] if low + 2048 < len(starts) else len(row)
                own = np.searchsorted(starts, np.arange(first, last), "right") - 1 - low
                block = np.zeros((int(own.max()) + 1, n))
                np.add.at(block, (own, col[first:last]), value[first:last])
                g[:] += block.T @ block

        for batch in batches:
            if not batch.num_rows:
                continue
            now = [np.concatenate([r, c.to_numpy(zero_copy_only=False)]) for r, c in zip(rest, batch.columns, strict=True)]
            # The last row may go on in the next batch.
            done = int(np.searchsorted(now[0], now[0][-1]))
            if done:
                add(*(x[:done] for x in now))
            rest = [x[done:] for x in now]
        add(*rest)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(n), pa.int32()), pa.array(list(g), pa.list_(pa.float64()))], names=["i", "sums"])

    def total(pdf):
        import pandas as pd

        return pd.DataFrame({"i": pdf["i"].iloc[:1], "sums": [np.sum(np.stack(pdf["sums"].to_numpy()), 0)]})

    out = np.zeros((n, n))
    if n:
        # Only the order of rows matters; a hash of the id serves for ids of any type.
        rows = a.join(at, "col_id").select(F.xxhash64("row_id").alias("row_"), F.col("at_").cast("long").alias("at_"), F.col("value").cast("double").alias("value"))
        dealt = rows.repartition("row_").sortWithinPartitions("row_")
        for r in dealt.mapInArrow(partial, "i int, sums array<double>").groupBy("i").applyInPandas(total, "i int, sums array<double>").toLocalIterator():
            out[r["i"]] = r["sums"]
    return ids, out


def _block(batch: pa.RecordBatch, columns: Sequence[str]) -> np.ndarray:
    """The wide columns of a batch as a matrix; nulls count as zero."""
    out = np.zeros((batch.num_rows, len(columns)))
    for i, c in enumerate(columns):
        out[:, i] = pc.fill_null(batch.column(batch.schema.get_field_index(c)), 0.0).to_numpy(zero_copy_only=False)
    return out


def rotate(factor: DataFrame, key: str, old: Sequence[str], matrix: np.ndarray, new: Sequence[str]) -> DataFrame:
    """factor times matrix, in Arrow batches.

    As expressions, l x l literals that differ each round would be compiled anew
    each round, which costs more than the product.
    """
    kind = factor.schema[key].dataType.simpleString()
    old, matrix = list(old), np.asarray(matrix, dtype=float)

    def times(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = _block(batch, old) @ matrix
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(out[:, j]) for j in range(out.shape[1]))], names=[key, *new])

    return factor.select(key, *old).mapInArrow(times, f"`{key}` {kind}" + "".join(f", {c} double" for c in new))


def inner(factor: DataFrame, columns: Sequence[str]) -> np.ndarray:
    """The l x l matrix of products of columns: a partial matrix a partition, then sums by entry."""
    columns = list(columns)
    l = len(columns)

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g = np.zeros((l, l))
        for batch in batches:
            m = _block(batch, columns)
            g += m.T @ m
        at = np.indices((l, l)).reshape(2, -1)
        yield pa.RecordBatch.from_arrays([pa.array(at[0], pa.int32()), pa.array(at[1], pa.int32()), pa.array(g.ravel())], names=["i", "j", "s"])

    out = np.zeros((l, l))
    for r in factor.select(*columns).mapInArrow(partial, "i int, j int, s double").groupBy("i", "j").agg(F.sum("s").alias("s")).collect():
        out[r["i"], r["j"]] = r["s"]
    return (out + out.T) / 2


def orthonormal(factor: DataFrame, key: str, columns: Sequence[str]) -> DataFrame:
    """An orthonormal basis of the columns' span; directions below rounding go."""
    g = inner(factor, columns)
    values, vectors = np.linalg.eigh(g)
    live = values > max(values.max(), 0) * 1e-13
    w = (vectors[:, live] / np.sqrt(values[live]))[:, ::-1]
    return rotate(factor, key, columns, w, names(w.shape[1], "q"))


def multiply(a: DataFrame, factor: DataFrame, join_on: str, group_by: str, columns: Sequence[str], stem: str) -> DataFrame:
    """A V (join on col_id, group by row_id) or A'U: one join, one aggregate."""
    sums = [F.sum(F.col("value") * F.col(c)).alias(n) for c, n in zip(columns, names(len(columns), stem), strict=True)]
    return a.join(factor, join_on).groupBy(group_by).agg(*sums)


def _signed(ids: list, v: np.ndarray) -> np.ndarray:
    """The entry of largest magnitude of each vector is positive."""
    top = np.abs(v).argmax(0)
    return v * np.where(v[top, np.arange(v.shape[1])] < 0, -1.0, 1.0)


def topk(a: DataFrame, k: int, method: str = "auto", oversample: int = 8, power: int = 4, seed: int = 0, known: tuple[list, np.ndarray] | None = None) -> Svd:
    """Top right singular vectors and values; min(k, rank) of them.

    gram: eigenvectors of A'A, for few columns. subspace: block iteration by
    joins over wide factor frames, for any number; a round is two shuffles each
    way, and only l x l matrices come to the driver. known: a Gram matrix that
    has been formed before.
    """
    require(a, COO)
    spark = a.sparkSession
    if known is not None:
        method = "gram"
    total = squared_norm(a) if known is None else float(np.trace(known[1]))
    if method == "auto":
        few = a.select("col_id").distinct().limit(GRAM_COLUMNS + 1).count()
        method = "gram" if few <= GRAM_COLUMNS else "subspace"
    if method == "gram":
        ids, g = known or gram(a)
        values, vectors = np.linalg.eigh(g) if ids else (np.zeros(0), np.zeros((0, 0)))
        order = np.argsort(-values)[:k]
        order = [i for i in order if values[i] > max(values.max(), 0) * 1e-12]
        v = _signed(ids, vectors[:, order]) if len(order) else np.zeros((len(ids), 0))
        kind = a.schema["col_id"].dataType.simpleString()
        rows = [(c, *map(float, v[i])) for i, c in enumerate(ids)]
        frame = spark.createDataFrame(rows, f"col_id {kind}" + "".join(f", {c} double" for c in names(len(order))))
        return Svd(frame, np.sqrt(values[order]), total, (ids, g))
    start = start_block(a, k + oversample, seed).cache()
    try:
        n = start.count()
        if n <= HELD_ENTRIES and n * (k + oversample) <= DRIVER_ENTRIES:
            return _held_topk(a, start, k, power, total)
    finally:
        start.unpersist()
    # Every round reads the matrix twice: derive it (tokens, joins) only once.
    a = cut_lineage(a.select("row_id", "col_id", "value"))
    q = start_block(a, k + oversample, seed)
    for _ in range(power):
        cols = [c for c in q.columns if c != "col_id"]
        u = orthonormal(cut_lineage(multiply(a, q, "col_id", "row_id", cols, "y")), "row_id", names(len(cols), "y"))
        cols = [c for c in u.columns if c != "row_id"]
        z = cut_lineage(multiply(a, u, "row_id", "col_id", cols, "z"))
        q = orthonormal(z, "col_id", names(len(cols), "z"))
    cols = [c for c in q.columns if c != "col_id"]
    values, vectors = np.linalg.eigh(inner(multiply(a, q, "col_id", "row_id", cols, "y"), names(len(cols), "y")))
    order = [i for i in np.argsort(-values)[:k] if values[i] > values.max() * 1e-12]
    v = rotate(q, "col_id", cols, vectors[:, order], names(len(order)))
    tops = v.agg(*[F.max_by(c, F.struct(F.abs(c), "col_id")).alias(c) for c in names(len(order))]).first()
    flip = np.diag([-1.0 if tops[c] < 0 else 1.0 for c in names(len(order))])
    return Svd(cut_lineage(rotate(v, "col_id", names(len(order)), flip, names(len(order)))), np.sqrt(values[order]), total)


def _held_topk(a: DataFrame, start: DataFrame, k: int, power: int, total: float) -> Svd:
    """Block iteration with the factor of the columns held in every task.

    A round is one pass over whole rows, A'(A q), and one sum by column; the rows
    are brought together once. Only the factor comes to the driver. Vectors of a
    factor don't meet in the product, so one that is too large for a task at once
    goes a few vectors a pass.
    """
    spark, table = a.sparkSession, start.orderBy("col_id").toArrow()
    ids, l = table.column("col_id"), table.num_columns - 1
    q = np.stack([table.column(i + 1).to_numpy() for i in range(l)], 1) if table.num_rows else np.zeros((0, l))
    at = spark.createDataFrame(pa.table({"col_id": ids, "at_": pa.array(np.arange(len(q)), pa.int32())}), schema=f"col_id {a.schema['col_id'].dataType.simpleString()}, at_ int")
    rows = a.join(F.broadcast(at), "col_id").select(F.xxhash64("row_id").alias("row_"), "at_", F.col("value").cast("double").alias("value"))
    # Cached columns are compressed; a checkpoint would not be.
    # Every task gives out a factor of its own, so there are no more of them than cores.
    rows = rows.repartition(spark.sparkContext.defaultParallelism, "row_").sortWithinPartitions("row_").cache()

    def times(q: np.ndarray) -> np.ndarray:
        """A'(A q)."""
        wide = max(1, HELD_ENTRIES // max(1, len(q)))
        return np.concatenate([some(q[:, i : i + wide]) for i in range(0, q.shape[1], wide)], 1)

    def some(q: np.ndarray) -> np.ndarray:
        """times() of vectors that every task holds."""
        held, n, l = ship(spark, q), len(q), q.shape[1]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            q, z, rest, met = held(), np.zeros((l, n)), None, np.zeros(n, bool)

            def add(row: np.ndarray, col: np.ndarray, value: np.ndarray) -> None:
                starts = np.flatnonzero(np.diff(row, prepend=row[0])) if len(row) else np.zeros(0, int)
                starts = np.concatenate([[0], starts])
                y = np.add.reduceat(q[col] * value[:, None], starts)
                y = np.repeat(y, np.diff(np.append(starts, len(row))), 0) * value[:, None]
                for i in range(l):
                    z[i] += np.bincount(col, y[:, i], n)
                met[col] = True

            for batch in batches:
                if not batch.num_rows:
                    continue
                now = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
                now = now if rest is None else [np.concatenate(x) for x in zip(rest, now, strict=True)]
                # The last row may go on in the next batch; short pieces wait for more.
                done = int(np.searchsorted(now[0], now[0][-1])) if len(now[0]) >= 200_000 else 0
                if done:
                    add(*(x[:done] for x in now))
                rest = [x[done:] for x in now]
            if rest is not None:
                add(*rest)
            found = np.flatnonzero(met)
            yield pa.RecordBatch.from_arrays([pa.array(found, pa.int64()), *(pa.array(z[i][found]) for i in range(l))], names=["at_", *names(l, "z")])

        moved = rows.mapInArrow(run, "at_ long" + "".join(f", {c} double" for c in names(l, "z")))
        sums = moved.groupBy("at_").agg(*[F.sum(c).alias(c) for c in names(l, "z")]).toArrow()
        out = np.zeros((n, l))
        out[sums.column("at_").to_numpy()] = np.stack([sums.column(c).to_numpy() for c in names(l, "z")], 1)
        del moved
        release(spark)
        return out

    def basis_of(z: np.ndarray) -> np.ndarray:
        u, sizes, _ = np.linalg.svd(z, full_matrices=False)
        return u[:, sizes > max(sizes.max(initial=0.0), 0) * 1e-13]

    try:
        q = basis_of(q) if power == 0 else q
        for _ in range(power):
            q = basis_of(times(q)) if q.shape[1] else q
        values, vectors = np.linalg.eigh(q.T @ times(q)) if q.shape[1] else (np.zeros(0), np.zeros((0, 0)))
    finally:
        rows.unpersist()
    order = [i for i in np.argsort(-values)[:k] if values[i] > values.max() * 1e-12]
    v = q @ vectors[:, order]
    v = _signed(ids, v) if v.size else v
    kind = a.schema["col_id"].dataType.simpleString()
    frame = pa.table({"col_id": ids, **{c: pa.array(v[:, i]) for i, c in enumerate(names(len(order)))}})
    return Svd(spark.createDataFrame(frame, schema=f"col_id {kind}" + "".join(f", {c} double" for c in names(len(order)))), np.sqrt(values[order]), total)


def start_block(a: DataFrame, width: int, seed: int) -> DataFrame:
    """Uniform entries that column id and seed fix."""
    return a.select("col_id").distinct().select("col_id", *[(u01("col_id", seed * 1000 + i) - 0.5).alias(c) for i, c in enumerate(names(width, "q"))])


def basis(a: DataFrame, k: int, seed: int = 0, power: int = 2) -> DataFrame:
    """Any orthonormal basis of about the top-k right subspace: k columns, no values."""
    q = start_block(a, k, seed)
    for _ in range(power):
        cols = [c for c in q.columns if c != "col_id"]
        y = multiply(a, q, "col_id", "row_id", cols, "y")
        z = cut_lineage(multiply(a, y, "row_id", "col_id", names(len(cols), "y"), "z"))
        q = orthonormal(z, "col_id", names(len(cols), "z"))
    return q.select("col_id", *[F.col(c).alias(n) for c, n in zip(q.columns[1:], names(k), strict=False)])


def left(a: DataFrame, found: Svd) -> DataFrame:
    """row_id, u0..: left vectors A v / sigma."""
    u = multiply(a, found.v, "col_id", "row_id", names(found.k), "u")
    return u.select("row_id", *[(F.col(f"u{i}") / float(s)).alias(f"u{i}") for i, s in enumerate(found.sigma)])


def pca(a: DataFrame, k: int) -> tuple[DataFrame, np.ndarray]:
    """Components and variances: the Gram matrix less the rank-one part of the means."""
    ids, g = gram(a)
    m = a.select("row_id").distinct().count()
    sums = {r["col_id"]: r["s"] for r in a.groupBy("col_id").agg(F.sum("value").alias("s")).collect()}
    s = np.array([sums[c] for c in ids])
    values, vectors = np.linalg.eigh((g - np.outer(s, s) / m) / (m - 1))
    order = np.argsort(-values)[:k]
    v = _signed(ids, vectors[:, order])
    kind = a.schema["col_id"].dataType.simpleString()
    rows = [(c, *map(float, v[i])) for i, c in enumerate(ids)]
    return a.sparkSession.createDataFrame(rows, f"col_id {kind}" + "".join(f", {c} double" for c in names(len(order)))), values[order]


def weigh(tf: DataFrame, weighting: str) -> DataFrame:
    """Raw counts, presence, or counts times log inverse document frequency."""
    if weighting == "raw":
        return tf
    if weighting == "binary":
        return tf.withColumn("value", F.lit(1.0))
    if weighting != "tfidf":
        raise ValueError(weighting)
    n = tf.select("row_id").distinct().count()
    idf = tf.groupBy("col_id").agg(F.log(F.lit(float(n)) / F.count("*")).alias("idf"))
    return tf.join(idf, "col_id").select("row_id", "col_id", (F.col("value") * F.col("idf")).alias("value"))


def lsa(tf: DataFrame, k: int, weighting: str = "raw") -> DataFrame:
    """row_id and k coordinates of each document."""
    a = weigh(tf, weighting)
    found = topk(a, k)
    return multiply(a, found.v, "col_id", "row_id", names(found.k), "d")


def normalize(a: DataFrame, how: str) -> DataFrame:
    """unit: columns of norm one; center: less the column mean over all rows; sign: -1, 0, 1; binary.

    Centering moves absent entries too, so its result has every cell and columns
    must be few; for many columns take pca(), which never forms it.
    """
    if how == "binary":
        return a.withColumn("value", F.lit(1.0))
    if how == "sign":
        return a.withColumn("value", F.signum("value"))
    if how == "unit":
        s = a.groupBy("col_id").agg(F.sqrt(F.sum(F.col("value") * F.col("value"))).alias("s")).filter("s > 0")
        return a.join(s, "col_id").select("row_id", "col_id", (F.col("value") / F.col("s")).alias("value"))
    if how == "center":
        rows = a.select("row_id").distinct()
        m = rows.count()
        sums = bounded(a.groupBy("col_id").agg(F.sum("value").alias("s")), GRAM_COLUMNS)
        if not sums:
            return a
        means = F.array(*[F.struct(F.lit(r["col_id"]).alias("col_id"), F.lit(r["s"] / m).alias("mean")) for r in sums])
        cells = rows.withColumn("c_", F.explode(means)).select("row_id", "c_.col_id", "c_.mean")
        return cells.join(a, ["row_id", "col_id"], "left").select("row_id", "col_id", (F.coalesce("value", F.lit(0.0)) - F.col("mean")).alias("value"))
    raise ValueError(how)
