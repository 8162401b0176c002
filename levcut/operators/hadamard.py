"""Randomized Hadamard preprocessing, random projections, and what they even out."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levcut.functions.portable import u01
from levcut.operators import lsq


def padded(m: int) -> int:
    return 1 << max(0, (m - 1).bit_length())


def sampled_rows(df: DataFrame, names: Sequence[str], index: str, rows: Sequence[int], size: int, seed: int) -> DataFrame:
    """The given rows of H D A: i and the transformed columns.

    index must count 0..m-1. Entries of H are signs of the parity of i & j; each
    task sums its rows for all i before one small shuffle.
    """
    chosen = F.explode(F.array(*[F.lit(int(i)).cast("long") for i in rows]))
    sign = F.when(u01(index, seed) < 0.5, -1.0).otherwise(1.0)
    flip = F.when(F.bit_count(F.col("to_").bitwiseAND(F.col("at_"))) % 2 == 1, -1.0).otherwise(1.0)
    spread = df.select(chosen.alias("to_"), F.col(index).alias("at_"), sign.alias("sign_"), *names)
    scale = 1.0 / np.sqrt(size)
    return spread.groupBy(F.col("to_").alias("i")).agg(*[F.sum(F.col(c) * F.col("sign_") * flip * F.lit(scale)).alias(c) for c in names])


def transform(df: DataFrame, names: Sequence[str], index: str, size: int, seed: int) -> DataFrame:
    """All rows of H D A by splitting H as a Kronecker product: two grouped passes.

    Rows whose index reaches size fall on their place modulo size, as the parity
    of i & index has it: H is then repeated side by side, and the signed rows of
    a place are added up first.
    """
    bits = size.bit_length() - 1
    low = 1 << (bits // 2)
    high = size // low
    sign = F.when(u01(index, seed) < 0.5, -1.0).otherwise(1.0)
    at = F.col(index).bitwiseAND(F.lit(size - 1).cast("long"))
    rows = df.groupBy(F.shiftright(at, low.bit_length() - 1).alias("a"), at.bitwiseAND(F.lit(low - 1).cast("long")).alias("b")).agg(*[F.sum(F.col(c) * sign).alias(c) for c in names])

    def half(key: str, other: str, width: int):
        def run(pdf):
            import pandas as pd

            block = np.zeros((width, len(names)))
            block[pdf[other].to_numpy()] = pdf[list(names)].to_numpy()
            h = 1
            while h < width:
                block = block.reshape(-1, 2, h, len(names))
                block = np.stack([block[:, 0] + block[:, 1], block[:, 0] - block[:, 1]], 1).reshape(width, len(names))
                h *= 2
            out = pd.DataFrame(block / np.sqrt(width), columns=list(names))
            out.insert(0, other, np.arange(width))
            out.insert(0, key, pdf[key].iloc[0])
            return out[["a", "b", *names]]

        return run

    schema = "a long, b long, " + ", ".join(f"`{c}` double" for c in names)
    once = rows.groupBy("a").applyInPandas(half("a", "b", low), schema)
    twice = once.groupBy("b").applyInPandas(half("b", "a", high), schema)
    return twice.select((F.col("a") * low + F.col("b")).alias(index), *names)


def fast(df: DataFrame, y: str, xs: Sequence[str], index: str, m: int, r: int, seed: int, after: str = "uniform", size: int | None = None) -> np.ndarray:
    """Least squares after uniformization: about r rows of H D [A b] by hash, or r random sums.

    The transform moves every row twice whatever r is; the rows it keeps are a filter.
    size, a power of two, replaces that of the m rows; more rows than it are folded.
    """
    size = size or padded(m)
    names = [*xs, y]
    if after == "uniform":
        rows = transform(df, names, index, size, seed).filter(u01(index, seed + 1) < r / size)
    else:
        rows = project(df, names, index, r, "gauss" if after == "gauss" else "sign", seed)
    return lsq.solve(rows, y, xs, "qr")


def project(df: DataFrame, names: Sequence[str], key: str, r: int, kind: str, seed: int) -> DataFrame:
    """r random combinations of all rows: signs, or sums of twelve uniforms as normals."""
    i = F.explode(F.sequence(F.lit(0), F.lit(r - 1)))
    mark = F.concat_ws("-", F.col("to_"), F.col("at_"))
    if kind == "sign":
        entry = F.when(u01(mark, seed) < 0.5, -1.0).otherwise(1.0)
    elif kind == "gauss":
        entry = F.lit(-6.0)
        for t in range(12):
            entry = entry + u01(mark, seed * 100 + t)
    else:
        raise ValueError(kind)
    spread = df.select(i.alias("to_"), F.col(key).alias("at_"), *names)
    return spread.groupBy(F.col("to_").alias("i")).agg(*[F.sum(F.col(c) * entry / F.lit(float(np.sqrt(r)))).alias(c) for c in names])


def uniformity(df: DataFrame, xs: Sequence[str]) -> float:
    """Largest leverage over the average."""
    scored = lsq.leverage(df, xs)
    row = scored.agg(F.max("h").alias("top"), F.avg("h").alias("mean")).first()
    return row["top"] / row["mean"]
