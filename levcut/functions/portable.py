"""Expressions with equal values in Spark and in DuckDB."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def u01(value: Column | str, seed: int) -> Column:
    """A number in [0, 1) from the first 32 bits of md5("seed:value")."""
    column = F.col(value) if isinstance(value, str) else value
    digest = F.md5(F.concat(F.lit(f"{seed}:"), column.cast("string")))
    return F.conv(F.substring(digest, 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def u01_sql(value: str, seed: int) -> str:
    return f"(('0x' || substr(md5('{seed}:' || ({value})::VARCHAR), 1, 8))::BIGINT / 4294967296.0)"


def key60(value: Column) -> Column:
    """A 60-bit id of a string."""
    return F.conv(F.substring(F.md5(value), 1, 15), 16, 10).cast("long")


def key60_sql(value: str) -> str:
    return f"('0x' || substr(md5({value}), 1, 15))::BIGINT"


def r6(value: Column, digits: int = 6) -> Column:
    """Rounded, with -0.0 made 0.0."""
    return F.round(value + F.lit(0.0), digits) + F.lit(0.0)


def entropy_term(count: Column, total: Column) -> Column:
    """-p log2 p with 0 at p = 0."""
    p = count / total
    return F.when(count > 0, -p * F.log2(p)).otherwise(0.0)
