"""Declared schemas, checked on entry."""

from __future__ import annotations

from pyspark.sql import DataFrame

COO = {"row_id", "col_id", "value"}
EDGES = {"src", "dst", "w"}
SETS = {"set_id", "node"}


def require(df: DataFrame, columns: set[str]) -> DataFrame:
    missing = columns - set(df.columns)
    if missing:
        raise ValueError(f"columns missing: {sorted(missing)}")
    return df
