"""Operators around the methods: prefix sums, range, as-of and interval joins, salting."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from levcut.runtime import bounded, cut_lineage


def prefix_sum(df: DataFrame, order: Sequence[Column], value: str, name: str, place: str | None = None, part: str | None = None) -> DataFrame:
    """Running sum of value over all rows in order; place names a column for the row's number, part one for its range."""
    return prefix_sums(df, order, {name: value}, place, part)


def prefix_sums(df: DataFrame, order: Sequence[Column], sums: dict[str, str], place: str | None = None, part: str | None = None) -> DataFrame:
    """Running sums (name: column) over all rows in order, without one task for all.

    Rows are dealt by range; sums of the ranges, one row each, give the offsets.
    The dealt frame is checkpointed so that both uses see the same ranges.
    """
    ranged = cut_lineage(df.repartitionByRange(*order).withColumn("part_", F.spark_partition_id()))
    before = Window.orderBy("part_").rowsBetween(Window.unboundedPreceding, -1)
    inside = Window.partitionBy("part_").orderBy(*order)
    run = inside.rowsBetween(Window.unboundedPreceding, 0)
    held = [f"sum{i}_" for i in range(len(sums))]
    totals = ranged.groupBy("part_").agg(*[F.sum(v).alias(h) for h, v in zip(held, sums.values(), strict=True)], F.count("*").alias("n_"))
    offsets = totals.select("part_", *[F.coalesce(F.sum(h).over(before), F.lit(0.0)).alias(h) for h in held], F.coalesce(F.sum("n_").over(before), F.lit(0)).alias("n_"))
    out = ranged.join(F.broadcast(offsets), "part_").withColumns({name: F.col(h) + F.sum(v).over(run) for h, (name, v) in zip(held, sums.items(), strict=True)})
    if place:
        out = out.withColumn(place, F.col("n_") + F.row_number().over(inside))
    if part:
        out = out.withColumn(part, F.col("part_"))
    return out.drop("part_", *held, "n_")


def numbered(df: DataFrame, key: str) -> DataFrame:
    """id, key: the rows counted from 0 in the order of a unique key."""
    placed = prefix_sum(df.select(key, F.lit(1.0).alias("one_")), [F.col(key)], "one_", "sum_", "place_")
    return placed.select((F.col("place_") - 1).cast("long").alias("id"), key)


def ranks(df: DataFrame, value: str, name: str) -> DataFrame:
    """The rows with the rank of value among all (ties share the least), by running sums over its distinct values."""
    counts = df.groupBy(value).agg(F.count("*").cast("double").alias("ties_"))
    placed = prefix_sum(counts, [F.col(value)], "ties_", "upto_").select(F.col(value).alias("value_"), (F.col("upto_") - F.col("ties_") + 1).alias(name))
    return df.join(placed, F.col(value).eqNullSafe(F.col("value_"))).drop("value_")


def range_join(points: DataFrame, at: str, intervals: DataFrame, low: str, high: str, width: float) -> DataFrame:
    """Points within [low, high): an equi-join on cells of the width, then the exact test."""
    cells = F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width)))
    return (
        points.withColumn("cell_", F.floor(F.col(at) / width))
        .join(intervals.withColumn("cell_", cells), "cell_")
        .filter((F.col(at) >= F.col(low)) & (F.col(at) < F.col(high)))
        .drop("cell_")
    )


def as_of(left: DataFrame, right: DataFrame, key: str, ts: str, value: str, name: str) -> DataFrame:
    """Each left row with the latest right value at or before its time: one shuffle by key."""
    both = left.withColumn("side_", F.lit(1)).withColumn("value_", F.lit(None).cast(right.schema[value].dataType)).unionByName(
        right.select(key, ts, F.lit(0).alias("side_"), F.col(value).alias("value_")), allowMissingColumns=True
    )
    w = Window.partitionBy(key).orderBy(ts, "side_").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(name, F.last("value_", ignorenulls=True).over(w)).filter("side_ = 1").drop("side_", "value_")


def interval_join(left: DataFrame, right: DataFrame, key: str, left_ts: str, right_ts: str, seconds: int) -> DataFrame:
    """Pairs of a key with right_ts within the seconds after left_ts."""
    cell = lambda c: F.floor(F.unix_micros(F.col(c).cast("timestamp")) / F.lit(seconds * 1_000_000))
    near = right.withColumn("cell_", F.explode(F.array(cell(right_ts), cell(right_ts) - 1)))
    gap = (F.unix_micros(F.col(right_ts).cast("timestamp")) - F.unix_micros(F.col(left_ts).cast("timestamp"))) / 1e6
    return left.withColumn("cell_", cell(left_ts)).join(near, [key, "cell_"]).filter((gap >= 0) & (gap <= seconds)).drop("cell_")


def salted_join(left: DataFrame, right: DataFrame, key: str, salt_of: str, salts: int = 16, share: float = 0.001) -> DataFrame:
    """Equi-join with the left rows of frequent keys dealt over salts and the right rows of those keys repeated.

    A key is frequent with more than ``share`` of the left rows, so at most 1 / share
    keys are. Rows of all other keys keep salt 0. Neither side is broadcast: Spark
    takes the repeated one for small by its files.
    """
    counts = left.groupBy(key).agg(F.count("*").alias("n_"))
    total = left.count()
    heavy = [r[0] for r in bounded(counts.filter(F.col("n_") > share * total).select(key), int(1 / share) + 1)]
    often = F.coalesce(F.col(key).isin(heavy), F.lit(False)) if heavy else F.lit(False)
    salted = left.withColumn("salt_", F.when(often, F.pmod(F.xxhash64(salt_of), F.lit(salts))).otherwise(0).cast("int"))
    repeated = right.withColumn("salt_", F.explode(F.when(often, F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0)))))
    return salted.join(repeated.hint("merge"), [key, "salt_"]).drop("salt_")
