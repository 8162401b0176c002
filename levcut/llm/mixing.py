"""Mixing sources to target weights by repetition rates.

Token counts are summed per source, targets are filled like water under a cap
of three times the source, and each document is emitted floor(rate) times plus
once more with the fraction as probability, drawn from a hash of its id.

Nulls: a null text has size 0; a null source is a source of its own, the last;
a null doc_id draws as the empty string. Rows with equal ids draw alike.
A source with no words has target 0 and emits its documents once, since they
take nothing. Empty tables give empty results; other columns pass through.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from levcut.llm.common import cut_lineage, text_column

#: Words are what lies between these.
BLANKS = " \t\n\x0b\x0c\r"
#: Up to so many sources their targets are broadcast; more are joined by shuffle.
BROADCAST_SOURCES = 10_000


def word_count(name: str = "text") -> Column:
    """Number of ``[^\\x20\\x09-\\x0D]+`` in the text, 0 for null."""
    pieces = F.split(F.translate(text_column(name), BLANKS, " " * len(BLANKS)), " ")
    return F.size(F.array_remove(pieces, "")).cast("long")


def uniform(column: Column, seed: int) -> Column:
    """A number in [0, 1) that seed and value fix, in any engine with md5."""
    digest = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(column.cast("string"), F.lit(""))))
    return F.conv(F.substring(digest, 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def targets(totals: DataFrame, weights: Sequence[float], cap: float) -> DataFrame:
    """source, source_size and target of each row of (source, source_size).

    The fill level is found by sorting the sources by cap over weight: the
    sources below the level stand at their caps, the others share the rest.
    This is one row a source, the size of the aggregate before it.
    """
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    turn = F.pmod(F.row_number().over(by_name) - 1, F.lit(len(weights)))
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (turn + 1).cast("int"))
    with_weight = totals.withColumn("weight", weight).withColumn("most", F.col("source_size") * F.lit(float(cap)))
    order = Window.orderBy(F.col("most") / F.col("weight"), F.col("source").asc_nulls_last())
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy()
    levels = with_weight.withColumn(
        "level",
        (F.sum("source_size").over(everything) - F.coalesce(F.sum("most").over(before), F.lit(0.0)))
        / (F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))),
    ).withColumn("under", F.col("weight") * F.col("level") <= F.col("most"))
    # The first source under its cap fixes the level; those before it are full.
    level = F.min(F.when(F.col("under"), F.struct(F.col("most") / F.col("weight"), F.col("level")))).over(everything)
    return levels.withColumn("fixed", level["level"]).select(
        "source",
        "source_size",
        F.round(F.least(F.col("most"), F.col("weight") * F.coalesce("fixed", F.lit(float("inf")))), 6).alias("target"),
    )


def plan(docs: DataFrame, weights: Sequence[float] = (5, 2, 1), cap: float = 3.0, seed: int = 11) -> DataFrame:
    """The rows of docs with size, source_size, target, rate and copies added.

    Names that clash with columns of docs are replaced.
    """
    added = ("size", "source_size", "target", "rate", "copies")
    docs = docs.drop(*added)
    sized = docs.withColumn("size", word_count())
    totals = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    goal = targets(totals, weights, cap).select(
        F.struct("source", "source_size", "target").alias("goal_"), F.col("source").alias("goal_source_")
    )
    goal = cut_lineage(goal)
    if goal.count() <= BROADCAST_SOURCES:
        goal = F.broadcast(goal)
    rate = F.when(F.col("source_size") > 0, F.least(F.lit(float(cap)), F.col("target") / F.col("source_size"))).otherwise(F.lit(1.0))
    whole = F.floor("rate")
    extra = (uniform(F.col("doc_id"), seed) < F.col("rate") - whole).cast("long")
    return (
        sized.join(goal, F.col("source").eqNullSafe(F.col("goal_source_")), "left")
        .withColumns({"source_size": F.col("goal_.source_size"), "target": F.col("goal_.target")})
        .drop("goal_", "goal_source_")
        .withColumn("rate", rate)
        .withColumn("copies", (whole + extra).cast("long"))
    )


def emit(planned: DataFrame, columns: Sequence[str]) -> DataFrame:
    """Each document as often as the plan says."""
    again = F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))
    return planned.filter("copies > 0").select(*columns, again.alias("copy_no_")).drop("copy_no_")


def mixed(docs: DataFrame) -> DataFrame:
    return plan(docs.select("doc_id", "text", "source")).select(
        "doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken")
    )
