"""Chat formatting by rotating the perspective over all participants.

For every participant of a conversation the dialogue is rendered once more with
that participant as the assistant and the others as named users; only what the
assistant says is to be trained on. The result has a row for each perspective
and message, in order, with the rendered segment, its character offsets in the
whole rendering and the part of it that the mask covers. A long conversation is
never gathered into one value: offsets are sums over blocks of turns, then
within a block. ``assemble`` joins the segments where a caller knows that
conversations are short.

Rendering: ``<|assistant|>\\n`` or ``<|user name=NAME|>\\n``, the text, ``<|end|>\\n``;
the mask covers text and end mark of the assistant's messages. In names and texts
``<|`` becomes ``< |``, so no text can open a mark of its own.

Nulls: a null role takes part under the name ``unknown``; a null text is empty;
a null turn comes first; rows with null conv_id form one conversation. Ties of a
turn are ordered by role and text; repeated rows are messages of their own.
Empty tables give empty results; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from levcut.llm.common import text_column

#: Turns of a block, within which one task sums offsets.
BLOCK_TURNS = 1024
ASSISTANT, END = "<|assistant|>\n", "<|end|>\n"


def _plain(column: Column) -> Column:
    return F.replace(column, F.lit("<|"), F.lit("< |"))


def rotate(turns: DataFrame) -> DataFrame:
    """conv_id, perspective, turn, speaker, segment, start_char, end_char, mask_start, mask_end, trained."""
    speaker = _plain(F.coalesce(F.col("role").cast("string"), F.lit("unknown")))
    user = lambda name: F.concat(F.lit("<|user name="), name, F.lit("|>\n"))
    rows = turns.select(
        "conv_id",
        F.coalesce(F.concat(F.lit("c"), F.col("conv_id").cast("string")), F.lit("")).alias("key"),
        F.col("turn").cast("long").alias("turn"),
        speaker.alias("speaker"),
        _plain(text_column()).alias("said"),
        F.floor(F.coalesce(F.col("turn").cast("long"), F.lit(0)) / BLOCK_TURNS).alias("block"),
    )
    # Offsets of blocks come from sums by speaker: as a user each turn has one
    # length, and its own speaker's perspective changes that by a constant.
    as_user = F.length(user(F.col("speaker"))) + F.length("said") + len(END)
    sums = rows.groupBy("key", "block", "speaker").agg(F.sum(as_user).alias("chars"), F.count("*").alias("n"))
    cast = sums.select("key", F.col("speaker").alias("perspective")).distinct()
    blocks = sums.groupBy("key", "block").agg(F.sum("chars").alias("chars"))
    own_turns = sums.select("key", "block", F.col("speaker").alias("perspective"), "n")
    grid = blocks.join(cast, "key").join(own_turns, ["key", "block", "perspective"], "left")
    total = F.col("chars") + F.coalesce("n", F.lit(0)) * (len(ASSISTANT) - F.length(user(F.col("perspective"))))
    before = Window.partitionBy("key", "perspective").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    offsets = grid.select("key", "block", "perspective", F.coalesce(F.sum(total).over(before), F.lit(0)).alias("offset"))
    # The turns themselves move once, by conversation and block, which also suits the window.
    own = F.col("speaker") == F.col("perspective")
    full = (
        rows.join(offsets, ["key", "block"])
        .withColumns({"own": own, "head": F.when(own, F.lit(ASSISTANT)).otherwise(user(F.col("speaker")))})
        .withColumn("segment", F.concat("head", "said", F.lit(END)))
        .withColumns({"chars": F.length("segment").cast("long"), "head": F.length("head").cast("long")})
    )
    inside = Window.partitionBy("key", "block", "perspective").orderBy(F.col("turn").asc_nulls_first(), "speaker", "said")
    start = F.col("offset") + F.coalesce(F.sum("chars").over(inside.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    placed = full.withColumn("start_char", start)
    return placed.select(
        "conv_id",
        "perspective",
        "turn",
        "speaker",
        "segment",
        F.col("start_char").cast("long").alias("start_char"),
        (F.col("start_char") + F.col("chars")).cast("long").alias("end_char"),
        F.when(F.col("own"), F.col("start_char") + F.col("head")).cast("long").alias("mask_start"),
        F.when(F.col("own"), F.col("start_char") + F.col("chars")).cast("long").alias("mask_end"),
        F.col("own").alias("trained"),
    )


def assemble(rotated: DataFrame) -> DataFrame:
    """conv_id, perspective, rendered text and mask spans; for short conversations."""
    piece = F.struct("start_char", "end_char", "segment", "mask_start", "mask_end")
    return (
        rotated.groupBy("conv_id", "perspective")
        .agg(F.array_sort(F.collect_list(piece)).alias("pieces"))
        .select(
            "conv_id",
            "perspective",
            F.concat_ws("", F.transform("pieces", lambda p: p["segment"])).alias("rendered"),
            F.transform(
                F.filter("pieces", lambda p: p["mask_start"].isNotNull()), lambda p: F.array(p["mask_start"], p["mask_end"])
            ).alias("mask"),
        )
    )
