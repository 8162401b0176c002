"""Minimax contiguous sharding over atomic groups of equal texts.

Groups are ordered by the hash of their text. The smallest capacity is searched
for which greedy filling needs no more shards than there are, and cuts are made
for it. The search never holds all groups: it starts from 65,536 ranges of the
hash and splits only ranges in which a cut can fall, 256 ways a level, until
what remains are single groups. So the driver sees a bounded number of rows at
any input size, and a document's shard is a comparison of its hash with cuts.

The law is ``bytes``: no partition has a smaller largest shard. Where capacity
leaves room (one group may outweigh a fair share), each cut moves as near to an
even split of the rest as the capacity allows.

Nulls: a null text has no bytes, its checksum is that of the empty text, and it
is grouped with empty texts. Texts whose 64-bit hashes collide stay together,
which only merges two groups. Repeated rows get slots of their own. Empty
tables give empty results; columns of other names are ignored.
"""

from __future__ import annotations

from bisect import bisect_right
from itertools import accumulate

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from levcut.llm.common import cut_lineage, text_column

FIRST_BITS, MORE_BITS = 16, 8
#: So many groups may be fetched at once instead of splitting further.
FETCH = 100_000
#: Rows of a cell, within which slots are numbered by one task.
CELL_ROWS = 20_000


def fills(prefix: list[int], shards: int, capacity: int) -> list[int] | None:
    """Ends of the greedily filled shards over item boundaries, or None."""
    ends, at = [], 0
    for _ in range(shards):
        at = bisect_right(prefix, prefix[at] + capacity) - 1
        ends.append(at)
    return ends if at == len(prefix) - 1 else None


def smallest_capacity(prefix: list[int], shards: int, low: int, high: int) -> int:
    while low < high:
        middle = (low + high) // 2
        if fills(prefix, shards, middle):
            high = middle
        else:
            low = middle + 1
    return low


def level_cuts(prefix: list[int], shards: int, capacity: int) -> list[int]:
    """Boundaries between shards, each near an even split of the rest.

    A cut lies between the last boundary that leaves too much for the shards
    after it and the first that overfills its own shard.
    """
    latest_start, at = [len(prefix) - 1] * (shards + 1), len(prefix) - 1
    for i in range(shards - 1, -1, -1):
        # The earliest boundary from which shards i.. still hold the rest.
        need = prefix[at] - capacity
        at = max(0, bisect_right(prefix, need - 1))
        latest_start[i] = at
    cuts, at = [], 0
    for i in range(shards - 1):
        most = bisect_right(prefix, prefix[at] + capacity) - 1
        least = max(at, latest_start[i + 1])
        goal = prefix[at] + (prefix[-1] - prefix[at]) / (shards - i)
        near = bisect_right(prefix, goal) - 1
        if near + 1 < len(prefix) and prefix[near + 1] - goal < goal - prefix[near]:
            near += 1
        at = min(max(near, least), most)
        cuts.append(at)
    return cuts


def _regions(items: list[tuple], shards: int, low: int, high: int) -> list[int]:
    """Indexes of the items in which a cut may fall for a capacity in low..high."""
    prefix = [0, *accumulate(x[2] for x in items)]
    found: set[int] = set()
    first, last = 0, 0
    for _ in range(shards):
        # Pessimistic: full at low and stopped before the item that overflows.
        first = bisect_right(prefix, prefix[first] + low) - 1
        last = min(len(items), bisect_right(prefix, prefix[last] + high))
        found.update(range(first, min(last + 1, len(items))))
    return sorted(found)


def _within(groups: DataFrame, ranges: list[int], bits: int) -> DataFrame:
    """The groups whose hash begins with one of these bits."""
    keys = groups.sparkSession.createDataFrame([(k,) for k in ranges], "key_ long")
    return groups.join(F.broadcast(keys), F.shiftright("hash", 64 - bits) == F.col("key_"), "left_semi")


def _split(groups: DataFrame, bits: int) -> list[tuple]:
    """(first hash, range, bytes, largest group, groups, bits) of each range."""
    rows = (
        groups.groupBy(F.shiftright("hash", 64 - bits).alias("part"))
        .agg(F.sum("bytes").alias("b"), F.max("bytes").alias("m"), F.count("*").alias("n"))
        .collect()
    )
    return [(r["part"] << (64 - bits), r["part"], r["b"], r["m"], r["n"], bits) for r in rows]


def cut_hashes(groups: DataFrame, shards: int, fetch: int = FETCH, first_bits: int = FIRST_BITS) -> list[int | None]:
    """The first hash of each shard but shard 0; None where no group is left.

    groups: hash, bytes; one row a group.
    """
    items = sorted(_split(groups, first_bits))
    if not items:
        return [None] * (shards - 1)
    total, largest = sum(x[2] for x in items), max(x[3] for x in items)
    low = max(largest, -(-total // shards))
    while True:
        prefix = [0, *accumulate(x[2] for x in items)]
        # Ranges as atoms can only need more capacity than the groups in them.
        high = smallest_capacity(prefix, shards, max(low, max(x[2] for x in items)), total)
        opened = [items[i] for i in _regions(items, shards, low, high) if items[i][4] > 1]
        if not opened:
            break
        finer: list[tuple] = []
        for bits in sorted({x[5] for x in opened}):
            level = [x for x in opened if x[5] == bits]
            inside = _within(groups, [x[1] for x in level], bits)
            if sum(x[4] for x in level) <= fetch or bits + MORE_BITS >= 64:
                finer += [(r["hash"], r["hash"], r["bytes"], r["bytes"], 1, 64) for r in inside.collect()]
            else:
                finer += _split(inside, bits + MORE_BITS)
        gone = {(x[1], x[5]) for x in opened}
        items = sorted([x for x in items if (x[1], x[5]) not in gone] + finer)
    capacity = smallest_capacity(prefix, shards, low, high)
    # Boundaries between items are boundaries between groups, so all cuts are exact.
    return [items[i][0] if i < len(items) else None for i in level_cuts(prefix, shards, capacity)]


def assign(docs: DataFrame, shards: int = 24) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard."""
    text = text_column()
    rows = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        (F.octet_length(text) + 8).cast("long").alias("size"),
        F.crc32(text.cast("binary")).cast("long").alias("text_crc32"),
        F.xxhash64(text).alias("hash"),
    )
    groups = cut_lineage(rows.groupBy("hash").agg(F.sum("size").alias("bytes"), F.count("*").alias("n")))
    count = groups.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).first()["n"]
    shard = F.lit(0)
    for cut in cut_hashes(groups.select("hash", "bytes"), shards):
        if cut is not None:
            shard = shard + (F.col("hash") >= F.lit(cut)).cast("int")
    # Slots are numbered inside salted cells; a cell's offset is the sum before it.
    cells = max(1, count // (shards * CELL_ROWS))
    placed = rows.withColumn("shard", shard).withColumn("cell", F.pmod(F.xxhash64("doc_id", "hash"), F.lit(cells)).cast("int"))
    before = Window.partitionBy("shard").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    offsets = (
        placed.groupBy("shard", "cell")
        .agg(F.count("*").alias("n"))
        .select("shard", "cell", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("offset"))
    )
    inside = Window.partitionBy("shard", "cell").orderBy(F.col("doc_id").asc_nulls_last(), "hash", "size")
    return (
        placed.withColumn("place", F.row_number().over(inside) - 1)
        .join(offsets, ["shard", "cell"])
        .select(
            "doc_id",
            "size",
            "text_crc32",
            F.lit("bytes").alias("law"),
            F.col("shard").cast("int").alias("shard"),
            (F.col("offset") + F.col("place")).cast("long").alias("slot"),
            F.lit(None).cast("int").alias("grown_shard"),
        )
    )
