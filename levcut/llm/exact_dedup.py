"""Exact deduplication by a cuckoo-filter index of live digests.

Texts are equal when they agree after all of ``[\\x20\\x09-\\x0D]`` is deleted.
Every map task folds its rows into an index of bounded size: a digest that the
index holds only updates its record, and a full index emits its oldest half as
partial groups and deletes those digests. So a text that a third of all rows
share leaves each task a few rows, and the shuffle carries partial groups, not
documents. The same index then merges the partial groups of each digest range.

Nulls: a null text counts as empty; a null doc_id loses every tie, and is the
keep_id only of a group without any other id. Repeated rows are members of
their group like others; kept marks every row that carries the keep_id (rows
with equal ids and texts can't be told apart), or, where ids are null, none
but those. Empty tables give empty results; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levcut.llm.common import text_column
from levcut.llm.cuckoo import CuckooIndex

#: Live digests of a task's index before it emits some: about 100 MB.
LIVE = 200_000

PARTIAL = "digest binary, best_chars long, best_id long, members long"


def digests(docs: DataFrame) -> DataFrame:
    """doc_id, digest of the normalised text, code points of the original."""
    text = text_column()
    normal = F.translate(text, " \t\n\x0b\x0c\r", "")
    return docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.unhex(F.sha2(normal.cast("binary"), 256)).alias("digest"),
        F.length(text).cast("long").alias("chars"),
    )


def _better(a: tuple, b: tuple) -> tuple:
    """Of two (chars, id): more code points, then the smaller id, null last."""
    if a[0] != b[0]:
        return a if a[0] > b[0] else b
    if a[1] is None or b[1] is None:
        return b if a[1] is None else a
    return a if a[1] <= b[1] else b


def fold(live: int):
    """Folds rows (digest, chars, id, members) into one row a digest, as far as the index reaches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = CuckooIndex(4096)

        def rows(taken: list) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays(
                [
                    pa.array([k for k, _ in taken], pa.binary()),
                    *(pa.array([v[i] for _, v in taken], pa.int64()) for i in range(3)),
                ],
                names=["digest", "best_chars", "best_id", "members"],
            )

        for batch in batches:
            for digest, chars, doc, members in zip(*(column.to_pylist() for column in batch.columns), strict=True):
                held = index.get(digest)
                if held is None:
                    index.insert(digest, (chars, doc, members))
                else:
                    index.insert(digest, (*_better(held[:2], (chars, doc)), held[2] + members))
            if live and len(index) > live:
                out = []
                for i, record in enumerate(index.items()):
                    if i >= live // 2:
                        break
                    out.append(record)
                for digest, _ in out:
                    index.delete(digest)
                yield rows(out)
        out = []
        for record in index.items():
            out.append(record)
            if len(out) == 10_000:
                yield rows(out)
                out = []
        if out:
            yield rows(out)

    return run


def groups(rows: DataFrame, live: int = LIVE) -> DataFrame:
    """One row a digest: digest, best_chars, best_id, members.

    The second fold keeps all digests of its partition; the partition, like
    that of any hash aggregate, is sized by the session's shuffle partitions.
    """
    partial = rows.select("digest", "chars", "doc_id", F.lit(1).cast("long").alias("members")).mapInArrow(fold(live), PARTIAL)
    return partial.repartition("digest").mapInArrow(fold(0), PARTIAL)


def dedup(docs: DataFrame) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256: one row a document."""
    rows = digests(docs)
    shared = groups(rows).filter("members > 1").select("digest", "best_id", "members")
    # Only texts with copies meet the join, and its left side may be split where skewed.
    joined = rows.join(shared, "digest", "left")
    keep = F.when(F.col("members").isNull(), F.col("doc_id")).otherwise(F.col("best_id"))
    return joined.select(
        "doc_id",
        keep.alias("keep_id"),
        F.coalesce("members", F.lit(1)).cast("long").alias("group_size"),
        (F.col("members").isNull() | F.col("doc_id").eqNullSafe(F.col("best_id"))).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )
