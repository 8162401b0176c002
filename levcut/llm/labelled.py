"""Bounded samples of labelled documents, to fit classifiers on the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levcut.llm.common import text_column

#: Labelled rows of each class that a fit may use at most; their texts are whole.
ROWS_PER_CLASS = 1200


def held_out(modulus: int, rest: int):
    """Rows whose crc32(doc_id as text) leaves this remainder take no part in a fit."""
    return F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(modulus)) == rest, F.lit(False))


def choose(docs: DataFrame, labels: DataFrame, label: str, modulus: int, rest: int, rows: int = ROWS_PER_CLASS) -> tuple[DataFrame | None, dict[int, int], float]:
    """(doc_id, text) of the chosen documents, their labels, and the share of label 1
    among all rows that may be learnt from.

    Labels that are null or not 0 or 1 are left out; a document with both labels
    counts as 1. The choice within a class is by a hash of doc_id.
    """
    usable = (
        labels.filter(F.col("doc_id").isNotNull() & F.col(label).isin(0, 1) & ~held_out(modulus, rest))
        .groupBy("doc_id")
        .agg(F.max(label).cast("int").alias("label"))
    )
    counts = {r["label"]: r["count"] for r in usable.groupBy("label").count().collect()}
    chosen: dict[int, int] = {}
    for one in counts:
        taken = usable.filter(F.col("label") == one).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
        chosen |= {r["doc_id"]: r["label"] for r in taken.collect()}
    if not chosen:
        return None, {}, 0.5
    ids = docs.sparkSession.createDataFrame([(k,) for k in chosen], "doc_id long")
    found = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_column().alias("text")).join(F.broadcast(ids), "doc_id", "left_semi")
    return found, chosen, counts.get(1, 0) / sum(counts.values())


def sample(docs: DataFrame, labels: DataFrame, label: str, modulus: int, rest: int, rows: int = ROWS_PER_CLASS) -> tuple[list[tuple[int, str, int]], float]:
    """(doc_id, text, label) of the chosen documents in order of doc_id, and the share of label 1.

    Of several texts of one doc_id the first in order is taken.
    """
    found, chosen, share = choose(docs, labels, label, modulus, rest, rows)
    texts: dict[int, str] = {}
    for r in found.collect() if found is not None else []:
        texts[r["doc_id"]] = min(r["text"], texts.get(r["doc_id"], r["text"]))
    return sorted((k, t, chosen[k]) for k, t in texts.items()), share
