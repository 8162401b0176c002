"""Benchmark decontamination by Wu-Manber multi-pattern search over words.

The patterns are the windows of consecutive benchmark words. A table over pairs
of words says how far the search may jump: a pair in no pattern lets it skip a
whole window less one. Where the jump is zero, the bucket of the pair lists the
patterns that end in it, and whole windows are compared. Patterns of one length
share a searcher; items shorter than a window have searchers of their own.

The benchmark's words are sent to the executors in blocks of bounded size (in all
the size of its texts). A task holds one block's tables at a time: with one block
they stay, with more a task gathers documents up to HELD bytes and passes them
through block after block. So memory is bounded for any benchmark, texts cross to
Python once, and there is no shuffle at all.

Nulls: a null text has no words and hits nothing; an item without words gives
no window; a null item_id counts as an item but not in the list of ids.
Repeated items count once. Very long texts are searched whole. Empty tables give
empty results or no hits; columns of other names pass through flag(), result
columns of the same name are replaced; clean() keeps every column as it is.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from levcut.llm.common import WORD_BYTES, map_arrow, ship, text_column

WINDOW = 10
#: Windows of a pattern block: about 200 MB in a Python worker.
BLOCK_WINDOWS = 200_000
#: Bytes of documents that a task passes through the blocks at once.
HELD = 32 << 20


def words(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "replace").translate(WORD_BYTES).split() if text else []


class Searcher:
    """Wu-Manber over words for patterns of one length."""

    def __init__(self, patterns: Iterable[tuple[bytes, ...]]):
        self.patterns = list(dict.fromkeys(patterns))
        self.length = len(self.patterns[0])
        self.block = min(2, self.length)
        self.default = self.length - self.block + 1
        self.shift: dict = {}
        self.bucket: dict = {}
        for i, pattern in enumerate(self.patterns):
            for end in range(self.block, self.length + 1):
                key = self._key(pattern, end)
                self.shift[key] = min(self.shift.get(key, self.default), self.length - end)
            self.bucket.setdefault(self._key(pattern, self.length), {}).setdefault(pattern, i)

    def _key(self, sequence, end: int):
        return (sequence[end - 2], sequence[end - 1]) if self.block == 2 else sequence[end - 1]

    def find(self, text: list[bytes]) -> Iterator[tuple[int, int]]:
        """(start, index of the pattern) of every occurrence."""
        end, length, default, shift = self.length, self.length, self.default, self.shift.get
        n, pair = len(text), self.block == 2
        while end <= n:
            key = (text[end - 2], text[end - 1]) if pair else text[end - 1]
            jump = shift(key, default)
            if jump:
                end += jump
                continue
            # The bucket holds the patterns that end in this block, by their words.
            at = self.bucket[key].get(tuple(text[end - length : end]))
            if at is not None:
                yield end - length, at
            end += 1


class Patterns:
    """Windows of benchmark items, with the items that own each window."""

    def __init__(self, items: Iterable[tuple[object, list[bytes]]], window: int = WINDOW):
        self.owners: dict[tuple[bytes, ...], set] = {}
        for item, text in items:
            size = min(window, len(text))
            for start in range(len(text) - size + 1 if size else 0):
                self.owners.setdefault(tuple(text[start : start + size]), set()).add(item)
        by_length: dict[int, list] = {}
        for pattern in self.owners:
            by_length.setdefault(len(pattern), []).append(pattern)
        self.searchers = [Searcher(patterns) for _, patterns in sorted(by_length.items())]

    def search(self, text: list[bytes]) -> tuple[list[tuple[int, int]], set]:
        """Spans of hit words and the items found."""
        spans, found = [], set()
        for searcher in self.searchers:
            for start, at in searcher.find(text):
                spans.append((start, start + searcher.length))
                found |= self.owners[searcher.patterns[at]]
        return spans, found


def merge(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for start, end in sorted(spans):
        if out and start <= out[-1][1]:
            out[-1][1] = max(out[-1][1], end)
        else:
            out.append([start, end])
    return [(a, b) for a, b in out]


def blocks(benchmark: DataFrame, window: int, limit: int) -> Iterator[list[tuple[str | None, bytes]]]:
    """(item, words) of the benchmark in blocks of at most about ``limit`` windows."""
    taken: list[tuple[str | None, bytes]] = []
    size = 0
    for row in benchmark.select("item_id", "text").toLocalIterator():
        text = words(row["text"])
        taken.append((None if row["item_id"] is None else str(row["item_id"]), b" ".join(text)))
        size += max(1, len(text) - window + 1)
        if size >= limit:
            yield taken
            taken, size = [], 0
    yield taken


ADDED = "n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, hit_spans array<array<int>>"


def search(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, limit: int = BLOCK_WINDOWS, held_bytes: int = HELD) -> DataFrame:
    """The rows of docs in a struct ``kept``, and n_words ... hit_spans beside it.

    hit_spans holds the merged [start, end) word positions inside occurrences.
    """
    spark = docs.sparkSession
    names = [x.split()[0] for x in ADDED.split(", ")]
    taken = list(blocks(benchmark, window, limit))
    single = len(taken) == 1
    shared = [ship(spark, block, keep=single) for block in taken]
    del taken

    def found_in(texts: list[list[bytes]], patterns: Callable[[int], Patterns]) -> tuple[list, list]:
        spans: list[list[tuple[int, int]]] = [[] for _ in texts]
        items: list[set] = [set() for _ in texts]
        for k in range(len(shared)):
            block = patterns(k)
            for i, one in enumerate(texts):
                more, found = block.search(one)
                if more:
                    spans[i] = merge([*spans[i], *more])
                    items[i] |= found
        return spans, items

    def result(batch: pa.RecordBatch, texts: list[list[bytes]], spans: list, items: list) -> pa.RecordBatch:
        listed = [",".join(sorted(y for y in x if y is not None)) for x in items]
        hit = [sum(b - a for a, b in x) for x in spans]
        added = [
            pa.array([len(x) for x in texts], pa.int64()),
            pa.array(hit, pa.int64()),
            pa.array([len(x) for x in items], pa.int64()),
            pa.array([hashlib.sha256(x.encode()).hexdigest() for x in listed], pa.string()),
            pa.array([x > 0 for x in hit], pa.bool_()),
            pa.array([[list(x) for x in y] for y in spans], pa.list_(pa.list_(pa.int32()))),
        ]
        return pa.RecordBatch.from_arrays([batch.column(0), *added], names=["kept", *names])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[int, Patterns] = {}

        def patterns(k: int) -> Patterns:
            built = known.get(k) or Patterns(((item, text.split()) for item, text in shared[k]()), window)
            if single:
                known[k] = built
            return built

        def flush(waiting: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            texts = [[words(x) for x in batch.column(1).to_pylist()] for batch in waiting]
            spans, items = found_in([x for one in texts for x in one], patterns)
            at = 0
            for batch, one in zip(waiting, texts, strict=True):
                yield result(batch, one, spans[at : at + len(one)], items[at : at + len(one)])
                at += len(one)

        waiting: list[pa.RecordBatch] = []
        size = 0
        for batch in batches:
            waiting.append(batch)
            size += batch.nbytes
            if single or size >= held_bytes:
                yield from flush(waiting)
                waiting, size = [], 0
        if waiting:
            yield from flush(waiting)

    chosen = docs.select(F.struct("*").alias("kept"), text_column().alias("text"))
    return map_arrow(chosen, run, StructType([chosen.schema["kept"], *StructType.fromDDL(ADDED).fields]))


def flag(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, limit: int = BLOCK_WINDOWS, held_bytes: int = HELD) -> DataFrame:
    """docs with n_words, n_hit, n_items, items_sha256, contaminated, hit_spans."""
    names = [x.split()[0] for x in ADDED.split(", ")]
    return search(docs, benchmark, window, limit, held_bytes).select(*(F.col("kept")[c].alias(c) for c in docs.columns if c not in names), *names)


def clean(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The documents without any occurrence, with their columns."""
    return search(docs, benchmark).filter("not contaminated").select("kept.*")
