"""Toxicity from the nearest labelled examples by exact TF-IDF cosine.

The space has every word of every labelled example of a bounded sample. A weight
is the count's logarithm times the inverse document frequency over all documents;
for words whose presence tells the classes apart (chi-square over SURE) it is
scaled by the root of that value, all others keep it as it is, so no word and no
example leaves the space. ``scaled=False`` is the plain TF-IDF cosine.

Examples stand in an inverted index whose posting lists are cut into blocks of
examples, with the largest weight of each word in each block. A query bounds its
cosine with every block, visits blocks from the largest bound down and stops when
no bound exceeds the k-th best cosine, so the neighbours are exact. Votes weighted
by cosine, classes weighing alike, are calibrated on the leave-one-out votes of
the examples.

Nulls: a null or empty text, or one without any word of the space, has no
neighbours and scores the share of toxic examples. A null doc_id is not held out.
Without usable labels every score is 0. Ties among neighbours go to the smaller
example id. Repeated rows get equal scores; very long texts are counted whole, in
memory of their distinct words; other columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levcut.llm import labelled
from levcut.llm.common import WORD_BYTES, map_arrow, ship, text_column

HOLD_OUT = (3, 1)
THRESHOLD = 0.7
NEIGHBOURS = 15
#: Examples of a block.
BLOCK = 32
#: Chi-square value of one in a thousand, from which a word's weight is scaled.
SURE = 10.8
#: Blocks of the first visit; each further one takes twice as many.
FIRST_VISIT = 8


def words(text: str) -> list[bytes]:
    return text.encode("utf-8", "replace").translate(WORD_BYTES).split()


def _ranges(starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Every index of the ranges, and the range that each comes from."""
    sizes = ends - starts
    owner = np.repeat(np.arange(len(sizes)), sizes)
    total = int(sizes.sum())
    return np.arange(total) + np.repeat(starts - np.cumsum(sizes) + sizes, sizes), owner


class BlockMaxIndex:
    """Exact nearest neighbours by cosine over blocked posting lists.

    vectors: (terms, weights) of each example, terms in 0..terms-1 and distinct.
    """

    def __init__(self, vectors: list[tuple[np.ndarray, np.ndarray]], terms: int, block: int = BLOCK):
        self.block, self.n = block, len(vectors)
        self.blocks = max(1, -(-self.n // block))
        self.visited = 0
        example = np.repeat(np.arange(self.n), [len(t) for t, _ in vectors])
        term = np.concatenate([t for t, _ in vectors]) if vectors else np.zeros(0, np.int64)
        weight = np.concatenate([w for _, w in vectors]) if vectors else np.zeros(0)
        order = np.lexsort((example, term))
        self.example, self.weight, term = example[order], weight[order], term[order]
        # One entry a block of a posting list: where it begins and its largest weight.
        key = term.astype(np.int64) * self.blocks + self.example // block
        first = np.flatnonzero(np.diff(key, prepend=-1))
        self.starts = np.append(first, len(key))
        self.largest = np.maximum.reduceat(self.weight, first) if len(first) else np.zeros(0)
        self.of_block = key[first] % self.blocks
        self.lists = np.searchsorted(key[first] // self.blocks, np.arange(terms + 1))

    def nearest(self, terms: np.ndarray, weights: np.ndarray, k: int, leave_out: int = -1) -> list[tuple[float, int]]:
        """The k examples of largest positive cosine as (cosine, example)."""
        if not len(terms) or not self.n:
            return []
        entry, owner = _ranges(self.lists[terms], self.lists[terms + 1])
        by_block = self.of_block[entry]
        bounds = np.bincount(by_block, weights[owner] * self.largest[entry], self.blocks)
        order = np.argsort(-bounds, kind="stable")
        best: list[tuple[float, int]] = []
        at, step = 0, FIRST_VISIT
        while at < len(order):
            visit = order[at : at + step]
            least = best[-1][0] if len(best) == k else 0.0
            # Sums in another order may differ in the last bits.
            visit = visit[bounds[visit] * (1 + 1e-9) >= least] if least else visit[bounds[visit] > 0]
            if not len(visit):
                break
            chosen = np.zeros(self.blocks, bool)
            chosen[visit] = True
            inside = np.flatnonzero(chosen[by_block])
            posting, of = _ranges(self.starts[entry[inside]], self.starts[entry[inside] + 1])
            scores = np.bincount(self.example[posting], weights[owner[inside]][of] * self.weight[posting], self.n)
            if leave_out >= 0:
                scores[leave_out] = 0
            hit = np.flatnonzero(scores > least) if not least else np.flatnonzero(scores >= least)
            if len(hit) > k:
                border = np.partition(scores[hit], len(hit) - k)[len(hit) - k]
                hit = hit[scores[hit] >= border]
            best = sorted(best + [(float(scores[i]), i) for i in hit.tolist()], key=lambda x: (-x[0], x[1]))[:k]
            self.visited += len(visit)
            at, step = at + step, step * 2
        return best


class Model:
    """Space, weights, index and calibration."""

    def __init__(self, rows: list[tuple[int, dict[bytes, int], int]], frequency: dict[bytes, int], documents: int, k: int = NEIGHBOURS, scaled: bool = True):
        self.k = k
        ones = sum(y for _, _, y in rows)
        self.blank = ones / len(rows) if rows else 0.0
        space = sorted({w for _, counts, _ in rows for w in counts})
        self.place = {w: i for i, w in enumerate(space)}
        seen = np.zeros((2, len(space)))
        for _, counts, y in rows:
            seen[y, [self.place[w] for w in counts]] += 1
        found = np.array([frequency.get(w, 0) for w in space], float)
        self.scale = (np.log((1 + documents) / (1 + found)) + 1) * (separation(seen, len(rows) - ones, ones) if scaled else 1)
        held = [(doc, y, self.vector(counts)) for doc, counts, y in rows]
        held = [x for x in held if len(x[2][0])]
        # Examples whose heaviest word is the same stand in the same blocks.
        held.sort(key=lambda x: (int(x[2][0][x[2][1].argmax()]), x[0]))
        self.ids = [doc for doc, _, _ in held]
        self.labels = np.array([y for _, y, _ in held], int)
        totals = np.bincount(self.labels, minlength=2)
        self.voice = np.where(self.labels == 1, 1 / max(1, totals[1]), 1 / max(1, totals[0]))
        self.index = BlockMaxIndex([v for _, _, v in held], len(space))
        votes = np.array([self.vote(self.index.nearest(*v, k, i)) for i, (_, _, v) in enumerate(held)])
        self.slope, self.shift = calibrate(votes, self.labels)

    def vector(self, counts: dict[bytes, int]) -> tuple[np.ndarray, np.ndarray]:
        """Terms of the space and their weights, of length one together."""
        get = self.place.get
        listed = [(at, c) for w, c in counts.items() if (at := get(w)) is not None]
        if not listed:
            return np.zeros(0, np.int64), np.zeros(0)
        terms, n = np.array(listed, np.int64).T
        weights = (1 + np.log(n)) * self.scale[terms]
        return terms, weights / np.sqrt((weights * weights).sum())

    def vote(self, near: list[tuple[float, int]]) -> float:
        voices = [(s * self.voice[i], self.labels[i]) for s, i in near]
        total = sum(v for v, _ in voices)
        return float(sum(v for v, y in voices if y) / total) if total else self.blank

    def score(self, text: str) -> tuple[float, list[tuple[int, float, int]]]:
        """Calibrated score and evidence: (doc_id, cosine, label) of neighbours."""
        near = self.index.nearest(*self.vector(Counter(words(text))), self.k)
        if not near:
            return self.blank, []
        value = 1 / (1 + np.exp(-(self.slope * (self.vote(near) - 0.5) + self.shift)))
        return float(value), [(self.ids[i], s, int(self.labels[i])) for s, i in near]


def separation(seen: np.ndarray, zeros: int, ones: int) -> np.ndarray:
    """Root of the chi-square value of each word's presence against the label where it is sure, else 1.

    seen: documents of label 0 and 1 that hold each word.
    """
    n, df = zeros + ones, seen.sum(0)
    spread = df * (n - df) * zeros * ones
    cross = seen[1] * (zeros - seen[0]) - seen[0] * (ones - seen[1])
    chi = n * cross**2 / np.where(spread > 0, spread, np.inf)
    return np.where(chi > SURE, np.sqrt(chi), 1.0)


def calibrate(votes: np.ndarray, labels: np.ndarray) -> tuple[float, float]:
    """Slope and shift of the logistic curve of label on vote, by Newton steps with a weak prior."""
    slope, shift = 4.0, 0.0
    if not len(votes):
        return slope, shift
    x = np.stack([votes - 0.5, np.ones(len(votes))], 1)
    prior, mean = np.diag([0.05, 0.05]), np.array([4.0, 0.0])
    w = mean.copy()
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        gradient = x.T @ (p - labels) + prior @ (w - mean)
        hessian = (x * (p * (1 - p))[:, None]).T @ x + prior
        w = w - np.linalg.solve(hessian, gradient)
    return float(w[0]), float(w[1])


def examples(docs: DataFrame, labels: DataFrame, rows: int = labelled.ROWS_PER_CLASS) -> list[tuple[int, dict[bytes, int], int]]:
    """(doc_id, counts of its words, label) of the labelled sample; whole texts are counted by the executors.

    Of several texts of one doc_id the one whose words come first in order is taken.
    """
    found, chosen, _ = labelled.choose(docs, labels, "toxic", *HOLD_OUT, rows)
    if found is None:
        return []

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts = [sorted(Counter(words(x)).items()) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([[w for w, _ in c] for c in counts], pa.list_(pa.binary())), pa.array([[n for _, n in c] for c in counts], pa.list_(pa.int64()))],
                names=["doc_id", "words", "counts"],
            )

    taken: dict[int, list[tuple[bytes, int]]] = {}
    for r in map_arrow(found, run, "doc_id long, words array<binary>, counts array<long>").collect():
        one = [(bytes(w), n) for w, n in zip(r["words"], r["counts"], strict=True)]
        taken[r["doc_id"]] = min(one, taken.get(r["doc_id"], one))
    return [(doc, dict(one), chosen[doc]) for doc, one in sorted(taken.items())]


def frequencies(docs: DataFrame, space: frozenset[bytes]) -> tuple[dict[bytes, int], int]:
    """Documents that hold each word of the space, and all documents.

    Every task sends one count a word at most, whatever it reads.
    """
    shared = ship(docs.sparkSession, space)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, counts, n = shared(), Counter(), 0
        for batch in batches:
            for text in batch.column(0).to_pylist():
                n += 1
                counts.update(known.intersection(words(text)))
        listed = [(w, c) for w, c in counts.items()] + [(b"", n)]
        yield pa.RecordBatch.from_arrays(
            [pa.array([w for w, _ in listed], pa.binary()), pa.array([c for _, c in listed], pa.int64())], names=["term", "n"]
        )

    rows = map_arrow(docs.select(text_column().alias("text_")), run, "term binary, n long").groupBy("term").agg(F.sum("n").alias("n")).collect()
    found = {bytes(r["term"]): r["n"] for r in rows}
    return found, found.pop(b"", 0)


def train(docs: DataFrame, labels: DataFrame, rows: int = labelled.ROWS_PER_CLASS, scaled: bool = True) -> Model:
    taken = examples(docs, labels, rows)
    frequency, documents = frequencies(docs, frozenset(w for _, counts, _ in taken for w in counts))
    return Model(taken, frequency, documents, scaled=scaled)


SCORED = "doc_id long, score double, evidence array<struct<doc_id:long,cosine:double,toxic:int>>"


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, score and evidence for every document."""
    shared = ship(docs.sparkSession, model)
    evidence = pa.list_(pa.struct([("doc_id", pa.int64()), ("cosine", pa.float64()), ("toxic", pa.int32())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        judge_one = shared().score
        for batch in batches:
            out = [judge_one(x) for x in batch.column(1).to_pylist()]
            near = [[{"doc_id": d, "cosine": s, "toxic": y} for d, s, y in e] for _, e in out]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([s for s, _ in out], pa.float64()), pa.array(near, evidence)],
                names=["doc_id", "score", "evidence"],
            )

    return map_arrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_column().alias("text_")), run, SCORED)


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted, evidence for every document."""
    scored = score(docs, train(docs, labels))
    return scored.select(
        "doc_id",
        labelled.held_out(*HOLD_OUT).alias("held_out"),
        "score",
        (F.col("score") >= THRESHOLD).cast("int").alias("predicted"),
        "evidence",
    )
