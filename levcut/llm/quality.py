"""Quality classifier: a convolutional network over bytes, in numpy.

Bytes are embedded; learned filters, twelve bytes wide and four apart, run over
the whole document. Overlapping chunks of windows are max-pooled, and the mean,
the least and the largest of the pooled responses over all chunks of the
document are combined by a logistic layer into one probability. Long documents
go through in pieces of whole chunks that overlap as chunks do, so memory is bounded
for any length and the score is the same as that of the whole at once.

Labels come from a bounded sample (``labelled``): ROWS_PER_CLASS documents a
class, with their whole texts. Scores use the text alone.

Nulls: a null or empty text is one chunk of padding and gets that score. A null
doc_id is not held out. Without usable labels every score is the share of ones
(0.5 without any). Repeated rows get equal scores; other columns are ignored, and
those that clash with names of results are kept by accept().
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from levcut.llm import labelled
from levcut.llm.common import map_arrow, ship, text_column

HOLD_OUT = (4, 2)
THRESHOLD = 0.7

WIDTH, STEP, DIM, FILTERS = 12, 4, 8, 32
#: A group is 8 windows; a chunk is 8 groups (256 bytes) and overlaps the next by one.
GROUP, CHUNK, HOP = 8, 8, 7
TAPS = WIDTH // STEP
#: Chunks of a document in one piece, and the bytes from which one is cut.
PIECE_CHUNKS = 1024
PIECE = STEP * GROUP * HOP * PIECE_CHUNKS
PAD = WIDTH - STEP


@dataclass
class Net:
    embed: np.ndarray  # 256 x DIM
    filters: np.ndarray  # STEP*DIM x TAPS*FILTERS
    bias: np.ndarray  # FILTERS
    out: np.ndarray  # 3*FILTERS
    shift: float


def _layout(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """All bytes, each document between zeros, and its number of groups."""
    unit = STEP * GROUP
    sizes = np.array([max(1, -(-(len(x) + PAD) // unit)) for x in texts])
    data = np.zeros(int(sizes.sum()) * unit + PAD, np.uint8)
    at = 0
    for text, n in zip(texts, sizes, strict=True):
        data[at + PAD : at + PAD + len(text)] = np.frombuffer(text, np.uint8)
        at += int(n) * unit
    return data, sizes


def _responses(net: Net, data: np.ndarray) -> np.ndarray:
    """Rectified filter responses, one row a window."""
    grams = net.embed[data].reshape(-1, STEP * DIM) @ net.filters
    n = len(grams) - TAPS + 1
    total = grams[:n, :FILTERS].copy()
    for t in range(1, TAPS):
        total += grams[t : t + n, t * FILTERS : (t + 1) * FILTERS]
    total += net.bias
    return np.maximum(total, 0, out=total)


def _chunk_bounds(sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First and last group of each chunk, and the first chunk of each document."""
    starts, ends, first, at, seen = [], [], [], 0, 0
    for n in sizes.tolist():
        s = np.arange(0, max(1, n - (CHUNK - HOP)), HOP)
        starts.append(s + at)
        ends.append(np.minimum(s + CHUNK, n) + at)
        first.append(seen)
        seen += len(s)
        at += n
    return np.concatenate(starts), np.concatenate(ends), np.array(first)


def _pool(groups: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Maximum of groups[start:end] for each chunk."""
    padded = np.concatenate([groups, np.zeros((1, groups.shape[1]), groups.dtype)])
    return np.maximum.reduceat(padded, np.stack([starts, ends], 1).ravel(), axis=0)[::2]


def _chunks(net: Net, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    data, sizes = _layout(texts)
    groups = _responses(net, data).reshape(-1, GROUP, FILTERS).max(1)
    starts, ends, first = _chunk_bounds(sizes)
    return _pool(groups, starts, ends), first


def _summary(pooled: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    return pooled.sum(0, dtype=np.float64), pooled.min(0), pooled.max(0), len(pooled)


def _long(net: Net, text: bytes, piece_chunks: int = PIECE_CHUNKS) -> np.ndarray:
    """The pooled features of one text, ``piece_chunks`` chunks at a time.

    A piece holds the groups of its chunks and the bytes that their last windows
    reach into, as they lie in the whole layout.
    """
    unit = STEP * GROUP
    n = max(1, -(-(len(text) + PAD) // unit))
    starts, ends, _ = _chunk_bounds(np.array([n]))
    total, least, most, count = 0.0, np.inf, -np.inf, 0
    for at in range(0, len(starts), piece_chunks):
        low, high = int(starts[at]), int(ends[min(at + piece_chunks, len(starts)) - 1])
        data = np.zeros((high - low) * unit + PAD, np.uint8)
        # Byte i of the layout is byte i - PAD of the text.
        first, last = max(0, low * unit - PAD), min(len(text), high * unit)
        data[first + PAD - low * unit : last + PAD - low * unit] = np.frombuffer(text, np.uint8, last - first, first)
        groups = _responses(net, data).reshape(-1, GROUP, FILTERS).max(1)
        some = slice(at, at + piece_chunks)
        part, small, large, k = _summary(_pool(groups, starts[some] - low, ends[some] - low))
        total, least, most, count = total + part, np.minimum(least, small), np.maximum(most, large), count + k
    return np.concatenate([total / count, least, most])


def probabilities(net: Net, texts: list[bytes], budget: int = 1 << 19) -> np.ndarray:
    """One probability a text, in bounded memory."""
    features = np.zeros((len(texts), 3 * FILTERS), np.float32)

    def flush(batch: list[tuple[int, bytes]]) -> None:
        pooled, first = _chunks(net, [x for _, x in batch])
        count = np.diff([*first, len(pooled)])[:, None]
        rows = [i for i, _ in batch]
        features[rows] = np.concatenate(
            [np.add.reduceat(pooled, first) / count, np.minimum.reduceat(pooled, first), np.maximum.reduceat(pooled, first)], 1
        )

    batch, held = [], 0
    for i, text in enumerate(texts):
        if len(text) > PIECE:
            features[i] = _long(net, text)
            continue
        batch.append((i, text))
        held += len(text)
        if held >= budget:
            flush(batch)
            batch, held = [], 0
    if batch:
        flush(batch)
    return 1 / (1 + np.exp(-np.clip(features @ net.out + net.shift, -30, 30)))


def pieces(rows: list[tuple[bytes, int]], most: int = 32_768) -> list[tuple[bytes, int, float]]:
    """(text, label, share): a training text over ``most`` bytes enters as pieces that share its weight.

    Together the pieces are the whole text, so a step of the fit holds a bounded
    number of bytes and no part of a text is left out.
    """
    out = []
    for text, label in rows:
        n = max(1, -(-len(text) // most))
        out += [(text[at * most : (at + 1) * most], label, 1 / n) for at in range(n)]
    return out


def fit(rows: list[tuple[bytes, int]], share: float, epochs: int = 14, least_steps: int = 600, batch: int = 24, seed: int = 5, rate: float = 0.004) -> Net:
    """Stochastic gradient descent with momentum terms on the log loss.

    Only the windows that won a maximum carry gradient. Classes weigh alike in
    the fit; the shift then moves the odds back to the share of label 1.
    """
    rng = np.random.default_rng(seed)
    net = Net(
        rng.normal(0, 0.5, (256, DIM)).astype(np.float32),
        rng.normal(0, 1 / np.sqrt(STEP * DIM * TAPS), (STEP * DIM, TAPS * FILTERS)).astype(np.float32),
        np.zeros(FILTERS, np.float32),
        rng.normal(0, 0.1, 3 * FILTERS).astype(np.float32),
        0.0,
    )
    rows = pieces(rows)
    labels, parts = np.array([y for _, y, _ in rows], np.float32), np.array([w for _, _, w in rows])
    ones = float((labels * parts).sum() / parts.sum()) if len(labels) else 0.0
    if not 0 < ones < 1:
        net.out[:] = 0
        net.shift = float(np.log((share + 1e-3) / (1 - share + 1e-3)))
        return net
    weight = parts * np.where(labels == 1, 0.5 / ones, 0.5 / (1 - ones))
    names = ("embed", "filters", "bias", "out")
    moments = {k: [np.zeros_like(getattr(net, k)), np.zeros_like(getattr(net, k))] for k in names}
    moments["shift"] = [np.zeros(1), np.zeros(1)]
    per_epoch = -(-len(rows) // batch)
    epochs = max(epochs, -(-least_steps // per_epoch))
    steps, total = 0, epochs * per_epoch
    for _ in range(epochs):
        order = rng.permutation(len(rows))
        for at in range(0, len(rows), batch):
            pick = order[at : at + batch]
            data, sizes = _layout([rows[i][0] for i in pick])
            responses = _responses(net, data)
            by_group = responses.reshape(-1, GROUP, FILTERS)
            winner = by_group.argmax(1) + np.arange(len(by_group))[:, None] * GROUP
            groups = by_group.max(1)
            starts, ends, first = _chunk_bounds(sizes)
            pooled = _pool(groups, starts, ends)
            bounds = [*first.tolist(), len(pooled)]
            count = np.diff(bounds)
            mean = np.add.reduceat(pooled, first) / count[:, None]
            least, most = np.minimum.reduceat(pooled, first), np.maximum.reduceat(pooled, first)
            features = np.concatenate([mean, least, most], 1)
            p = 1 / (1 + np.exp(-np.clip(features @ net.out + net.shift, -30, 30)))
            slope = ((p - labels[pick]) * weight[pick] / len(pick)).astype(np.float32)
            grads = {"out": features.T @ slope + 1e-5 * net.out, "shift": np.array([slope.sum()])}
            back = slope[:, None] * net.out[None, :]
            owner = np.repeat(np.arange(len(pick)), count)
            to_chunk = (back[:, :FILTERS] / count[:, None])[owner]
            for part, value in ((1, least), (2, most)):
                hit = pooled == value[owner]
                share_hit = np.add.reduceat(hit.astype(np.float32), first)[owner]
                to_chunk += np.where(hit, back[owner, part * FILTERS : (part + 1) * FILTERS] / share_hit, 0)
            to_chunk[pooled <= 0] = 0
            # The group that won each chunk, then the window that won the group.
            to_window = np.zeros_like(responses)
            column = np.arange(FILTERS)
            best, at_group = np.full(pooled.shape, -1.0, np.float32), np.zeros(pooled.shape, np.int64)
            for k in range(CHUNK):
                index = np.minimum(starts + k, ends - 1)
                better = groups[index] > best
                best = np.where(better, groups[index], best)
                at_group = np.where(better, index[:, None], at_group)
            np.add.at(to_window, (winner[at_group, column[None, :]], np.broadcast_to(column, at_group.shape)), to_chunk)
            live = np.flatnonzero(to_window.any(1))
            d = to_window[live]
            grads["bias"] = d.sum(0)
            embedded = net.embed[data].reshape(-1, STEP * DIM)
            grads["filters"] = np.concatenate([embedded[live + t].T @ d for t in range(TAPS)], 1)
            to_embed = np.zeros_like(net.embed)
            bytes_ = data.reshape(-1, STEP)
            for t in range(TAPS):
                piece = (d @ net.filters[:, t * FILTERS : (t + 1) * FILTERS].T).reshape(-1, DIM)
                np.add.at(to_embed, bytes_[live + t].ravel(), piece)
            grads["embed"] = to_embed
            steps += 1
            pace = rate * min(1.0, steps / 50) * (1 - 0.9 * steps / total)
            for k, g in grads.items():
                m, v = moments[k]
                m *= 0.9
                m += 0.1 * g
                v *= 0.99
                v += 0.01 * g * g
                move = pace * (m / (1 - 0.9**steps)) / (np.sqrt(v / (1 - 0.99**steps)) + 1e-8)
                if k == "shift":
                    net.shift -= float(move[0])
                else:
                    setattr(net, k, (getattr(net, k) - move).astype(np.float32))
    clipped = min(max(share, 0.02), 0.98)
    net.shift += float(np.log(clipped / (1 - clipped)))
    return net


def train(docs: DataFrame, labels: DataFrame, rows: int = labelled.ROWS_PER_CLASS) -> Net:
    taken, share = labelled.sample(docs, labels, "quality", *HOLD_OUT, rows)
    return fit([(text.encode("utf-8", "replace"), y) for _, text, y in taken], share)


def score(docs: DataFrame, net: Net, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The named columns of docs, in a struct ``kept``, and ``score``."""
    shared = ship(docs.sparkSession, net)
    chosen = docs.select(F.struct(*keep).alias("kept"), text_column().alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [x.encode("utf-8", "replace") for x in batch.column(1).to_pylist()]
            values = probabilities(shared(), texts) if texts else np.zeros(0)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(values.astype(np.float64))], names=["kept", "score"])

    return map_arrow(chosen, run, StructType([chosen.schema["kept"]]).add("score", "double"))


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted for every document."""
    scored = score(docs, train(docs, labels)).select("kept.doc_id", "score")
    return scored.select(
        "doc_id", held_out_column(), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted")
    )


def held_out_column():
    return labelled.held_out(*HOLD_OUT).alias("held_out")


def accept(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The documents with a predicted label of 1, with their columns."""
    scored = score(docs, train(docs, labels), tuple(docs.columns))
    return scored.filter(F.col("score") >= THRESHOLD).select("kept.*")
