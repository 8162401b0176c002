"""SimHash near-duplicates, found exactly by sharded vantage-point trees.

Every text gets a 64-bit fingerprint of its three-word shingles. Fingerprints
within ``radius`` bits link; components are the transitive closure.

Search: distinct fingerprints are cut into ``bands`` of bits. Of more bands than
``radius``, two near fingerprints agree on all but ``radius``, so each choice of the
others is a key on which they are equal; with fewer bands they are within
``radius // bands`` on some band. Every key has a vantage-point tree of its own,
grown from a bounded sample, whose leaves are shards. A fingerprint is stored in its
home leaf and also visits every leaf that its ball overlaps, by the triangle bound;
where equal keys suffice the ball has radius zero, and leaves are cut further by the
key itself, so shards stay small at any count (``bands_for`` takes more bands where
sixteen bits are too few). One band is the plain tree over whole fingerprints.
Inside a shard a second vantage-point tree over whole fingerprints finds the
pairs; the shard keeps a spanning forest of them, so copies never expand into
all pairs and no link between components is lost.

Nulls: a null or empty text has no words and fingerprint zero, linked like any
other. Rows with null doc_id are fingerprinted and link; their component is the
least doc_id reachable, null if there is none. Repeated rows are one fingerprint.
Empty tables give empty results; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levcut.llm.common import LOWER_BYTES, cut_lineage, map_arrow, ship, text_column

SHINGLE, SEED, RADIUS, BANDS = 3, 42, 3, 4
#: Fingerprints of the sample that grows the trees, and of a leaf of them.
SAMPLE, LEAF = 8192, 8
#: Distinct fingerprints that a shard should hold at least before trees grow deeper.
SHARD = 1024
#: Shingles of one numpy pass over a text.
PIECE = 65_536


def words(text: str) -> list[bytes]:
    return text.encode("utf-8", "replace").translate(LOWER_BYTES).split()


def fingerprint(text: str) -> int:
    """A bit is 1 if more than half of the shingles' hashes set it."""
    listed = words(text)
    if not listed:
        return 0
    joined = b" ".join(listed)
    if len(listed) <= SHINGLE:
        return xxhash.xxh64_intdigest(joined, SEED)
    ends = np.cumsum([len(w) + 1 for w in listed])
    starts = [0, *ends[: -SHINGLE].tolist()]
    stops = (ends[SHINGLE - 1 :] - 1).tolist()
    hash_ = xxhash.xxh64_intdigest
    n, ones = len(stops), np.zeros(64, np.int64)
    for at in range(0, n, PIECE):
        values = np.array([hash_(joined[a:b], SEED) for a, b in zip(starts[at : at + PIECE], stops[at : at + PIECE], strict=True)], ">u8")
        ones += np.unpackbits(values.view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > n).tobytes(), "big")


def text_id(name: str = "text") -> Column:
    """With doc_id, what tells one row from another."""
    return F.xxhash64(text_column(name))


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, text_id, fp (the 64 bits as a signed long)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = np.array([fingerprint(x) for x in batch.column(2).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(values)], names=["doc_id", "text_id", "fp"])

    chosen = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_id().alias("text_id"), text_column().alias("text_"))
    return map_arrow(chosen, run, "doc_id long, text_id long, fp long")


class VantageTree:
    """Leaves are numbered; a node sends what lies within its radius to the left."""

    def __init__(self, sample: np.ndarray, leaf: int, depth: int):
        self.nodes: list[tuple[int, int, int, int]] = []  # vantage, radius, left, right; leaves are ~number
        self.leaves = 0
        self.root = self._grow(np.unique(sample), leaf, depth)

    def _grow(self, values: np.ndarray, leaf: int, depth: int) -> int:
        if depth > 0 and len(values) > leaf:
            # The first values in order are as good as any; take the one that spreads best.
            picks = values[:: max(1, len(values) // 8)][:8]
            distances = np.bitwise_count(values[None, :] ^ picks[:, None]).astype(np.int64)
            best = int(distances.var(1).argmax())
            d = distances[best]
            middle = int(np.sort(d)[(len(d) - 1) // 2])
            if (d <= middle).all():
                middle -= 1
            inside = d <= middle
            if inside.any() and not inside.all():
                at = len(self.nodes)
                self.nodes.append((int(picks[best]), middle, 0, 0))
                left = self._grow(values[inside], leaf, depth - 1)
                right = self._grow(values[~inside], leaf, depth - 1)
                self.nodes[at] = (int(picks[best]), middle, left, right)
                return at
        self.leaves += 1
        return ~(self.leaves - 1)

    def visit(self, values: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row, leaf, home): each leaf that the ball around a value overlaps; home where the value itself lies."""
        rows, leaves, homes = [], [], []
        open_ = [(self.root, np.arange(len(values)), np.ones(len(values), bool))]
        while open_:
            node, index, home = open_.pop()
            if not len(index):
                continue
            if node < 0:
                rows.append(index)
                leaves.append(np.full(len(index), ~node))
                homes.append(home)
                continue
            vantage, bound, left, right = self.nodes[node]
            d = np.bitwise_count(values[index] ^ np.uint64(vantage)).astype(np.int64)
            near, far = d - radius <= bound, d + radius > bound
            open_.append((left, index[near], home[near] & (d[near] <= bound)))
            open_.append((right, index[far], home[far] & (d[far] > bound)))
        if not rows:
            none = np.zeros(0, np.int64)
            return none, none, none.astype(bool)
        return np.concatenate(rows), np.concatenate(leaves), np.concatenate(homes)


class Forest:
    """Union-find over positions."""

    def __init__(self, n: int):
        self.up = np.arange(n)

    def root(self, i: int) -> int:
        up = self.up
        while up[i] != i:
            up[i] = up[up[i]]
            i = up[i]
        return int(i)

    def roots(self, index: np.ndarray) -> np.ndarray:
        at = self.up[index]
        while (self.up[at] != at).any():
            at = self.up[at]
        return at

    def link(self, a: int, b: int) -> None:
        a, b = self.root(a), self.root(b)
        if a != b:
            self.up[max(a, b)] = min(a, b)

    def link_hits(self, left: np.ndarray, right: np.ndarray) -> None:
        """Joins pairs; each round one open pair a position, so dense hits take few rounds."""
        while len(left):
            open_ = self.roots(left) != self.roots(right)
            left, right = left[open_], right[open_]
            for side in (left, right):
                for i in np.unique(side, return_index=True)[1].tolist():
                    self.link(int(left[i]), int(right[i]))


def link_all(values: np.ndarray, radius: int, forest: Forest, leaf: int = 256) -> None:
    """Joins all pairs of distinct values within radius by a vantage-point tree.

    The values are split at the median distance to a vantage point; pairs across
    the split can only lie where both distances are within the radius of it.
    """

    def across(a: np.ndarray, b: np.ndarray) -> None:
        for at in range(0, len(a), 512):
            part = a[at : at + 512]
            for to in range(0, len(b), 4096):
                other = b[to : to + 4096]
                x, y = np.nonzero(np.bitwise_count(values[part][:, None] ^ values[other][None, :]) <= radius)
                forest.link_hits(part[x], other[y])

    open_ = [np.arange(len(values))]
    while open_:
        index = open_.pop()
        if len(index) <= leaf:
            across(index, index)
            continue
        d = np.bitwise_count(values[index] ^ values[index[0]]).astype(np.int64)
        middle = int(np.median(d))
        if (d <= middle).all():
            middle = int(d.max()) - 1
        inside = d <= middle
        if not inside.any() or inside.all():
            across(index, index)
            continue
        open_ += [index[inside], index[~inside]]
        border_in, border_out = index[inside & (d > middle - radius)], index[~inside & (d <= middle + radius)]
        if len(border_in) and len(border_out):
            # Of the border, only distances that differ by the radius at most can pair.
            at_in, at_out = d[inside & (d > middle - radius)], d[~inside & (d <= middle + radius)]
            for step in range(middle - radius + 1, middle + 1):
                across(border_in[at_in == step], border_out[at_out <= step + radius])


def band_values(values: np.ndarray, bands: int, band: int) -> np.ndarray:
    """Bits of one of ``bands`` bands of nearly equal width."""
    low, high = 64 * band // bands, 64 * (band + 1) // bands
    return (values >> np.uint64(low)) & np.uint64((1 << (high - low)) - 1)


def key_bands(bands: int, radius: int) -> list[tuple[int, ...]]:
    """The bands that make up each key."""
    return list(combinations(range(bands), max(1, bands - radius)))


def key_values(values: np.ndarray, bands: int, chosen: tuple[int, ...]) -> np.ndarray:
    out = np.zeros(len(values), np.uint64)
    for band in chosen:
        width = 64 * (band + 1) // bands - 64 * band // bands
        out = (out << np.uint64(width)) | band_values(values, bands, band) if width < 64 else values.copy()
    return out


def bands_for(count: int, radius: int = RADIUS, shard: int = SHARD) -> int:
    """The fewest bands over the radius whose keys have values enough for shards of that size."""
    bands = radius + 1
    while bands < 2 * radius and count > shard << (64 * (bands - radius) // bands):
        bands += 1
    return bands


def links(distinct: DataFrame, radius: int = RADIUS, bands: int | None = None, sample: int = SAMPLE, shard: int = SHARD) -> DataFrame:
    """fp, to: a spanning forest, within shards, of all links of distinct fingerprints."""
    taken = distinct.orderBy(F.xxhash64("fp")).limit(sample).collect()
    count = distinct.count() if len(taken) == sample else len(taken)
    known = np.array([r["fp"] for r in taken], np.int64).view(np.uint64)
    bands = bands_for(count, radius, shard) if bands is None else bands
    depth = max(0, int(np.ceil(np.log2(max(1, count / shard)))))
    keys = key_bands(bands, radius)
    reach = 0 if bands > radius else radius // bands
    grown = [VantageTree(key_values(known, bands, k), LEAF, depth) for k in keys]
    # Where the bounded tree has too few leaves, equal keys still meet in a part of one.
    parts = [1 if reach else max(1, -(-count // (shard * tree.leaves))) for tree in grown]
    shared = ship(distinct.sparkSession, grown)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trees = shared()
        for batch in batches:
            values = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
            for at, (tree, chosen) in enumerate(zip(trees, keys, strict=True)):
                of_key = key_values(values, bands, chosen)
                rows, leaves, _ = tree.visit(of_key, reach)
                part = (of_key[rows] * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(33)) % np.uint64(parts[at])
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.full(len(rows), at, np.int32)), pa.array(leaves * parts[at] + part.astype(np.int64)), pa.array(values[rows].view(np.int64))],
                    names=["band", "leaf", "fp"],
                )

    def pair(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        columns: list[list[np.ndarray]] = [[], [], []]
        for batch in batches:
            for held, column in zip(columns, batch.columns, strict=True):
                held.append(column.to_numpy(zero_copy_only=False))
        if not columns[0]:
            return
        band, leaf, fp = (np.concatenate(x) for x in columns)
        order = np.lexsort((fp, leaf, band))
        band, leaf, fp = band[order], leaf[order], fp[order]
        edges = np.flatnonzero((np.diff(band) != 0) | (np.diff(leaf) != 0)) + 1
        for a, b in zip([0, *edges.tolist()], [*edges.tolist(), len(fp)], strict=True):
            if b - a < 2:
                continue
            forest = Forest(b - a)
            link_all(fp[a:b].view(np.uint64), radius, forest)
            roots = np.array([forest.root(i) for i in range(b - a)])
            moved = np.flatnonzero(roots != np.arange(b - a))
            if len(moved):
                yield pa.RecordBatch.from_arrays([pa.array(fp[a:b][moved]), pa.array(fp[a:b][roots[moved]])], names=["fp", "to"])

    dealt = distinct.select("fp").mapInArrow(deal, "band int, leaf long, fp long")
    return dealt.repartition("band", "leaf").mapInArrow(pair, "fp long, to long").distinct()


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """fp, root: nodes of the edges with the least node they reach.

    Rounds of two steps bring every node next to its least neighbour until a
    star stands for each component; each round is cut off by a checkpoint.
    """
    edges = cut_lineage(edges.select(F.greatest("fp", "to").alias("a"), F.least("fp", "to").alias("b")).filter("a != b").distinct())

    def mark(df: DataFrame) -> tuple:
        row = df.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
        return row["n"], row["h"]

    last = mark(edges)
    for _ in range(most_rounds):
        if not last[0]:
            break
        both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.filter("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a != b").distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").filter("b != m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        edges = cut_lineage(small.union(least.select("a", F.col("m").alias("b"))).distinct())
        now = mark(edges)
        if now == last:
            break
        last = now
    else:
        raise RuntimeError("components did not settle")
    roots = edges.select(F.col("a").alias("fp"), F.col("b").alias("root"))
    return roots.union(edges.select(F.col("b").alias("fp"), F.col("b").alias("root")).distinct())


def cluster(docs: DataFrame, radius: int = RADIUS, bands: int | None = None) -> DataFrame:
    """doc_id, text_id, fp, group, component_id for every document."""
    rows = cut_lineage(fingerprints(docs))
    distinct = cut_lineage(rows.groupBy("fp").agg(F.min("doc_id").alias("least")))
    found = components(links(distinct, radius, bands))
    rooted = distinct.join(found, "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    lowest = rooted.filter("fp != root").groupBy("root").agg(F.min("least").alias("below"))
    roots = rooted.filter("fp = root").join(lowest, "root", "left").select("root", F.least("least", "below").alias("component_id"))
    by_fp = rooted.select("fp", "root").join(roots, "root").select("fp", F.col("root").alias("group"), "component_id")
    return rows.join(by_fp, "fp").select("doc_id", "text_id", "fp", "group", "component_id")


def near_duplicates(docs: DataFrame) -> DataFrame:
    """doc_id, fingerprint as 16 hex digits, component_id."""
    digits = F.lpad(F.lower(F.hex("fp")), 16, "0")
    return cluster(docs).select("doc_id", digits.alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, found: DataFrame | None = None) -> DataFrame:
    """One row of each component, the one of least doc_id, then text_id, with its columns.

    ``found`` has doc_id, text_id and group of every row; by default those of
    cluster(). Rows are told apart by doc_id and text, so of rows that share a
    doc_id each stays or goes with its own component; a null doc_id is last. Rows
    equal in both are copies, of which one stays.
    """
    found = cut_lineage((cluster(docs) if found is None else found).groupBy("group", "doc_id", "text_id").agg(F.count("*").alias("n")))
    first = found.groupBy("group").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text_id")).alias("first"))
    stays = found.join(first, "group").withColumn("stays", F.col("doc_id").eqNullSafe(F.col("first.doc_id")) & (F.col("text_id") == F.col("first.text_id")))
    stays = cut_lineage(stays.select(F.col("doc_id").alias("id_"), F.col("text_id").alias("key_"), "stays", "n"))
    keyed = docs.select(F.struct("*").alias("kept"), F.col("doc_id").cast("long").alias("doc"), text_id().alias("key"))
    same = F.col("doc").eqNullSafe(F.col("id_")) & (F.col("key") == F.col("key_"))
    kept = keyed.join(stays.filter("not stays"), same, "left_anti")
    again = stays.filter("stays and n > 1")
    if again.isEmpty():
        return kept.select("kept.*")
    once = kept.join(again, same, "left_anti")
    return once.unionByName(kept.join(again, same, "left_semi").dropDuplicates(["doc", "key"])).select("kept.*")
