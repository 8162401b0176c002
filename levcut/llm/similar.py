"""Near copies by exact similarity of their sets of five-word shingles.

Two texts link if their shingle sets have a Jaccard similarity of at least
``SIMILAR``, or if their fingerprints link as in ``simhash``; components are the
transitive closure of both.

Candidates come from min-hashes in ``BANDS`` bands of ``ROWS`` each: a pair at
the threshold shares no band with probability (1 - 0.8^6)^40, about 5e-6, a more
similar one with less. Each candidate is then decided by its whole shingle sets.
Equal sets are one node. Within a bucket first all members are compared with the
one that meets the most others, so a large group of copies takes as many
comparisons as it has members. What then still lies in several components is
compared in full: small buckets as pairs, larger ones in cells of two chunks of
bounded size, whose comparisons are made inside one task and give out links alone.
So a large group whose members are alike but below the threshold is never
written out as pairs: its rows are its members, once a chunk.

Nulls: a null or empty text has no shingles and an empty set, like any other
equal set. Rows with null doc_id link as in ``simhash``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levcut.llm import simhash
from levcut.llm.common import map_arrow, stored, text_column

SHINGLE, SEED, SIMILAR = 5, 43, 0.8
BANDS, ROWS = 40, 6
#: Shingles of one numpy pass of the min-hashes.
PIECE = 4096
#: Buckets up to so many sets are compared as pairs of rows.
PAIRED = 12
#: Sets and shingles of a chunk at most, but for a set that is larger alone.
CHUNK_SETS, CHUNK_SHINGLES = 2048, 500_000


def shingles(text: str) -> np.ndarray:
    """The distinct hashes of a text's shingles, sorted; a shorter text is one shingle."""
    listed = simhash.words(text)
    if not listed:
        return np.zeros(0, np.uint64)
    joined = b" ".join(listed)
    if len(listed) <= SHINGLE:
        return np.array([xxhash.xxh64_intdigest(joined, SEED)], np.uint64)
    ends = np.cumsum([len(w) + 1 for w in listed])
    starts = [0, *ends[:-SHINGLE].tolist()]
    stops = (ends[SHINGLE - 1 :] - 1).tolist()
    hash_ = xxhash.xxh64_intdigest
    return np.unique(np.fromiter((hash_(joined[a:b], SEED) for a, b in zip(starts, stops, strict=True)), np.uint64, len(stops)))


def _mixers() -> tuple[np.ndarray, np.ndarray]:
    random = np.random.default_rng(SEED)
    draw = random.integers(0, 2**64, (2, BANDS * ROWS), dtype=np.uint64)
    return draw[0] | np.uint64(1), draw[1]


def band_keys(values: np.ndarray, times: np.ndarray, plus: np.ndarray) -> np.ndarray:
    """One key a band, of its rows' least mixed hashes; none for an empty set."""
    if not len(values):
        return np.zeros(0, np.int64)
    least = np.full(len(times), 2**64 - 1, np.uint64)
    for at in range(0, len(values), PIECE):
        part = values[at : at + PIECE]
        np.minimum(least, ((part[None, :] ^ plus[:, None]) * times[:, None]).min(1), out=least)
    rows = least.reshape(BANDS, ROWS)
    return np.array([xxhash.xxh64_intdigest(rows[b].tobytes(), b) for b in range(BANDS)], np.uint64).view(np.int64)


def sketches(docs: DataFrame) -> DataFrame:
    """doc_id, text_id, fp, set_id (hash of the shingle set), keys, hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        times, plus = _mixers()
        for whole in batches:
            for at in range(0, whole.num_rows, 100):
                batch = whole.slice(at, 100)
                texts = batch.column(2).to_pylist()
                sets = [shingles(x) for x in texts]
                columns = [
                    batch.column(0),
                    batch.column(1),
                    pa.array(np.array([simhash.fingerprint(x) for x in texts], np.uint64).view(np.int64)),
                    pa.array(np.array([xxhash.xxh64_intdigest(s.tobytes(), SEED) for s in sets], np.uint64).view(np.int64)),
                    pa.array([band_keys(s, times, plus) for s in sets], pa.list_(pa.int64())),
                    pa.array([s.view(np.int64) for s in sets], pa.list_(pa.int64())),
                ]
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "text_id", "fp", "set_id", "keys", "hashes"])

    chosen = docs.select(F.col("doc_id").cast("long").alias("doc_id"), simhash.text_id().alias("text_id"), text_column().alias("text_"))
    return map_arrow(chosen, run, "doc_id long, text_id long, fp long, set_id long, keys array<long>, hashes array<long>")


def verified(pairs: DataFrame, sets: DataFrame, similar: float = SIMILAR) -> DataFrame:
    """The pairs (a, b) whose sets are as similar as that."""
    low, high = F.least("n", "m"), F.greatest("n", "m")
    sizes = sets.select("set_id", "size")
    small = pairs.join(sizes.toDF("a", "n"), "a").join(sizes.toDF("b", "m"), "b").filter(low >= similar * high - 1e-9).select("a", "b")
    left = small.join(sets.select(F.col("set_id").alias("b"), F.col("hashes").alias("y")), "b")
    both = left.join(sets.select(F.col("set_id").alias("a"), F.col("hashes").alias("x")), "a")
    common = F.size(F.array_intersect("x", "y"))
    scored = both.select("a", "b", common.alias("common"), (F.size("x") + F.size("y") - common).alias("any"))
    return scored.filter(F.col("common") >= similar * F.col("any") - 1e-9).select("a", "b")


def links(rows: DataFrame, similar: float = SIMILAR, paired: int = PAIRED) -> DataFrame:
    """fp, to: pairs of set_ids that connect all sets of at least that similarity."""
    one = rows.dropDuplicates(["set_id"])
    buckets = one.select("set_id", F.explode("keys").alias("key"))
    several = buckets.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1")
    shared = stored(buckets.join(several, "key"))
    met = stored(shared.groupBy("set_id").agg(F.sum("n").alias("met")))
    held = one.join(met.select("set_id"), "set_id", "left_semi")
    sets = stored(held.select("set_id", F.size("hashes").alias("size"), "hashes"))
    lead = shared.join(met, "set_id").groupBy("key").agg(F.max(F.struct("met", "set_id"))["set_id"].alias("lead"))
    first = shared.join(lead, "key").filter("set_id != lead")
    tried = stored(first.select(F.least("set_id", "lead").alias("a"), F.greatest("set_id", "lead").alias("b")).distinct())
    near = stored(verified(tried, sets, similar)).toDF("fp", "to")
    roots = stored(simhash.components(near)).withColumnRenamed("fp", "set_id")
    placed = shared.join(roots, "set_id", "left").select("key", "set_id", "n", F.coalesce("root", "set_id").alias("root"))
    open_ = placed.groupBy("key").agg(F.min("root").alias("low"), F.max("root").alias("high")).filter("low != high").select("key")
    left = stored(placed.join(open_, "key"))
    few = left.filter(F.col("n") <= paired).select("key", "set_id", "root")
    x, y = few.toDF("key", "a", "ra"), few.toDF("key", "b", "rb")
    rest = x.join(y, "key").filter("a < b and ra != rb").select("a", "b").distinct().join(tried, ["a", "b"], "left_anti")
    pairs = near.unionByName(stored(verified(stored(rest), sets, similar)).toDF("fp", "to"))
    return pairs.unionByName(stored(in_cells(left.filter(F.col("n") > paired), sets, similar).toDF("fp", "to").distinct()))


def in_cells(buckets: DataFrame, sets: DataFrame, similar: float, chunk_sets: int = CHUNK_SETS, chunk_shingles: int = CHUNK_SHINGLES) -> DataFrame:
    """a, b: the sets of one bucket but two components that are as similar as that.

    buckets: key, set_id, root. A bucket is dealt over chunks by hash of the set;
    each pair of chunks is a cell, and a set goes to every cell of its chunk.
    """
    sized = buckets.join(sets.select("set_id", "size"), "set_id")
    chunks = F.greatest(F.ceil(F.count("*") / chunk_sets), F.ceil(F.sum("size") / chunk_shingles)).cast("int")
    dealt = sized.select("key", "set_id", "root").join(sized.groupBy("key").agg(chunks.alias("chunks")), "key")
    own = F.pmod(F.xxhash64("set_id"), F.col("chunks")).cast("int")
    sent = dealt.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    cells = sent.select("key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "set_id", "root", (F.col("own") <= F.col("other")).alias("first"))

    def compare(table: pa.Table) -> pa.Table:
        ids, roots, first = (table.column(c).to_numpy() for c in ("set_id", "root", "first"))
        lists = table.column("hashes").combine_chunks()
        ends = np.cumsum([len(x) for x in lists])
        values = lists.flatten().to_numpy(zero_copy_only=False)
        member = np.repeat(np.arange(len(ids)), np.diff(ends, prepend=0))
        sizes = np.diff(ends, prepend=0)
        order = np.argsort(values, kind="stable")
        by_value = member[order]
        # The run of equal shingles that each shingle of a set stands in.
        sorted_ = values[order]
        starts = np.searchsorted(sorted_, values, "left")
        stops = np.searchsorted(sorted_, values, "right")
        one_chunk = bool(first.all())
        a, b = [], []
        for x in np.flatnonzero(first).tolist():
            low, high = ends[x] - sizes[x], ends[x]
            runs = stops[low:high] - starts[low:high]
            at = np.arange(int(runs.sum())) + np.repeat(starts[low:high] - np.cumsum(runs) + runs, runs)
            common = np.bincount(by_value[at], minlength=len(ids))
            hit = (common >= similar * (sizes + sizes[x] - common) - 1e-9) & (roots != roots[x])
            hit &= (ids > ids[x]) if one_chunk else ~first
            found = np.flatnonzero(hit)
            a.append(np.minimum(ids[found], ids[x]))
            b.append(np.maximum(ids[found], ids[x]))
        none = [np.zeros(0, np.int64)]
        return pa.table({"a": pa.array(np.concatenate(a or none)), "b": pa.array(np.concatenate(b or none))})

    return cells.join(sets.select("set_id", "hashes"), "set_id").groupBy("key", "i", "j").applyInArrow(compare, "a long, b long")


def cluster(docs: DataFrame, similar: float = SIMILAR) -> DataFrame:
    """doc_id, text_id, group, component_id for every document, by fingerprints and by shingle sets."""
    rows = stored(sketches(docs))
    known = rows.select("fp", "set_id").distinct()
    found = stored(simhash.components(simhash.links(stored(known.select("fp").distinct()))))
    # A hub stands for a component of fingerprints and joins the sets that it holds.
    hubs = known.join(found, "fp", "left").select("set_id", F.xxhash64(F.lit("hub"), F.coalesce("root", "fp")).alias("hub")).distinct()
    wide = hubs.groupBy("hub").agg(F.count("*").alias("n")).filter("n > 1").select("hub")
    edges = hubs.join(wide, "hub").select(F.col("set_id").alias("fp"), F.col("hub").alias("to"))
    roots = simhash.components(stored(edges.unionByName(links(rows, similar)))).withColumnRenamed("fp", "set_id")
    least = rows.groupBy("set_id").agg(F.min("doc_id").alias("least"))
    rooted = stored(least.join(roots, "set_id", "left").withColumn("root", F.coalesce("root", "set_id")))
    lowest = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    by_set = rooted.join(lowest, "root").select("set_id", F.col("root").alias("group"), "component_id")
    return rows.select("doc_id", "text_id", "set_id").join(by_set, "set_id").select("doc_id", "text_id", "group", "component_id")
