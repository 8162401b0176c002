"""Near copies of the pipeline against brute force over all pairs."""

import random

import corpus_pipeline
from levcut.llm import similar, simhash

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def _texts():
    rng = random.Random(5)
    out = []
    for length in (30, 60, 120, 400):
        for _ in range(6):
            base = [f"v{rng.randrange(3000)}" for _ in range(length)]
            out.append(" ".join(base))
            for changes in (1, 2, 3, 4, 6):
                copy = list(base)
                for at in rng.sample(range(length), max(1, changes * length // 100)):
                    copy[at] = f"c{rng.randrange(9999)}"
                out.append(" ".join(copy))
    return out + ["", None, "one", "one", "one two three four five", "One two  three four five", out[0].upper()]


def _sets(text):
    w = (text or "").lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def _groups(texts):
    """Brute force: components of pairs with similar sets or near fingerprints."""
    sets, marks = [_sets(t) for t in texts], [simhash.fingerprint(t or "") for t in texts]
    group = list(range(len(texts)))
    for a in range(len(texts)):
        for b in range(a):
            any_ = len(sets[a] | sets[b])
            if any_ == 0 or len(sets[a] & sets[b]) >= 0.8 * any_ or (marks[a] ^ marks[b]).bit_count() <= simhash.RADIUS:
                old, new = group[a], group[b]
                group = [new if g == old else g for g in group]
    return group


def test_pipeline_drops_all_similar_documents(spark):
    texts = _texts()
    docs = spark.createDataFrame([(i, t, "en", "a", 1) for i, t in enumerate(texts)], SCHEMA).repartition(3)
    group = _groups(texts)
    expected = {i: min(k for k, g in enumerate(group) if g == group[i]) for i in range(len(texts))}
    assert {r["doc_id"]: r["component_id"] for r in similar.cluster(docs).collect()} == expected
    kept = corpus_pipeline.drop_near_copies(spark, docs, "")
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(set(expected.values()))
    assert kept.columns == docs.columns
    assert similar.cluster(docs.limit(0)).count() == 0


def test_pairs_beyond_the_first_comparison(spark):
    """Copies of one text that are only similar to it, not to each other, and a chain."""
    base = [f"b{i}" for i in range(100)]
    texts = []
    for i in range(12):
        copy = list(base)
        copy[8 * i + 2], copy[(8 * i + 45) % 100] = f"x{i}", f"y{i}"
        texts.append(" ".join(copy))
    texts += [" ".join(base)]
    texts += [" ".join(f"s{i + 8 * k}" for i in range(100)) for k in range(6)]
    docs = spark.createDataFrame([(i, t, "en", "a", 1) for i, t in enumerate(texts)], SCHEMA)
    group = _groups(texts)
    expected = {i: min(k for k, g in enumerate(group) if g == group[i]) for i in range(len(texts))}
    assert {r["doc_id"]: r["component_id"] for r in similar.cluster(docs).collect()} == expected


def test_cells_give_the_links_of_all_pairs(spark):
    rng = random.Random(8)
    base = list(range(1, 120))
    made = []
    for _ in range(70):
        copy = set(base) - set(rng.sample(base, rng.randrange(2, 16)))
        made.append(sorted(copy | {1000 + rng.randrange(10**6) for _ in range(rng.randrange(1, 14))}))
    roots = [rng.randrange(6) if i % 3 else 100 + i for i in range(70)]
    buckets = spark.createDataFrame([(7, i, roots[i]) for i in range(70)] + [(8, i, roots[i]) for i in range(0, 70, 7)], "key long, set_id long, root long").repartition(3)
    sets = spark.createDataFrame([(i, len(x), x) for i, x in enumerate(made)], "set_id long, size int, hashes array<long>").repartition(3)
    jaccard = lambda a, b: len(set(a) & set(b)) / len(set(a) | set(b))
    expected = {(i, j) for j in range(70) for i in range(j) if roots[i] != roots[j] and jaccard(made[i], made[j]) >= 0.8}
    assert 20 < len(expected) < 2000
    for chunk_sets, chunk_shingles in ((1000, 10**6), (16, 10**6), (1000, 900)):
        got = similar.in_cells(buckets, sets, 0.8, chunk_sets, chunk_shingles)
        assert {(r["a"], r["b"]) for r in got.collect()} == expected


def test_pairs_and_cells_agree(spark):
    docs = spark.createDataFrame([(i, t, "en", "a", 1) for i, t in enumerate(_texts())], SCHEMA).repartition(3)
    rows = similar.stored(similar.sketches(docs))
    parts = []
    for paired in (0, 10**6):
        roots = {r["fp"]: r["root"] for r in simhash.components(similar.stored(similar.links(rows, paired=paired))).collect()}
        parts.append(roots)
    assert parts[0] == parts[1]
