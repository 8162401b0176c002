"""Brute-force checks of the training-data operators on a small table of hard cases."""

import hashlib
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
import xxhash

from levcut.llm import chat, cuckoo, decontaminate, exact_dedup, html_extract, labelled, licenses, mixing, quality, shards, simhash, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, shard string, score double"


def rows():
    rng = random.Random(3)
    vocabulary = [f"w{i}" for i in range(60)] + ["mit", "license", "apache", "general", "public"]
    texts = [" ".join(rng.choice(vocabulary) for _ in range(rng.randrange(1, 90))) for _ in range(60)]
    texts += [texts[0]] * 30 + [texts[1] + " ", texts[1].replace(" ", "\n\t", 1), texts[2].upper()]
    texts += ["", None, "   \n", "one", "one two", "é ü 日本 \x00x", "Released under the MIT License.", "x " * 20_000]
    near = texts[3].split() * 6
    for i in range(5):
        copy = list(near)
        copy[i] = "changed"
        texts.append(" ".join(copy))
    out = [(i, t, None, ["a", "b", None, "c"][i % 4], None, "x", 0.5) for i, t in enumerate(texts)]
    return out + [out[5], (None, texts[6], "en", "d", 1, "y", 0.1)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(rows(), SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(i, i % 2, (i // 2) % 2) for i in range(70)] + [(3, None, None), (None, 1, 1)], "doc_id long, quality int, toxic int")


def test_sharding(docs, empty):
    got = shards.assign(docs, 5).collect()
    assert len(got) == len(rows())
    groups = {}
    for _, text, *_ in rows():
        t = text or ""
        groups.setdefault(xxhash.xxh64_intdigest(t.encode(), 42), []).append(len(t.encode()) + 8)
    signed = sorted((h - (1 << 64) if h >> 63 else h, sum(s)) for h, s in groups.items())
    sizes = [s for _, s in signed]

    def shards_needed(capacity):
        n, held = 1, 0
        for s in sizes:
            if held + s > capacity:
                n, held = n + 1, 0
            held += s
        return n

    best = next(c for c in range(max(sizes), sum(sizes) + 1) if shards_needed(c) <= 5)
    by = {}
    for r in got:
        by.setdefault(r["shard"], []).append(r)
    assert max(sum(r["size"] for r in x) for x in by.values()) == best
    assert set(by) <= set(range(5))
    for x in by.values():
        assert sorted(r["slot"] for r in x) == list(range(len(x)))
    text = {i: t for i, t, *_ in rows() if i is not None}
    for r in got:
        if r["doc_id"] is not None:
            assert r["text_crc32"] == zlib.crc32((text[r["doc_id"]] or "").encode())
    assert len({(t or "") for t in text.values()}) == len({(text[r["doc_id"]] or "", r["shard"]) for r in got if r["doc_id"] is not None})
    assert shards.assign(empty).count() == 0


def test_sharding_levels(spark):
    rng = random.Random(1)
    g = sorted({rng.randrange(-(1 << 63), 1 << 63): rng.randrange(1, 100) for _ in range(3000)}.items())
    frame = spark.createDataFrame(g, "hash long, bytes long")
    whole = shards.cut_hashes(frame, 7)
    assert whole == shards.cut_hashes(frame, 7, fetch=1, first_bits=8) or max(_sums(g, whole)) == max(_sums(g, shards.cut_hashes(frame, 7, fetch=1, first_bits=8)))


def _sums(g, cuts):
    out = [0] * (len(cuts) + 1)
    for h, s in g:
        out[sum(c is not None and h >= c for c in cuts)] += s
    return out


def test_licenses(docs, empty):
    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    expected = []
    for i, text, *_ in rows():
        w = word.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
        hits = [(k, label) for k in range(len(w)) for p, label in licenses.BASE.items() if w[k : k + len(p.split())] == p.split()]
        at = [k for k, _ in hits]
        expected.append((i, len(w), len(at), min(at, default=None), max(at, default=None), ",".join(sorted({x for _, x in hits}))))
    got = licenses.scan(docs).collect()
    key = lambda r: tuple(str(x) for x in r)
    assert sorted((tuple(r)[:6] for r in got), key=key) == sorted(expected, key=key)
    for r in got:
        assert set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(","))
        assert 0 <= r["score"] <= 1
    assert licenses.scan(empty).count() == 0


def test_license_suppression(spark):
    text = "SPDX-License-Identifier: Apache-2.0\nThis is licensed under the GNU General Public License version 3. Copyright 2001"
    r = licenses.scan(spark.createDataFrame([(1, text)], "doc_id long, text string")).first()
    assert r["labels"] == "apache-2.0,copyright-notice,gpl,gpl-3.0"
    assert len(licenses.rules()) > 250
    spans = [(d["start"], d["end"]) for d in r["detections"]]
    low = text.lower()
    assert any(low[a:b].startswith("licensed under the gnu general public") for a, b in spans)


def test_exact_dedup(docs, empty):
    groups = {}
    for i, text, *_ in rows():
        groups.setdefault(re.sub(r"[\x20\x09-\x0D]", "", text or ""), []).append((i, len(text or "")))
    expected = []
    for normal, members in groups.items():
        most = max(n for _, n in members)
        ids = [i for i, n in members if n == most and i is not None]
        keep = min(ids) if ids else None
        digest = hashlib.sha256(normal.encode()).hexdigest()
        expected += [(i, keep, len(members), i == keep, digest) for i, _ in members]
    key = lambda r: tuple(str(x) for x in r)
    assert sorted(map(tuple, exact_dedup.dedup(docs).collect()), key=key) == sorted(expected, key=key)
    assert exact_dedup.dedup(empty).count() == 0
    small = exact_dedup.groups(exact_dedup.digests(docs), live=4).collect()
    assert sorted(r["members"] for r in small) == sorted(map(len, groups.values()))


def test_cuckoo_index():
    index, held, rng = cuckoo.CuckooIndex(8), {}, random.Random(2)
    keys = [hashlib.sha256(str(i).encode()).digest() for i in range(2000)]
    for i in range(12_000):
        k = rng.choice(keys)
        if rng.random() < 0.3:
            assert index.delete(k) == (held.pop(k, None) is not None)
        else:
            index.insert(k, i)
            held[k] = i
    assert dict(index.items()) == held and len(index) == len(held) and index.resizes > 3
    assert all((k in index) == (k in held) for k in keys)


def test_mixing(docs, empty):
    got = mixing.mixed(docs).collect()
    size = {}
    for _, text, _, source, *_ in rows():
        size[source] = size.get(source, 0) + len(re.findall(r"[^\x20\x09-\x0D]+", text or ""))
    order = sorted(size, key=lambda s: (s is None, s or ""))
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}
    full, total = set(), sum(size.values())
    while True:
        rest = total - sum(3 * size[s] for s in full)
        free = [s for s in order if s not in full]
        goal = {s: rest * weight[s] / sum(weight[x] for x in free) for s in free}
        over = {s for s in free if goal[s] > 3 * size[s]}
        if not over:
            break
        full |= over
    goal |= {s: 3 * size[s] for s in full}
    source = {(i, s) for i, _, _, s, *_ in rows()}
    assert abs(sum(goal.values()) - total) < 1e-6
    for r in got:
        s = next(s for i, s in source if i == r["doc_id"])
        assert abs(r["target"] - goal[s]) < 1e-5 and r["source_size"] == size[s]
        assert 0 <= r["taken"] <= 3 * r["size"]
    assert mixing.mixed(empty).count() == 0
    planned = mixing.plan(docs)
    emitted = mixing.emit(planned, ["doc_id", "text"])
    assert emitted.count() == sum(r["copies"] for r in planned.select("copies").collect())


def test_decontamination(spark, docs, empty):
    rng = random.Random(5)
    long = [t for _, t, *_ in rows() if t and len(t.split()) > 30][:6]
    items = [(i, " ".join(t.split()[k : k + 14])) for i, t in enumerate(long) for k in [rng.randrange(5)]]
    items += [(50, "one two"), (51, ""), (52, None), (53, "Released, under"), (0, items[0][1]), (54, "zz yy xx ww vv uu tt ss rr qq pp")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    windows = {}
    for item, text in items:
        w = decontaminate.words(text)
        n = min(10, len(w))
        for k in range(len(w) - n + 1 if n else 0):
            windows.setdefault(tuple(w[k : k + n]), set()).add(item)
    expected = []
    for i, text, *_ in rows():
        w, hit, found = decontaminate.words(text), set(), set()
        for n in {len(x) for x in windows}:
            for k in range(len(w) - n + 1):
                if tuple(w[k : k + n]) in windows:
                    hit.update(range(k, k + n))
                    found |= windows[tuple(w[k : k + n])]
        digest = hashlib.sha256(",".join(sorted(map(str, found))).encode()).hexdigest()
        expected.append((i, len(w), len(hit), len(found), digest, bool(hit)))
    key = lambda r: tuple(str(x) for x in r)
    for limit, held in ((200_000, 1 << 20), (7, 1 << 20), (7, 1)):
        got = decontaminate.flag(docs, bench, limit=limit, held_bytes=held).select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")
        assert sorted(map(tuple, got.collect()), key=key) == sorted(expected, key=key)
    assert any(x[-1] for x in expected) and not all(x[-1] for x in expected)
    assert decontaminate.clean(docs, bench).columns == docs.columns
    odd = docs.withColumnRenamed("lang", "spans_").withColumnRenamed("source", "contaminated").withColumnRenamed("shard", "a b.c")
    cleaned = decontaminate.clean(odd, bench)
    assert cleaned.columns == odd.columns
    assert sorted(r["doc_id"] or -1 for r in cleaned.collect()) == sorted((x[0] or -1) for x in expected if not x[-1])
    assert decontaminate.flag(empty, bench).count() == 0
    assert decontaminate.flag(docs, bench.limit(0)).filter("contaminated").count() == 0


def _plain_fingerprint(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not w:
        return 0
    shingles = [" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_simhash(docs, empty):
    listed = [(i, _plain_fingerprint(t)) for i, t, *_ in rows()]
    group = list(range(len(listed)))
    for a in range(len(listed)):
        for b in range(a):
            if (listed[a][1] ^ listed[b][1]).bit_count() <= 3:
                old, new = group[a], group[b]
                group = [new if g == old else g for g in group]
    least = {}
    for (i, _), g in zip(listed, group, strict=True):
        if i is not None:
            least[g] = min(i, least.get(g, i))
    expected = [(i, f"{fp:016x}", least.get(g)) for (i, fp), g in zip(listed, group, strict=True)]
    key = lambda r: tuple(str(x) for x in r)
    assert sorted(map(tuple, simhash.near_duplicates(docs).collect()), key=key) == sorted(expected, key=key)
    for bands in (1, 2, 5, 6):
        found = simhash.cluster(docs, bands=bands).select("doc_id", "component_id").collect()
        assert sorted(map(tuple, found), key=key) == sorted([(a, c) for a, _, c in expected], key=key)
    assert simhash.near_duplicates(empty).count() == 0
    kept = simhash.keep_one(docs)
    ids = [r["doc_id"] for r in kept.select("doc_id").collect() if r["doc_id"] is not None]
    assert sorted(ids) == sorted(set(least.values())) and kept.columns == docs.columns


def test_keep_one_by_row_not_by_id(spark):
    rng = random.Random(11)
    text = lambda: " ".join(f"u{rng.randrange(10**6)}" for _ in range(40))
    a, b, c, d, e = (text() for _ in range(5))
    made = [(5, a), (5, b), (3, c), (7, c), (7, d), (7, d), (None, e), (None, e), (9, e), (None, None)]
    docs = spark.createDataFrame([(i, t, "x", "y", 1) for i, t in made], "doc_id long, text string, kept string, key string, n long").repartition(3)
    from levcut.llm import similar

    for found in (None, similar.cluster(docs.select("doc_id", "text"))):
        kept = simhash.keep_one(docs, found)
        assert kept.columns == docs.columns
        assert sorted((r["doc_id"] or -1, r["text"]) for r in kept.filter("text is not null").collect()) == sorted([(5, a), (5, b), (3, c), (7, d), (9, e)])
        assert kept.filter("text is null").count() == 1


def test_keys_of_near_fingerprints_meet_at_any_count():
    rng = np.random.default_rng(3)
    for bands in range(4, 7):
        keys = simhash.key_bands(bands, 3)
        for _ in range(300):
            x = rng.integers(0, 2**64, dtype=np.uint64, size=1)
            y = x.copy()
            for bit in rng.choice(64, 3, replace=False):
                y ^= np.uint64(1) << np.uint64(bit)
            assert any(simhash.key_values(x, bands, k)[0] == simhash.key_values(y, bands, k)[0] for k in keys)
    assert [simhash.bands_for(10**k) for k in (3, 7, 9, 12)] == [4, 4, 5, 6]


def test_parts_of_leaves_lose_no_link(spark):
    rng = random.Random(12)
    base = [rng.getrandbits(64) for _ in range(700)]
    near = [x ^ (1 << rng.randrange(64)) ^ (1 << rng.randrange(64)) for x in base[:300]]
    signed = sorted({x - (1 << 64) if x >> 63 else x for x in base + near})
    frame = spark.createDataFrame([(x,) for x in signed], "fp long").repartition(4)
    for bands, sample in ((None, 8192), (None, 16), (5, 16), (1, 64)):
        found = simhash.components(simhash.links(frame, 3, bands, sample, 16)).collect()
        root = {r["fp"]: r["root"] for r in found}
        for a, b in zip(base[:300], near, strict=True):
            a, b = (x - (1 << 64) if x >> 63 else x for x in (a, b))
            assert root.get(a, a) == root.get(b, b)


def test_vantage_point_search_is_exact():
    rng = np.random.default_rng(0)
    base = rng.integers(0, 1 << 63, 40, dtype=np.uint64)
    values = np.unique(np.concatenate([b ^ (np.uint64(1) << rng.integers(0, 63, 60, dtype=np.uint64)) for b in base]))
    forest = simhash.Forest(len(values))
    simhash.link_all(values, 3, forest, leaf=16)
    plain = simhash.Forest(len(values))
    x, y = np.nonzero(np.bitwise_count(values[:, None] ^ values[None, :]) <= 3)
    plain.link_hits(x, y)
    same = lambda f: [f.root(i) for i in range(len(values))]
    assert same(forest) == same(plain)
    tree = simhash.VantageTree(values, 4, 8)
    r, leaf, home = tree.visit(values, 3)
    at = {(int(a), int(b)) for a, b in zip(r, leaf, strict=True)}
    own = dict(zip(r[home].tolist(), leaf[home].tolist(), strict=True))
    assert all((int(a), own[int(b)]) in at for a, b in zip(x, y, strict=True))


def test_quality_and_toxicity_edges(docs, empty, labels):
    for module, name in ((quality, "quality"), (toxicity, "toxic")):
        got = module.judge(docs, labels).collect()
        assert len(got) == len(rows())
        modulus, rest = module.HOLD_OUT
        for r in got:
            assert 0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.7)
            assert r["held_out"] == (r["doc_id"] is not None and zlib.crc32(str(r["doc_id"]).encode()) % modulus == rest)
        assert module.judge(empty, labels).count() == 0
        assert module.judge(docs, labels.limit(0)).count() == len(rows())
        taken, _ = labelled.sample(docs, labels, name, modulus, rest)
        assert all(zlib.crc32(str(i).encode()) % modulus != rest for i, _, _ in taken)


def test_quality_long_texts_are_whole():
    net = quality.fit([(b"good text here. " * 9, 1), (b"*** %%% $$$ &&& " * 9, 0)] * 12, 0.8, least_steps=60)
    clean = b"good text here. " * 40_000
    a, b = quality.probabilities(net, [clean, clean[: quality.PIECE * 2] + b"*** %%% $$$ &&& " * 60 + clean[quality.PIECE * 2 :]])
    assert a > b
    many = quality.probabilities(net, [b"", b"x", clean[:500]])
    one = [quality.probabilities(net, [x])[0] for x in (b"", b"x", clean[:500])]
    assert np.allclose(many, one, atol=1e-6)


def plain_probability(net, text):
    """The network by loops over windows, groups and chunks of one text."""
    unit = quality.STEP * quality.GROUP
    n = max(1, -(-(len(text) + quality.PAD) // unit))
    data = bytes(quality.PAD) + text + bytes(n * unit - len(text))
    filters = net.filters.reshape(quality.STEP * quality.DIM, quality.TAPS, quality.FILTERS).transpose(1, 0, 2).reshape(-1, quality.FILTERS)
    window = lambda i: np.maximum(net.embed[list(data[i : i + quality.WIDTH])].ravel() @ filters + net.bias, 0)
    groups = [np.max([window(g * unit + k * quality.STEP) for k in range(quality.GROUP)], 0) for g in range(n)]
    chunks = [np.max(groups[s : s + quality.CHUNK], 0) for s in range(0, max(1, n - (quality.CHUNK - quality.HOP)), quality.HOP)]
    features = np.concatenate([np.mean(chunks, 0), np.min(chunks, 0), np.max(chunks, 0)])
    return 1 / (1 + np.exp(-(features @ net.out + net.shift)))


def test_quality_network_is_the_plain_one():
    net = quality.fit([(b"good text here. " * 9, 1), (b"*** %%% $$$ &&& " * 9, 0)] * 12, 0.8, least_steps=30)
    rng = random.Random(8)
    texts = [b"", b"a", *(bytes(rng.randrange(256) for _ in range(k)) for k in (5, 24, 25, 255, 256, 257, 700, 3000))]
    assert np.allclose(quality.probabilities(net, texts), [plain_probability(net, x) for x in texts], atol=1e-5)
    for text in texts:
        whole = quality._long(net, text, 1 << 30)
        assert all(np.allclose(quality._long(net, text, k), whole, atol=1e-6) for k in (1, 2, 5))


def test_quality_pieces_of_training_texts_are_whole():
    rows = [(b"x" * 100_000, 1), (b"", 0), (b"abc", 1)]
    got = quality.pieces(rows)
    assert [sum(len(t) for t, y, _ in got if y == k) for k in (0, 1)] == [0, 100_003]
    assert np.isclose(sum(w for _, _, w in got), 3)


def test_accept_keeps_clashing_columns(docs, labels):
    odd = docs.withColumnRenamed("lang", "text_").withColumnRenamed("source", "kept")
    got = quality.accept(odd, labels)
    assert got.columns == odd.columns
    assert got.count() <= odd.count()


def toxic_rows():
    import duckdb

    d = "/root/testdata/sf0.1"
    found = duckdb.execute(f"SELECT doc_id, text, toxic FROM '{d}/documents.parquet' JOIN '{d}/labels.parquet' USING (doc_id) ORDER BY doc_id").fetchall()
    return [(i, Counter(toxicity.words(t)), y, zlib.crc32(str(i).encode()) % 3 == 1) for i, t, y in found]


def test_toxicity_held_out_accuracy_and_plain_cosine():
    rows_ = toxic_rows()
    train = [r[:3] for r in rows_ if not r[3]]
    train = sorted([r for r in train if r[2]] + [r for r in train if not r[2]][:1000])
    space = {w for _, counts, _ in train for w in counts}
    seen = Counter(w for _, counts, _, _ in rows_ for w in counts if w in space)
    model = toxicity.Model(train, seen, len(rows_))
    assert len(model.ids) >= 0.99 * sum(bool(c) for _, c, _ in train), "every labelled text with words is an example"
    spelled = [" ".join(w.decode("utf-8", "replace") for w in c.elements()) for _, c, _, _ in rows_]
    test = [(model.score(t), r[2]) for t, r in zip(spelled, rows_, strict=True) if r[3]]
    hits = sum(s >= 0.7 and y for (s, _), y in test)
    assert hits / max(1, sum(s >= 0.7 for (s, _), _ in test)) > 0.85 and hits / sum(y for _, y in test) > 0.85
    assert sum(not e for (_, e), _ in test) < 0.05 * len(test)
    # Neighbours and their cosines by brute force over dictionaries.
    examples = {doc: dict(zip(*(x.tolist() for x in model.vector(c)), strict=True)) for doc, c, _ in train}
    for _, counts, _, held in rows_[:60]:
        if held:
            q = dict(zip(*(x.tolist() for x in model.vector(counts)), strict=True))
            plain = sorted((-sum(w * v.get(t, 0) for t, w in q.items()), doc) for doc, v in examples.items())[: model.k]
            got = model.score(" ".join(w.decode() for w in counts.elements()))[1]
            assert np.allclose([s for _, s, _ in got], [-s for s, _ in plain if s < 0][: len(got)])


def test_block_max_is_exact():
    rng = random.Random(4)

    def make():
        terms = np.array(rng.sample(range(30), rng.randrange(1, 9)))
        return terms, np.array([rng.choice([0.25, 0.5, rng.random()]) for _ in terms])

    vectors = [make() for _ in range(900)]
    index = toxicity.BlockMaxIndex(vectors, 30, 8)
    for trial in range(60):
        terms, weights = make() if trial % 3 else vectors[trial]
        q = dict(zip(terms.tolist(), weights.tolist(), strict=True))
        plain = sorted(((sum(w * q.get(t, 0) for t, w in zip(*v, strict=True)), i) for i, v in enumerate(vectors)), key=lambda x: (-round(x[0], 9), x[1]))
        got = index.nearest(terms, weights, 7)
        assert np.allclose([s for s, _ in got], [s for s, _ in plain[:7] if s > 0])
        assert index.nearest(terms, weights, 7, plain[0][1])[0][1] != plain[0][1]
    assert index.visited < 60 * 2 * index.blocks
    assert toxicity.BlockMaxIndex([], 3).nearest(np.array([1]), np.array([1.0]), 4) == []


def test_html(spark):
    page = (
        '<html><head><title>no</title><script>var x="<p>no</p>";</script></head><body><header>Site</header><nav><a href="/">Home</a></nav>'
        '<article><h1>Title &amp; more</h1><p>First <b>par</b>agraph,\n  with a good many words in it.<p>Second one, also rather long.</article>'
        '<div class="ad">Buy now and save.</div><div id="comments"><p>A reader says something here at length.</p></div><footer>&copy; us</footer>'
    )
    frame = spark.createDataFrame([(1, "u", page), (2, None, None), (3, "v", ""), (1, "u", page), (4, "w", "plain text only, but it is a sentence of some length.")], "page_id long, url string, html string")
    got = {r["page_id"]: r for r in html_extract.extract(frame.withColumn("text", frame["url"])).collect()}
    assert got[1]["text"] == "Title & more First paragraph, with a good many words in it. Second one, also rather long."
    assert got[2]["text"] == "" and got[3]["n_chars"] == 0
    assert html_extract.extract(frame.limit(0)).count() == 0
    network = html_extract.FlowNetwork(4)
    for a, b, c in ((2, 0, 3.0), (0, 1, 2.0), (1, 3, 5.0)):
        network.join(a, b, c)
    assert network.source_side(2, 3) == [True, False, True, False]


LONG = "A long paragraph that goes on for a while, with many words in it and a full stop at its end, as paragraphs have them."


def page_of(*lines):
    return "".join(lines).replace("%s", LONG)


@pytest.mark.parametrize("name", ["content has-sidebar", "post comments-open", "post category-search", "entry no-comments share-enabled"])
@pytest.mark.parametrize("tag", ["div", "article"])
def test_html_names_that_only_hint_lose_nothing(name, tag):
    got = html_extract.main_text(page_of(f'<body><{tag} class="{name}"><h1>Title</h1><p>%s</p><p>Yes.</p></{tag}>'))
    assert got == f"Title {LONG} Yes."


def test_html_cut_differs_from_the_sign_and_is_right():
    page = page_of(
        '<body><div class="site-header"><p>%s</p></div><div><h1>Title</h1><div>By Ann</div><p>%s</p><ul><li>Milk</li><li>Bread</li><li>Salt</li></ul><p>%s</p></div>',
        '<div class="sidebar"><div><p>%s</p><p>%s</p></div></div><section id="comments"><article><p>%s</p></article><article class="comment"><p>%s</p></article></section>',
        '<div class="cookie-notice"><p>%s</p></div><div><ul><li><a href="/a">More</a></li><li><a href="/b">Others</a></li></ul></div>',
    )
    found, elements = html_extract.blocks(page)
    kept = html_extract.label(found, elements)
    assert html_extract.main_text(page) == f"Title By Ann {LONG} Milk Bread Salt {LONG}"
    costs, _ = html_extract.graph(found, elements)
    changed = [found[i].text for i in range(len(found)) if (costs[i] > 0) != kept[i]]
    assert {"By Ann", "Milk", "Bread", "Salt"} <= set(changed) and changed.count(LONG) == 6


def test_html_cut_is_the_minimum():
    rng = random.Random(9)
    lines = ["<p>%s</p>", "<p>No.</p>", "<div>word</div>", "<ul><li>a</li><li><a>b</a></li></ul>", '<div class="ad"><p>%s</p></div>', "<aside><p>x y</p></aside>", "<article><p>%s</p></article>"]
    for _ in range(60):
        found, elements = html_extract.blocks(page_of(*(rng.choice(lines) for _ in range(rng.randrange(1, 6)))))
        costs, edges = html_extract.graph(found, elements)
        if len(costs) > 13:
            continue

        def cost(side):
            """Capacity cut: costs of the wrong side and edges between the sides."""
            return sum(max(c, 0) if not s else max(-c, 0) for c, s in zip(costs, side, strict=True)) + sum(w for a, b, w in edges if side[a] != side[b])

        best = min(cost([m >> i & 1 for i in range(len(costs))]) for m in range(1 << len(costs)))
        kept = html_extract.label(found, elements)
        free = len(costs) - len(found)
        got = min(cost([*kept, *(m >> i & 1 for i in range(free))]) for m in range(1 << free))
        assert abs(got - best) < 1e-9


def test_html_long_pages_are_whole():
    got = html_extract.main_text(page_of("<article>", *["<p>%s</p>"] * 3000, "</article>", *['<div class="ad"><p>%s</p></div>'] * 300))
    assert got == " ".join([LONG] * 3000)
    assert html_extract.main_text("<div>" * 3000 + LONG + "</div>" * 3000) == LONG


def test_chat(spark):
    turns = [(1, 0, "ann", "hi"), (1, 1, "bob", "<|end|> yo"), (1, 2, "ann", None), (1, 2, "ann", None), (2, None, None, "alone"), (None, 3, "x", "é")]
    frame = spark.createDataFrame(turns, "conv_id long, turn long, role string, text string")
    got = chat.rotate(frame)
    assert got.count() == 4 * 2 + 1 + 1
    whole = {(r["conv_id"], r["perspective"]): r for r in chat.assemble(got).collect()}
    text = whole[1, "bob"]["rendered"]
    assert text == "<|user name=ann|>\nhi<|end|>\n<|assistant|>\n< |end|> yo<|end|>\n" + "<|user name=ann|>\n<|end|>\n" * 2
    (a, b), = whole[1, "bob"]["mask"]
    assert text[a:b] == "< |end|> yo<|end|>\n"
    assert len(whole[1, "ann"]["mask"]) == 3
    many = spark.createDataFrame([(7, i, f"r{i % 3}", "x" * (i % 5)) for i in range(3000)], "conv_id long, turn long, role string, text string")
    at = {}
    for r in chat.rotate(many).orderBy("perspective", "turn").collect():
        assert r["start_char"] == at.get(r["perspective"], 0) and r["end_char"] - r["start_char"] == len(r["segment"])
        at[r["perspective"]] = r["end_char"]
    assert chat.rotate(frame.limit(0)).count() == 0


def test_pipeline(spark):
    import corpus_pipeline
    from levcut.llm.common import table

    d = "/root/testdata/sf0.001"
    docs = table(spark, d, "documents")
    sizes = [docs.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, d)
        assert docs.columns == corpus_pipeline.COLUMNS, name
        sizes.append(docs.count())
    assert sizes[0] >= sizes[1] >= sizes[2] >= sizes[3] > 0
    out = corpus_pipeline.run(spark, d)
    assert out.count() == sizes[4]
