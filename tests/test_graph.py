"""Golden fixtures, identities and brute force for the graph half."""

import hashlib
import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from levcut.operators import graph, local, models, multilevel, probes, resistance, small, spectral

#: A public club network of 34 nodes, larger neighbours only.
CLUB = {
    1: "2 3 4 5 6 7 8 9 11 12 13 14 18 20 22 32", 2: "3 4 8 14 18 20 22 31", 3: "4 8 9 10 14 28 29 33", 4: "8 13 14", 5: "7 11", 6: "7 11 17",
    7: "17", 9: "31 33 34", 10: "34", 14: "34", 15: "33 34", 16: "33 34", 19: "33 34", 20: "34", 21: "33 34", 23: "33 34", 24: "26 28 30 33 34",
    25: "26 28 32", 26: "32", 27: "30 34", 28: "34", 29: "32 34", 30: "33 34", 31: "33 34", 32: "33 34", 33: "34",
}
EDGES = [(a, int(b), 1.0) for a, bs in CLUB.items() for b in bs.split()]


@pytest.fixture(scope="module")
def club(spark):
    return spark.createDataFrame(EDGES, "src long, dst long, w double").cache()


def test_club_edge_leverage(club):
    g = small.SmallGraph(EDGES)
    assert (g.n, len(EDGES)) == (34, 78)
    scores = resistance.exact(club)
    row = resistance.check(club, scores).first()
    assert abs(row["total"] - 33) < 1e-8 and row["expected"] == 33.0
    one = scores.filter("src = 1 and dst = 12").first()
    assert abs(one["leverage"] - 1) < 1e-9
    assert abs(scores.agg(F.min("leverage")).first()[0] - 0.142) < 5e-4


def test_club_spectral(club):
    lam, vector = small.SmallGraph(EDGES).fiedler()
    phi, side = small.SmallGraph(EDGES).sweep(vector)
    assert abs(lam - 0.13227) < 1e-4 and abs(phi - 10 / 76) < 1e-9
    assert lam / 2 <= phi <= np.sqrt(2 * lam)
    found, quotient = spectral.fiedler(club, 60)
    best = graph.best_prefix(spectral.sweep(club, found)).first()
    assert abs(quotient - lam) < 2e-3 and abs(best["phi"] - 10 / 76) < 0.02


def test_exact_profiles():
    path = small.SmallGraph([(i, i + 1, 1) for i in range(7)])
    assert np.allclose([path.profile()[k] for k in (1, 2, 3, 4)], [1, 1 / 3, 1 / 5, 1 / 7])
    clique = lambda at: [(a, b, 1) for a, b in itertools.combinations(range(at, at + 4), 2)]
    two = small.SmallGraph([*clique(0), *clique(4), (3, 4, 1)])
    assert np.allclose([two.profile()[k] for k in (1, 2, 3, 4)], [1, 2 / 3, 1 / 3, 1 / 13])
    star = small.SmallGraph([(0, i, 1) for i in range(1, 6)])
    assert all(abs(p - 1) < 1e-9 for p in star.profile().values())
    assert len(path.bridges()) == 7 and two.bridges() == [(3, 4)]


def test_scores_and_sweep_agree(spark, club):
    sets = spark.createDataFrame([(s, n) for s, ns in (("a", range(1, 12)), ("b", [34, 33]), ("all", range(1, 35))) for n in ns], "set_id string, node long")
    g = small.SmallGraph(EDGES)
    rows = {r["set_id"]: r for r in graph.score(club, sets).collect()}
    side = [g.ids.index(n) for n in range(1, 12)]
    assert abs(rows["a"]["conductance"] - g.phi(side)) < 1e-9
    assert rows["all"]["conductance"] is None
    for r in rows.values():
        if r["conductance"]:
            assert r["conductance"] <= r["conductance_product"] <= 2 * r["conductance"] + 1e-9
    values = spark.createDataFrame([(0, n, float(40 - n)) for n in range(1, 35)], "seed_id int, node long, value double")
    swept = {r["rank"]: r["phi"] for r in graph.sweep(club, values).collect()}
    assert all(abs(swept[k] - g.phi(range(k))) < 1e-9 for k in (1, 5, 20, 33)) and swept[34] is None


def test_push_keeps_mass_and_equals_the_walk(spark, club):
    seeds = spark.createDataFrame([(7, 1), (9, 34)], "seed_id long, node long")
    state = local.ppr(club, seeds, 0.2, 1e-3).collect()
    g = small.SmallGraph(EDGES)
    a = g.adjacency()
    w = 0.5 * (np.eye(34) + a / g.degree)
    for seed in (7, 9):
        p, r = np.zeros(34), np.zeros(34)
        for x in state:
            if x["seed_id"] == seed:
                p[g.ids.index(x["node"])], r[g.ids.index(x["node"])] = x["p"], x["r"]
        assert abs(p.sum() + r.sum() - 1) < 1e-9 and (r < 1e-3 * g.degree + 1e-12).all()
        start = np.zeros(34)
        start[g.ids.index(1 if seed == 7 else 34)] = 1
        rank = lambda s: 0.2 * np.linalg.solve(np.eye(34) - 0.8 * w, s)
        assert np.allclose(p + rank(r), rank(start), atol=1e-9)


def test_bridges_and_whiskers(spark):
    rng = random.Random(3)
    rows = {(min(a, b), max(a, b)) for a, b in ((rng.randrange(40), rng.randrange(40)) for _ in range(60)) if a != b}
    rows |= {(rng.randrange(40), 40 + i) for i in range(6)} | {(45, 46), (46, 47)}
    edges = spark.createDataFrame([(a, b, 1.0) for a, b in rows], "src long, dst long, w double")
    g = small.SmallGraph((a, b, 1.0) for a, b in rows)
    exact = {(g.ids[i], g.ids[j]) for i, j in g.bridges()}
    assert {(r["src"], r["dst"]) for r in probes.bridges(edges).collect()} == exact
    big = graph.giant(edges).cache()
    roles = probes.decompose(big)
    scored = graph.score(big, roles.filter("role = 'whisker'").select(F.col("whisker_id").alias("set_id"), "node"))
    assert all(r["cut"] == 1.0 for r in scored.collect())
    summary = probes.whisker_summary(big, roles)
    best = {r["size"]: r["phi"] for r in probes.bag(summary).collect()}
    kinds = [(r["size"], r["vol"]) for r in summary.collect()]
    for n in range(1, min(5, len(kinds)) + 1):
        for chosen in itertools.combinations(kinds, n):
            size = sum(s for s, _ in chosen)
            assert best[size] <= n / sum(v for _, v in chosen) + 1e-9


def test_flow_improvement_is_best_subset():
    rng = random.Random(8)
    for _ in range(15):
        rows = [(a, b, rng.randrange(1, 4)) for a, b in itertools.combinations(range(10), 2) if rng.random() < 0.4]
        g = small.SmallGraph(rows)
        side = [i for i in range(g.n) if rng.random() < 0.5]
        if not side or g.degree[side].sum() * 2 > g.volume:
            continue
        subsets = (c for k in range(1, len(side) + 1) for c in itertools.combinations(side, k))
        assert abs(g.improve(side)[0] - min(g.phi(c) for c in subsets)) < 1e-9


def test_bounds_hold():
    rng = random.Random(4)
    g = small.SmallGraph([(a, b, 1) for a, b in itertools.combinations(range(12), 2) if rng.random() < 0.45])
    exact = g.exact()[0]
    lam, vector = g.fiedler()
    assert lam / 2 <= exact + 1e-9 <= g.sweep(vector)[0] + 2e-9
    assert small.metric_cut(g)[0] >= exact - 1e-9 and small.cut_matching(g)[0] >= exact - 1e-9
    even = [s for k in range(1, g.n) for s in itertools.combinations(range(g.n), k) if 0.25 * g.volume <= g.degree[list(s)].sum() <= 0.75 * g.volume]
    assert small.sdp_bound(g, 0.25) <= min(g.cut(set(s)) for s in even) + 1e-6


def test_improvement_partition_betweenness():
    g = small.SmallGraph(EDGES)
    start = [g.ids.index(n) for n in (1, 2, 3, 4, 8)]
    assert small.spectral_improve(g, start)[0] <= g.phi(start)
    parts = small.kway(g, 4)
    assert set(parts) == {0, 1, 2, 3}
    path = small.SmallGraph([(i, i + 1, 1) for i in range(4)])
    assert [small.betweenness(path)[i, i + 1] for i in range(4)] == [8.0, 12.0, 12.0, 8.0]


def test_components_distances_cores(spark):
    edges = models.path(spark, 60).unionByName(models.ring(spark, 8).select((F.col("src") + 100).alias("src"), (F.col("dst") + 100).alias("dst"), "w"))
    assert {(r["component"], r["count"]) for r in graph.components(edges).groupBy("component").count().collect()} == {(0, 60), (100, 8)}
    far = graph.bfs(edges, spark.createDataFrame([(100,)], "node long")).agg(F.max("dist")).first()[0]
    assert far == 4 and graph.peel(edges, 2).count() == 8
    assert graph.components(edges.limit(0)).count() == 0


def test_models_and_profiles(spark):
    e = models.expander(spark, 101, 6)
    assert graph.degrees(e).agg(F.max("deg")).first()[0] <= 6
    twin = models.rewired(e, 3)
    assert abs(twin.count() - e.count()) <= 0.15 * e.count()
    lattice = models.lattice(spark, 14).cache()
    curve = {r["bin"]: r["phi"] for r in probes.profile(probes.local_profile(lattice, 3, (0.02,), 1e-4)).collect()}
    assert curve[2.0] > curve[16.0] > curve[64.0]
    for make in (models.copying(spark, 200), models.forest_fire(spark, 100), models.geometric(spark, 200, 0.1), models.power_law(spark, 200, 4, 2.5), models.core_periphery(spark, 50, 20), models.hierarchical(spark, 4)):
        assert make.filter("src >= dst").count() == 0 and make.count() > 0


def test_matching_pairs_neighbours_and_leaves(spark):
    star = spark.createDataFrame([(0, i, 1.0) for i in range(1, 10)], "src long, dst long, w double")
    parents = {r["node"]: r["parent"] for r in multilevel.match(star, multilevel.volumes(star)).collect()}
    assert set(parents) == set(range(10))
    sizes = sorted(sum(p == q for p in parents.values()) for q in set(parents.values()))
    assert sizes == [2, 2, 2, 2, 2]
    coarse, mass = multilevel.contract(star, multilevel.volumes(star), spark.createDataFrame(list(parents.items()), "node long, parent long"))
    assert mass.agg(F.sum("mass")).first()[0] == 18.0
    assert coarse.agg(F.sum("w")).first()[0] == 8.0


def test_multilevel_on_a_graph_over_the_limit(spark):
    rng = random.Random(5)
    blocks = {(min(a, b), max(a, b)) for k in (0, 100) for _ in range(500) for a, b in [(k + rng.randrange(100), k + rng.randrange(100))] if a != b}
    rows = [(a, b, 1.0) for a, b in sorted(blocks)] + [(i, 100 + i, 1.0) for i in range(4)]
    e = spark.createDataFrame(rows, "src long, dst long, w double").cache()
    sides = multilevel.bisect(e, coarsest=30)
    assert sides.count() == small.SmallGraph(rows).n
    assert {r["cut"] for r in multilevel.summary(e, sides.withColumnRenamed("side", "part")).collect()} == {4.0}
    parts = multilevel.kway(e, 4, coarsest=30)
    assert parts.select("part").distinct().count() == 4 and parts.count() == sides.count()


def test_refinement_never_raises_the_cut_and_keeps_balance(spark, club):
    g = small.SmallGraph(EDGES)
    masses = multilevel.volumes(club)
    start = masses.select("node", (F.col("node") % 2).cast("int").alias("side"))
    before = g.cut({g.ids.index(r["node"]) for r in start.filter("side = 1").collect()})
    for rounds in (1, 3):
        after = {g.ids.index(r["node"]) for r in multilevel.refine(club, masses, start, 0.3, rounds).filter("side = 1").collect()}
        assert g.cut(after) < before
        assert 0.3 * g.volume <= g.degree[list(after)].sum() <= 0.7 * g.volume


def test_distributed_betweenness(spark, club):
    g = small.SmallGraph(EDGES)
    for sources in ([1, 17, 34], g.ids):
        expected = {(g.ids[i], g.ids[j]): b for (i, j), b in small.betweenness(g, [g.ids.index(x) for x in sources]).items()}
        rows = graph.betweenness(club, spark.createDataFrame([(x,) for x in sources], "node long")).collect()
        assert len(rows) == len(expected)
        assert all(abs(r["betweenness"] - expected[r["src"], r["dst"]]) < 1e-9 for r in rows)


def test_path_through_a_table(spark):
    keys = spark.createDataFrame([(7 * i % 101,) for i in range(40)], "k long").repartition(3)
    listed = sorted(7 * i % 101 for i in range(40))
    assert sorted(models.path_through(keys, "k").collect()) == [(a, b, 1.0) for a, b in zip(listed, listed[1:])]


def test_lattice_of_a_table(spark):
    full = models.lattice_of(spark.range(25), 25).collect()
    assert sorted(full) == sorted(models.lattice(spark, 5).collect())
    short = {(r["src"], r["dst"]) for r in models.lattice_of(spark.range(22), 22).collect()}
    assert short == {(r["src"], r["dst"]) for r in full if r["dst"] < 22}


def test_copying_over_a_table(spark):
    from levcut.plans import graphs

    e = graphs._copying(spark, "/root/testdata/sf0.001")
    assert graph.degrees(e).count() == spark.read.parquet("/root/testdata/sf0.001/customer.parquet").count()
    assert sorted(e.collect()) == sorted(models.copying(spark, 150).collect())


def test_forest_fire_over_a_table(spark):
    from levcut.plans import graphs
    from levcut.runtime import TooLarge

    keys = {r[0] for r in spark.read.parquet("/root/testdata/sf0.01/supplier.parquet").select("s_suppkey").collect()}
    e = graphs._forest_fire(spark, "/root/testdata/sf0.01")
    rows = e.collect()
    assert {x for r in rows for x in (r["src"], r["dst"])} == keys and all(r["src"] < r["dst"] for r in rows)
    assert graph.degree_tail(e).drop("exponent").first()["mean"] == graph.degree_tail(models.forest_fire(spark, len(keys))).first()["mean"]
    with pytest.raises(TooLarge):
        graphs._forest_fire(spark, "/root/testdata/sf0.01", len(keys) - 1)


def test_copying_follows_every_pointer(spark):
    n = 3000
    u = lambda key, seed: int(hashlib.md5(f"{seed}:{key}".encode()).hexdigest()[:8], 16) / 2**32
    end, want = {}, set()
    for i in range(1, n):
        for k in range(2):
            at = int(u(f"{i}-{k}", 0) * i)
            end[i, k] = end.get((at, k), at) if u(f"{i}-{k}", 1) < 0.5 else at
            want.add((end[i, k], i))
    assert {(r["src"], r["dst"]) for r in models.copying(spark, n).collect()} == want
