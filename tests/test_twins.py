"""Operators against brute force, and queries against their SQL twins on small tables."""

import itertools
import os
import random

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from levcut.functions import sqlkit
from levcut.operators import columns, graph, local, multilevel, probes, relational, sample, small, spectral, svd
from levcut.plans import cuts, linear, studies
from levcut.runtime import traced

SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for name in os.listdir(SMALL):
        c.execute(f"CREATE VIEW {name[:-8]} AS SELECT * FROM '{SMALL}/{name}'")
    return c


TWINS = [
    (linear, n) for n in ("svd_values_brand", "leverage_columns_two_term", "leverage_rows_customer_brand", "leverage_cumulative_brand", "cssp_qr_matrix", "cssp_by_norms",
                          "cssp_spectral_error", "matrix_normalized", "cssp_reconstruct", "ls_ridge", "ls_early_stopping", "ls_delete_effect", "ls_assumptions", "regression_ten_points")
] + [(cuts, n) for n in ("edge_leverage_exact", "cut_bounds_exact", "flow_improvement_exact", "club_edge_leverage", "club_leverage_and_degree", "set_out_degree_fractions", "ground_truth_agreement", "sweep_balanced",
                         "whisker_shares", "whisker_bag_prefixes", "model_geometric", "model_expander", "model_hierarchical", "model_core_periphery", "workload_pages")] + [(studies, "artifacts_known")]


@pytest.mark.parametrize("plan, name", TWINS, ids=lambda x: x if isinstance(x, str) else "")
def test_twin(spark, con, plan, name):
    df = plan.QUERIES[name](spark, SMALL)
    cols = sorted(df.columns)
    clean = lambda v: v + 0.0 if isinstance(v, float) else v
    got = sorted((tuple(clean(r[c]) for c in cols) for r in df.collect()), key=str)
    found = con.execute(plan.ORACLES[name])
    names = [x[0] for x in found.description]
    want = sorted((tuple(clean(dict(zip(names, row, strict=True))[c]) for c in cols) for row in found.fetchall()), key=str)
    assert len(got) == len(want) > 0
    for a, b in zip(got, want, strict=True):
        assert all(x == pytest.approx(y, abs=2e-4) if isinstance(x, float) and y is not None else x == y for x, y in zip(a, b, strict=True)), (a, b)


def test_sql_algebra(con):
    rng = np.random.default_rng(1)
    a = rng.normal(size=(9, 5))
    g = a.T @ a
    rows = ", ".join(f"({i}, {j}, {g[i, j]!r}::DOUBLE)" for i in range(5) for j in range(5)).replace("np.float64(", "").replace(")::DOUBLE", "::DOUBLE")
    head = f"WITH RECURSIVE t(i, j, s) AS (VALUES {rows}), {sqlkit.matrix('t')}"
    lam = con.execute(f"{head}, {sqlkit.eigen(5)} SELECT lam FROM eig").fetchall()[0][0]
    assert np.allclose(lam, np.linalg.eigvalsh(g)[::-1])
    inv = con.execute(f"{head}, {sqlkit.inverse('mat', 'inv')} SELECT m FROM inv").fetchall()[0][0]
    assert np.allclose(inv, np.linalg.inv(g))


def test_gram_and_residuals(spark):
    rng = np.random.default_rng(2)
    dense = rng.normal(size=(300, 7)) * (rng.random((300, 7)) < 0.6)
    a = spark.createDataFrame([(f"r{i}", int(j), float(dense[i, j])) for i in range(300) for j in range(7) if dense[i, j]], "row_id string, col_id long, value double").repartition(5)
    ids, g = svd.gram(a)
    assert ids == list(range(7)) and np.allclose(g, dense.T @ dense)
    for norm, rank, mode in (("fro", None, "best_in_span"), ("fro", 1, "best_in_span"), ("fro", 1, "truncate_c"), ("spec", None, "best_in_span")):
        assert np.isclose(columns.residual(a, [1, 4, 5], norm, rank, mode), columns.residual(a, [1, 4, 5], norm, rank, mode, known=(ids, g)))
    centered = svd.normalize(a, "center").groupBy("col_id").agg(F.sum("value").alias("s"), F.count("*").alias("n")).collect()
    assert all(abs(r["s"]) < 1e-9 and r["n"] == 300 for r in centered)


def test_draws_follow_the_intervals(spark):
    p = spark.createDataFrame([(i, (i + 1) / 55) for i in range(10)], "col_id long, p double").repartition(4)
    got = {r["col_id"]: r["draws"] for r in sample.draw(p, 5500, "with_replacement", 2).collect()}
    assert sum(got.values()) == 5500
    assert all(abs(got[i] - 100 * (i + 1)) < 6 * (100 * (i + 1)) ** 0.5 for i in range(10))


def test_ranks_and_sums(spark):
    rng = random.Random(3)
    values = [float(rng.randrange(8)) for _ in range(60)]
    df = spark.createDataFrame(list(enumerate(values)), "id long, x double").repartition(3)
    got = {r["id"]: r["rank"] for r in relational.ranks(df, "x", "rank").collect()}
    assert all(got[i] == 1 + sum(y < x for y in values) for i, x in enumerate(values))


def _random_edges(seed, n=30, m=60):
    rng = random.Random(seed)
    return sorted({(min(a, b), max(a, b), 1.0) for a, b in ((rng.randrange(n), rng.randrange(n)) for _ in range(m)) if a != b})


def test_whole_sweep_is_the_plain_one(spark):
    e = spark.createDataFrame(_random_edges(4), "src long, dst long, w double").cache()
    v = graph.degrees(e).select("node", (F.col("node") % 5).cast("double").alias("value"))
    plain = graph.sweep(e, v.withColumn("seed_id", F.lit(0))).select("rank", "node", "vol", "cut").collect()
    assert sorted(spectral.sweep(e, v).select("rank", "node", "vol", "cut").collect()) == sorted(plain)


def test_best_subset_by_enumeration():
    for seed in range(25):
        rows = _random_edges(seed, 14, 34)
        g = small.SmallGraph(rows)
        order = sorted(range(g.n), key=lambda i: (i * 7 + seed) % 11)
        side = []
        while len(side) < g.n - 1 and g.degree[side + [order[len(side)]]].sum() <= g.volume / 2:
            side.append(order[len(side)])
        if not side:
            continue
        links = [(i, j, w) for i, j, w in g.edges() if i in side and j in side]
        got = small.best_subset({i: float(g.degree[i]) for i in side}, links)
        best = min(g.phi(s) for k in range(1, len(side) + 1) for s in itertools.combinations(side, k))
        assert abs(g.phi(got) - best) < 1e-9


def test_flow_sets_improve(spark):
    e = spark.createDataFrame(_random_edges(9, 40, 70), "src long, dst long, w double").cache()
    e = graph.giant(e).cache()
    found = probes.local_sets(e, 3, 3, 12, 0.1, 1e-3).cache()
    phi = lambda s: {r["set_id"].split("/")[1]: r["phi"] for r in probes.set_summaries(e, s).collect()}
    before, after = phi(found), phi(probes.flow_sets(e, found))
    assert before and all(after[k] <= before[k] + 1e-9 for k in after)
    both = probes.compare(e, found.unionByName(probes.flow_sets(e, found)))
    assert {r["method"] for r in both.collect()} == {"local_spectral", "local_flow"}


def test_heat_drops_what_is_small(spark):
    e = spark.createDataFrame([(i, i + 1, 1.0) for i in range(200)], "src long, dst long, w double").cache()
    seeds = spark.createDataFrame([(1, 100)], "seed_id long, node long")
    whole, short = local.heat(e, seeds, eps=0.0).collect(), local.heat(e, seeds, eps=1e-2).collect()
    assert len(short) < len(whole) and sum(r["value"] for r in short) <= sum(r["value"] for r in whole) + 1e-12


def test_lower_bound_is_under_the_cut(spark):
    e = cuts._club(spark).cache()
    low = spectral.lower_bound(e, 60)
    assert 0.05 < low <= 10 / 76


def test_refinement_keeps_the_balance(spark):
    e = spark.createDataFrame(_random_edges(5, 60, 160), "src long, dst long, w double").cache()
    masses = multilevel.volumes(e).cache()
    start = masses.select("node", (F.col("node") % 2).cast("int").alias("side"))
    cut = lambda s: multilevel.summary(e, s.withColumnRenamed("side", "part")).collect()
    before, after = cut(start), cut(multilevel.refine(e, masses, start, 0.3, 4))
    total = sum(r["vol"] for r in after)
    assert after[0]["cut"] <= before[0]["cut"] and min(r["vol"] for r in after) >= 0.3 * total - 1e-9


def test_clusters_and_costs(spark):
    a = spark.createDataFrame([(i, j, 1.0) for i in range(20) for j in ((0, 1) if i < 10 else (2, 3))], "row_id long, col_id long, value double")
    parts = {r["row_id"]: r["part"] for r in columns.cluster(a, [0, 2], 2).collect()}
    assert len({parts[i] for i in range(10)}) == len({parts[i] for i in range(10, 20)}) == 1 and parts[0] != parts[10]
    n, trace = traced(spark, lambda: a.count())
    assert n == 40 and trace.jobs >= 1 and trace.tasks >= 1 and trace.seconds > 0


def test_salted_join_repeats_frequent_keys_alone(spark):
    left = spark.createDataFrame([(0 if i < 400 else i if i % 9 else None, i) for i in range(1000)], "k long, v long")
    right = spark.createDataFrame([(i, f"n{(i or 0) % 3}") for i in [*range(900), 0, None]], "k long, name string")
    joined = relational.salted_join(left, right, "k", "v", 16, 0.01)
    assert sorted(joined.collect()) == sorted(left.join(right, "k").collect()) and joined.count() > 800
    # The repeated side is never sent through the driver, however small its files look.
    assert "Broadcast" not in joined._jdf.queryExecution().executedPlan().toString()


def test_geometric_takes_every_customer(spark, con):
    """Pairs within the radius, by trying all pairs."""
    row = cuts.QUERIES["model_geometric"](spark, SMALL).first()
    at = [(x, y) for x, y in con.execute("SELECT ('0x' || substr(md5('0:' || c_custkey), 1, 8))::BIGINT / 4294967296.0, ('0x' || substr(md5('1:' || c_custkey), 1, 8))::BIGINT / 4294967296.0 FROM customer").fetchall()]
    limit = 0.06**2 * 1000 / len(at)
    degree = [sum((x - u) ** 2 + (y - v) ** 2 <= limit for u, v in at) - 1 for x, y in at]
    assert row["nodes"] == sum(k > 0 for k in degree) and row["mean"] == pytest.approx(sum(degree) / row["nodes"], abs=1e-6)
