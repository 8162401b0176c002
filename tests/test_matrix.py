"""Golden fixtures, identities and brute force for the matrix half."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from levcut.functions.portable import u01
from levcut.operators import columns, hadamard, leverage, lsq, qr, sample, svd

#: A public ten-point data set and its leverage.
X1 = [0.499, 0.558, 0.604, 0.441, 0.550, 0.528, 0.418, 0.480, 0.406, 0.467]
X2 = [11.1, 8.9, 8.8, 8.9, 8.8, 9.9, 10.7, 10.5, 10.5, 10.7]
LEVERAGE = [0.418, 0.242, 0.417, 0.604, 0.252, 0.148, 0.262, 0.154, 0.316, 0.187]


@pytest.fixture(scope="module")
def ten(spark):
    return spark.createDataFrame([(i, 1.0, a, b, a * 2 + b) for i, (a, b) in enumerate(zip(X1, X2, strict=True))], "id long, one double, x1 double, x2 double, y double")


@pytest.fixture(scope="module")
def sparse(spark):
    rng = np.random.default_rng(7)
    m = rng.poisson(0.6, (80, 14)).astype(float) + np.outer(rng.random(80) * 3, rng.random(14) > 0.6)
    rows = [(i, j, float(m[i, j])) for i in range(80) for j in range(14) if m[i, j]]
    return m, spark.createDataFrame(rows, "row_id long, col_id long, value double").cache()


def test_hash_has_one_value(spark):
    assert abs(spark.range(42, 43).select(u01("id", 7).alias("u")).first()["u"] - 0.676139617105946) < 1e-12


def test_ten_points(ten):
    h = [r["h"] for r in lsq.leverage(ten, ["one", "x1", "x2"]).orderBy("id").collect()]
    assert np.allclose(h, LEVERAGE, atol=6e-4) and abs(sum(h) - 3) < 1e-9
    assert [r["id"] for r in lsq.flag(ten, ["one", "x1", "x2"]).collect()] == [3]
    for method in ("cholesky", "qr", "svd"):
        assert np.allclose(lsq.solve(ten, "y", ["one", "x1", "x2"], method), [0, 2, 1], atol=1e-6)


def test_influence_is_the_hat_matrix(spark, ten):
    a = np.array([[1, x, y] for x, y in zip(X1, X2, strict=True)])
    hat = a @ np.linalg.pinv(a)
    pairs = spark.createDataFrame([(0, 3), (5, 5)], "i long, j long")
    for r in lsq.influence(ten, ["one", "x1", "x2"], "id", pairs).collect():
        assert abs(r["h"] - hat[r["i"], r["j"]]) < 1e-8


def test_rank_deficient_scores_sum_to_rank(ten):
    doubled = ten.withColumn("x3", F.col("x1") * 2).withColumn("zero", F.lit(0.0))
    total = lsq.leverage(doubled, ["one", "x1", "x3", "zero"]).agg(F.sum("h")).first()[0]
    assert abs(total - 2) < 1e-8


def test_deleting_flagged_points(ten):
    _, without, n = lsq.delete_effect(ten, "y", ["one", "x1", "x2"])
    assert n == 1 and np.allclose(without, [0, 2, 1], atol=1e-5)


def test_hadamard_is_orthogonal_and_evens_out(spark):
    rows = spark.range(64).select(F.col("id").alias("i"), (F.col("id") == 5).cast("double").alias("x"), F.lit(1.0).alias("one"))
    full = hadamard.transform(rows, ["x", "one"], "i", 64, 2)
    assert abs(full.agg(F.sum(F.col("x") ** 2)).first()[0] - 1) < 1e-9
    part = {r["i"]: r["x"] for r in hadamard.sampled_rows(rows, ["x", "one"], "i", [0, 9, 33], 64, 2).collect()}
    whole = {r["i"]: r["x"] for r in full.collect()}
    assert all(abs(part[i] - whole[i]) < 1e-9 for i in part)
    assert hadamard.uniformity(full, ["x", "one"]) < hadamard.uniformity(rows, ["x", "one"])


def test_svd_against_numpy(sparse):
    m, a = sparse
    s = np.linalg.svd(m, compute_uv=False)
    for method in ("gram", "subspace"):
        found = svd.topk(a, 4, method, power=6)
        assert np.allclose(found.sigma, s[:4], rtol=2e-2 if method == "subspace" else 1e-8)
        v = np.array([list(r)[1:] for r in found.v.orderBy("col_id").collect()])
        assert np.allclose(v.T @ v, np.eye(4), atol=1e-6)
    assert abs(svd.topk(a, 4, "gram").tail() - np.sqrt((s[4:] ** 2).sum())) < 1e-6
    assert svd.topk(a, 99, "gram").k == np.linalg.matrix_rank(m)


def test_leverage_identities(sparse):
    _, a = sparse
    found = svd.topk(a, 4)
    scores = leverage.columns(found.v)
    assert abs(scores.agg(F.sum("p")).first()[0] - 1) < 1e-9
    rotated = leverage.projector_diag(found.v).select("col_id", F.col("score").alias("other"))
    assert scores.join(rotated, "col_id").agg(F.max(F.abs(F.col("score") - F.col("other")))).first()[0] < 1e-9
    two = leverage.columns(found.v, probs="two_term", a=a)
    assert abs(two.agg(F.sum("p")).first()[0] - 1) < 1e-6
    last = leverage.cumulative(scores).orderBy(F.desc("t")).first()
    assert abs(last["cum"] - 4) < 1e-9 and last["t"] == 14


def test_draws(sparse):
    _, a = sparse
    p = sample.by_norm(a)
    got = sample.draw(p, 30, "with_replacement", 2)
    assert got.agg(F.sum("draws")).first()[0] == 30
    assert sample.draw(p, 5, "exponential_keys", 2).count() == 5
    assert sample.draw(p, 10**9, "bernoulli", 2).count() == 14


def test_residuals_and_exhaustive_choice(sparse):
    m, a = sparse
    ids = [1, 4, 9]
    c = m[:, ids]
    r = m - c @ np.linalg.pinv(c) @ m
    assert abs(columns.residual(a, ids) - np.linalg.norm(r)) < 1e-6
    assert abs(columns.residual(a, ids, "spec") - np.linalg.norm(r, 2)) < 1e-6
    assert columns.residual(a, list(range(14))) < 1e-4
    best = columns.best_columns(a, 2).agg(F.min("error")).first()[0]
    optimum = svd.topk(a, 2).tail()
    s = np.linalg.svd(m, compute_uv=False)
    assert optimum <= best <= np.sqrt(3) * optimum + 1e-9
    assert best <= np.sqrt(3 * 12) * s[2] + 1e-9
    for rule in qr.RULES:
        chosen = columns.two_stage(a, 2, rule=rule)
        assert len(set(chosen)) == 2 and columns.residual(a, chosen) >= best - 1e-6
    both = [columns.residual(a, list(range(6)), rank=2, mode=x) for x in ("best_in_span", "truncate_c")]
    assert both[0] <= both[1] + 1e-9


def test_rules_pick_independent_columns():
    rng = np.random.default_rng(1)
    base = rng.normal(size=(4, 4))
    mat = np.concatenate([base, base[:, :1] * 1.001, base[:, :2] @ rng.normal(size=(2, 3))], 1)
    for rule in qr.RULES:
        chosen = qr.select(mat, 4, rule)
        assert np.linalg.matrix_rank(mat[:, chosen]) == 4
    with pytest.raises(ValueError):
        qr.select(mat, 20)


def test_hadamard_folds_what_is_past_its_size(spark):
    from levcut.functions.portable import u01

    rows = spark.range(50).select(F.col("id").alias("i"), (F.col("id") * F.col("id") % 7).cast("double").alias("x"))
    signed = rows.select("i", (F.col("x") * F.when(u01("i", 2) < 0.5, -1.0).otherwise(1.0)).alias("s")).collect()
    want = [sum(r["s"] * (-1) ** (i & r["i"]).bit_count() for r in signed) / 4 for i in range(16)]
    got = {r["i"]: r["x"] for r in hadamard.transform(rows, ["x"], "i", 16, 2).collect()}
    assert len(got) == 16 and all(abs(got[i] - want[i]) < 1e-9 for i in range(16))


def test_bounds_follow_the_matrix(spark, tmp_path):
    from levcut.plans import matrix

    source = "/root/testdata/sf0.001"
    for name in ("lineitem", "orders", "part"):
        rows = spark.read.parquet(f"{source}/{name}.parquet")
        (rows.filter("p_brand < 'Brand#3'") if name == "part" else rows).write.parquet(f"{tmp_path}/{name}.parquet")
    n = spark.read.parquet(f"{tmp_path}/part.parquet").select("p_brand").distinct().count()
    got = {r["bound"]: r["factor"] for r in matrix.cssp_bounds(spark, str(tmp_path)).collect()}
    assert 3 < n < 25 and got == columns.bounds(3, n)


def test_uniformity_transforms_the_whole_table(spark):
    import duckdb

    from levcut.plans import linear

    source = "/root/testdata/sf0.1"
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{source}/events.parquet'")
    got = linear.hadamard_uniformity(spark, source).first()
    assert tuple(got) == pytest.approx(con.execute(linear.ORACLES["hadamard_uniformity"]).fetchone(), abs=2e-4)
    assert got["after"] < 0.5 * got["before"]
