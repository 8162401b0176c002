"""Registered queries of the matrix half, with DuckDB twins where SQL can say it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levcut.functions.portable import r6, u01, u01_sql
from levcut.operators import columns, hadamard, leverage, lsq, patterns, qr, sample, svd
from levcut.sources import tables as t

QUERIES: dict = {}
ORACLES: dict = {}
XS = ("one", "value", "hour")
LINE = ("one", "quantity", "discount", "tax")


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


EVENTS = """d AS (
  SELECT event_id AS id, value, hour(ts)::DOUBLE AS hour, (props->>'$.k')::DOUBLE AS y FROM events),
m AS (
  SELECT count(*) AS m, avg(value) AS av, avg(hour) AS ah, avg(y) AS ay, var_pop(value) * count(*) AS vv, var_pop(hour) * count(*) AS hh,
         covar_pop(value, hour) * count(*) AS vh, covar_pop(value, y) * count(*) AS vy, covar_pop(hour, y) * count(*) AS hy FROM d),
h AS (
  SELECT d.*, 1.0 / m.m + (hh * (value - av) ** 2 - 2 * vh * (value - av) * (hour - ah) + vv * (hour - ah) ** 2) / (vv * hh - vh * vh) AS h, m.*
  FROM d, m)"""


@query(f"WITH {EVENTS} SELECT id, round(h * m / 3, 4) AS h_over_mean FROM h WHERE h > 6.0 / m")
def ls_leverage_flags(spark: SparkSession, d: str) -> DataFrame:
    rows = t.design_events(spark, d)
    m = rows.count()
    return lsq.flag(rows, XS).select("id", F.round(F.col("h") * m / 3, 4).alias("h_over_mean"))


@query(f"WITH {EVENTS} SELECT any_value(m) AS m, round(sum(h), 6) AS trace, round(max(h) * any_value(m) / 3, 4) AS max_over_mean, count(*) FILTER (h > 6.0 / m) AS over_two, count(*) FILTER (h > 9.0 / m) AS over_three FROM h")
def ls_leverage_summary(spark: SparkSession, d: str) -> DataFrame:
    rows = lsq.leverage(t.design_events(spark, d), XS)
    m = rows.count()
    return rows.agg(
        F.count("*").alias("m"), r6(F.sum("h")).alias("trace"), F.round(F.max("h") * m / 3, 4).alias("max_over_mean"),
        F.sum((F.col("h") > 6.0 / m).cast("long")).alias("over_two"), F.sum((F.col("h") > 9.0 / m).cast("long")).alias("over_three"),
    )


_BETA = f"""WITH {EVENTS},
b AS (
  SELECT (hh * vy - vh * hy) / (vv * hh - vh * vh) AS b1, (vv * hy - vh * vy) / (vv * hh - vh * vh) AS b2, av, ah, ay FROM m)
SELECT round(ay - b1 * av - b2 * ah, 4) AS b_one, round(b1, 6) AS b_value, round(b2, 6) AS b_hour FROM b"""


def _solve(method: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        b = lsq.solve(t.design_events(spark, d), "y", XS, method)
        return spark.createDataFrame([(round(float(b[0]), 4), round(float(b[1]), 6), round(float(b[2]), 6))], "b_one double, b_value double, b_hour double")

    return run


for _method in ("cholesky", "qr", "svd"):
    QUERIES[f"ls_solve_{_method}"] = _solve(_method)
    ORACLES[f"ls_solve_{_method}"] = _BETA


@query(f"""WITH {EVENTS},
b AS (SELECT (hh * vy - vh * hy) / (vv * hh - vh * vh) AS b1, (vv * hy - vh * vy) / (vv * hh - vh * vh) AS b2, av, ah, ay FROM m)
SELECT id, round(ay + b1 * (value - av) + b2 * (hour - ah), 4) AS fitted, round(y - ay - b1 * (value - av) - b2 * (hour - ah), 4) AS residual FROM d, b""")
def ls_fit_diagnostics(spark: SparkSession, d: str) -> DataFrame:
    rows = lsq.fit_diagnostics(t.design_events(spark, d), "y", XS)
    return rows.select("id", F.round("fitted", 4).alias("fitted"), F.round("residual", 4).alias("residual"))


def _compare(spark: SparkSession, rows: DataFrame, y: str, xs, r: int, seeds: int = 5) -> DataFrame:
    rows = rows.cache()
    exact = lsq.solve(rows, y, xs)
    out = []
    for probs in ("leverage", "uniform"):
        for s in range(seeds):
            out.append((probs, s, *lsq.errors(rows, y, xs, exact, lsq.sampled(rows, y, xs, r, "id", s, probs))))
    rows.unpersist()
    return spark.createDataFrame(out, "probs string, seed int, residual_ratio double, solution_error double")


@query()
def ls_sampled_spiky(spark: SparkSession, d: str) -> DataFrame:
    return _compare(spark, t.design_events(spark, d), "y", XS, lsq.sample_size(3, 0.1))


@query()
def ls_sampled_benign(spark: SparkSession, d: str) -> DataFrame:
    return _compare(spark, t.design_lineitem(spark, d), "y", LINE, lsq.sample_size(4, 0.1))


@query()
def ls_regularized(spark: SparkSession, d: str) -> DataFrame:
    rows = t.design_lineitem(spark, d)
    out = [(l1, l2, *map(float, lsq.regularized(rows, "y", LINE, l1, l2))) for l1, l2 in ((0.0, 0.0), (0.0, 10.0), (50.0, 0.0))]
    return spark.createDataFrame(out, "l1 double, l2 double, " + ", ".join(f"{c} double" for c in LINE))


_HROWS = (0, 1, 77, 4095)


@query(f"""WITH d AS (SELECT event_id AS j, value, hour(ts)::DOUBLE AS hour FROM events)
SELECT i, round(sum(value * CASE WHEN {u01_sql("j", 5)} < 0.5 THEN -1 ELSE 1 END * CASE WHEN bit_count(i & j) % 2 = 1 THEN -1 ELSE 1 END / 128.0), 4) AS value,
       round(sum(hour * CASE WHEN {u01_sql("j", 5)} < 0.5 THEN -1 ELSE 1 END * CASE WHEN bit_count(i & j) % 2 = 1 THEN -1 ELSE 1 END / 128.0), 4) AS hour
FROM d, (SELECT unnest([0, 1, 77, 4095])::BIGINT AS i) GROUP BY i""")
def hadamard_rows(spark: SparkSession, d: str) -> DataFrame:
    rows = t.design_events(spark, d)
    out = hadamard.sampled_rows(rows, ["value", "hour"], "id", _HROWS, 16384, 5)
    return out.select("i", (F.round("value", 4) + 0.0).alias("value"), (F.round("hour", 4) + 0.0).alias("hour"))


BRAND = """a AS (
  SELECT o_custkey AS r, p_brand AS c, count(*)::DOUBLE AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY ALL),
g AS (SELECT x.c AS i, y.c AS j, sum(x.v * y.v) AS s FROM a x JOIN a y USING (r) GROUP BY ALL),
tr AS (SELECT sum(s) AS total FROM g WHERE i = j)"""


@query(f"WITH {BRAND} SELECT i AS col_id, round(s, 6) AS score, round(s / total, 9) AS p FROM g, tr WHERE i = j")
def column_norm_probabilities(spark: SparkSession, d: str) -> DataFrame:
    return sample.by_norm(t.customer_brand(spark, d)).select("col_id", r6(F.col("score")).alias("score"), F.round("p", 9).alias("p"))


@query(f"""WITH {BRAND},
q AS (SELECT i, sum(s * s) AS q FROM g GROUP BY i)
SELECT q.i AS c1, round(sqrt(total - q.q / g.s), 4) AS error FROM q JOIN g ON q.i = g.i AND g.j = g.i, tr""")
def best_columns_k1(spark: SparkSession, d: str) -> DataFrame:
    found = columns.best_columns(t.customer_brand(spark, d), 1)
    return found.select(F.col("col_ids")[0].alias("c1"), F.round("error", 4).alias("error"))


@query(f"""WITH {BRAND},
q AS (SELECT x.i AS i, y.i AS j, sum(x.s * y.s) AS q FROM g x JOIN g y ON x.j = y.j GROUP BY ALL)
SELECT q.i AS c1, q.j AS c2, round(sqrt(total - (gj.s * qi.q - 2 * g.s * q.q + gi.s * qj.q) / (gi.s * gj.s - g.s * g.s)), 4) AS error
FROM q JOIN g ON g.i = q.i AND g.j = q.j JOIN g gi ON gi.i = q.i AND gi.j = q.i JOIN g gj ON gj.i = q.j AND gj.j = q.j
JOIN q qi ON qi.i = q.i AND qi.j = q.i JOIN q qj ON qj.i = q.j AND qj.j = q.j, tr WHERE q.i < q.j""")
def best_columns_k2(spark: SparkSession, d: str) -> DataFrame:
    found = columns.best_columns(t.customer_brand(spark, d), 2)
    return found.select(F.col("col_ids")[0].alias("c1"), F.col("col_ids")[1].alias("c2"), F.round("error", 4).alias("error"))


@query(f"WITH {BRAND}, p AS (SELECT i AS col_id, s / total AS p FROM g, tr WHERE i = j) SELECT col_id, round(1 / sqrt(least(1.0, 8 * p)), 6) AS scale FROM p WHERE {u01_sql('col_id', 3)} < least(1.0, 8 * p)")
def sample_bernoulli(spark: SparkSession, d: str) -> DataFrame:
    p = sample.by_norm(t.customer_brand(spark, d))
    return sample.draw(p, 8, "bernoulli", 3).select("col_id", r6(F.col("scale")).alias("scale"))


@query(f"WITH {BRAND}, p AS (SELECT i AS col_id, s / total AS p FROM g, tr WHERE i = j) SELECT col_id FROM p ORDER BY -ln(greatest({u01_sql('col_id', 3)}, pow(2.0, -33))) / p LIMIT 8")
def sample_exponential_keys(spark: SparkSession, d: str) -> DataFrame:
    return sample.draw(sample.by_norm(t.customer_brand(spark, d)), 8, "exponential_keys", 3).select("col_id")


@query("SELECT p_brand AS col_id, 0.04::DOUBLE AS p FROM part GROUP BY p_brand")
def sample_uniform_probabilities(spark: SparkSession, d: str) -> DataFrame:
    return sample.uniform(t.customer_brand(spark, d)).select("col_id", F.round("p", 9).alias("p"))


@query(f"""WITH {BRAND}, p AS (SELECT i AS col_id, s / total AS p FROM g, tr WHERE i = j),
h AS (SELECT col_id, p, sum(p) OVER (ORDER BY col_id ROWS UNBOUNDED PRECEDING) AS high FROM p),
u AS (SELECT {u01_sql('id', 3)} * (1 - 1e-12) AS u FROM range(40) r(id)),
w AS (SELECT u, min(high) AS high FROM u JOIN h ON h.high > u.u GROUP BY u)
SELECT col_id, round(p, 9) AS p, count(*)::INT AS draws, round(sqrt(count(*) / (40 * p)), 6) AS scale FROM w JOIN h USING (high) GROUP BY col_id, p""")
def sample_with_replacement(spark: SparkSession, d: str) -> DataFrame:
    found = sample.draw(sample.by_norm(t.customer_brand(spark, d)), 40, "with_replacement", 3)
    return found.select("col_id", F.round("p", 9).alias("p"), "draws", r6(F.col("scale")).alias("scale"))


@query()
def leverage_columns_customer_part(spark: SparkSession, d: str) -> DataFrame:
    return leverage.columns(svd.topk(t.customer_part(spark, d), 5, "subspace", power=3).v)


@query()
def leverage_cumulative_terms(spark: SparkSession, d: str) -> DataFrame:
    v = svd.topk(t.term_counts(spark, d), 10, "subspace", power=3).v
    return leverage.cumulative(leverage.columns(v), top=100)


@query()
def leverage_signature_terms(spark: SparkSession, d: str) -> DataFrame:
    v = svd.topk(t.term_counts(spark, d), 10, "subspace", power=3).v
    return leverage.signature(leverage.columns(v), 10)


@query()
def leverage_flag_terms(spark: SparkSession, d: str) -> DataFrame:
    v = svd.topk(t.term_counts(spark, d), 10, "subspace", power=3).v
    return leverage.flag(leverage.columns(v), 10)


@query()
def leverage_columns_approximate(spark: SparkSession, d: str) -> DataFrame:
    return leverage.columns_approx(t.customer_part(spark, d), 5)


TERMS = r"""o AS (SELECT doc_id, lang, unnest(regexp_extract_all(lower(text), '([\p{L}\p{M}\p{N}_]+)', 1)) AS term FROM documents),
b AS (SELECT DISTINCT doc_id, lang, term FROM o),
k AS (SELECT term FROM b GROUP BY term HAVING count(*) >= 5),
c AS (SELECT term, lang, count(*)::DOUBLE AS n FROM b JOIN k USING (term) GROUP BY ALL),
l AS (SELECT lang, count(*)::DOUBLE AS nl FROM documents GROUP BY lang),
m AS (SELECT sum(nl) AS m, -sum(nl / (SELECT count(*) FROM documents) * log2(nl / (SELECT count(*) FROM documents))) AS prior FROM l),
f AS (SELECT term, sum(n) AS df FROM c GROUP BY term)"""


@query(f"""WITH {TERMS},
x AS (SELECT f.term, f.df, l.nl, coalesce(c.n, 0) AS n, m.m, m.prior FROM f CROSS JOIN l CROSS JOIN m LEFT JOIN c ON c.term = f.term AND c.lang = l.lang)
SELECT term AS col_id, any_value(df) AS df,
       round(any_value(prior) - any_value(df) / any_value(m) * sum(CASE WHEN n > 0 THEN -n / df * log2(n / df) ELSE 0 END)
             - (1 - any_value(df) / any_value(m)) * sum(CASE WHEN nl - n > 0 THEN -(nl - n) / (m - df) * log2((nl - n) / (m - df)) ELSE 0 END), 6) AS gain
FROM x GROUP BY term""")
def information_gain_terms(spark: SparkSession, d: str) -> DataFrame:
    found = leverage.information_gain(t.term_binary(spark, d), t.doc_labels(spark, d))
    return found.select("col_id", "df", r6(F.col("gain")).alias("gain"))


@query()
def leverage_vs_information_gain(spark: SparkSession, d: str) -> DataFrame:
    return leverage.vs_information_gain(t.term_binary(spark, d).cache(), t.doc_labels(spark, d), (1, 2, 3, 4, 5, 10))


@query()
def leverage_vs_gain_control(spark: SparkSession, d: str) -> DataFrame:
    """Embeddings with random labels: no clusters, so no correlation."""
    a = t.embedding_matrix(spark, d)
    labels = t.load(spark, d, "embeddings").select(F.col("vec_id").alias("row_id"), "label")
    mi = leverage.mutual_information(a, labels)
    return leverage.columns(svd.topk(a, 10).v).join(mi, "col_id").agg(F.corr("score", "mi").alias("pearson"))


@query()
def svd_lsa_documents(spark: SparkSession, d: str) -> DataFrame:
    return svd.lsa(t.term_binary(spark, d).cache(), 5, "tfidf")


@query()
def cssp_two_stage_brand(spark: SparkSession, d: str) -> DataFrame:
    a = t.customer_brand(spark, d).cache()
    found = svd.topk(a, 3)
    rows = []
    for rule in qr.RULES:
        ids = columns.two_stage(a, 3, rule=rule, found=found)
        rows.append((rule, [str(i) for i in ids], *(columns.residual(a, ids, n, known=found.gram) for n in ("fro", "spec")), found.tail()))
    return spark.createDataFrame(rows, "rule string, col_ids array<string>, fro double, spectral double, optimum double")


@query()
def cssp_two_stage_terms(spark: SparkSession, d: str) -> DataFrame:
    a = t.term_binary(spark, d).cache()
    found = svd.topk(a, 5, "subspace", power=3)
    ids = columns.two_stage(a, 5, found=found)
    return spark.createDataFrame([([str(i) for i in ids], columns.residual(a, ids, known=found.gram), found.tail())], "col_ids array<string>, fro double, optimum double")


@query()
def cssp_rules_compared(spark: SparkSession, d: str) -> DataFrame:
    return columns.compare_rules(t.customer_brand(spark, d).cache(), 3, qr.RULES, (0,))


@query()
def cssp_sweep_c(spark: SparkSession, d: str) -> DataFrame:
    return columns.sweep_c(t.customer_brand(spark, d).cache(), 4, (4, 6, 8, 12, 16), (0, 1))


@query()
def cssp_sweep_k(spark: SparkSession, d: str) -> DataFrame:
    return columns.sweep_k(t.customer_brand(spark, d).cache(), (1, 2, 4, 8))


@query()
def cssp_relative_error(spark: SparkSession, d: str) -> DataFrame:
    a = t.customer_brand(spark, d).cache()
    optimum = svd.topk(a, 3).tail()
    _, best, errors = columns.best_of(a, 3, 0.5, 4)
    return spark.createDataFrame([(best, optimum, columns.success(errors, optimum, 0.5))], "error double, optimum double, success double")


@query()
def cssp_coverage(spark: SparkSession, d: str) -> DataFrame:
    v = svd.topk(t.customer_brand(spark, d), 4).v
    return columns.coverage(leverage.columns(v), v, 4, (4, 6, 10), 3)


@query()
def cssp_bounds(spark: SparkSession, d: str) -> DataFrame:
    """The factors for three of the columns that the customer-brand matrix has."""
    n = t.customer_brand(spark, d).select("col_id").distinct().count()
    return spark.createDataFrame([(k, float(v)) for k, v in columns.bounds(3, n).items()], "bound string, factor double")



@query()
def cssp_classify(spark: SparkSession, d: str) -> DataFrame:
    a = t.term_binary(spark, d).cache()
    return spark.createDataFrame([(k, columns.classify(a, columns.two_stage(a, k, found=svd.topk(a, k, "subspace", power=2)), t.doc_labels(spark, d))) for k in (4, 8)], "k int, accuracy double")


@query()
def cssp_cluster(spark: SparkSession, d: str) -> DataFrame:
    """Documents grouped by the chosen terms alone: how the groups meet the languages."""
    a = t.term_binary(spark, d).cache()
    parts = columns.cluster(a, columns.two_stage(a, 8, found=svd.topk(a, 8, "subspace", power=2)), 4)
    return parts.join(t.doc_labels(spark, d), "row_id").groupBy("part", "label").agg(F.count("*").alias("n"))


@query()
def cssp_transfer(spark: SparkSession, d: str) -> DataFrame:
    a = t.customer_brand(spark, d).cache()
    return columns.transfer(a.filter(u01("row_id", 9) < 0.5), a.filter(u01("row_id", 9) >= 0.5), 3)


_PAIRS = """b AS (SELECT DISTINCT l_orderkey AS basket, l_partkey AS item FROM lineitem),
f AS (SELECT item, count(*) AS c FROM b GROUP BY item HAVING count(*) >= 2),
p AS (SELECT x.item AS a, y.item AS b, count(*) AS n FROM b x JOIN b y ON x.basket = y.basket AND x.item < y.item
      WHERE x.item IN (SELECT item FROM f) AND y.item IN (SELECT item FROM f) GROUP BY ALL HAVING count(*) >= 2)"""


@query(f"WITH {_PAIRS} SELECT a, b, n FROM p")
def itemset_pairs(spark: SparkSession, d: str) -> DataFrame:
    return patterns.item_pairs(t.baskets(spark, d), 2)


@query(f"""WITH {_PAIRS}, r AS (SELECT a AS lhs, b AS rhs, n FROM p UNION ALL SELECT b, a, n FROM p)
SELECT lhs, rhs, round(n / (SELECT count(DISTINCT basket) FROM b), 9) AS support, round(n / x.c, 9) AS confidence,
       round(n * (SELECT count(DISTINCT basket) FROM b)::DOUBLE / (x.c * y.c), 6) AS lift
FROM r JOIN f x ON x.item = lhs JOIN f y ON y.item = rhs""")
def association_rules(spark: SparkSession, d: str) -> DataFrame:
    out = patterns.rules(t.baskets(spark, d), 2)
    return out.select("lhs", "rhs", F.round("support", 9).alias("support"), F.round("confidence", 9).alias("confidence"), r6(F.col("lift")).alias("lift"))


@query("""WITH u AS (SELECT user_id, max((event_type = 'view')::INT) AS a, max((event_type = 'click')::INT) AS b FROM events WHERE hour(ts) BETWEEN 17 AND 20 GROUP BY user_id)
SELECT sum(a)::BIGINT AS with_first, sum(a * b)::BIGINT AS with_both, round(sum(a * b) / sum(a), 9) AS confidence FROM u""")
def timed_rule(spark: SparkSession, d: str) -> DataFrame:
    return patterns.timed_rule(t.load(spark, d, "events"), "view", "click", 17, 21).withColumn("confidence", F.round("confidence", 9))


@query("""WITH e AS (SELECT user_id, hour(ts)::INT AS hour, (event_type = 'click')::INT AS hit FROM events),
base AS (SELECT ln((sum(hit) + 0.5) / (count(*) - sum(hit) + 0.5)) AS o FROM e),
u AS (SELECT user_id, ln((sum(hit) + 0.5) / (count(*) - sum(hit) + 0.5)) AS o FROM e GROUP BY user_id),
h AS (SELECT hour, ln((sum(hit) + 0.5) / (count(*) - sum(hit) + 0.5)) AS o FROM e GROUP BY hour)
SELECT user_id, hour, round(1 / (1 + exp(-(u.o + h.o - base.o))), 6) AS prob FROM base, u, h""")
def unseen_cell_probability(spark: SparkSession, d: str) -> DataFrame:
    e = t.load(spark, d, "events").select("user_id", F.hour("ts").alias("hour"), (F.col("event_type") == "click").cast("int").alias("hit"))
    return patterns.predict_unseen(e, ("user_id", "hour"), "hit").withColumn("prob", r6(F.col("prob")))
