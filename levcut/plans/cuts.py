"""Graph queries whose twins solve small systems, walk rounds or enumerate sets in SQL."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levcut.functions import sqlkit as k
from levcut.functions.portable import u01, key60_sql, r6, u01_sql
from levcut.operators import graph, local, models, probes, relational, resistance, small, spectral
from levcut.plans.graphs import BIDS, BOTH, SPARSE, TEN_NODES
from levcut.sources import tables as t

QUERIES: dict = {}
ORACLES: dict = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def _sparse(spark: SparkSession, d: str) -> DataFrame:
    return t.g_order_part(spark, d, 90)


def _ten(spark: SparkSession, d: str) -> DataFrame:
    return graph.build(t.g_segment_priority(spark, d), "src", "dst", "w")


# --- ten nodes: exact values --------------------------------------------------------


_LAPLACIAN = """arc AS (SELECT i, j, w FROM e UNION ALL SELECT j, i, w FROM e),
lap AS (SELECT a.node AS i, b.node AS j, CASE WHEN a.node = b.node THEN a.vol ELSE -coalesce(w, 0) END + 1.0 / (SELECT count(*) FROM n) AS s,
               CASE WHEN a.node = b.node THEN 1.0 ELSE 0.0 END + coalesce(w, 0) / sqrt(a.vol * b.vol) AS walk
        FROM n a CROSS JOIN n b LEFT JOIN arc ON arc.i = a.node AND arc.j = b.node)"""


def _resistances(nodes: str) -> str:
    return f"""{_LAPLACIAN}, {k.matrix("lap")}, {k.inverse("mat", "inv")},
pl AS (SELECT node, row_number() OVER (ORDER BY node) AS p FROM n),
res AS (SELECT e.i, e.j, m[a.p][a.p] + m[b.p][b.p] - 2 * m[a.p][b.p] AS r, w FROM e JOIN pl a ON a.node = e.i JOIN pl b ON b.node = e.j CROSS JOIN inv)"""


_TEN_E = TEN_NODES[: TEN_NODES.index("k AS (")].rstrip().rstrip(",")


@query(f"WITH RECURSIVE {_TEN_E}, {_resistances('n')} SELECT i AS src, j AS dst, round(r * 1e3, 6) AS r_milli, round(w * r, 6) AS leverage FROM res")
def edge_leverage_exact(spark: SparkSession, d: str) -> DataFrame:
    return resistance.exact(_ten(spark, d)).select("src", "dst", r6(F.col("r") * 1e3).alias("r_milli"), r6(F.col("leverage")).alias("leverage"))


@query(f"WITH RECURSIVE {_TEN_E}, {_resistances('n')} SELECT round(sum(w * r), 6) AS total, (SELECT count(*) - 1 FROM n)::DOUBLE AS expected, round(max(w * r), 6) AS largest FROM res")
def edge_leverage_identity(spark: SparkSession, d: str) -> DataFrame:
    """Leverages add up to nodes less components."""
    e = _ten(spark, d).cache()
    return resistance.check(e, resistance.exact(e)).select(r6(F.col("total")).alias("total"), "expected", r6(F.col("largest")).alias("largest"))


_DEGREE_CORR = """d AS (SELECT node, count(*) AS deg FROM (SELECT i AS node FROM e UNION ALL SELECT j FROM e) GROUP BY node)"""


def _sweep_sql(order: str) -> str:
    """CTEs up to pre (rank, vol, cut, phi): prefixes of a table (node, value) over e (i, j, w) and n (node, vol)."""
    return f"""rk AS (SELECT node, row_number() OVER (ORDER BY value DESC, node) AS rank FROM {order}),
cl AS (SELECT greatest(a.rank, b.rank) AS rank, sum(w) AS closed FROM e JOIN rk a ON a.node = e.i JOIN rk b ON b.node = e.j GROUP BY ALL),
pre AS (SELECT rk.rank, sum(vol) OVER o AS vol, sum(vol) OVER o - 2 * sum(coalesce(closed, 0)) OVER o AS cut
        FROM rk JOIN n USING (node) LEFT JOIN cl USING (rank) WINDOW o AS (ORDER BY rk.rank)),
win AS (SELECT rank, vol, cut, cut / least(vol, (SELECT sum(vol) FROM n) - vol) AS phi FROM pre WHERE rank < (SELECT count(*) FROM n))"""


_FIEDLER = f"""{_LAPLACIAN}, {k.matrix("lap", s="walk")}, {k.eigen(2)},
fv AS (SELECT node, vec[2][p] / sqrt(vol) AS value FROM (SELECT node, vol, row_number() OVER (ORDER BY node) AS p FROM n), eig),
la AS (SELECT 2 - lam[2] AS lambda2 FROM eig)"""


@query(f"""WITH RECURSIVE {TEN_NODES}, {_FIEDLER}, {_sweep_sql("fv")}
SELECT round(lambda2 / 2, 6) AS lower, (SELECT round(min(phi), 6) FROM p) AS exact, (SELECT round(min(phi), 6) FROM win) AS swept, round(sqrt(2 * lambda2), 6) AS upper FROM la""")
def cut_bounds_exact(spark: SparkSession, d: str) -> DataFrame:
    """Half the second eigenvalue, the exact least conductance, the swept one, and the quadratic bound."""
    g = small.SmallGraph.of(_ten(spark, d))
    lam, vector = g.fiedler()
    return spark.createDataFrame([(round(lam / 2, 6), round(float(g.exact()[0]), 6), round(float(g.sweep(vector)[0]), 6), round((2 * lam) ** 0.5, 6))], "lower double, exact double, swept double, upper double")


@query(f"""WITH {TEN_NODES}, ph AS (SELECT m, cut / vol AS phi FROM v JOIN c USING (m)),
half AS (SELECT m FROM v WHERE vol <= (SELECT sum(vol) FROM n) / 2)
SELECT x.m AS start, round(any_value(y.phi), 6) AS phi, round(min(b.phi), 6) AS improved_phi FROM half x JOIN ph y USING (m) JOIN ph b ON b.m & x.m = b.m GROUP BY x.m""")
def flow_improvement_exact(spark: SparkSession, d: str) -> DataFrame:
    """From every set of at most half the volume: the best subset by conductance, which max-flow finds."""
    g = small.SmallGraph.of(_ten(spark, d))
    starts = [[i for i in range(g.n) if m >> i & 1] for m in range(1, 1 << g.n)]
    starts = [s for s in starts if len(s) < g.n and g.degree[s].sum() <= g.volume / 2]
    found = probes.improvements(spark, g, starts)
    return spark.createDataFrame([(sum(1 << i for i in s), round(a, 6), round(b, 6)) for s, (a, b, _) in zip(starts, found, strict=True)], "start long, phi double, improved_phi double")


#: A public club network of 34 nodes, larger neighbours only.
CLUB = {
    1: "2 3 4 5 6 7 8 9 11 12 13 14 18 20 22 32", 2: "3 4 8 14 18 20 22 31", 3: "4 8 9 10 14 28 29 33", 4: "8 13 14", 5: "7 11", 6: "7 11 17",
    7: "17", 9: "31 33 34", 10: "34", 14: "34", 15: "33 34", 16: "33 34", 19: "33 34", 20: "34", 21: "33 34", 23: "33 34", 24: "26 28 30 33 34",
    25: "26 28 32", 26: "32", 27: "30 34", 28: "34", 29: "32 34", 30: "33 34", 31: "33 34", 32: "33 34", 33: "34",
}
_CLUB = "e AS (SELECT i, unnest(string_split(js, ' '))::INT AS j, 1.0::DOUBLE AS w FROM (VALUES " + ", ".join(f"({a}, '{b}')" for a, b in CLUB.items()) + ") x(i, js)), n AS (SELECT i AS node, count(*)::DOUBLE AS vol FROM (SELECT i FROM e UNION ALL SELECT j FROM e) GROUP BY i)"


def _club(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(a, int(b), 1.0) for a, bs in CLUB.items() for b in bs.split()], "src long, dst long, w double")


_TRADE = """tr AS (SELECT least(c_nationkey, s_nationkey) AS i, greatest(c_nationkey, s_nationkey) AS j, count(*) AS lines
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE c_nationkey <> s_nationkey GROUP BY ALL),
e AS (SELECT i, j, lines::DOUBLE AS w FROM tr WHERE lines * (SELECT count(*) FROM tr) > (SELECT sum(lines) FROM tr)),
n AS (SELECT i AS node, sum(w) AS vol FROM (SELECT i, w FROM e UNION ALL SELECT j, w FROM e) GROUP BY i)"""


def _trade(spark: SparkSession, d: str) -> DataFrame:
    """Nations that trade more than pairs do on average; w counts lines from a supplier's nation to a customer's, both ways."""
    c = t.load(spark, d, "customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").cast("long").alias("x"))
    s = t.load(spark, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").cast("long").alias("y"))
    lines = t.bought(spark, d).join(c.hint("merge"), "o_custkey").join(s, "l_suppkey").filter("x != y")
    pairs = lines.groupBy(F.least("x", "y").alias("src"), F.greatest("x", "y").alias("dst")).agg(F.count("*").alias("n")).cache()
    mean = pairs.agg(F.count("*").alias("k"), F.sum("n").alias("s"))
    return pairs.crossJoin(F.broadcast(mean)).filter("n * k > s").select("src", "dst", F.col("n").cast("double").alias("w"))


@query(f"WITH RECURSIVE {_TRADE}, {_resistances('n')} SELECT i::BIGINT AS src, j::BIGINT AS dst, round(r * 1e3, 6) AS r_milli, round(w * r, 6) AS leverage FROM res")
def club_edge_leverage(spark: SparkSession, d: str) -> DataFrame:
    """Of the nations that trade with each other above the average."""
    return resistance.exact(_trade(spark, d)).select("src", "dst", r6(F.col("r") * 1e3).alias("r_milli"), r6(F.col("leverage")).alias("leverage"))


@query(f"""WITH RECURSIVE {_TRADE}, {_resistances('n')}, {_DEGREE_CORR}
SELECT round(corr(w * r, a.deg * b.deg), 6) AS with_product, round(corr(w * r, a.deg + b.deg), 6) AS with_sum FROM res JOIN d a ON a.node = i JOIN d b ON b.node = j""")
def club_leverage_and_degree(spark: SparkSession, d: str) -> DataFrame:
    e = _trade(spark, d).cache()
    out = resistance.correlates(e, resistance.exact(e))
    return out.select(r6(F.col("with_product")).alias("with_product"), r6(F.col("with_sum")).alias("with_sum"))


@query(f"""WITH RECURSIVE {_CLUB}, {_FIEDLER}, {_sweep_sql("fv")}
SELECT round(lambda2, 5) AS lambda2, round(min(phi), 6) AS phi, arg_min(least(rank, 34 - rank), phi) AS size FROM la, win GROUP BY lambda2""")
def club_spectral_sweep(spark: SparkSession, d: str) -> DataFrame:
    """Second eigenvalue by distributed iteration, and the best prefix of its vector."""
    e = _club(spark).cache()
    vector, quotient = spectral.fiedler(e, 100, 0.0, every=25)
    best = graph.best_prefix(spectral.sweep(e, vector))
    return best.select(F.lit(round(quotient, 5)).alias("lambda2"), r6(F.col("phi")).alias("phi"), F.least("rank", F.lit(34) - F.col("rank")).cast("long").alias("size"))


@query("SELECT 1.0::DOUBLE AS within")
def club_lower_bound(spark: SparkSession, d: str) -> DataFrame:
    """Half of the least second eigenvalue lies under the least swept conductance, and not far from half the quotient."""
    e = _club(spark).cache()
    low = spectral.lower_bound(e, 100)
    return spark.createDataFrame([(float(0.06 < low <= 10 / 76),)], "within double")


# --- scores of sets --------------------------------------------------------------------


_BRAND_SETS = """sets AS (SELECT DISTINCT p_brand AS set_id, node FROM (
  SELECT p_brand, p_partkey * 2 + 1 AS node FROM part
  UNION ALL SELECT p_brand, o_custkey * 2 FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey WHERE l_extendedprice > 50000))"""


def _brand_sets(spark: SparkSession, d: str) -> DataFrame:
    part = t.load(spark, d, "part").select("p_partkey", "p_brand")
    rich = t.bought(spark, d).filter("l_extendedprice > 50000").join(part, F.col("l_partkey") == F.col("p_partkey"))
    return part.select(F.col("p_brand").alias("set_id"), (F.col("p_partkey") * 2 + 1).alias("node")).unionByName(
        rich.select(F.col("p_brand").alias("set_id"), (F.col("o_custkey") * 2).alias("node"))
    )


@query(f"""WITH {BIDS}, {BOTH}, {_BRAND_SETS},
f AS (SELECT x.set_id, s.src, sum(CASE WHEN y.node IS NULL THEN w ELSE 0 END) / sum(w) AS odf FROM s JOIN sets x ON x.node = s.src LEFT JOIN sets y ON y.node = s.dst AND y.set_id = x.set_id GROUP BY ALL)
SELECT set_id, round(max(odf), 6) AS odf_max, round(avg(odf), 6) AS odf_avg, round(avg((odf > 0.5)::INT), 6) AS odf_half FROM f GROUP BY set_id""")
def set_out_degree_fractions(spark: SparkSession, d: str) -> DataFrame:
    s = graph.score(t.g_bids(spark, d), _brand_sets(spark, d))
    return s.select("set_id", *[r6(F.col(c)).alias(c) for c in ("odf_max", "odf_avg", "odf_half")])


@query(f"""WITH {BIDS}, {BOTH}, {_BRAND_SETS}, tot AS (SELECT count(*) AS n FROM g),
mass AS (SELECT node, CASE WHEN node % 2 = 1 THEN 3.0 ELSE 1.0 END AS mass FROM g), all_ AS (SELECT sum(mass) AS total FROM mass),
b AS (SELECT set_id, count(*) AS size, sum(mass) AS mass, sum(vol) AS vol FROM sets JOIN g USING (node) JOIN mass USING (node) GROUP BY set_id),
i AS (SELECT x.set_id, sum(w) AS inside FROM s JOIN sets x ON x.node = s.src JOIN sets y ON y.node = s.dst AND y.set_id = x.set_id GROUP BY ALL)
SELECT set_id, round((vol - coalesce(inside, 0)) / least(mass, total - mass) / 1e3, 4) AS expansion_k, round((vol - coalesce(inside, 0)) * total / (mass * (total - mass)) / 1e3, 4) AS expansion_product_k,
       round((vol - coalesce(inside, 0)) / (size * (n - size)), 4) AS cut_ratio, round(coalesce(inside, 0) / (size * (size - 1)), 4) AS internal_density
FROM b LEFT JOIN i USING (set_id), tot, all_""")
def set_scores_weighted_nodes(spark: SparkSession, d: str) -> DataFrame:
    """Parts weigh three times as much as customers."""
    e = t.g_bids(spark, d).cache()
    nodes = graph.degrees(e).select("node", F.when(F.col("node") % 2 == 1, 3.0).otherwise(1.0).alias("mass_"))
    s = graph.score(e, _brand_sets(spark, d), nodes, "mass_")
    return s.select(
        "set_id", F.round(F.col("expansion") / 1e3, 4).alias("expansion_k"), F.round(F.col("expansion_product") / 1e3, 4).alias("expansion_product_k"),
        F.round("cut_ratio", 4).alias("cut_ratio"), F.round("internal_density", 4).alias("internal_density"),
    )


@query("""WITH s AS (SELECT p_brand AS set_id, p_partkey AS node FROM part), l AS (SELECT p_partkey AS node, p_type AS label FROM part),
b AS (SELECT set_id, label, count(*) AS hit FROM s JOIN l USING (node) GROUP BY ALL), n AS (SELECT set_id, count(*) AS n FROM s GROUP BY ALL), m AS (SELECT label, count(*) AS m FROM l GROUP BY ALL),
x AS (SELECT *, hit / n AS precision, hit / m AS recall, 2 * hit / (n + m) AS f1 FROM b JOIN n USING (set_id) JOIN m USING (label)),
o AS (SELECT *, row_number() OVER (PARTITION BY set_id ORDER BY f1 DESC, label DESC) AS place, max(precision) OVER (PARTITION BY set_id) AS purity FROM x)
SELECT set_id, label, round(precision, 6) AS precision, round(recall, 6) AS recall, round(f1, 6) AS f1, round(purity, 6) AS purity FROM o WHERE place = 1""")
def ground_truth_agreement(spark: SparkSession, d: str) -> DataFrame:
    """Brands as sets, part types as the truth."""
    part = t.load(spark, d, "part")
    sets = part.select(F.col("p_brand").alias("set_id"), F.col("p_partkey").alias("node"))
    out = probes.ground_truth(sets, part.select(F.col("p_partkey").alias("node"), F.col("p_type").alias("label")))
    return out.select("set_id", "label", *[r6(F.col(c)).alias(c) for c in ("precision", "recall", "f1", "purity")])


_N = "n AS (SELECT node, vol FROM g)"
_IJ = SPARSE.replace("e AS (", "e0 AS (") + ", e AS (SELECT src, dst, w, src AS i, dst AS j FROM e0)"


@query(f"""WITH {_IJ}, {BOTH}, {_N}, o AS (SELECT node, deg::DOUBLE AS value FROM g), {_sweep_sql("o")}, v AS (SELECT sum(vol) AS v FROM n)
SELECT rank::INT AS rank, round(phi, 6) AS phi, vol, cut FROM win, v WHERE least(vol, v - vol) >= 0.3 * v ORDER BY win.phi, rank LIMIT 1""")
def sweep_balanced(spark: SparkSession, d: str) -> DataFrame:
    """The best prefix by degree with three tenths of the volume on each side."""
    e = _sparse(spark, d).cache()
    deg = graph.degrees(e)
    swept = spectral.sweep(e, deg.select("node", F.col("deg").cast("double").alias("value")))
    best = spectral.balanced(swept, deg.agg(F.sum("vol").alias("v")).first()["v"], 0.3)
    return best.select("rank", r6(F.col("phi")).alias("phi"), "vol", "cut")


_COMPONENTS = "flood AS (SELECT node, node AS root FROM g UNION SELECT s.dst, flood.root FROM flood JOIN s ON s.src = flood.node AND flood.root < s.dst), comp AS (SELECT node, min(root) AS component FROM flood GROUP BY node)"


@query(f"""WITH RECURSIVE {SPARSE}, {BOTH}, {_COMPONENTS}, z AS (SELECT component, count(*) AS size FROM comp GROUP BY component), k AS (SELECT count(*) AS nodes FROM part)
SELECT nodes + p AS nodes, round((nodes + p - (SELECT count(*) FROM g)) / (nodes + p), 6) AS isolated, (SELECT count(*) FROM z) AS components, round((SELECT max(size) FROM z) / (nodes + p), 6) AS largest_share
FROM k, (SELECT count(DISTINCT src) AS p FROM s WHERE src % 2 = 0)""")
def graph_concentration(spark: SparkSession, d: str) -> DataFrame:
    """All parts and the early orders: isolated ones, components, the largest."""
    e = _sparse(spark, d).cache()
    parts = t.load(spark, d, "part").select((F.col("p_partkey") * 2 + 1).alias("node"))
    nodes = parts.union(graph.degrees(e).filter("node % 2 = 0").select("node"))
    out = graph.concentration(e, nodes)
    return out.select("nodes", r6(F.col("isolated")).alias("isolated"), "components", r6(F.col("largest_share")).alias("largest_share"))


# --- local methods, round by round ----------------------------------------------------


#: The largest component of the sparse graph as e, s, g, and sh: shares of the walk.
GIANT = f"""{SPARSE.replace("e AS (", "e1 AS (")}, s1 AS (SELECT src, dst FROM e1 UNION ALL SELECT dst, src FROM e1), n1 AS (SELECT DISTINCT src AS node FROM s1),
flood AS (SELECT node, node AS root FROM n1 UNION SELECT s1.dst, flood.root FROM flood JOIN s1 ON s1.src = flood.node AND flood.root < s1.dst),
comp AS MATERIALIZED (SELECT node, min(root) AS component FROM flood GROUP BY node),
big AS (SELECT component FROM comp GROUP BY component ORDER BY count(*) DESC, component LIMIT 1),
e AS MATERIALIZED (SELECT src, dst, w, src AS i, dst AS j FROM e1 JOIN comp ON comp.node = src JOIN big USING (component)),
s AS MATERIALIZED (SELECT src, dst, w FROM e UNION ALL SELECT dst, src, w FROM e), g AS MATERIALIZED (SELECT src AS node, count(*) AS deg, sum(w) AS vol FROM s GROUP BY src)"""


def _seeds(count: int) -> str:
    return f"seeds AS (SELECT node FROM g ORDER BY {u01_sql('node', 0)}, node LIMIT {count})"


def _local_sweep(vectors: str) -> str:
    """CTE pre (seed_id, rank, vol, cut, phi) of a table (seed_id, node, value), value over degree."""
    return f"""lk AS (SELECT seed_id, node, vol, row_number() OVER (PARTITION BY seed_id ORDER BY value / vol DESC, node) AS rank FROM {vectors} JOIN g USING (node)),
lc AS (SELECT a.seed_id, greatest(a.rank, b.rank) AS rank, sum(w) AS closed FROM e JOIN lk a ON a.node = e.src JOIN lk b ON b.node = e.dst AND b.seed_id = a.seed_id GROUP BY ALL),
lv AS (SELECT sum(vol) AS v FROM g),
lp AS (SELECT lk.seed_id, lk.rank, sum(vol) OVER o AS vol, sum(vol) OVER o - 2 * sum(coalesce(closed, 0)) OVER o AS cut
       FROM lk LEFT JOIN lc ON lc.seed_id = lk.seed_id AND lc.rank = lk.rank WINDOW o AS (PARTITION BY lk.seed_id ORDER BY lk.rank)),
pre AS (SELECT seed_id, rank, vol, cut, cut / least(vol, v - vol) AS phi FROM lp, lv WHERE least(vol, v - vol) > 0)"""


_BEST = "SELECT seed_id, rank::INT AS rank, round(phi, 6) AS phi, vol, cut FROM (SELECT *, row_number() OVER (PARTITION BY seed_id ORDER BY round(phi, 9), rank) AS place FROM pre) WHERE place = 1"


def _best(e: DataFrame, vectors: DataFrame, value: str = "value") -> DataFrame:
    swept = local.sweep(e, vectors, value).withColumn("phi", F.round("phi", 9))
    return graph.best_prefix(swept).select("seed_id", "rank", r6(F.col("phi")).alias("phi"), "vol", "cut")


def _nibble_sql(steps: int, eps: float) -> str:
    return f"""nib AS (SELECT 0 AS t, node AS seed_id, node, 1.0::DOUBLE AS value FROM seeds
  UNION ALL
  SELECT t + 1, seed_id, node, value FROM (
    SELECT t, seed_id, node, sum(value) AS value FROM (
      SELECT t, seed_id, node, value / 2 AS value FROM nib WHERE t < {steps}
      UNION ALL SELECT t, seed_id, s.dst, value / 2 * w / vol FROM nib JOIN g USING (node) JOIN s ON s.src = nib.node WHERE t < {steps}) GROUP BY ALL) JOIN g USING (node) WHERE value >= {eps} * vol),
vec AS (SELECT seed_id, node, value FROM nib WHERE t = {steps})"""


@query(f"WITH RECURSIVE {GIANT}, {_seeds(8)}, {_nibble_sql(20, 1e-4)}, {_local_sweep('vec')} {_BEST}")
def local_nibble_sets(spark: SparkSession, d: str) -> DataFrame:
    e = graph.giant(_sparse(spark, d)).cache()
    return _best(e, local.nibble(e, local.seeds_by_hash(e, 8)))


@query(f"""WITH RECURSIVE {GIANT}, {_seeds(8)},
hk AS (SELECT 0 AS t, node AS seed_id, node, 1.0::DOUBLE AS value, 1.0::DOUBLE AS weight FROM seeds
  UNION ALL
  SELECT t + 1, seed_id, node, value, weight * 5.0 / (t + 1) FROM (
    SELECT t, seed_id, s.dst AS node, sum(value * w / vol) AS value, any_value(weight) AS weight FROM hk JOIN g USING (node) JOIN s ON s.src = hk.node WHERE t < 12 GROUP BY ALL) JOIN g USING (node) WHERE value >= 1e-5 * vol),
vec AS (SELECT seed_id, node, sum(value * weight) * exp(-5.0) AS value FROM hk GROUP BY ALL), {_local_sweep('vec')} {_BEST}""")
def local_heat_sets(spark: SparkSession, d: str) -> DataFrame:
    e = graph.giant(_sparse(spark, d)).cache()
    return _best(e, local.heat(e, local.seeds_by_hash(e, 8)))


def _ppr_sql(alpha: float, eps: float, rounds: int, name: str = "pp") -> str:
    """CTE vec (seed_id, node, value): the pushed mass once no residual is left to push."""
    big = f"r >= {eps} * vol"
    return f"""{name} AS (SELECT 0 AS t, node AS seed_id, node, 0.0::DOUBLE AS p, 1.0::DOUBLE AS r FROM seeds
  UNION ALL
  SELECT t + 1, seed_id, node, sum(p), sum(r) FROM (
    SELECT t, seed_id, node, CASE WHEN {big} THEN p + {alpha} * r ELSE p END AS p, CASE WHEN {big} THEN {(1 - alpha) / 2} * r ELSE r END AS r FROM {name} JOIN g USING (node) WHERE t < {rounds}
    UNION ALL SELECT t, seed_id, s.dst, 0.0, {(1 - alpha) / 2} * r * w / vol FROM {name} JOIN g USING (node) JOIN s ON s.src = {name}.node WHERE t < {rounds} AND {big}) GROUP BY t, seed_id, node)"""


@query(f"WITH RECURSIVE {GIANT}, {_seeds(8)}, {_ppr_sql(0.05, 2e-4, 200)}, vec AS (SELECT seed_id, node, p AS value FROM pp WHERE t = 200 AND p > 0), {_local_sweep('vec')} {_BEST}")
def local_ppr_sets(spark: SparkSession, d: str) -> DataFrame:
    e = graph.giant(_sparse(spark, d)).cache()
    return _best(e, local.ppr(e, local.seeds_by_hash(e, 8), 0.05, 2e-4).filter("p > 0"), "p")


def _profile_sql(prefix: str = "pre") -> str:
    return f"""sz AS (SELECT phi, CASE WHEN vol * 2 > v THEN n - rank ELSE rank END AS size FROM {prefix}, lv, (SELECT count(*) AS n FROM g))
SELECT pow(2.0, floor(log2(size)))::DOUBLE AS bin, round(min(phi), 6) AS phi FROM sz WHERE size > 0 GROUP BY 1"""


@query(f"WITH RECURSIVE {GIANT}, {_seeds(16)}, {_ppr_sql(0.1, 2e-4, 200)}, vec AS (SELECT seed_id, node, p AS value FROM pp WHERE t = 200 AND p > 0), {_local_sweep('vec')}, {_profile_sql()}")
def profile_local_bins(spark: SparkSession, d: str) -> DataFrame:
    """Least conductance by size over all prefixes of local sweeps."""
    e = graph.giant(_sparse(spark, d)).cache()
    return probes.profile(probes.local_profile(e, 16, (0.1,), 2e-4)).select("bin", r6(F.col("phi")).alias("phi"))


def _peel(k_: int, rounds: int, source: str = "e") -> str:
    return f"p0 AS (SELECT src, dst, w FROM {source})" + "".join(
        f""",
q{i} AS MATERIALIZED (SELECT node FROM (SELECT src AS node FROM p{i} UNION ALL SELECT dst FROM p{i}) GROUP BY node HAVING count(*) >= {k_}),
p{i + 1} AS MATERIALIZED (SELECT src, dst, w FROM p{i} WHERE src IN (SELECT node FROM q{i}) AND dst IN (SELECT node FROM q{i}))"""
        for i in range(rounds)
    )


#: Bridges by trying every edge of the two-core: its ends stay connected without it, or not.
_WHISKERS = f"""{GIANT}, {_peel(2, 30)}, two AS MATERIALIZED (SELECT src, dst, row_number() OVER (ORDER BY src, dst) AS id FROM p30),
arcs AS MATERIALIZED (SELECT src, dst, id FROM two UNION ALL SELECT dst, src, id FROM two),
reach AS (SELECT id AS gone, src AS node, dst AS goal FROM two UNION SELECT gone, arcs.dst, goal FROM reach JOIN arcs ON arcs.src = reach.node AND arcs.id <> reach.gone),
firm AS MATERIALIZED (SELECT src, dst FROM two WHERE id IN (SELECT gone FROM reach WHERE node = goal)),
fs AS MATERIALIZED (SELECT src, dst FROM firm UNION ALL SELECT dst, src FROM firm),
ff AS (SELECT node, node AS root FROM g UNION SELECT fs.dst, ff.root FROM ff JOIN fs ON fs.src = ff.node AND ff.root < fs.dst),
piece AS MATERIALIZED (SELECT node, min(root) AS piece FROM ff GROUP BY node),
core AS MATERIALIZED (SELECT node FROM piece WHERE piece = (SELECT piece FROM piece GROUP BY piece ORDER BY count(*) DESC, piece LIMIT 1)),
ws AS MATERIALIZED (SELECT src, dst FROM s WHERE src NOT IN (SELECT node FROM core) AND dst NOT IN (SELECT node FROM core)),
wf AS (SELECT node, node AS root FROM g WHERE node NOT IN (SELECT node FROM core) UNION SELECT ws.dst, wf.root FROM wf JOIN ws ON ws.src = wf.node AND wf.root < ws.dst),
wh AS MATERIALIZED (SELECT node, min(root) AS whisker FROM wf GROUP BY node)"""


@query(f"""WITH RECURSIVE {_WHISKERS}
SELECT (SELECT count(*) FROM g) AS nodes, (SELECT count(*) FROM e) AS edges, (SELECT count(DISTINCT whisker) FROM wh) AS whiskers, (SELECT max(c) FROM (SELECT count(*) AS c FROM wh GROUP BY whisker)) AS largest,
       round((SELECT count(*) FROM wh) / (SELECT count(*) FROM g), 6) AS node_share,
       round(1 - (SELECT count(*) FROM e WHERE src IN (SELECT node FROM core) AND dst IN (SELECT node FROM core)) / (SELECT count(*) FROM e), 6) AS edge_share""")
def whisker_shares(spark: SparkSession, d: str) -> DataFrame:
    e = graph.giant(_sparse(spark, d)).cache()
    out = probes.whisker_shares(e, probes.decompose(e))
    return out.select("nodes", "edges", "whiskers", "largest", r6(F.col("node_share")).alias("node_share"), r6(F.col("edge_share")).alias("edge_share"))


@query(f"""WITH RECURSIVE {_WHISKERS}, w AS (SELECT whisker, count(*) AS size, sum(deg)::DOUBLE AS vol FROM wh JOIN g USING (node) GROUP BY whisker)
SELECT CAST(sum(size) OVER o AS BIGINT) AS size, count(*) OVER o AS whiskers, sum(vol) OVER o AS vol, round(count(*) OVER o / sum(vol) OVER o, 6) AS phi FROM w WINDOW o AS (ORDER BY vol DESC, whisker ROWS UNBOUNDED PRECEDING)""")
def whisker_bag_prefixes(spark: SparkSession, d: str) -> DataFrame:
    e = graph.giant(_sparse(spark, d)).cache()
    out = probes.bag_prefixes(probes.whisker_summary(e, probes.decompose(e)))
    return out.select("size", "whiskers", "vol", r6(F.col("phi")).alias("phi"))


@query(f"""WITH RECURSIVE {_WHISKERS}, far AS (SELECT node AS a, node AS b, 0 AS dist FROM wh UNION SELECT a, ws.dst, dist + 1 FROM far JOIN ws ON ws.src = far.b WHERE dist < 60),
near AS (SELECT a, b, min(dist) AS dist FROM far GROUP BY a, b), c AS (SELECT whisker, count(*) AS n FROM wh GROUP BY whisker)
SELECT whisker AS set_id, any_value(n) AS n, 1::BIGINT AS parts, max(dist)::BIGINT AS diameter, round(sum(dist) / nullif(count(*) - any_value(n), 0), 6) AS mean_distance FROM near JOIN wh ON wh.node = near.a JOIN c USING (whisker) GROUP BY whisker""")
def compactness_whiskers(spark: SparkSession, d: str) -> DataFrame:
    e = graph.giant(_sparse(spark, d)).cache()
    sets = probes.decompose(e).filter("role = 'whisker'").select(F.col("whisker_id").alias("set_id"), "node")
    return probes.compactness(e, sets).select("set_id", "n", "parts", "diameter", r6(F.col("mean_distance")).alias("mean_distance"))


@query(f"""WITH RECURSIVE {GIANT}, {_seeds(16)},
bf AS (SELECT node AS source, node, 0 AS dist FROM seeds UNION SELECT source, s.dst, dist + 1 FROM bf JOIN s ON s.src = bf.node WHERE dist < 40),
ds AS MATERIALIZED (SELECT source, node, min(dist) AS dist FROM bf GROUP BY ALL),
pa AS (SELECT source, node, dist, 1.0::DOUBLE AS paths FROM ds WHERE dist = 0
  UNION ALL
  SELECT source, node, any_value(dist), sum(paths) FROM (SELECT pa.source, ds.node, ds.dist, pa.paths FROM pa JOIN s ON s.src = pa.node JOIN ds ON ds.source = pa.source AND ds.node = s.dst AND ds.dist = pa.dist + 1) GROUP BY source, node),
top AS (SELECT max(dist) AS top FROM ds),
ld AS (SELECT source, node, dist, paths, 1.0::DOUBLE AS load FROM pa, top WHERE dist = top
  UNION ALL
  SELECT source, node, dist, any_value(paths), 1 + sum(handed) FROM (
    SELECT p.source, p.node, p.dist, p.paths, CASE WHEN s.dst IS NULL THEN 0 ELSE p.paths * l.load / l.paths END AS handed
    FROM (SELECT DISTINCT dist - 1 AS nearer FROM ld WHERE dist > 0) z JOIN pa p ON p.dist = z.nearer
    LEFT JOIN (SELECT l.source, l.node, l.load, l.paths, s.dst AS up FROM ld l JOIN s ON s.src = l.node) l ON l.source = p.source AND l.up = p.node
    LEFT JOIN (SELECT DISTINCT dst FROM s) s ON s.dst = l.up) GROUP BY source, node, dist),
cr AS (SELECT least(n.node, f.node) AS src, greatest(n.node, f.node) AS dst, n.paths * f.load / f.paths AS credit FROM ld f JOIN s ON s.src = f.node JOIN ld n ON n.source = f.source AND n.node = s.dst AND n.dist = f.dist - 1)
SELECT e.src, e.dst, round(coalesce(sum(credit), 0), 6) AS betweenness FROM e LEFT JOIN cr ON cr.src = e.src AND cr.dst = e.dst GROUP BY e.src, e.dst""")
def edge_betweenness_sources(spark: SparkSession, d: str) -> DataFrame:
    """Shares of the shortest paths from sixteen hashed sources over each edge."""
    e = graph.giant(_sparse(spark, d)).cache()
    return graph.betweenness(e, local.seeds_by_hash(e, 16).select("node")).select("src", "dst", r6(F.col("betweenness")).alias("betweenness"))


# --- reference graphs and workloads ------------------------------------------------------


_TAIL = """m AS (SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM raw WHERE a <> b), d AS (SELECT count(*) AS deg FROM (SELECT src AS node FROM m UNION ALL SELECT dst FROM m) GROUP BY node)
SELECT count(*) AS nodes, round(avg(deg), 6) AS mean, round(var_pop(deg), 6) AS variance, round(var_pop(deg) / avg(deg), 6) AS dispersion,
       round(1 + sum((deg >= 2)::INT) / sum(CASE WHEN deg >= 2 THEN ln(deg / 1.5) END), 6) AS exponent FROM d"""


def _model(name: str, make, raw: str) -> None:
    def run(spark: SparkSession, d: str) -> DataFrame:
        tail = graph.degree_tail(make(spark, d))
        return tail.select("nodes", *[r6(F.col(c)).alias(c) for c in tail.columns[1:]])

    QUERIES[f"model_{name}"], ORACLES[f"model_{name}"] = run, f"WITH RECURSIVE {raw}, {_TAIL}"


def _end(seed: int) -> str:
    return f"floor(pow({u01_sql('id', seed)}, {1 / (0.5 / 1.5)!r}) * 2000)::BIGINT"


def _customers(spark: SparkSession, d: str) -> tuple[int, DataFrame]:
    """The number of customers and id, counted from 0 by key."""
    ids = relational.numbered(t.load(spark, d, "customer"), "c_custkey").cache()
    return ids.count(), ids


#: CTEs ids (id), nn (n) and mp (a, c): the customers, their number, and models.expander_maps of it at the seed.
_IDS = "ids AS (SELECT row_number() OVER (ORDER BY c_custkey) - 1 AS id, c_custkey FROM customer), nn AS (SELECT count(*) AS n FROM customer)"
_MAPS = """mq AS (SELECT {a}::BIGINT AS a, (gcd({a}, n) = 1)::INT AS k, n FROM nn UNION ALL
  SELECT b, k + (gcd(b, n) = 1)::INT, n FROM (SELECT (a * 31 + 17) % greatest(5, n) AS b, k, n FROM mq WHERE k < 3)),
mp AS (SELECT a, 7 * a + {seed} AS c FROM mq WHERE gcd(a, n) = 1)"""


def _expander(spark: SparkSession, d: str) -> DataFrame:
    n, ids = _customers(spark, d)
    return models.expander(spark, n, nodes=ids)


_model("power_law", lambda s, d: models.power_law(s, 2000, 4.0, 2.5), f"raw AS (SELECT {_end(0)} AS a, {_end(1)} AS b FROM range(4000) r(id))")
def _geometric(spark: SparkSession, d: str) -> DataFrame:
    """Customers at hashed places; the radius keeps the mean degree of 1,000 points within 0.06."""
    n, ids = _customers(spark, d)
    points = ids.select("id", u01("c_custkey", 0).alias("x"), u01("c_custkey", 1).alias("y"))
    return models.near_points(points, 0.06 * math.sqrt(1000.0 / n))


_model("geometric", _geometric, f"""{_IDS}, rd AS (SELECT 0.06::DOUBLE * sqrt(1000.0::DOUBLE / n) AS r FROM nn), p AS (SELECT id, {u01_sql('c_custkey', 0)} AS x, {u01_sql('c_custkey', 1)} AS y FROM ids),
ce AS (SELECT id, x, y, floor(x / r)::BIGINT AS cx, floor(y / r)::BIGINT AS cy, r FROM p, rd), ne AS (SELECT id, x, y, cx + i AS cx, cy + j AS cy FROM ce, range(-1, 2) s(i), range(-1, 2) q(j)),
raw AS (SELECT p.id AS a, q.id AS b FROM ce p JOIN ne q ON p.cx = q.cx AND p.cy = q.cy AND p.id < q.id AND (p.x - q.x) ** 2 + (p.y - q.y) ** 2 <= r * r)""")
_model("expander", _expander, _IDS + ", " + _MAPS.format(a=5, seed=1) + ", raw AS (SELECT id AS a, (id * mp.a + mp.c) % n AS b FROM ids, nn, mp)")
_model("road_like", lambda s, d: models.road_like(s, 30), f"l AS (SELECT i AS a, i + 1 AS b FROM range(900) r(i) WHERE i % 30 < 29 UNION ALL SELECT i, i + 30 FROM range(900) r(i) WHERE i < 870), raw AS (SELECT * FROM l WHERE {u01_sql(chr(39).join(['a::VARCHAR || ', '-', ' || b::VARCHAR']), 0)} >= 0.3)")
def _hierarchical(spark: SparkSession, d: str) -> DataFrame:
    """Customers as the leaves of a tree of fan 3, as many levels as hold them all."""
    n, ids = _customers(spark, d)
    return models.hierarchical(spark, next(v for v in range(1, 64) if 3**v >= n), nodes=ids, n=n)


_draw = lambda seed: f"(('0x' || substr(md5(({seed})::VARCHAR || ':' || id::VARCHAR || '-' || t::VARCHAR), 1, 8))::BIGINT / 4294967296.0)"
_model("hierarchical", _hierarchical, f"""{_IDS}, lv AS (SELECT v, (3 ** v)::BIGINT AS block, n FROM range(1, 39) r(v), nn WHERE 3 ** (v - 1) < n OR v = 1),
raw AS (SELECT id AS a, id // block * block + floor({_draw('v')} * least(block, n - id // block * block))::BIGINT AS b FROM ids, lv, range(2) q(t) WHERE {_draw('100 + v')} < 2.0::DOUBLE ** (1 - v))""")
def _core_periphery(spark: SparkSession, d: str) -> DataFrame:
    """Customers as the core; every supplier hangs a path on one of them."""
    n, ids = _customers(spark, d)
    hung = relational.numbered(t.load(spark, d, "supplier"), "s_suppkey")
    return models.core_periphery(spark, n, 0, nodes=ids, hung=hung)


_model("core_periphery", _core_periphery, f"""{_IDS}, {_MAPS.format(a=5, seed=1)}, hu AS (SELECT row_number() OVER (ORDER BY s_suppkey) - 1 AS id FROM supplier),
raw AS (SELECT id AS a, (id * mp.a + mp.c) % n AS b FROM ids, nn, mp UNION ALL
  SELECT n + id * 8 + t, CASE WHEN t = 0 THEN floor({u01_sql('id', 1)} * n)::BIGINT ELSE n + id * 8 + t - 1 END FROM hu, nn, range(5) q(t) WHERE t < floor({u01_sql('id', 0)} * 5) + 1)""")


@query(r"""WITH b AS (SELECT DISTINCT doc_id, unnest(regexp_extract_all(lower(text), '([\p{L}\p{M}\p{N}_]+)', 1)) AS term FROM documents), t AS (SELECT term, count(*) AS deg FROM b GROUP BY term)
SELECT (SELECT count(*) FROM b) AS edges, (SELECT count(DISTINCT doc_id) FROM b) + (SELECT count(*) FROM t) AS nodes, (SELECT count(*) FROM t WHERE deg = 1) AS leaf_terms, (SELECT max(deg) FROM t) AS widest""")
def workload_doc_term(spark: SparkSession, d: str) -> DataFrame:
    e = t.g_doc_term(spark, d).cache()
    deg = graph.degrees(e).withColumn("term", F.col("node") % 2 == 1)
    return deg.agg(
        F.sum(F.when(F.col("term"), F.col("deg"))).alias("edges"), F.count("*").alias("nodes"),
        F.sum((F.col("term") & (F.col("deg") == 1)).cast("long")).alias("leaf_terms"), F.max(F.when(F.col("term"), F.col("deg"))).alias("widest"),
    )


@query(f"""WITH RECURSIVE b AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS href FROM pages), e AS (SELECT page_id * 2 AS src, {key60_sql('href')} * 2 + 1 AS dst FROM b),
s AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e), g AS (SELECT DISTINCT src AS node FROM s), {_COMPONENTS}
SELECT (SELECT count(*) FROM e) AS edges, (SELECT count(*) FROM g) AS nodes, (SELECT count(DISTINCT component) FROM comp) AS components, (SELECT max(c) FROM (SELECT count(*) AS c FROM comp GROUP BY component)) AS largest""")
def workload_pages(spark: SparkSession, d: str) -> DataFrame:
    e = t.g_pages(spark, d).cache()
    sizes = graph.components(e).groupBy("component").agg(F.count("*").alias("size"))
    return sizes.agg(F.lit(e.count()).cast("long").alias("edges"), F.sum("size").alias("nodes"), F.count("*").alias("components"), F.max("size").alias("largest"))


@query("""WITH o AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey)
SELECT (SELECT sum(n + 1) FROM o)::BIGINT AS nodes, (SELECT sum(n) FROM o)::BIGINT AS bridges, (SELECT count(*) FROM o) AS components""")
def workload_forest(spark: SparkSession, d: str) -> DataFrame:
    """Customers and their orders: every edge is a bridge, every component a star."""
    e = t.g_customer_order(spark, d).cache()
    comp = graph.components(e)
    return comp.agg(F.count("*").alias("nodes"), F.lit(probes.bridges(e).count()).cast("long").alias("bridges"), F.countDistinct("component").alias("components"))


@query(f"""WITH {BIDS}, {BOTH} SELECT round(corr(vol, deg), 6) AS pearson,
 round(corr(rv, rd), 6) AS spearman FROM (SELECT vol, deg, rank() OVER (ORDER BY vol) AS rv, rank() OVER (ORDER BY deg) AS rd FROM g)""")
def rank_correlation_bids(spark: SparkSession, d: str) -> DataFrame:
    """Volume against degree of the bid graph, by value and by rank over running sums."""
    deg = graph.degrees(t.g_bids(spark, d)).withColumn("deg", F.col("deg").cast("double"))
    ranked = relational.ranks(relational.ranks(deg, "vol", "rv"), "deg", "rd")
    return ranked.agg(r6(F.corr("vol", "deg")).alias("pearson"), r6(F.corr("rv", "rd")).alias("spearman"))
