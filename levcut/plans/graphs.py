"""Registered queries of the graph half, with DuckDB twins where SQL can say it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levcut.functions.portable import r6, u01_sql
from levcut.operators import graph, local, models, multilevel, probes, resistance, small, spectral
from levcut.operators.relational import numbered
from levcut.runtime import bounded
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


BIDS = """e AS (SELECT least(o_custkey * 2, l_partkey * 2 + 1) AS src, greatest(o_custkey * 2, l_partkey * 2 + 1) AS dst, sum(l_extendedprice::DECIMAL(18, 2))::DOUBLE AS w
      FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL)"""
SPARSE = """e AS (SELECT DISTINCT least(l_orderkey * 2, l_partkey * 2 + 1) AS src, greatest(l_orderkey * 2, l_partkey * 2 + 1) AS dst, 1.0::DOUBLE AS w
      FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_orderdate < (SELECT min(o_orderdate) FROM orders) + INTERVAL 90 DAYS)"""
BOTH = "s AS (SELECT src, dst, w FROM e UNION ALL SELECT dst, src, w FROM e), g AS (SELECT src AS node, count(*) AS deg, sum(w) AS vol FROM s GROUP BY src)"


class AllDays(str):
    """A folder whose orders and parts are wanted whole."""


def _sparse(spark: SparkSession, d: str) -> DataFrame:
    """Orders and parts, of the first 90 days unless AllDays is given."""
    return t.g_order_part(spark, d, None if isinstance(d, AllDays) else 90)


@query(f"WITH {BIDS} SELECT src, dst, round(w, 2) AS w FROM e")
def graph_bids(spark: SparkSession, d: str) -> DataFrame:
    return t.g_bids(spark, d).withColumn("w", F.round("w", 2))


@query(f"WITH {SPARSE}, {BOTH} SELECT node, deg, vol FROM g")
def graph_degrees(spark: SparkSession, d: str) -> DataFrame:
    return graph.degrees(_sparse(spark, d))


@query(f"""WITH RECURSIVE {SPARSE}, {BOTH},
r AS (SELECT node, node AS root FROM g UNION SELECT s.dst, r.root FROM r JOIN s ON s.src = r.node AND r.root < s.dst)
SELECT node, min(root) AS component FROM r GROUP BY node""")
def graph_components(spark: SparkSession, d: str) -> DataFrame:
    return graph.components(_sparse(spark, d))


@query(f"""WITH RECURSIVE {SPARSE}, {BOTH},
z AS (SELECT min(node) AS node FROM g),
r AS (SELECT node, 0 AS dist FROM z UNION SELECT s.dst, r.dist + 1 FROM r JOIN s ON s.src = r.node WHERE r.dist < 6)
SELECT z.node AS source, r.node, min(dist)::INT AS dist FROM r, z GROUP BY ALL""")
def graph_bfs(spark: SparkSession, d: str) -> DataFrame:
    e = _sparse(spark, d)
    return graph.bfs(e, graph.degrees(e).agg(F.min("node").alias("node")), 6)


def _peel_sql(k: int, rounds: int) -> str:
    """Rounds of peeling, one CTE each; rounds past the fixpoint change nothing."""
    steps = "".join(
        f""",
n{i} AS MATERIALIZED (SELECT node FROM (SELECT src AS node FROM p{i} UNION ALL SELECT dst FROM p{i}) GROUP BY node HAVING count(*) >= {k}),
p{i + 1} AS MATERIALIZED (SELECT src, dst, w FROM p{i} WHERE src IN (SELECT node FROM n{i}) AND dst IN (SELECT node FROM n{i}))"""
        for i in range(rounds)
    )
    return f"WITH {SPARSE}, p0 AS MATERIALIZED (SELECT * FROM e){steps} SELECT src, dst, w FROM p{rounds}"


@query(_peel_sql(2, 30))
def graph_two_core(spark: SparkSession, d: str) -> DataFrame:
    return graph.peel(_sparse(spark, d), 2)


@query(r"""WITH b AS (SELECT DISTINCT doc_id, unnest(regexp_extract_all(lower(text), '([\p{L}\p{M}\p{N}_]+)', 1)) AS term FROM documents),
g AS (SELECT count(*) AS deg FROM b GROUP BY doc_id UNION ALL SELECT count(*) FROM b GROUP BY term)
SELECT count(*) AS nodes, round(avg(deg), 6) AS mean, round(var_pop(deg), 6) AS variance, round(var_pop(deg) / avg(deg), 6) AS dispersion,
       round(1 + sum((deg >= 2)::INT) / sum(CASE WHEN deg >= 2 THEN ln(deg / 1.5) END), 6) AS exponent
FROM g""")
def graph_degree_tail(spark: SparkSession, d: str) -> DataFrame:
    tail = graph.degree_tail(t.g_doc_term(spark, d))
    return tail.select("nodes", *[r6(F.col(c)).alias(c) for c in tail.columns[1:]])


@query(f"""WITH {BIDS}, {BOTH},
sets AS (SELECT 'nation' || c_nationkey AS set_id, c_custkey * 2 AS node FROM customer),
tot AS (SELECT sum(vol) AS v, count(*) AS n FROM g),
b AS (SELECT set_id, count(*) AS k, sum(vol) AS vol FROM sets JOIN g USING (node) GROUP BY set_id)
SELECT set_id, k AS n_nodes, round(vol / 1e6, 4) AS vol_m, round(vol / least(vol, v - vol), 6) AS conductance, round(vol / least(k, n - k) / 1e3, 4) AS expansion_k,
       round(vol * v / (vol * (v - vol)), 6) AS conductance_product, round(1 + vol / (v - vol), 6) AS normalized_cut
FROM b, tot""")
def set_scores_nations(spark: SparkSession, d: str) -> DataFrame:
    """Customers of one nation: no edges inside, as the graph is bipartite."""
    sets = t.load(spark, d, "customer").select(F.concat(F.lit("nation"), "c_nationkey").alias("set_id"), (F.col("c_custkey") * 2).alias("node"))
    s = graph.score(t.g_bids(spark, d), sets)
    return s.select(
        "set_id", "n_nodes", F.round(F.col("vol") / 1e6, 4).alias("vol_m"), r6(F.col("conductance")).alias("conductance"),
        F.round(F.col("expansion") / 1e3, 4).alias("expansion_k"), r6(F.col("conductance_product")).alias("conductance_product"),
        r6(F.col("normalized_cut")).alias("normalized_cut"),
    )


@query(f"""WITH {BIDS}, {BOTH},
sets AS (SELECT DISTINCT p_brand AS set_id, node FROM (
  SELECT p_brand, p_partkey * 2 + 1 AS node FROM part
  UNION ALL SELECT p_brand, o_custkey * 2 FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey WHERE l_extendedprice > 50000)),
tot AS (SELECT sum(vol) AS v FROM g),
b AS (SELECT set_id, sum(vol) AS vol FROM sets JOIN g USING (node) GROUP BY set_id),
i AS (SELECT x.set_id, sum(w) AS inside FROM s JOIN sets x ON x.node = s.src JOIN sets y ON y.node = s.dst AND y.set_id = x.set_id GROUP BY ALL)
SELECT set_id, round((vol - coalesce(inside, 0)) / least(vol, v - vol), 6) AS conductance, round((coalesce(inside, 0) - vol * vol / v) / v, 6) AS modularity
FROM b LEFT JOIN i USING (set_id), tot""")
def set_scores_brands(spark: SparkSession, d: str) -> DataFrame:
    part = t.load(spark, d, "part").select("p_partkey", "p_brand")
    rich = t.bought(spark, d).filter("l_extendedprice > 50000").join(part, F.col("l_partkey") == F.col("p_partkey"))
    sets = part.select(F.col("p_brand").alias("set_id"), (F.col("p_partkey") * 2 + 1).alias("node")).unionByName(
        rich.select(F.col("p_brand").alias("set_id"), (F.col("o_custkey") * 2).alias("node"))
    )
    s = graph.score(t.g_bids(spark, d), sets)
    return s.select("set_id", r6(F.col("conductance")).alias("conductance"), r6(F.col("modularity")).alias("modularity"))


TEN_NODES = """a AS (SELECT c_mktsegment AS x, o_orderpriority AS y, count(*)::DOUBLE AS w FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL),
e AS (SELECT dense_rank() OVER (ORDER BY x) - 1 AS i, dense_rank() OVER (ORDER BY y) + 4 AS j, w FROM a),
n AS (SELECT i AS node, sum(w) AS vol FROM (SELECT i, w FROM e UNION ALL SELECT j, w FROM e) GROUP BY i),
k AS (SELECT unnest(range(1, 1023))::BIGINT AS m),
v AS (SELECT m, sum(vol) AS vol, count(*) AS size FROM k JOIN n ON (m >> node::INT) & 1 = 1 GROUP BY m),
c AS (SELECT m, sum(w) AS cut FROM k JOIN e ON ((m >> i::INT) & 1) <> ((m >> j::INT) & 1) GROUP BY m),
p AS (SELECT size, cut / vol AS phi FROM v JOIN c USING (m) WHERE vol <= (SELECT sum(vol) FROM n) / 2)"""


@query(f"WITH {TEN_NODES} SELECT size::BIGINT AS size, round(min(phi), 6) AS phi FROM p GROUP BY size")
def profile_exact(spark: SparkSession, d: str) -> DataFrame:
    g = small.SmallGraph.of(graph.build(t.g_segment_priority(spark, d), "src", "dst", "w"))
    return spark.createDataFrame([(k, round(p, 6)) for k, p in g.profile().items()], "size long, phi double")


@query(f"WITH {TEN_NODES} SELECT round(min(phi), 6) AS phi FROM p")
def conductance_exact(spark: SparkSession, d: str) -> DataFrame:
    g = small.SmallGraph.of(graph.build(t.g_segment_priority(spark, d), "src", "dst", "w"))
    return spark.createDataFrame([(round(g.exact()[0], 6),)], "phi double")


@query(f"""WITH {SPARSE}, {BOTH},
r AS (SELECT node, vol, row_number() OVER (ORDER BY deg DESC, node) AS rank FROM g),
c AS (SELECT greatest(a.rank, b.rank) AS rank, sum(w) AS closed FROM e JOIN r a ON a.node = src JOIN r b ON b.node = dst GROUP BY ALL),
x AS (SELECT r.rank, r.node, sum(vol) OVER o AS vol, sum(vol) OVER o - 2 * sum(coalesce(closed, 0)) OVER o AS cut FROM r LEFT JOIN c USING (rank) WINDOW o AS (ORDER BY rank))
SELECT rank::INT AS rank, node, vol, cut, round(CASE WHEN least(vol, (SELECT sum(vol) FROM g) - vol) > 0 THEN cut / least(vol, (SELECT sum(vol) FROM g) - vol) END, 6) AS phi FROM x""")
def sweep_by_degree(spark: SparkSession, d: str) -> DataFrame:
    e = _sparse(spark, d)
    out = spectral.sweep(e, graph.degrees(e).select("node", F.col("deg").cast("double").alias("value")))
    return out.select("rank", "node", "vol", "cut", r6(F.col("phi")).alias("phi"))


def _ppr_sql(rounds: int, alpha: float, eps: float) -> str:
    sql = f"WITH {SPARSE}, {BOTH}, r0 AS (SELECT min(node) AS node, 0.0::DOUBLE AS p, 1.0::DOUBLE AS r FROM g)"
    for i in range(rounds):
        sql += f""",
r{i + 1} AS (SELECT node, sum(p) AS p, sum(r) AS r FROM (
  SELECT x.node, p + CASE WHEN r >= {eps} * vol THEN {alpha} * r ELSE 0 END AS p, CASE WHEN r >= {eps} * vol THEN {(1 - alpha) / 2} * r ELSE r END AS r FROM r{i} x JOIN g USING (node)
  UNION ALL SELECT s.dst, 0.0, {(1 - alpha) / 2} * r * w / vol FROM r{i} x JOIN g USING (node) JOIN s ON s.src = x.node WHERE r >= {eps} * vol) GROUP BY node)"""
    return sql + f" SELECT node, round(p, 9) AS p, round(r, 9) AS r FROM r{rounds}"


@query(_ppr_sql(6, 0.1, 0.0001))
def ppr_push_rounds(spark: SparkSession, d: str) -> DataFrame:
    e = _sparse(spark, d)
    seeds = graph.degrees(e).agg(F.min("node").alias("node")).select(F.col("node").alias("seed_id"), "node")
    out = local.ppr(e, seeds, 0.1, 0.0001, rounds=6, every=50)
    return out.select("node", F.round("p", 9).alias("p"), F.round("r", 9).alias("r"))


@query()
def spectral_sweep(spark: SparkSession, d: str) -> DataFrame:
    e = graph.giant(_sparse(spark, d)).cache()
    vector, quotient = spectral.fiedler(e, 60)
    return graph.best_prefix(spectral.sweep(e, vector)).withColumn("lambda2_upper", F.lit(quotient))


@query()
def spectral_embedding_kmeans(spark: SparkSession, d: str) -> DataFrame:
    e = graph.giant(_sparse(spark, d)).cache()
    return spectral.kmeans(spectral.embed(e, 3, 8), 3).groupBy("part").agg(F.count("*").alias("nodes"))


@query()
def whisker_bag(spark: SparkSession, d: str) -> DataFrame:
    e = graph.giant(_sparse(spark, d)).cache()
    return probes.bag(probes.whisker_summary(e, probes.decompose(e)))


@query(f"""WITH {SPARSE}, {BOTH}, l AS (SELECT node FROM g WHERE deg = 1)
SELECT (SELECT count(*) FROM l)::BIGINT AS leaves, (SELECT count(*) FROM g)::BIGINT AS nodes""")
def leaf_whiskers(spark: SparkSession, d: str) -> DataFrame:
    g = graph.degrees(_sparse(spark, d))
    return g.agg(F.sum((F.col("deg") == 1).cast("long")).alias("leaves"), F.count("*").alias("nodes"))


@query()
def profile_local(spark: SparkSession, d: str) -> DataFrame:
    e = graph.giant(_sparse(spark, d)).cache()
    return probes.profile(probes.local_profile(e, 8))


@query()
def profile_flow(spark: SparkSession, d: str) -> DataFrame:
    e = graph.giant(_sparse(spark, d)).cache()
    return probes.profile(probes.set_summaries(e, probes.flow_kinds(e, {"flow": False, "flow_connected": True})))


@query()
def profile_core(spark: SparkSession, d: str) -> DataFrame:
    e = graph.giant(_sparse(spark, d)).cache()
    c = probes.core(e).cache()
    return probes.profile(probes.local_profile(c, 8))


@query()
def profile_shape_by_graph(spark: SparkSession, d: str) -> DataFrame:
    """The curve's class for a lattice, an expander-like graph and the sparse graph."""
    parts = None
    for name, e in (("lattice", models.lattice(spark, 30)), ("part_supplier", t.g_part_supplier(spark, d)), ("sparse", graph.giant(_sparse(spark, d)))):
        one = probes.local_profile(e.cache(), 5, (0.05,), 5e-4, name)
        parts = one if parts is None else parts.unionByName(one)
    return probes.shape(probes.profile(parts))


@query()
def flow_improvement(spark: SparkSession, d: str) -> DataFrame:
    """All orders and parts: pieces of recursive bisection, each improved by flow."""
    found = probes.piece_improvements(graph.giant(_sparse(spark, AllDays(d))), 20)
    rows = [(i, size, phi, better_size, better) for i, (size, phi, better, better_size) in enumerate(found)]
    return spark.createDataFrame(rows, "piece int, size int, phi double, improved_size int, improved_phi double")


@query()
def multilevel_bisection(spark: SparkSession, d: str) -> DataFrame:
    g = small.SmallGraph.of(graph.giant(_sparse(spark, d)))
    side = g.bisect()
    return spark.createDataFrame([(int(g.ids[i]), int(i in side)) for i in range(g.n)], "node long, part int")


@query()
def multilevel_refinement(spark: SparkSession, d: str) -> DataFrame:
    """Local improvement alone, from a split by a hash: cut before and after."""
    e = graph.giant(_sparse(spark, d)).cache()
    start = multilevel.volumes(e).select("node", F.pmod(F.xxhash64("node"), F.lit(2)).cast("int").alias("side"))
    after = multilevel.refine(e, multilevel.volumes(e), start)
    both = [multilevel.summary(e, s.withColumnRenamed("side", "part")).withColumn("step", F.lit(n)) for n, s in (("before", start), ("after", after))]
    return both[0].unionByName(both[1])


@query()
def kway_partition(spark: SparkSession, d: str) -> DataFrame:
    g = small.SmallGraph.of(graph.giant(_sparse(spark, d)))
    return spark.createDataFrame([(int(g.ids[i]), p) for i, p in enumerate(small.kway(g, 8))], "node long, part int")


@query()
def spectral_improvement(spark: SparkSession, d: str) -> DataFrame:
    g = small.SmallGraph.of(graph.build(t.g_segment_priority(spark, d), "src", "dst", "w"))
    rows = []
    for i in range(g.n - 1):
        phi, side = small.spectral_improve(g, [i, i + 1])
        rows.append((i, float(g.phi([i, i + 1])), float(phi), len(side)))
    return spark.createDataFrame(rows, "start int, phi double, improved_phi double, size int")


@query()
def edge_betweenness_distributed(spark: SparkSession, d: str) -> DataFrame:
    """All orders and parts, from 16 sources by hash."""
    whole = t.g_order_part(spark, d).cache()
    e = graph.giant(whole).cache()
    sources = graph.degrees(e).select("node").orderBy(F.xxhash64("node"), "node").limit(16)
    return graph.betweenness(e, sources).select("src", "dst", r6(F.col("betweenness")).alias("betweenness"))


@query()
def cut_bounds_and_methods(spark: SparkSession, d: str) -> DataFrame:
    g = small.SmallGraph.of(graph.build(t.g_segment_priority(spark, d), "src", "dst", "w"))
    lam, vector = g.fiedler()
    rows = [
        ("exact", g.exact()[0]), ("lambda2_half", lam / 2), ("spectral_sweep", g.sweep(vector)[0]), ("metric_flow", small.metric_cut(g)[0]),
        ("cut_matching", small.cut_matching(g)[0]), ("multilevel", g.phi(g.bisect())), ("sdp_cut_bound_over_volume", small.sdp_bound(g) / g.volume),
    ]
    return spark.createDataFrame([(a, float(b)) for a, b in rows], "method string, value double")


@query()
def edge_leverage_sketch(spark: SparkSession, d: str) -> DataFrame:
    e = graph.build(t.g_segment_priority(spark, d), "src", "dst", "w").cache()
    return resistance.check(e, resistance.sketch(e, 16, 12))


@query()
def expand_phrases(spark: SparkSession, d: str) -> DataFrame:
    e = graph.giant(_sparse(spark, d)).cache()
    phrases = graph.degrees(e).filter("node % 2 = 1").orderBy(F.desc("deg"), "node").limit(5).select("node")
    return probes.expand_phrases(e, phrases)


@query()
def graph_look(spark: SparkSession, d: str) -> DataFrame:
    return probes.look(graph.giant(_sparse(spark, d)))


@query("""WITH c AS (SELECT row_number() OVER (ORDER BY p_partkey) - 1 AS i FROM part), n AS (SELECT count(*) AS n, ceil(sqrt(count(*)))::BIGINT AS side FROM part)
SELECT a AS src, b AS dst, 1.0::DOUBLE AS w FROM (
  SELECT i AS a, i + 1 AS b FROM c, n WHERE i % side < side - 1 AND i + 1 < n UNION ALL SELECT i, i + side FROM c, n WHERE i + side < n)""")
def model_lattice(spark: SparkSession, d: str) -> DataFrame:
    """All parts by key, laid out row by row in a square."""
    parts = numbered(t.load(spark, d, "part"), "p_partkey").cache()
    return models.lattice_of(parts, parts.count())


@query(f"""SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst, 1.0::DOUBLE AS w FROM (
  SELECT floor({u01_sql("i", 0)} * 500)::BIGINT AS a, floor({u01_sql("i", 1)} * 500)::BIGINT AS b FROM range(750) r(i)) WHERE a <> b""")
def model_random(spark: SparkSession, d: str) -> DataFrame:
    return models.random(spark, 500, 3.0)


@query("SELECT * FROM (SELECT o_orderkey AS src, lead(o_orderkey) OVER (ORDER BY o_orderkey) AS dst, 1.0::DOUBLE AS w FROM orders) WHERE dst IS NOT NULL")
def model_path(spark: SparkSession, d: str) -> DataFrame:
    """All orders in a row, each linked to the next key."""
    return models.path_through(t.load(spark, d, "orders"), "o_orderkey")


def _model_summary(name: str, make):
    def run(spark: SparkSession, d: str) -> DataFrame:
        return graph.degree_tail(make(spark, d))

    QUERIES[f"model_{name}"] = run


def _customers(spark: SparkSession, d: str) -> tuple[DataFrame, int]:
    """id of every customer, and their number."""
    ids = numbered(t.load(spark, d, "customer"), "c_custkey").select("id").cache()
    return ids, ids.count()


def _copying(spark: SparkSession, d: str) -> DataFrame:
    """Customers in order of key: each copies links of earlier ones."""
    ids, n = _customers(spark, d)
    return models.copying(spark, n, nodes=ids)


_model_summary("copying", _copying)
def _forest_fire(spark: SparkSession, d: str, most: int = 100_000) -> DataFrame:
    """Suppliers arrive by balance and key; the fire is sequential, so more than ``most`` of them are refused."""
    rows = bounded(t.load(spark, d, "supplier").select("s_acctbal", "s_suppkey"), most)
    ids = [key for _, key in sorted((r["s_acctbal"], r["s_suppkey"]) for r in rows)]
    return models.forest_fire(spark, len(ids), most=most, ids=ids)


_model_summary("forest_fire", _forest_fire)
_model_summary("rewired", lambda s, d: models.rewired(t.g_order_part(s, d, 90)))


def _graph_summary(name: str, make):
    def run(spark: SparkSession, d: str) -> DataFrame:
        e = make(spark, d)
        return e.agg(F.count("*").alias("edges"), F.round(F.sum("w"), 2).alias("weight"))

    QUERIES[f"workload_{name}"] = run


_graph_summary("part_supplier", t.g_part_supplier)
_graph_summary("customer_order", t.g_customer_order)
_graph_summary("turns", t.g_turns)
_graph_summary("copurchase", t.g_copurchase)
ORACLES["workload_customer_order"] = "SELECT count(*) AS edges, count(*)::DOUBLE AS weight FROM orders"
ORACLES["workload_part_supplier"] = "SELECT count(*) AS edges, count(*)::DOUBLE AS weight FROM (SELECT DISTINCT l_partkey, l_suppkey FROM lineitem)"
ORACLES["workload_turns"] = """WITH c AS (SELECT DISTINCT conv_id * 1000 + turn AS k FROM conversations)
SELECT count(*) AS edges, count(*)::DOUBLE AS weight FROM c a JOIN c b ON b.k = a.k + 1"""
ORACLES["workload_copurchase"] = """WITH b AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem),
e AS (SELECT x.p, y.p AS q, count(*) AS w FROM b x JOIN b y ON x.o = y.o AND x.p < y.p GROUP BY ALL)
SELECT count(*) AS edges, sum(w)::DOUBLE AS weight FROM e"""
