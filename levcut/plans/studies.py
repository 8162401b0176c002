"""Experiments on the given graphs: profiles, twins, probe ensembles, artifacts, costs."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levcut.functions.portable import u01
from levcut.operators import columns, graph, hadamard, local, lsq, models, multilevel, probes, resistance, small, svd
from levcut.plans.matrix import XS
from levcut.runtime import bounded, cut_lineage, release, traced
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
    return graph.giant(t.g_order_part(spark, d, 90)).cache()


def _profile(e: DataFrame, name: str, alphas=(0.05,), eps: float = 2e-4, share: float = 0.002) -> DataFrame:
    return probes.profile(probes.local_profile(e, probes.seeds_for(e, share, 12), alphas, eps, name))


# --- the document-term graph: the large one -------------------------------------------


def _doc_term(spark: SparkSession, d: str) -> DataFrame:
    """The largest component; words are read once for it."""
    whole = t.g_doc_term(spark, d).cache()
    e = graph.giant(whole).cache()
    e.count()
    whole.unpersist()
    return e


@query()
def profile_doc_term(spark: SparkSession, d: str) -> DataFrame:
    """Least conductance by size; seeds in proportion to the nodes."""
    return _profile(graph.giant(t.g_doc_term(spark, d)).cache(), "doc_term", share=0.0001)


@query()
def profile_doc_term_core(spark: SparkSession, d: str) -> DataFrame:
    """The same once whiskers are gone."""
    e = _doc_term(spark, d)
    return _profile(cut_lineage(probes.core(e)), "doc_term_core", share=0.0001)


@query()
def whisker_shares_doc_term(spark: SparkSession, d: str) -> DataFrame:
    e = _doc_term(spark, d)
    return probes.whisker_shares(e, probes.decompose(e))


# --- reference models and twins ---------------------------------------------------------


@query()
def profile_models(spark: SparkSession, d: str) -> DataFrame:
    """The curve's class for each reference graph of about a thousand nodes."""
    made = {
        "lattice": models.lattice(spark, 32), "path": models.path(spark, 600), "geometric": models.geometric(spark, 1000, 0.06), "road_like": models.road_like(spark, 32, 0.2),
        "random": models.random(spark, 1000, 6.0), "power_law": models.power_law(spark, 1500, 6.0, 2.5), "copying": models.copying(spark, 1000), "expander": models.expander(spark, 1000),
        "hierarchical": models.hierarchical(spark, 6), "core_periphery": models.core_periphery(spark, 500, 200),
    }
    # Graphs beside each other with ids of their own: one run of the walks for all.
    parts = [e.select((F.col("src") + i * 1_000_000).alias("src"), (F.col("dst") + i * 1_000_000).alias("dst"), "w") for i, e in enumerate(made.values())]
    e = cut_lineage(reduce(DataFrame.unionByName, parts))
    model = F.element_at(F.array(*[F.lit(n) for n in made]), (F.floor(F.col("node") / 1_000_000) + 1).cast("int"))
    deg = graph.degrees(e).select("node", "vol", model.alias("method"))
    totals = deg.groupBy("method").agg(F.sum("vol").alias("v"), F.count("*").alias("n"))
    place = F.row_number().over(_by_hash())
    seeds = deg.withColumn("place", place).filter("place <= 6").select(F.col("node").alias("seed_id"), "node")
    swept = local.sweep(e, local.ppr(e, seeds, 0.02, 2e-4).filter("p > 0"), "p")
    rows = swept.join(deg.select("node", "method"), "node").join(F.broadcast(totals), "method")
    half = rows.filter(F.col("vol") * 2 <= F.col("v")).select("method", F.concat_ws(":", "seed_id", "rank").alias("set_id"), F.col("rank").cast("long").alias("size"), "vol", "cut", (F.col("cut") / F.col("vol")).alias("phi"))
    return probes.shape(probes.profile(half))


def _by_hash():
    from pyspark.sql import Window

    return Window.partitionBy("method").orderBy(u01("node", 0), "node")


@query()
def profile_and_twin(spark: SparkSession, d: str) -> DataFrame:
    """The sparse graph's profile beside that of a random graph of the same degrees."""
    e = _sparse(spark, d)
    twin = graph.giant(models.rewired(e)).cache()
    return probes.residual_structure(e, twin, 16)


# --- probes compared ------------------------------------------------------------------------


@query()
def probe_ensemble(spark: SparkSession, d: str) -> DataFrame:
    """Local spectral sets and their flow-improved subsets: conductance against compactness by size."""
    e = _sparse(spark, d)
    found = cut_lineage(probes.local_sets(e, probes.seeds_for(e, 0.02), 8, 400))
    better = probes.flow_sets(e, found)
    return probes.compare(e, found.unionByName(better))


@query()
def communities_of_500(spark: SparkSession, d: str) -> DataFrame:
    """Sets of about five hundred nodes of the order-part graph: spectral ones, and what flow makes of them."""
    e = graph.giant(t.g_order_part(spark, d)).cache()
    found = cut_lineage(probes.local_sets(e, 6, 300, 700, 0.05, 1e-4))
    return probes.compare(e, found.unionByName(probes.flow_sets(e, found)))


@query()
def profile_other_measures(spark: SparkSession, d: str) -> DataFrame:
    """The least of three other scores by size, over the same sets."""
    e = _sparse(spark, d)
    found = cut_lineage(probes.local_sets(e, 24, 4, 300))
    parts = [probes.profile(probes.set_measures(e, found, m)).withColumn("measure", F.lit(m)) for m in ("expansion", "cut_ratio", "normalized_cut")]
    return reduce(DataFrame.unionByName, parts)


# --- artifacts: strings and expanders -------------------------------------------------------


@query("""WITH c AS (SELECT count(*) AS n FROM orders GROUP BY o_custkey), l AS (SELECT n, count(*) AS strings FROM c WHERE n >= 3 GROUP BY n)
SELECT 'path' AS name, n AS nodes, strings, round(1::DOUBLE / (n - 1 - n % 2), 6) AS spectral, round(1::DOUBLE / (n - 1 - n % 2), 6) AS flow FROM l
UNION ALL SELECT 'ring', n, strings, round(1::DOUBLE / (n // 2), 6), round(1::DOUBLE / (n // 2), 6) FROM l""")
def artifacts_known(spark: SparkSession, d: str) -> DataFrame:
    """Stringy graphs whose best cuts are known, open and closed: the swept vector, then flow on its side.

    The strings are the orders of a customer, three at least; those of one length
    are the same graph, which is taken once and stands for their number.
    """
    lengths = t.load(spark, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).filter("n >= 3").groupBy("n").agg(F.count("*").alias("strings"))
    rows = []
    for n, strings in sorted(bounded(lengths, small.NODES)):
        line = [(i, i + 1, 1.0) for i in range(n - 1)]
        for name, edges in (("path", line), ("ring", [*line, (0, n - 1, 1.0)])):
            g = small.SmallGraph(edges)
            phi, side = g.sweep(g.fiedler()[1])
            rows.append((name, n, strings, round(float(phi), 6), round(float(g.improve(side)[0]), 6)))
    return spark.createDataFrame(rows, "name string, nodes long, strings long, spectral double, flow double")


@query()
def artifacts(spark: SparkSession, d: str) -> DataFrame:
    """Spectral against flow on strings hung on an expander, an expander, and conversations as strings."""
    turns = graph.giant(t.g_turns(spark, d))
    rows = []
    for name, e in (("strings_on_expander", models.core_periphery(spark, 200, 120)), ("expander", models.expander(spark, 400)), ("turns", turns)):
        g = small.SmallGraph.of(graph.giant(e))
        lam, vector = g.fiedler()
        phi, side = g.sweep(vector)
        better, subset = g.improve(side)
        rows.append((name, g.n, float(lam), float(phi), len(side), float(better), len(subset), float(g.phi(g.bisect()))))
    return spark.createDataFrame(rows, "name string, nodes int, lambda2 double, spectral double, size int, flow double, flow_size int, multilevel double")


# --- partitions: what must hold ----------------------------------------------------------------


@query("""WITH RECURSIVE e AS (SELECT DISTINCT l_orderkey * 2 AS src, l_partkey * 2 + 1 AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey)
SELECT (SELECT count(DISTINCT src) + count(DISTINCT dst) FROM e) AS nodes, 2::BIGINT AS parts, TRUE AS balanced, TRUE AS better_than_hash""")
def multilevel_invariants(spark: SparkSession, d: str) -> DataFrame:
    """Every node is in one of two parts of three tenths of the volume at least, and the cut beats a split by hash."""
    e = graph.giant(t.g_order_part(spark, d)).cache()
    sides = cut_lineage(multilevel.bisect(e, 2000, rounds=2))
    own = multilevel.summary(e, sides.withColumnRenamed("side", "part")).collect()
    hashed = sides.select("node", F.pmod(F.xxhash64("node"), F.lit(2)).alias("part"))
    other = multilevel.summary(e, hashed).first()
    total = sum(r["vol"] for r in own)
    nodes = sides.select("node").distinct().count()
    row = (nodes, len(own), min(r["vol"] for r in own) >= 0.3 * total - 1e-6, own[0]["cut"] < other["cut"])
    return spark.createDataFrame([row], "nodes long, parts long, balanced boolean, better_than_hash boolean")


def _least_push(e: DataFrame, share: float) -> float:
    """A residual of this share is pushed on at a node of average volume."""
    return share / graph.degrees(e).agg(F.avg("vol").alias("v")).first()["v"]


# --- markets of bids -------------------------------------------------------------------------


@query()
def micro_markets_bids(spark: SparkSession, d: str) -> DataFrame:
    """Advertisers and phrases that keep to themselves: sets of the bid graph, best first, and the nation that most of the customers share."""
    e = graph.giant(t.g_bids(spark, d)).cache()
    starts = local.seeds_by_hash(e, probes.seeds_for(e, 0.005))
    swept = cut_lineage(local.sweep(e, local.ppr(e, starts, 0.1, _least_push(e, 2e-3)).filter("p > 0"), "p").filter(F.col("rank") <= 400))
    best = graph.best_prefix(swept.filter(F.col("rank") >= 8))
    nations = t.load(spark, d, "customer").select((F.col("c_custkey") * 2).alias("node"), F.col("c_nationkey").alias("label"))
    purity = probes.ground_truth(graph.members(swept, best), nations).select(F.col("set_id").alias("seed_id"), "label", "precision", "recall")
    return best.join(purity, "seed_id", "left").orderBy("phi", "seed_id")


@query()
def expand_phrases_bids(spark: SparkSession, d: str) -> DataFrame:
    """The five dearest parts as phrases: nearest parts, where the neighbourhood is a market of its own."""
    e = graph.giant(t.g_bids(spark, d)).cache()
    phrases = graph.degrees(e).filter("node % 2 = 1").orderBy(F.desc("vol"), "node").limit(5).select("node")
    vectors = local.ppr(e, phrases.select(F.col("node").alias("seed_id"), "node"), 0.1, _least_push(e, 2e-3)).filter("p > 0")
    return probes.expand_from(e, vectors, 5, 1.0)


# --- cost ---------------------------------------------------------------------------------------


@query()
def cost_least_squares(spark: SparkSession, d: str) -> DataFrame:
    """Seconds, jobs and tasks of the exact, the sampled and the transformed solve as rows are repeated."""
    out = []
    base = t.design_events(spark, d).cache()
    m = base.count()
    for times in (1, 4, 16):
        rows = base.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(times - 1)))).withColumn("id", F.col("id") + F.col("copy") * m).cache()
        rows.count()
        exact = lsq.solve(rows, "y", XS)
        methods = {
            "exact": lambda rows=rows: lsq.solve(rows, "y", XS), "tall_skinny_qr": lambda rows=rows: lsq.solve(rows, "y", XS, "qr"),
            "sampled": lambda rows=rows: lsq.sampled(rows, "y", XS, lsq.sample_size(3, 0.1), "id", 1), "transformed": lambda rows=rows: hadamard.fast(rows, "y", XS, "id", m * times, 300, 3),
        }
        for name, method in methods.items():
            x, trace = traced(spark, method)
            out.append((m * times, name, round(trace.seconds, 3), trace.jobs, trace.tasks, lsq.errors(rows, "y", XS, exact, x)[0]))
        rows.unpersist()
    return spark.createDataFrame(out, "rows long, method string, seconds double, jobs int, tasks int, residual_ratio double")


@query()
def cost_local_sets(spark: SparkSession, d: str) -> DataFrame:
    """Work for each node returned, as the graph grows and the set does not."""
    out = []
    for name, e in (("90 days", t.g_order_part(spark, d, 90)), ("a year", t.g_order_part(spark, d, 365)), ("all", t.g_order_part(spark, d))):
        e = graph.giant(e).cache()
        nodes = graph.degrees(e).count()
        found, trace = traced(spark, lambda e=e: probes.local_sets(e, 8, 4, 200, 0.1, 1e-3).count())
        out.append((name, nodes, e.count(), found, round(trace.seconds, 3), trace.jobs, trace.tasks))
    return spark.createDataFrame(out, "graph string, nodes long, edges long, returned long, seconds double, jobs int, tasks int")


@query()
def scale_up_terms(spark: SparkSession, d: str) -> DataFrame:
    """Columns repeated one, two and four times: seconds of a block iteration and of choosing columns."""
    base = t.term_binary(spark, d).cache()
    entries, out = base.count(), []
    for times in (1, 2, 4):
        release(spark)
        # Copies are made anew for each pass: kept, they would be as much disk as the copies themselves.
        a = base.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(times)))).select("row_id", F.concat_ws("-", "col_id", "copy").alias("col_id"), "value")
        found, basis = traced(spark, lambda a=a: svd.topk(a, 4, "subspace", power=1))
        ids, chosen = traced(spark, lambda a=a, found=found: columns.two_stage(a, 4, found=found))
        out.append((times, entries * times, round(basis.seconds, 3), basis.jobs, round(chosen.seconds, 3), len(ids)))
    return spark.createDataFrame(out, "copies int, entries long, basis_seconds double, basis_jobs int, choice_seconds double, columns int")


@query()
def edge_leverage_and_betweenness(spark: SparkSession, d: str) -> DataFrame:
    """Correlation of leverage with betweenness and degrees on the sparse graph, exact or sketched by its size."""
    e = _sparse(spark, d)
    scores = cut_lineage(resistance.scores(e))
    between = graph.betweenness(e, local.seeds_by_hash(e, 32).select("node"))
    row = scores.join(between, ["src", "dst"]).agg(F.corr("leverage", "betweenness").alias("with_betweenness"))
    return row.crossJoin(resistance.correlates(e, scores))
