"""Interaction graphs: canonical edges, degrees, components, distances, cores."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from levcut.runtime import cut_lineage, release, ship
from levcut.schema import EDGES, require


#: Links between nodes that the driver takes to finish components.
HELD_STARS = 1_000_000
#: Edges up to which shortest paths have the graph in every task.
HELD_EDGES = 1_000_000


def build(df: DataFrame, src: str, dst: str, weight: str | None = None) -> DataFrame:
    """src < dst, w: loops dropped, parallel and opposite edges merged by summing."""
    w = F.lit(1.0) if weight is None else F.col(weight).cast("double")
    return (
        df.select(F.least(src, dst).alias("src"), F.greatest(src, dst).alias("dst"), w.alias("w"))
        .filter("src < dst")
        .groupBy("src", "dst")
        .agg(F.sum("w").alias("w"))
    )


def both_ways(edges: DataFrame) -> DataFrame:
    require(edges, EDGES)
    return edges.select("src", "dst", "w").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))


def degrees(edges: DataFrame, nodes: DataFrame | None = None) -> DataFrame:
    """node, deg (edges), vol (weights); isolated nodes if nodes are given."""
    out = both_ways(edges).groupBy(F.col("src").alias("node")).agg(F.count("*").alias("deg"), F.sum("w").alias("vol"))
    if nodes is None:
        return out
    return nodes.select("node").join(out, "node", "left").select("node", F.coalesce("deg", F.lit(0)).alias("deg"), F.coalesce("vol", F.lit(0.0)).alias("vol"))


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """node, component (its least node): alternating rounds towards stars.

    Each task first turns its own edges into stars around their least nodes. What
    is left is finished on the driver if it is at most ``HELD_STARS`` links. More of
    them are first brought down to links between centres of stars, which are few.
    """
    e = cut_lineage(edges.select(F.col("src").cast("long").alias("a"), F.col("dst").cast("long").alias("b")).filter("a != b").mapInArrow(_local_stars, "a long, b long"))
    if e.count() <= HELD_STARS:
        table = e.toArrow()
        ids, least = least_labels(table.column("a").to_numpy(), table.column("b").to_numpy())
        return e.sparkSession.createDataFrame(pa.table({"node": ids, "component": least}), "node long, component long")
    least = cut_lineage(e.groupBy("a").agg(F.min("b").alias("m")))
    centres = e.select("b").distinct()
    links = e.join(least, "a").filter("b != m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    # A centre of one task may be an end of a star in another.
    links = cut_lineage(links.union(least.join(centres.withColumnRenamed("b", "a"), "a", "left_semi")).distinct())
    if links.count() <= HELD_STARS:
        table = links.toArrow()
        ids, roots = least_labels(table.column("a").to_numpy(), table.column("b").to_numpy())
        root = e.sparkSession.createDataFrame(pa.table({"m": ids, "root": roots}), "m long, root long")
    else:
        root = cut_lineage(_join_components(links, most_rounds)).select(F.col("node").alias("m"), F.col("component").alias("root"))
    only = centres.join(least, centres["b"] == least["a"], "left_anti").select(F.col("b").alias("a"), F.col("b").alias("m"))
    return least.union(only).join(root, "m", "left").select(F.col("a").alias("node"), F.coalesce("root", "m").alias("component"))


def _join_components(e: DataFrame, most_rounds: int) -> DataFrame:
    """node, component of links a, b by rounds of joins."""

    def mark(df: DataFrame):
        r = df.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
        return r["n"], r["h"]

    last = mark(e)
    for _ in range(most_rounds):
        both = e.union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.filter("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").filter("b != m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        e = cut_lineage(small.union(least.select("a", F.col("m").alias("b"))).distinct())
        release(e.sparkSession)
        now = mark(e)
        if now == last:
            break
        last = now
    stars = e.select(F.col("a").alias("node"), F.col("b").alias("component"))
    return stars.union(stars.select(F.col("component").alias("node"), "component").distinct())


def least_labels(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes in order and the least node that each one reaches, of edges as arrays."""
    ids, ends = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y, label = ends[: len(a)], ends[len(a) :], np.arange(len(ids))
    while True:
        lx, ly = label[x], label[y]
        open_ = lx != ly
        if not open_.any():
            return ids, ids[label]
        x, y, lx, ly = x[open_], y[open_], lx[open_], ly[open_]
        np.minimum.at(label, np.maximum(lx, ly), np.minimum(lx, ly))
        while (label[label] != label).any():
            label = label[label]


def _local_stars(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Edges a, b of a task as links of a node to the least one it reaches through them, a > b."""
    a, b, room = [], [], 1 << 21

    def stars() -> tuple[np.ndarray, np.ndarray]:
        node, least = least_labels(np.concatenate(a), np.concatenate(b))
        return node[node != least], least[node != least]

    def out(node: np.ndarray, least: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(node, pa.int64()), pa.array(least, pa.int64())], names=["a", "b"])

    for batch in batches:
        a.append(batch.column(0).to_numpy())
        b.append(batch.column(1).to_numpy())
        if sum(map(len, a)) > room:
            node, least = stars()
            a, b = [node], [least]
            if 2 * len(node) > room:
                yield out(node, least)
                a, b = [], []
    if a:
        yield out(*stars())


def giant(edges: DataFrame) -> DataFrame:
    """Edges of the largest component; ties to the least node."""
    comp = cut_lineage(components(edges))
    best = comp.groupBy("component").count().orderBy(F.desc("count"), "component").limit(1)
    inside = comp.join(F.broadcast(best), "component", "left_semi").select(F.col("node").alias("src"))
    return edges.join(inside, "src", "left_semi").select("src", "dst", "w")


def induced(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """Edges with both ends among the nodes."""
    n = nodes.select("node").distinct()
    return edges.join(n.withColumnRenamed("node", "src"), "src", "left_semi").join(n.withColumnRenamed("node", "dst"), "dst", "left_semi").select("src", "dst", "w")


def without(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    n = nodes.select("node").distinct()
    return edges.join(n.withColumnRenamed("node", "src"), "src", "left_anti").join(n.withColumnRenamed("node", "dst"), "dst", "left_anti").select("src", "dst", "w")


def bfs(edges: DataFrame, sources: DataFrame, most: int = 1000) -> DataFrame:
    """source, node, dist: hops by rounds of joins over the new frontier only."""
    step = both_ways(edges).select("src", "dst").cache()
    seen = cut_lineage(sources.select(F.col("node").alias("source"), "node", F.lit(0).alias("dist")).distinct())
    frontier = seen
    for hop in range(1, most + 1):
        reached = frontier.join(step, frontier["node"] == step["src"]).select("source", F.col("dst").alias("node")).distinct()
        frontier = cut_lineage(reached.join(seen, ["source", "node"], "left_anti").withColumn("dist", F.lit(hop)))
        if frontier.isEmpty():
            break
        seen = cut_lineage(seen.unionByName(frontier)) if hop % 4 == 0 else seen.unionByName(frontier)
    step.unpersist()
    return seen


def betweenness(edges: DataFrame, sources: DataFrame, most: int = 1000) -> DataFrame:
    """src, dst, betweenness: share of the shortest paths from the sources over each edge.

    Rounds outwards count the paths to every node, rounds back hand each node's
    paths to its edges; both are keyed by source and node, so no key is hot but
    for hubs. Edges on no shortest path have 0. Of a graph of at most ``HELD_EDGES``
    edges every task holds all and takes its sources there, without a round of joins.
    """
    if edges.count() <= HELD_EDGES:
        return _held_betweenness(edges, sources, most)
    step = cut_lineage(both_ways(edges).select("src", "dst"))
    front = cut_lineage(sources.select(F.col("node").alias("source"), "node", F.lit(1.0).alias("paths")).distinct())
    seen, levels = front.select("source", "node"), [front]
    for hop in range(1, most + 1):
        reached = front.join(step, front["node"] == step["src"]).groupBy("source", F.col("dst").alias("node")).agg(F.sum("paths").alias("paths"))
        front = cut_lineage(reached.join(seen, ["source", "node"], "left_anti"))
        if front.isEmpty():
            break
        levels.append(front)
        seen = seen.union(front.select("source", "node"))
        if hop % 4 == 0:
            seen = cut_lineage(seen)
    credits = edges.select("src", "dst", F.lit(0.0).alias("credit"))
    load = levels[-1].withColumn("load", F.lit(1.0))
    for nearer in reversed(levels[:-1]):
        share = load.select("source", F.col("node").alias("dst"), (F.col("load") / F.col("paths")).alias("share"))
        arcs = share.join(step, "dst").join(nearer.withColumnRenamed("node", "src"), ["source", "src"])
        arcs = cut_lineage(arcs.select("source", "src", "dst", (F.col("paths") * F.col("share")).alias("credit")))
        credits = credits.union(arcs.select(F.least("src", "dst"), F.greatest("src", "dst"), "credit"))
        handed = arcs.groupBy("source", F.col("src").alias("node")).agg(F.sum("credit").alias("handed"))
        load = nearer.join(handed, ["source", "node"], "left").withColumn("load", 1 + F.coalesce("handed", F.lit(0.0)))
    return credits.groupBy("src", "dst").agg(F.sum("credit").alias("betweenness"))


def _held_betweenness(edges: DataFrame, sources: DataFrame, most: int) -> DataFrame:
    """betweenness() with the graph as arrays in each task; a task gives out one sum an edge."""
    spark, table = edges.sparkSession, edges.select(F.col("src").cast("long"), F.col("dst").cast("long")).toArrow()
    a, b = (table.column(c).to_numpy() for c in ("src", "dst"))
    ids, ends = np.unique(np.concatenate([a, b]), return_inverse=True)
    own, to = ends, np.concatenate([ends[len(a) :], ends[: len(a)]])
    order = np.argsort(own, kind="stable")
    first = np.searchsorted(own[order], np.arange(len(ids) + 1))
    held = ship(spark, (ids, first, to[order].astype(np.int32), (order % max(len(a), 1)).astype(np.int32), a, b))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, first, to, edge, a, b = held()
        credit = np.zeros(len(a))
        for batch in batches:
            for source in batch.column(0).to_numpy():
                at = int(np.searchsorted(ids, source))
                if at == len(ids) or ids[at] != source:
                    continue
                paths, dist, front, levels = np.zeros(len(ids)), np.full(len(ids), -1, np.int32), np.array([at]), []
                paths[at], dist[at] = 1.0, 0
                for hop in range(1, most + 1):
                    many = first[front + 1] - first[front]
                    # Places of all edges of the front, one node after the other.
                    place = np.repeat(first[front] - np.cumsum(many) + many, many) + np.arange(many.sum())
                    near, back = to[place], np.repeat(front, many)
                    outward = dist[near] < 0
                    near, back, place = near[outward], back[outward], place[outward]
                    if not len(near):
                        break
                    paths += np.bincount(near, paths[back], len(ids))
                    dist[near] = hop
                    levels.append((near, back, edge[place]))
                    front = np.unique(near)
                load = np.ones(len(ids))
                for near, back, which in reversed(levels):
                    given = paths[back] * (load[near] / paths[near])
                    credit += np.bincount(which, given, len(a))
                    load += np.bincount(back, given, len(ids))
        on = np.flatnonzero(credit)
        for low in range(0, len(on), 1 << 16):
            part = on[low : low + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(a[part]), pa.array(b[part]), pa.array(credit[part])], names=["src", "dst", "credit"])

    starts = sources.select(F.col("node").cast("long").alias("node")).distinct()
    dealt = starts.repartition(max(1, min(starts.count(), spark.sparkContext.defaultParallelism)))
    none = edges.select("src", "dst", F.lit(0.0).alias("credit"))
    credits = none.union(dealt.mapInArrow(run, "src long, dst long, credit double"))
    return credits.groupBy("src", "dst").agg(F.sum("credit").alias("betweenness"))


def peel(edges: DataFrame, k: int, rounds: int = 1000) -> DataFrame:
    """Edges of the k-core: nodes of smaller degree leave round by round."""
    live = edges
    for i in range(rounds):
        small = degrees(live).filter(F.col("deg") < k).select("node")
        if small.isEmpty():
            return live
        live = cut_lineage(without(live, small))
    return live


def concentration(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """nodes, isolated share, components with an edge, and the largest one's share of all nodes."""
    every = degrees(edges, nodes).agg(F.count("*").alias("nodes"), F.avg((F.col("deg") == 0).cast("double")).alias("isolated"))
    sizes = components(edges).groupBy("component").agg(F.count("*").alias("size")).agg(F.count("*").alias("components"), F.max("size").alias("largest"))
    return every.crossJoin(sizes).select("nodes", "isolated", "components", (F.col("largest") / F.col("nodes")).alias("largest_share"))


def degree_tail(edges: DataFrame, dmin: int = 2) -> DataFrame:
    """Failure of concentration: mean and variance of degrees, power-law exponent by maximum likelihood."""
    d = degrees(edges)
    tail = F.col("deg") >= dmin
    return d.agg(
        F.count("*").alias("nodes"),
        F.avg("deg").alias("mean"),
        F.var_pop("deg").alias("variance"),
        (F.var_pop("deg") / F.avg("deg")).alias("dispersion"),
        (1 + F.sum(tail.cast("double")) / F.sum(F.when(tail, F.log(F.col("deg") / (dmin - 0.5))))).alias("exponent"),
    )


# --- scores of node sets -----------------------------------------------------

MEASURES = (
    "expansion", "conductance", "expansion_product", "conductance_product", "cut_ratio", "normalized_cut", "internal_density", "modularity",
)


def score(edges: DataFrame, sets: DataFrame, nodes: DataFrame | None = None, node_weight: str | None = None) -> DataFrame:
    """Every cut score of every set (set_id, node), many sets in one pass.

    Scores are null for an empty side. node_weight names a column of nodes that
    replaces the count of nodes in expansion.
    """
    everything = degrees(edges, nodes)
    if node_weight is not None:
        everything = everything.join(nodes.select("node", F.col(node_weight).alias("mass")), "node")
    else:
        everything = everything.withColumn("mass", F.lit(1.0))
    totals = everything.agg(F.sum("mass").alias("N"), F.sum("vol").alias("V"), F.count("*").alias("n_all")).first()
    n, v, count = totals["N"], totals["V"], totals["n_all"]
    member = sets.select("set_id", "node").distinct()
    sizes = member.join(everything, "node").groupBy("set_id").agg(F.sum("mass").alias("size"), F.count("*").alias("n_nodes"), F.sum("vol").alias("vol"))
    left = member.select("set_id", F.col("node").alias("src"), F.lit(1).alias("in_src"))
    right = member.select("set_id", F.col("node").alias("dst"), F.lit(1).alias("in_dst"))
    touched = both_ways(edges).join(left, "src").join(right, ["set_id", "dst"], "left")
    out = F.col("in_dst").isNull()
    per_node = touched.groupBy("set_id", "src").agg(F.sum(F.when(out, F.col("w")).otherwise(0.0)).alias("o"), F.sum("w").alias("d"))
    cuts = per_node.groupBy("set_id").agg(
        F.sum("o").alias("cut"), F.max(F.col("o") / F.col("d")).alias("odf_max"), F.avg(F.col("o") / F.col("d")).alias("odf_avg"),
        F.avg((F.col("o") * 2 > F.col("d")).cast("double")).alias("odf_half"),
    )
    r = sizes.join(cuts, "set_id", "left").withColumn("cut", F.coalesce("cut", F.lit(0.0)))
    size, vol, cut = F.col("size"), F.col("vol"), F.col("cut")
    two_sided = (size > 0) & (size < n) & (vol > 0) & (vol < v)
    k = F.col("n_nodes")
    scored = {
        "expansion": cut / F.least(size, n - size),
        "conductance": cut / F.least(vol, v - vol),
        "expansion_product": cut * n / (size * (n - size)),
        "conductance_product": cut * v / (vol * (v - vol)),
        "cut_ratio": cut / (k * (count - k)),
        "normalized_cut": cut / vol + cut / (v - vol),
        "internal_density": F.when(k > 1, (vol - cut) / (k * (k - 1))),
        "modularity": ((vol - cut) - vol * vol / v) / v,
    }
    return r.withColumns({name: F.when(two_sided, value) for name, value in scored.items()})


def sweep(edges: DataFrame, vectors: DataFrame, key: str = "seed_id", most: int | None = None) -> DataFrame:
    """Prefix cuts by falling value: key, rank, node, size, vol, cut, phi.

    vectors: key, node, value; ties by node. An edge adds its weight where its
    first end enters and takes it back where the second does. A prefix needs
    nothing of later nodes, so with ``most`` only that many are ranked and joined.
    """
    w = Window.partitionBy(key).orderBy(F.col("value").desc(), "node")
    ranked = vectors.withColumn("rank", F.row_number().over(w))
    if most is not None:
        ranked = ranked.filter(F.col("rank") <= most)
    deg = degrees(edges)
    total = deg.agg(F.sum("vol").alias("v")).first()["v"]
    left = ranked.select(key, F.col("node").alias("src"), F.col("rank").alias("r1"))
    right = ranked.select(key, F.col("node").alias("dst"), F.col("rank").alias("r2"))
    inside = edges.join(left, "src").join(right, [key, "dst"])
    closing = inside.groupBy(key, F.greatest("r1", "r2").alias("rank")).agg(F.sum("w").alias("closed"))
    run = Window.partitionBy(key).orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    out = (
        ranked.join(deg, "node")
        .join(closing, [key, "rank"], "left")
        .withColumn("vol_", F.sum("vol").over(run))
        .withColumn("cut", F.col("vol_") - 2 * F.sum(F.coalesce("closed", F.lit(0.0))).over(run))
    )
    small = F.least(F.col("vol_"), F.lit(total) - F.col("vol_"))
    return out.select(key, "rank", "node", "value", F.col("vol_").alias("vol"), "cut", F.when(small > 0, F.col("cut") / small).alias("phi"))


def sweep_all(edges: DataFrame, vector: DataFrame) -> DataFrame:
    """sweep() of one vector over all nodes, by running sums over ranges: no task sees the whole graph."""
    from levcut.operators.relational import prefix_sums

    ranked = prefix_sums(vector.select("node", "value", F.lit(1.0).alias("one_")), [F.col("value").desc(), F.col("node")], {"sum_": "one_"}, "rank").drop("one_", "sum_")
    ranked = cut_lineage(ranked)
    deg = degrees(edges).select("node", "vol")
    total = deg.agg(F.sum("vol").alias("v")).first()["v"] or 0.0
    left = ranked.select(F.col("node").alias("src"), F.col("rank").alias("r1"))
    right = ranked.select(F.col("node").alias("dst"), F.col("rank").alias("r2"))
    closing = edges.join(left, "src").join(right, "dst").groupBy(F.greatest("r1", "r2").alias("rank")).agg(F.sum("w").alias("closed"))
    steps = ranked.join(deg, "node").join(closing, "rank", "left").withColumn("step_", F.col("vol") - 2 * F.coalesce("closed", F.lit(0.0)))
    out = prefix_sums(steps.withColumnRenamed("vol", "vol_"), [F.col("rank")], {"vol": "vol_", "cut": "step_"})
    small = F.least(F.col("vol"), F.lit(total) - F.col("vol"))
    return out.select(F.lit(0).alias("seed_id"), F.col("rank").cast("int").alias("rank"), "node", "value", "vol", "cut", F.when(small > 0, F.col("cut") / small).alias("phi"))


def best_prefix(swept: DataFrame, key: str = "seed_id") -> DataFrame:
    """key, rank, phi of the best prefix; ties to the shorter one."""
    best = F.min(F.struct("phi", "rank", "vol", "cut"))
    return swept.filter("phi is not null").groupBy(key).agg(best.alias("b")).select(key, "b.rank", "b.phi", "b.vol", "b.cut")


def members(swept: DataFrame, best: DataFrame, key: str = "seed_id") -> DataFrame:
    """set_id, node of the winning prefixes."""
    limit = best.select(key, F.col("rank").alias("upto"))
    return swept.join(limit, key).filter("rank <= upto").select(F.col(key).alias("set_id"), "node")

