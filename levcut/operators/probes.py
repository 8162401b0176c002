"""Whiskers and cores, community profiles, and ensembles of probes."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from levcut.operators import graph, local, spectral
from levcut.operators.small import SmallGraph
from levcut.runtime import TooLarge, bounded, cut_lineage, release, ship

#: Edges of two forests a task that one task takes to find the bridges.
HELD_FORESTS = 4_000_000

SUMMARY = "method string, set_id string, size long, vol double, cut double, phi double"


def bridges(edges: DataFrame, seed: int = 17) -> DataFrame:
    """src, dst of the edges on no cycle, whatever the graph's size.

    Of its edges each task keeps a spanning forest, and one of what remains: what
    lies on a cycle of the graph still lies on one of these, so edges fall to two
    a node, task by task and then of several tasks together. One task finds the
    bridges among at most ``HELD_FORESTS`` of them; of more, joins do.
    """
    kept = cut_lineage(edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")).filter("src != dst").mapInArrow(_two_forests, "src long, dst long"))
    count, tasks = kept.count(), kept.rdd.getNumPartitions()
    while count > HELD_FORESTS and tasks > 1:
        tasks = -(-tasks // 4)
        kept = cut_lineage(kept.repartition(tasks).mapInArrow(_two_forests, "src long, dst long"))
        release(edges.sparkSession)
        count, before = kept.count(), count
        if 2 * count > before:
            break
    if count > HELD_FORESTS:
        return _join_bridges(kept.withColumn("w", F.lit(1.0)), seed)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, b = [], []
        for batch in batches:
            a.append(batch.column(0).to_numpy())
            b.append(batch.column(1).to_numpy())
        if a:
            yield from _edge_batches(*_bridges_of(np.concatenate(a), np.concatenate(b), seed))

    return cut_lineage(kept.repartition(1).mapInArrow(run, "src long, dst long"))


def _edge_batches(a: np.ndarray, b: np.ndarray) -> Iterator[pa.RecordBatch]:
    for low in range(0, len(a), 1 << 16):
        yield pa.RecordBatch.from_arrays([pa.array(a[low : low + (1 << 16)]), pa.array(b[low : low + (1 << 16)])], names=["src", "dst"])


def _forest(x: np.ndarray, y: np.ndarray, n: int) -> np.ndarray:
    """Places of the edges of a spanning forest of nodes 0..n-1: every tree takes its first edge outwards, until none has any."""
    label, live, chosen = np.arange(n), np.arange(len(x)), []
    while True:
        lx, ly = label[x[live]], label[y[live]]
        out = lx != ly
        live, lx, ly = live[out], lx[out], ly[out]
        if not len(live):
            return np.concatenate(chosen) if chosen else live
        first = np.full(n, len(x))
        np.minimum.at(first, lx, live)
        np.minimum.at(first, ly, live)
        trees = np.flatnonzero(first < len(x))
        edge = first[trees]
        chosen.append(np.unique(edge))
        other = label[x[edge]] + label[y[edge]] - trees
        up = np.arange(n)
        up[trees] = other
        # Two trees that take the same edge: the smaller number is the root.
        both = (up[other] == trees) & (trees < other)
        up[trees[both]] = trees[both]
        while (up[up] != up).any():
            up = up[up]
        label = up[label]


def _two_forests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Edges of a task that are in a spanning forest or in one of the other edges."""
    a, b, room = [], [], 1 << 21

    def kept() -> tuple[np.ndarray, np.ndarray]:
        x, y = np.concatenate(a), np.concatenate(b)
        ids, ends = np.unique(np.concatenate([x, y]), return_inverse=True)
        ex, ey = ends[: len(x)], ends[len(x) :]
        one = _forest(ex, ey, len(ids))
        rest = np.setdiff1d(np.arange(len(x)), one, assume_unique=True)
        on = np.concatenate([one, rest[_forest(ex[rest], ey[rest], len(ids))]])
        return x[on], y[on]

    for batch in batches:
        a.append(batch.column(0).to_numpy())
        b.append(batch.column(1).to_numpy())
        if sum(map(len, a)) > room:
            x, y = kept()
            a, b = [x], [y]
            if 2 * len(x) > room:
                yield from _edge_batches(x, y)
                a, b = [], []
    if a:
        yield from _edge_batches(*kept())


def _bridges_of(a: np.ndarray, b: np.ndarray, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """Ends of the bridges of edges as arrays, the smaller one first; by labels that cancel out, as in _join_bridges()."""
    ids, ends = np.unique(np.concatenate([a, b]), return_inverse=True)
    n, x, y = len(ids), ends[: len(a)], ends[len(a) :]
    own, to, edge = np.concatenate([x, y]), np.concatenate([y, x]), np.tile(np.arange(len(a)), 2)
    # Only the forest's own edges are walked.
    trees = np.zeros(len(a), bool)
    trees[_forest(x, y, n)] = True
    mark = np.zeros(n, np.uint64)
    labels = np.random.default_rng(seed).integers(0, 1 << 64, int((~trees).sum()), np.uint64)
    np.bitwise_xor.at(mark, x[~trees], labels)
    np.bitwise_xor.at(mark, y[~trees], labels)
    live = trees[edge]
    own, to, edge = own[live], to[live], edge[live]
    left = np.bincount(own, minlength=n)
    # The sum of numbers of the tree edges that a node still has: of a leaf, the one edge.
    last = np.zeros(n, np.int64)
    np.add.at(last, own, edge)
    cut, leaves = [], np.flatnonzero(left == 1)
    while len(leaves):
        which = last[leaves]
        which, at = np.unique(which, return_index=True)
        leaf = leaves[at]
        up = x[which] + y[which] - leaf
        cut.append(which[mark[leaf] == 0])
        np.bitwise_xor.at(mark, up, mark[leaf])
        np.subtract.at(left, up, 1)
        np.subtract.at(last, up, which)
        left[leaf] = 0
        leaves = np.unique(up[left[up] == 1])
    cut = np.concatenate(cut) if cut else np.zeros(0, np.int64)
    return np.minimum(a[cut], b[cut]), np.maximum(a[cut], b[cut])


def _join_bridges(edges: DataFrame, seed: int) -> DataFrame:
    """bridges() of a graph that no task holds.

    A breadth-first forest is grown; every other edge gets a random 64-bit label.
    A tree edge is a bridge exactly if the labels at its subtree cancel out,
    which levels are summed upward to see. Two labels agree by chance with
    probability 2^-64 for each edge.
    """
    comp = cut_lineage(graph.components(edges))
    roots = comp.select(F.col("component").alias("node")).distinct()
    both = graph.both_ways(edges).select("src", "dst")
    level = cut_lineage(roots.select("node", F.lit(None).cast("long").alias("parent"), F.lit(0).alias("depth")))
    seen, depth = level, 0
    while True:
        depth += 1
        found = level.join(both, level["node"] == both["src"]).groupBy(F.col("dst").alias("node")).agg(F.min("src").alias("parent"))
        level = cut_lineage(found.join(seen.select("node"), "node", "left_anti").withColumn("depth", F.lit(depth)))
        if level.isEmpty():
            break
        seen = cut_lineage(seen.unionByName(level))
    tree = seen.filter("parent is not null").select(F.least("node", "parent").alias("src"), F.greatest("node", "parent").alias("dst"))
    rest = edges.select("src", "dst").join(tree, ["src", "dst"], "left_anti").withColumn("label", F.xxhash64("src", "dst", F.lit(seed)))
    ends = rest.select(F.col("src").alias("node"), "label").unionByName(rest.select(F.col("dst").alias("node"), "label"))
    own = ends.groupBy("node").agg(F.expr("bit_xor(label)").alias("mark"))
    state = cut_lineage(seen.join(own, "node", "left").select("node", "parent", "depth", F.coalesce("mark", F.lit(0)).cast("long").alias("mark")))
    for d in range(depth - 1, 0, -1):
        up = state.filter(F.col("depth") == d).groupBy(F.col("parent").alias("node")).agg(F.expr("bit_xor(mark)").alias("more"))
        state = state.join(up, "node", "left").select("node", "parent", "depth", F.col("mark").bitwiseXOR(F.coalesce("more", F.lit(0))).alias("mark"))
        if d % 2 == 0:
            state = cut_lineage(state)
    cut = state.filter("parent is not null and mark = 0")
    return cut_lineage(cut.select(F.least("node", "parent").alias("src"), F.greatest("node", "parent").alias("dst")))


def decompose(edges: DataFrame) -> DataFrame:
    """node, role (core or whisker), whisker_id (least node), for a connected graph.

    The core is the largest component once bridges are gone, ties to the least
    node; whiskers are the components of what remains without the core.
    """
    cuts = bridges(edges)
    nodes = graph.degrees(edges).select("node")
    solid = edges.join(cuts, ["src", "dst"], "left_anti")
    comp = nodes.join(graph.components(solid), "node", "left").select("node", F.coalesce("component", "node").alias("component"))
    comp = cut_lineage(comp)
    best = comp.groupBy("component").count().orderBy(F.desc("count"), "component").limit(1).select("component")
    core = cut_lineage(comp.join(F.broadcast(best), "component", "left_semi").select("node"))
    release(edges.sparkSession)
    outside = graph.without(edges, core)
    piece = nodes.join(core, "node", "left_anti").join(graph.components(outside), "node", "left")
    return cut_lineage(
        piece.select("node", F.lit("whisker").alias("role"), F.coalesce("component", "node").alias("whisker_id")).unionByName(
            core.select("node", F.lit("core").alias("role"), F.lit(None).cast("long").alias("whisker_id"))
        )
    )


def core(edges: DataFrame, roles: DataFrame | None = None) -> DataFrame:
    roles = decompose(edges) if roles is None else roles
    return graph.induced(edges, roles.filter("role = 'core'"))


def whisker_shares(edges: DataFrame, roles: DataFrame) -> DataFrame:
    """One row: shares of nodes and edges outside the core, whiskers, the largest one."""
    n = roles.agg(F.count("*").alias("nodes"), F.sum((F.col("role") == "whisker").cast("long")).alias("out"), F.countDistinct("whisker_id").alias("whiskers"))
    e = edges.agg(F.count("*").alias("edges"))
    kept = core(edges, roles).agg(F.count("*").alias("core_edges"))
    top = roles.filter("role = 'whisker'").groupBy("whisker_id").count().agg(F.coalesce(F.max("count"), F.lit(0)).alias("largest"))
    row = n.crossJoin(e).crossJoin(kept).crossJoin(top)
    return row.select(
        "nodes", "edges", "whiskers", "largest", (F.col("out") / F.col("nodes")).alias("node_share"),
        ((F.col("edges") - F.col("core_edges")) / F.col("edges")).alias("edge_share"),
    )


def whisker_summary(edges: DataFrame, roles: DataFrame) -> DataFrame:
    """whisker_id, size, vol (plain degrees): each meets the core by one edge."""
    plain = edges.select("src", "dst", F.lit(1.0).alias("w"))
    deg = graph.degrees(plain)
    return roles.filter("role = 'whisker'").join(deg, "node").groupBy("whisker_id").agg(F.count("*").alias("size"), F.sum("vol").alias("vol"))


def _best_unions(kinds: list[tuple[int, int, int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """size, whiskers, vol of the best union at every total size; kinds: (size, vol, number).

    At one total size the best of (whiskers j, volume v) has the largest v / j, so
    it is best for some price of a whisker. A price makes one sum of every lot, and
    all sizes are one array: lots of 1, 2, 4 ... make up every number of a kind.
    Each size keeps the best unions at a price below and at one above its own v / j;
    it is settled once they are equal or the line between them has nothing above.
    Prices are fractions and sums whole numbers, so nothing is rounded.
    """
    total, most = sum(a * n for a, _, n in kinds), sum(n for _, _, n in kinds) + 1
    lots = []
    for size, vol, left in sorted(kinds):
        lot = 1
        while left:
            lot = min(lot, left)
            lots.append((lot * size, lot * (vol - 2 * size + 1), lot))
            left, lot = left - lot, lot * 2
    none = np.iinfo(np.int64).min // 2
    spread = 1 + sum(abs(x) for _, x, _ in lots)
    if 2 * most * most * spread > -none // 2:
        raise TooLarge(f"{most - 1} whiskers of volumes apart by {spread}")

    def at(p: int, q: int) -> tuple[np.ndarray, np.ndarray]:
        """j and x = v + j - 2 size, 0 for trees, where q x - p j is largest; ties to the fewest whiskers."""
        best, reach = np.full(total + 1, none, np.int64), 0
        best[0] = 0
        for size, extra, n in lots:
            # An own copy of what is moved: the places overlap.
            moved = best[: reach + 1] + ((q * extra - p * n) * most - n)
            reach += size
            np.maximum(best[size : reach + 1], moved, out=best[size : reach + 1])
        j = np.where(best > none // 2, -best % most, -1)
        extra = np.where(j >= 0, ((best + j) // most + p * j) // max(q, 1), 0)
        return j, extra

    hj, hx = at(2 * spread, 1)
    sizes = np.flatnonzero(hj > 0)
    lj, lx = at(0, 1)
    hj, hx, lj, lx = (y[sizes] for y in (hj, hx, lj, lx))
    open_ = np.flatnonzero((hj != lj) | (hx != lx))
    while len(open_):
        up, over = lx[open_] - hx[open_], lj[open_] - hj[open_]
        by = np.gcd(up, over)
        prices, uses = np.unique(np.stack([up // by, over // by]), axis=1, return_counts=True)
        p, q = (int(y) for y in prices[:, uses.argmax()])
        mj, mx = (y[sizes[open_]] for y in at(p, q))
        gain = q * mx - p * mj
        same = (up * q == over * p) & (gain == q * hx[open_] - p * hj[open_])
        left = q * (mx + 2 * sizes[open_]) - p * mj
        # What the price leaves over tells on which side of it v / j lies; v + j in place of v adds 1 to both.
        low, high = ~same & (left >= 0), ~same & (left <= 0)
        lj[open_[low]], lx[open_[low]] = mj[low], mx[low]
        hj[open_[high]], hx[open_[high]] = mj[high], mx[high]
        open_ = open_[~same & ((hj[open_] != lj[open_]) | (hx[open_] != lx[open_]))]
    hv, lv = hx + 2 * sizes - hj, lx + 2 * sizes - lj
    low = lv * hj > hv * lj
    return sizes, np.where(low, lj, hj), np.where(low, lv, hv)


def bag(summary: DataFrame, most_total: int = 50_000_000, most_kinds: int = 20_000) -> DataFrame:
    """size, whiskers, vol, phi: best union of whiskers at each total size.

    A union of j whiskers has cut j. The histogram of (size, vol), small at any
    scale, goes to the driver, which holds a few whole numbers a total size; the
    result is exact. Volumes are plain degrees. Whiskers of more than
    ``most_total`` nodes in all are refused.
    """
    kinds = bounded(summary.groupBy("size", "vol").agg(F.count("*").alias("n")), most_kinds)
    total = sum(row["size"] * row["n"] for row in kinds)
    if total > most_total:
        raise TooLarge(f"whiskers of {total} nodes, more than {most_total} for the driver")
    if any(row["vol"] != int(row["vol"]) for row in kinds):
        raise ValueError("volumes of whiskers are counts of edge ends")
    size, j, vol = _best_unions([(int(r["size"]), int(r["vol"]), int(r["n"])) for r in kinds])
    table = pa.table({"size": size, "whiskers": j, "vol": vol.astype(float), "phi": j / vol})
    return summary.sparkSession.createDataFrame(table, "size long, whiskers long, vol double, phi double")


def bag_prefixes(summary: DataFrame) -> DataFrame:
    """size, whiskers, vol, phi of the first j whiskers by falling volume."""
    from levcut.operators.relational import prefix_sums

    order = [F.col("vol").desc(), F.col("whisker_id")]
    own = summary.select("whisker_id", "vol", F.col("size").cast("double").alias("size_"))
    out = prefix_sums(own, order, {"sizes": "size_", "volumes": "vol"}, "whiskers")
    return out.select(F.col("sizes").cast("long").alias("size"), F.col("whiskers").cast("long").alias("whiskers"), F.col("volumes").alias("vol"), (F.col("whiskers") / F.col("volumes")).alias("phi"))


# --- network community profile -----------------------------------------------


def summarize(swept: DataFrame, edges: DataFrame, method: str) -> DataFrame:
    """Every prefix of every sweep as (method, set_id, size, vol, cut, phi), by the smaller-volume side."""
    total = graph.degrees(edges).agg(F.sum("vol").alias("v"), F.count("*").alias("n")).first()
    flip = F.col("vol") * 2 > total["v"]
    return swept.filter("phi is not null").select(
        F.lit(method).alias("method"),
        F.concat_ws(":", "seed_id", "rank").alias("set_id"),
        F.when(flip, F.lit(total["n"]) - F.col("rank")).otherwise(F.col("rank")).cast("long").alias("size"),
        F.least(F.col("vol"), F.lit(total["v"]) - F.col("vol")).alias("vol"),
        "cut",
        "phi",
    )


def profile(summaries: DataFrame, bins_per_octave: int | None = 1) -> DataFrame:
    """method, bin, size, phi: least conductance per size bin; None: exact sizes."""
    size = F.col("size")
    place = size if bins_per_octave is None else F.pow(F.lit(2.0), F.floor(F.log2(size) * bins_per_octave) / bins_per_octave)
    best = F.min(F.struct("phi", "size", "set_id"))
    return summaries.filter("size > 0").groupBy("method", place.cast("double").alias("bin")).agg(best.alias("b")).select("method", "bin", "b.size", "b.phi", "b.set_id")


def envelope(profiled: DataFrame) -> DataFrame:
    """The least of all methods in each bin."""
    return profiled.groupBy("bin").agg(F.min("phi").alias("phi"), F.min_by("method", F.struct("phi", "method")).alias("method"))


def shape(profiled: DataFrame) -> DataFrame:
    """argmin size, least phi, slopes of log phi on log size before and after, and the curve's class."""
    low = profiled.groupBy("method").agg(F.min(F.struct("phi", "bin")).alias("m")).select("method", F.col("m.bin").alias("at"), F.col("m.phi").alias("least"))
    joined = profiled.join(low, "method")
    x, y = F.log2("bin"), F.log2(F.greatest("phi", F.lit(1e-12)))
    before, after = F.col("bin") <= F.col("at"), F.col("bin") >= F.col("at")
    out = joined.groupBy("method", "at", "least").agg(
        F.regr_slope(F.when(before, y), F.when(before, x)).alias("slope_before"),
        F.regr_slope(F.when(after, y), F.when(after, x)).alias("slope_after"),
        F.max("phi").alias("top"), F.max("bin").alias("widest"),
    )
    kind = (
        F.when(F.col("least") > 0.5 * F.col("top"), "flat")
        .when(F.col("at") * 4 > F.col("widest"), "falling")
        .when(F.coalesce("slope_after", F.lit(0.0)) > 0.05, "falls then rises")
        .otherwise("falls then level")
    )
    return out.withColumn("shape", kind)


def local_profile(edges: DataFrame, seeds: int = 12, alphas=(0.02, 0.1), eps: float = 2e-4, method: str = "local_spectral") -> DataFrame:
    """Summaries of all prefixes of local sweeps from hashed seeds over a grid of localities."""
    starts = local.seeds_by_hash(edges, seeds)
    parts = None
    for alpha in alphas:
        vectors = local.ppr(edges, starts, alpha, eps).filter("p > 0")
        one = summarize(local.sweep(edges, vectors, "p"), edges, method)
        parts = one if parts is None else parts.unionByName(one)
    return cut_lineage(parts)


def flow_pieces(edges: DataFrame, least: int = 6, connected: bool | None = None, method: str | None = None) -> DataFrame:
    """Multilevel pieces at all scales, each improved by flow: (method, set_id, node).

    connected=True keeps of each improved set its best component; False leaves
    sets as they come. A graph is held as arrays, so it is one up to the driver's
    limits; larger ones are cut first into components, cores or local sets.
    Pieces are made and their flows run in tasks.
    """
    return flow_kinds(edges, {method or ("flow_connected" if connected else "flow"): bool(connected)}, least)


def flow_kinds(edges: DataFrame, kinds: dict[str, bool], least: int = 6) -> DataFrame:
    """flow_pieces() by methods of several names, connected or not, from one flow a piece."""
    spark, g = edges.sparkSession, SmallGraph.of(edges)
    schema = "method string, set_id string, node long"
    held = ship(spark, g)
    pieces = sorted({x for _, x in _bisected(spark, held, g.n, least)})
    if not pieces:
        return spark.createDataFrame([], schema)

    def run(numbered):
        number, piece = numbered
        g = held()
        _, side = g.improve(_nodes(piece))
        for name, connected in kinds.items():
            kept = min(g.parts(side), key=lambda part: (g.phi(part), part)) if connected and side else side
            for i in kept:
                yield name, f"{number}", int(g.ids[i])

    return cut_lineage(spark.createDataFrame(_dealt(spark, list(enumerate(pieces))).flatMap(run), schema))


def set_summaries(edges: DataFrame, sets: DataFrame) -> DataFrame:
    """Summaries of explicit sets (method, set_id, node), by the smaller-volume side."""
    total = graph.degrees(edges).agg(F.sum("vol").alias("v"), F.count("*").alias("n")).first()
    keyed = sets.withColumn("set_id", F.concat_ws("/", "method", "set_id"))
    scored = graph.score(edges, keyed).filter("conductance is not null")
    flip = F.col("vol") * 2 > total["v"]
    return scored.select(
        F.split("set_id", "/")[0].alias("method"), "set_id",
        F.when(flip, F.lit(total["n"]) - F.col("n_nodes")).otherwise(F.col("n_nodes")).cast("long").alias("size"),
        F.least("vol", F.lit(total["v"]) - F.col("vol")).alias("vol"), "cut", F.col("conductance").alias("phi"),
    )


def piece_improvements(edges: DataFrame, least: int) -> list[tuple[int, float, float, int]]:
    """(size, phi, improved phi, improved size) of every piece of recursive bisection, by depth.

    Pieces are made and improved in tasks, so for graphs up to the driver's limit of edges.
    """
    spark, g = edges.sparkSession, SmallGraph.of(edges)
    held = ship(spark, g)
    pieces = [x for _, x in _bisected(spark, held, g.n, least)]
    found = _improved(spark, held, pieces) if pieces else []
    return [(len(x) // 4, *better) for x, better in zip(pieces, found, strict=True)]


def improvements(spark: SparkSession, g: SmallGraph, pieces: list[list[int]]) -> list[tuple[float, float, int]]:
    """(phi, improved phi, improved size) of every piece in order, dealt over tasks."""
    return _improved(spark, ship(spark, g), [_packed(x) for x in pieces]) if pieces else []


def _improved(spark: SparkSession, held, pieces: list[bytes]) -> list[tuple[float, float, int]]:
    def run(piece):
        g, nodes = held(), _nodes(piece)
        phi, side = g.improve(nodes)
        return float(g.phi(nodes)), float(phi), len(side)

    found = _dealt(spark, list(enumerate(pieces))).map(lambda x: (x[0], run(x[1]))).collect()
    return [x for _, x in sorted(found)]


def _packed(nodes: Sequence[int]) -> bytes:
    """Numbers of nodes, four bytes each; packed sets are in order as the lists are."""
    return np.asarray(nodes, ">i4").tobytes()


def _nodes(piece: bytes) -> list[int]:
    return np.frombuffer(piece, ">i4").tolist()


def _bisected(spark: SparkSession, held, n: int, least: int, alone: int = 4000) -> list[tuple[str, bytes]]:
    """(path, packed piece) of SmallGraph.descend() from all n nodes, in its order.

    A task splits a piece once, or wholly if it has at most ``alone`` nodes; the
    driver holds packed pieces alone.
    """

    def run(numbered):
        path, piece = numbered
        g, nodes = held(), _nodes(piece)
        if len(nodes) <= alone:
            return [(path + more, _packed(part), False) for more, part in g.descend(nodes, least)]
        return [(f"{path}{i}", _packed(part), True) for i, part in enumerate(g.halves(nodes, least))]

    out, level = [], [("", _packed(range(n)))]
    while level:
        found = _dealt(spark, level).flatMap(run).collect()
        out += [(path, piece) for path, piece, _ in found]
        level = [(path, piece) for path, piece, whole in found if whole]
    return sorted(out, key=lambda x: (len(x[0]), x[0]))


def _dealt(spark: SparkSession, numbered: list):
    """Numbered pieces over tasks, the large ones over all of them."""
    tasks = min(len(numbered), 256)
    by_size = sorted(numbered, key=lambda x: -len(x[1]))
    return spark.sparkContext.parallelize([by_size[i::tasks] for i in range(tasks)], tasks).flatMap(lambda x: x)


def look(edges: DataFrame, seeds: int = 24, rounds: int = 60) -> DataFrame:
    """Is the graph like a hot dog, an expander, or nibbled at: best balanced and best small cuts.

    The even cut is the best prefix of the global vector with 0.3 of the volume on
    each side; small cuts are its best prefix, those of local sweeps from hashed
    seeds, and the best union of whiskers' prefixes. All of it is distributed.
    """
    vector, _ = spectral.fiedler(edges, rounds)
    swept = cut_lineage(spectral.sweep(edges, vector))
    total = graph.degrees(edges).agg(F.sum("vol").alias("v")).first()["v"]
    even = spectral.balanced(swept, total, 0.3).first()
    near = local.sweep(edges, local.ppr(edges, local.seeds_by_hash(edges, seeds), 0.05, 2e-4).filter("p > 0"), "p")
    pieces = bag_prefixes(whisker_summary(edges, decompose(edges))).select("phi")
    small = graph.best_prefix(swept).select("phi").union(graph.best_prefix(near).select("phi")).union(pieces).agg(F.min("phi").alias("p")).first()["p"]
    balanced = even["phi"] if even else 1.0
    kind = "hot dog" if balanced < 0.1 and balanced < 2 * small else "expander" if small > 0.25 else "nibble"
    return edges.sparkSession.createDataFrame([(float(balanced), float(small), kind)], "balanced_phi double, small_phi double, look string")


def compactness(edges: DataFrame, sets: DataFrame, most: int = 5000) -> DataFrame:
    """set_id, n, parts, diameter, mean_distance, internal_phi: one Arrow group a set."""
    keyed = sets.select("set_id", "node").distinct()
    left, right = keyed.withColumnRenamed("node", "src"), keyed.withColumnRenamed("node", "dst")
    inside = edges.join(left, "src").join(right, ["set_id", "dst"]).select("set_id", "src", "dst", "w")
    sizes = keyed.groupBy("set_id").agg(F.count("*").alias("n"))

    def run(pdf):
        import pandas as pd

        g = SmallGraph(pdf[["src", "dst", "w"]].itertuples(index=False, name=None))
        if g.n > most:
            raise ValueError(f"a set of {g.n} nodes")
        far, total, pairs = 0, 0, 0
        for s in range(g.n):
            dist, queue = {s: 0}, [s]
            for i in queue:
                for j in g.near[i]:
                    if j not in dist:
                        dist[j] = dist[i] + 1
                        queue.append(j)
            far = max(far, max(dist.values()))
            total += sum(dist.values())
            pairs += len(dist) - 1
        parts = g.parts()
        phi = 0.0 if len(parts) > 1 else g.sweep(g.fiedler()[1])[0] if g.n > 2 else 1.0
        return pd.DataFrame([(pdf["set_id"].iloc[0], g.n, len(parts), far, total / pairs if pairs else 0.0, float(phi))], columns=["set_id", "linked", "parts", "diameter", "mean_distance", "internal_phi"])

    kind = sets.schema["set_id"].dataType.simpleString()
    found = inside.groupBy("set_id").applyInPandas(run, f"set_id {kind}, linked long, parts long, diameter long, mean_distance double, internal_phi double")
    # Nodes without an edge inside the set are parts of their own.
    return sizes.join(found, "set_id", "left").select(
        "set_id", "n", (F.coalesce("parts", F.lit(0)) + F.col("n") - F.coalesce("linked", F.lit(0))).alias("parts"),
        F.coalesce("diameter", F.lit(0)).alias("diameter"), "mean_distance",
        F.when(F.col("n") > F.coalesce("linked", F.lit(0)), 0.0).otherwise(F.col("internal_phi")).alias("internal_phi"),
    )


def ground_truth(sets: DataFrame, labels: DataFrame) -> DataFrame:
    """set_id, label, precision, recall, f1 of the best matching label, and purity."""
    n = sets.groupBy("set_id").agg(F.count("*").alias("n"))
    m = labels.groupBy("label").agg(F.count("*").alias("m"))
    both = sets.join(labels, "node").groupBy("set_id", "label").agg(F.count("*").alias("hit")).join(n, "set_id").join(F.broadcast(m), "label")
    scored = both.withColumns({"precision": F.col("hit") / F.col("n"), "recall": F.col("hit") / F.col("m"), "f1": 2 * F.col("hit") / (F.col("n") + F.col("m"))})
    best = F.max(F.struct("f1", "label", "precision", "recall"))
    return scored.groupBy("set_id").agg(best.alias("b"), F.max("precision").alias("purity")).select("set_id", "b.label", "b.precision", "b.recall", "b.f1", "purity")


# --- applications --------------------------------------------------------------


def seeds_for(edges: DataFrame, share: float = 0.01, least: int = 12) -> int:
    """Seeds in proportion to the graph's nodes: each is a key, so more of them are rows, not jobs."""
    return max(least, int(share * graph.degrees(edges).count()))


def micro_markets(edges: DataFrame, low: int, high: int, most_phi: float, seeds: int | None = None) -> DataFrame:
    """Sets of a size band below a conductance limit, best first; one per seed, seeds in proportion to the nodes."""
    starts = local.seeds_by_hash(edges, seeds or seeds_for(edges))
    swept = cut_lineage(local.sweep(edges, local.ppr(edges, starts, 0.05, 1e-4).filter("p > 0"), "p"))
    best = graph.best_prefix(swept.filter(F.col("rank").between(low, high)))
    return best.filter(F.col("phi") <= most_phi).orderBy("phi", "seed_id")


def expand_phrases(edges: DataFrame, phrases: DataFrame, top: int = 5, most_phi: float = 0.9) -> DataFrame:
    """seed_id, node, p, phi: nearest nodes of the phrase's own side, only where
    the phrase's neighbourhood is a set of low conductance."""
    vectors = local.ppr(edges, phrases.select(F.col("node").alias("seed_id"), "node"), 0.1, 1e-4).filter("p > 0")
    return expand_from(edges, vectors, top, most_phi)


def expand_from(edges: DataFrame, vectors: DataFrame, top: int, most_phi: float) -> DataFrame:
    """The same from walks (seed_id, node, p) that are known."""
    gate = graph.best_prefix(local.sweep(edges, vectors, "p")).filter(F.col("phi") <= most_phi).select("seed_id", "phi")
    same = vectors.filter((F.col("node") != F.col("seed_id")) & (F.col("node") % 2 == F.col("seed_id") % 2))
    w = Window.partitionBy("seed_id").orderBy(F.col("p").desc(), "node")
    return same.join(gate, "seed_id").withColumn("place", F.row_number().over(w)).filter(F.col("place") <= top)


def spectral_pieces(edges: DataFrame) -> DataFrame:
    """The global sweep's winner as a set."""
    swept = spectral.sweep(edges, spectral.fiedler(edges)[0])
    return graph.members(swept, graph.best_prefix(swept)).select(F.lit("global_spectral").alias("method"), F.col("set_id").cast("string"), "node")


def set_measures(edges: DataFrame, sets: DataFrame, measure: str) -> DataFrame:
    """Summaries of sets (method, set_id, node) with another score of graph.MEASURES in place of conductance."""
    keyed = sets.withColumn("set_id", F.concat_ws("/", "method", "set_id"))
    scored = graph.score(edges, keyed).filter(F.col(measure).isNotNull())
    return scored.select(F.split("set_id", "/")[0].alias("method"), "set_id", F.col("n_nodes").alias("size"), "vol", "cut", F.col(measure).alias("phi"))


def compare(edges: DataFrame, sets: DataFrame, most: int = 5000) -> DataFrame:
    """method, bin, sets, phi, internal_phi, mean_distance, parts: conductance against compactness by method and size.

    sets: method, set_id, node. Sets over ``most`` nodes are scored, not measured inside.
    """
    summaries = set_summaries(edges, sets)
    keyed = sets.select(F.concat_ws("/", "method", "set_id").alias("set_id"), "node")
    small = keyed.join(keyed.groupBy("set_id").count().filter(F.col("count") <= most), "set_id", "left_semi")
    inside = compactness(edges, small, most)
    both = summaries.join(inside, "set_id", "left").withColumn("bin", F.pow(F.lit(2.0), F.floor(F.log2(F.greatest("size", F.lit(1))))))
    return both.groupBy("method", "bin").agg(
        F.count("*").alias("sets"), F.min("phi").alias("least_phi"), F.avg("phi").alias("phi"), F.avg("internal_phi").alias("internal_phi"),
        F.avg("mean_distance").alias("mean_distance"), F.avg("parts").alias("parts"),
    )


def local_sets(edges: DataFrame, seeds: int, low: int, high: int, alpha: float = 0.02, eps: float = 5e-5, method: str = "local_spectral") -> DataFrame:
    """(method, set_id, node): of each seed the best prefix within a band of sizes."""
    vectors = local.ppr(edges, local.seeds_by_hash(edges, seeds), alpha, eps).filter("p > 0")
    swept = cut_lineage(local.sweep(edges, vectors, "p", high))
    best = graph.best_prefix(swept.filter(F.col("rank") >= low))
    return graph.members(swept, best).select(F.lit(method).alias("method"), F.col("set_id").cast("string").alias("set_id"), "node")


def flow_sets(edges: DataFrame, sets: DataFrame, method: str = "local_flow", most: int = 20_000) -> DataFrame:
    """(method, set_id, node): of each set the subset of least conductance, one max-flow a set and task.

    Only the set, the edges inside it and its boundary move, so the graph may be
    of any size; a set of more than ``most`` nodes is refused.
    """
    from levcut.operators.small import best_subset

    keyed = sets.select("set_id", "node").distinct()
    deg = graph.degrees(edges).select("node", "vol")
    left, right = keyed.withColumnRenamed("node", "src"), keyed.withColumnRenamed("node", "dst")
    arcs = edges.join(left, "src").join(right, ["set_id", "dst"]).select("set_id", F.col("src").alias("a"), F.col("dst").alias("b"), "w")
    own = keyed.join(deg, "node").select("set_id", F.col("node").alias("a"), F.lit(None).cast("long").alias("b"), F.col("vol").alias("w"))

    def run(pdf):
        import pandas as pd

        nodes = pdf[pdf["b"].isna()]
        if len(nodes) > most:
            raise ValueError(f"a set of {len(nodes)} nodes")
        inside = pdf[pdf["b"].notna()]
        volumes = dict(zip(nodes["a"].astype(int), nodes["w"], strict=True))
        links = list(zip(inside["a"].astype(int), inside["b"].astype(int), inside["w"], strict=True))
        kept = best_subset(volumes, links)
        return pd.DataFrame({"set_id": pdf["set_id"].iloc[0], "node": kept})

    found = arcs.unionByName(own).groupBy("set_id").applyInPandas(run, "set_id string, node long")
    return found.select(F.lit(method).alias("method"), "set_id", "node")


def residual_structure(edges: DataFrame, twin: DataFrame, seeds: int = 8) -> DataFrame:
    """bin, phi, twin_phi: profile of a graph and of its degree-preserving random twin."""
    own = profile(local_profile(edges, seeds)).select("bin", "phi")
    other = profile(local_profile(twin, seeds)).select("bin", F.col("phi").alias("twin_phi"))
    return own.join(other, "bin").withColumn("gap", F.col("twin_phi") - F.col("phi"))

