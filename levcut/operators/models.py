"""Reference graphs from hashes of ids; every generator returns src < dst, w."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from levcut.functions.portable import u01
from levcut.operators import graph
from levcut.runtime import cut_lineage


def _edges(df: DataFrame) -> DataFrame:
    return graph.build(df.withColumn("one_", F.lit(1.0)), "src", "dst", "one_").withColumn("w", F.lit(1.0))


def path(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1.0).alias("w"))


def path_through(keys: DataFrame, key: str) -> DataFrame:
    """The path over the rows of a table by rising key: each key to the next."""
    from levcut.operators.relational import numbered

    placed = cut_lineage(numbered(keys, key))
    following = placed.select((F.col("id") - 1).alias("id"), F.col(key).alias("dst"))
    return placed.join(following, "id").select(F.col(key).cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), F.lit(1.0).alias("w"))


def ring(spark: SparkSession, n: int) -> DataFrame:
    return _edges(spark.range(n).select(F.col("id").alias("src"), ((F.col("id") + 1) % n).alias("dst")))


def lattice(spark: SparkSession, side: int) -> DataFrame:
    i = spark.range(side * side)
    right = i.filter(F.col("id") % side < side - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1.0).alias("w"))
    down = i.filter(F.col("id") < side * (side - 1)).select(F.col("id").alias("src"), (F.col("id") + side).alias("dst"), F.lit(1.0).alias("w"))
    return right.unionByName(down)


def lattice_of(nodes: DataFrame, n: int) -> DataFrame:
    """The n rows of a table (id from 0) laid out row by row in a square; the last row may be short."""
    side = math.isqrt(n - 1) + 1 if n else 1
    i = nodes.select("id")
    right = i.filter((F.col("id") % side < side - 1) & (F.col("id") + 1 < n)).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1.0).alias("w"))
    down = i.filter(F.col("id") + side < n).select(F.col("id").alias("src"), (F.col("id") + side).alias("dst"), F.lit(1.0).alias("w"))
    return right.unionByName(down)


def random(spark: SparkSession, n: int, mean_degree: float, seed: int = 0) -> DataFrame:
    """Uniform random graph: n * mean_degree / 2 hashed endpoint pairs, loops and repeats merged."""
    m = spark.range(int(n * mean_degree / 2))
    return _edges(m.select(F.floor(u01("id", seed) * n).alias("src"), F.floor(u01("id", seed + 1) * n).alias("dst")))


def power_law(spark: SparkSession, n: int, mean_degree: float, beta: float, seed: int = 0) -> DataFrame:
    """Expected degrees falling as a power law of exponent beta, by inverse distribution draws."""
    gamma = (beta - 2) / (beta - 1)
    end = lambda s: F.floor(F.pow(u01("id", s), F.lit(1 / gamma)) * n)
    return _edges(spark.range(int(n * mean_degree / 2)).select(end(seed).alias("src"), end(seed + 1).alias("dst")))


def copying(spark: SparkSession, n: int, out: int = 2, seed: int = 0, nodes: DataFrame | None = None) -> DataFrame:
    """Each node copies the ends of earlier nodes' edges: pointers double by joins until all have their ends. nodes: id from 0 to n - 1, of a table."""
    slots = (spark.range(n) if nodes is None else nodes).filter("id > 0").select(F.col("id").alias("node"), F.explode(F.sequence(F.lit(0), F.lit(out - 1))).alias("k"))
    key = F.concat_ws("-", "node", "k")
    slots = slots.select("node", "k", F.floor(u01(key, seed) * F.col("node")).alias("at"), (u01(key, seed + 1) < 0.5).alias("copies"))
    links = cut_lineage(slots.select("node", "k", F.col("at").alias("goal"), F.col("copies").alias("live")))
    while not links.filter("live").isEmpty():
        nxt = links.select(F.col("node").alias("goal"), "k", F.col("goal").alias("next"), F.col("live").alias("more"))
        links = cut_lineage(links.join(nxt.hint("merge"), ["goal", "k"], "left").select(
            "node", "k", F.when(F.col("live") & F.col("next").isNotNull(), F.col("next")).otherwise(F.col("goal")).alias("goal"),
            (F.col("live") & F.coalesce("more", F.lit(False))).alias("live"),
        ))
    return _edges(links.select(F.col("node").alias("src"), F.col("goal").alias("dst")))


def preferential(spark: SparkSession, n: int, out: int = 2, seed: int = 0) -> DataFrame:
    """Attachment in proportion to degree: copying with even odds is the same law."""
    return copying(spark, n, out, seed)


def forest_fire(spark: SparkSession, n: int, forward: float = 0.35, seed: int = 0, most: int = 100_000, ids: Sequence[int] | None = None) -> DataFrame:
    """Each new node links to an ambassador and burns on along its links; sequential, so bounded.

    ids: the nodes in order of arrival, 0 to n - 1 without them.
    """
    import numpy as np

    if n > most:
        raise ValueError(f"{n} nodes")
    rng = np.random.default_rng(seed)
    near: list[list[int]] = [[] for _ in range(n)]
    rows = []
    for i in range(1, n):
        burnt, queue = set(), [int(rng.integers(i))]
        while queue and len(burnt) < 200:
            j = queue.pop()
            if j in burnt:
                continue
            burnt.add(j)
            k = min(len(near[j]), int(rng.geometric(1 - forward)) - 1)
            if k:
                queue += [near[j][x] for x in rng.choice(len(near[j]), k, replace=False)]
        for j in burnt:
            a, b = (j, i) if ids is None else (ids[j], ids[i])
            rows.append((min(a, b), max(a, b), 1.0))
            near[i].append(j)
            near[j].append(i)
    return spark.createDataFrame(rows, "src long, dst long, w double")


def geometric(spark: SparkSession, n: int, radius: float, seed: int = 0) -> DataFrame:
    """Points of the unit square joined within a radius: cells as an equi-join, then the distance."""
    p = spark.range(n).select("id", u01("id", seed).alias("x"), u01("id", seed + 1).alias("y"))
    return near_points(p, radius)


def near_points(points: DataFrame, radius: float) -> DataFrame:
    cell = lambda c: F.floor(F.col(c) / radius)
    a = points.select(F.col("id").alias("src"), F.col("x").alias("xa"), F.col("y").alias("ya"), cell("x").alias("cx"), cell("y").alias("cy"))
    steps = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in (-1, 0, 1) for j in (-1, 0, 1)])
    b = points.withColumn("s", F.explode(steps)).select(
        F.col("id").alias("dst"), F.col("x").alias("xb"), F.col("y").alias("yb"), (cell("x") + F.col("s.i")).alias("cx"), (cell("y") + F.col("s.j")).alias("cy")
    )
    close = (F.col("xa") - F.col("xb")) ** 2 + (F.col("ya") - F.col("yb")) ** 2 <= radius * radius
    return a.join(b, ["cx", "cy"]).filter((F.col("src") < F.col("dst")) & close).select("src", "dst", F.lit(1.0).alias("w"))


def road_like(spark: SparkSession, side: int, drop: float = 0.3, seed: int = 0) -> DataFrame:
    """A lattice with a share of its edges gone."""
    return lattice(spark, side).filter(u01(F.concat_ws("-", "src", "dst"), seed) >= drop)


def expander_maps(n: int, degree: int = 6, seed: int = 1) -> list[tuple[int, int]]:
    """Multiplier and shift of the affine permutations whose union is the expander."""
    maps = []
    a = 2 * seed + 3
    while len(maps) < degree // 2:
        if math.gcd(a, n) == 1:
            maps.append((a, 7 * a + seed))
        a = (a * 31 + 17) % max(5, n)
    return maps


def expander(spark: SparkSession, n: int, degree: int = 6, seed: int = 1, nodes: DataFrame | None = None) -> DataFrame:
    """A union of affine permutations of the ids. nodes: id from 0 to n - 1, of a table."""
    i = spark.range(n) if nodes is None else nodes.select("id")
    parts = [i.select(F.col("id").alias("src"), F.pmod(F.col("id") * m + c, F.lit(n)).alias("dst")) for m, c in expander_maps(n, degree, seed)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return _edges(out)


def rewired(edges: DataFrame, seed: int = 0) -> DataFrame:
    """A random graph of the same degrees: edge ends in hashed order, neighbours paired."""
    ends = edges.select(F.explode(F.array("src", "dst")).alias("node"), F.monotonically_increasing_id().alias("at"))
    spread = ends.withColumn("u", u01(F.concat_ws("-", "node", F.row_number().over(Window.partitionBy("node").orderBy("at"))), seed))
    from levcut.operators.relational import prefix_sum

    placed = prefix_sum(spread.withColumn("one", F.lit(1.0)), [F.col("u"), F.col("node")], "one", "s", "place").select("node", (F.col("place") - 1).alias("place"))
    pairs = placed.groupBy(F.floor(F.col("place") / 2).alias("pair")).agg(F.min("node").alias("src"), F.max("node").alias("dst"))
    return _edges(pairs.select("src", "dst"))


def hierarchical(spark: SparkSession, levels: int, fan: int = 3, seed: int = 0, nodes: DataFrame | None = None, n: int | None = None) -> DataFrame:
    """Leaves of a tree linked with odds that fall by level of their common ancestor.

    nodes: id from 0 to n - 1, of a table of at most fan ** levels rows; the last block of a level may be short.
    """
    n = fan**levels if n is None else n
    i = spark.range(n) if nodes is None else nodes.select("id")
    parts = None
    for level in range(1, levels + 1):
        block = fan**level
        start = F.floor(F.col("id") / block) * block
        one = i.withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(1)))).select(
            F.col("id").alias("src"),
            (start + F.floor(u01(F.concat_ws("-", "id", "t"), seed + level) * F.least(F.lit(block), F.lit(n) - start))).alias("dst"),
            u01(F.concat_ws("-", "id", "t"), seed + 100 + level).alias("u"),
        ).filter(F.col("u") < 2.0 ** (1 - level)).drop("u")
        parts = one if parts is None else parts.unionByName(one)
    return _edges(parts)


def core_periphery(spark: SparkSession, core: int, whiskers: int, seed: int = 0, nodes: DataFrame | None = None, hung: DataFrame | None = None) -> DataFrame:
    """An expander with paths hung on hashed core nodes by one edge each.

    nodes, hung: id from 0 of the core's nodes and of the paths, of tables.
    """
    inner = expander(spark, core, 6, seed + 1, nodes)
    w = spark.range(whiskers) if hung is None else hung.select("id")
    length = (F.floor(u01("id", seed) * 5) + 1).cast("int")
    nodes = w.select("id", F.explode(F.sequence(F.lit(0), length - 1)).alias("k"))
    me = F.lit(core) + F.col("id") * 8 + F.col("k")
    up = F.when(F.col("k") == 0, F.floor(u01("id", seed + 1) * core)).otherwise(me - 1)
    return inner.unionByName(nodes.select(F.least(up, me).alias("src"), F.greatest(up, me).alias("dst"), F.lit(1.0).alias("w")))
