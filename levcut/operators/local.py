"""Local spectral methods: sets near seeds, at a cost of the output's size."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levcut.operators import graph
from levcut.runtime import cut_lineage, release, ship

#: Edges up to which a graph is held in every task.
HELD_EDGES = 3_000_000


def ppr(edges: DataFrame, seeds: DataFrame, alpha: float = 0.1, eps: float = 1e-4, rounds: int = 200, every: int = 8) -> DataFrame:
    """seed_id, node, p, r: personalized PageRank by synchronous pushes.

    Each round all residuals of at least eps times the degree move: alpha of one
    stays, half of the rest stays in the residual, half spreads over the edges.
    The sum of p and r stays 1 for each seed, and work stops when no residual is
    large, so it depends on alpha and eps, not on the graph. Of a graph of at most
    ``HELD_EDGES`` edges every task holds all, and walks its seeds there; a larger
    one takes a join a round.
    seeds: seed_id, node.
    """
    if edges.count() <= HELD_EDGES:
        return _held_ppr(edges, seeds, alpha, eps, rounds)
    steps = cut_lineage(_steps(edges)).select("src", "dst", "share", "own", (F.col("vol") * eps).alias("limit"))
    state = seeds.select("seed_id", "node", F.lit(0.0).alias("p"), F.lit(1.0).alias("r")).join(
        steps.filter("own").select(F.col("src").alias("node"), "limit"), "node"
    )
    push = F.when(F.col("r") >= F.col("limit_"), F.col("r")).otherwise(0.0)
    for i in range(rounds):
        if i % every == 0:
            state = cut_lineage(state)
            release(edges.sparkSession)
            if state.filter("r >= limit").isEmpty():
                break
        # A loop edge carries what stays, so a round reads the state once.
        out = state.withColumnRenamed("limit", "limit_").join(steps, (F.col("node") == F.col("src")) & (F.col("own") | (F.col("r") >= F.col("limit_"))))
        half = (1 - alpha) / 2 * push
        state = out.groupBy("seed_id", F.col("dst").alias("node")).agg(
            F.sum(F.when(F.col("own"), F.col("p") + alpha * push).otherwise(0.0)).alias("p"),
            F.sum(F.when(F.col("own"), F.col("r") - push + half).otherwise(half * F.col("share"))).alias("r"),
            F.max("limit").alias("limit"),
        )
    return cut_lineage(state).select("seed_id", "node", "p", "r")


def _held_ppr(edges: DataFrame, seeds: DataFrame, alpha: float, eps: float, rounds: int) -> DataFrame:
    """ppr() with the graph as arrays in each task: the same pushes, one job for all rounds."""
    spark = edges.sparkSession
    held = ship(spark, _arrays(edges))
    kind, half = seeds.schema["seed_id"].dataType.simpleString(), (1 - alpha) / 2

    def walk(batches):
        ids, first, to, w, vol = held()
        limit = vol * eps
        starts: dict = {}
        for batch in batches:
            for seed, node in zip(batch["seed_id"], batch["node"], strict=True):
                starts.setdefault(seed, []).append(node)
        for seed, nodes in starts.items():
            at = np.searchsorted(ids, nodes)
            at = at[ids[np.minimum(at, len(ids) - 1)] == nodes] if len(ids) else at[:0]
            p, r = np.zeros(len(ids)), np.zeros(len(ids))
            np.add.at(r, at, 1.0)
            met = np.zeros(len(ids), bool)
            met[at] = True
            live = np.unique(at)
            live = live[r[live] >= limit[live]]
            for _ in range(rounds):
                if not len(live):
                    break
                pushed, many = r[live], first[live + 1] - first[live]
                p[live] += alpha * pushed
                r[live] = half * pushed
                # Places of all edges of the nodes that push, one after the other.
                edge = np.repeat(first[live] - np.cumsum(many) + many, many) + np.arange(many.sum())
                near = to[edge]
                given = np.repeat(half * pushed / vol[live], many) * w[edge]
                met[near] = True
                if 8 * len(near) > len(ids):
                    r += np.bincount(near, given, len(ids))
                    live = np.flatnonzero(met & (r >= limit))
                else:
                    np.add.at(r, near, given)
                    live = np.unique(np.concatenate([live, near]))
                    live = live[r[live] >= limit[live]]
            found = np.flatnonzero(met)
            yield pd.DataFrame({"seed_id": [seed] * len(found), "node": ids[found], "p": p[found], "r": r[found]})

    # Few seeds are few bytes, but each is much work: as many tasks as seeds, within reason.
    dealt = seeds.select("seed_id", "node").repartition(min(256, max(1, seeds.count())), "seed_id")
    return cut_lineage(dealt.mapInPandas(walk, f"seed_id {kind}, node long, p double, r double"))


def _arrays(edges: DataFrame) -> tuple[np.ndarray, ...]:
    """ids, first, to, w, vol: nodes in order, the neighbours of node i at first[i]:first[i + 1]; what is done with is let go."""
    table = edges.select("src", "dst", F.col("w").cast("double").alias("w")).toArrow()
    a, b, w = (table.column(c).to_numpy() for c in ("src", "dst", "w"))
    del table
    ids = np.union1d(a, b)
    x, y = (np.searchsorted(ids, z).astype(np.int32) for z in (a, b))
    del a, b
    src, to, w = np.concatenate([x, y]), np.concatenate([y, x]), np.concatenate([w, w])
    del x, y
    vol = np.bincount(src, w, len(ids))
    order = np.argsort(src, kind="stable")
    first = np.concatenate([[0], np.cumsum(np.bincount(src, minlength=len(ids)))]).astype(np.int64)
    del src
    to = to[order]
    return ids, first, to, w[order], vol


def _steps(edges: DataFrame) -> DataFrame:
    """src, dst, share of the walk, vol of dst, own: every edge both ways, and a loop at each node."""
    deg = graph.degrees(edges).select("node", "vol")
    out = graph.both_ways(edges).join(deg.select(F.col("node").alias("src"), F.col("vol").alias("from_")), "src")
    out = out.join(deg.withColumnRenamed("node", "dst"), "dst").select("src", "dst", (F.col("w") / F.col("from_")).alias("share"), "vol", F.lit(False).alias("own"))
    return out.unionByName(deg.select(F.col("node").alias("src"), F.col("node").alias("dst"), F.lit(1.0).alias("share"), "vol", F.lit(True).alias("own")))


def _walk(steps: DataFrame, x: DataFrame, lazy: float) -> DataFrame:
    """One step of the walk on seed_id, node, value; lazy is the share that stays."""
    part = F.when(F.col("own"), F.lit(lazy)).otherwise((1 - lazy) * F.col("share"))
    moved = x.join(steps if lazy else steps.filter("not own"), x["node"] == steps["src"])
    return moved.groupBy("seed_id", F.col("dst").alias("node")).agg(F.sum(F.col("value") * part).alias("value"), F.max("vol").alias("vol"))


def nibble(edges: DataFrame, seeds: DataFrame, steps: int = 20, eps: float = 1e-4) -> DataFrame:
    """seed_id, node, value: the lazy walk with entries below eps times the degree zeroed."""
    walk = cut_lineage(_steps(edges))
    x = seeds.select("seed_id", "node", F.lit(1.0).alias("value"))
    for i in range(steps):
        x = _walk(walk, x, 0.5).filter(F.col("value") >= F.col("vol") * eps).select("seed_id", "node", "value")
        if i % 5 == 4:
            x = cut_lineage(x)
    return x


def heat(edges: DataFrame, seeds: DataFrame, t: float = 5.0, terms: int = 12, eps: float = 1e-5) -> DataFrame:
    """seed_id, node, value: the heat kernel's Taylor terms of the walk; what is below eps times the degree goes."""
    x = seeds.select("seed_id", "node", F.lit(1.0).alias("value"))
    total = x.select("seed_id", "node", (F.col("value") * math.exp(-t)).alias("value"))
    walk = cut_lineage(_steps(edges))
    for j in range(1, terms + 1):
        x = cut_lineage(_walk(walk, x, 0.0).filter(F.col("value") >= F.col("vol") * eps).select("seed_id", "node", "value"))
        total = total.unionByName(x.select("seed_id", "node", (F.col("value") * math.exp(-t) * t**j / math.factorial(j)).alias("value")))
    return cut_lineage(total.groupBy("seed_id", "node").agg(F.sum("value").alias("value")))


def sweep(edges: DataFrame, vectors: DataFrame, value: str = "value", most: int | None = None) -> DataFrame:
    """Prefix cuts of each seed by value over degree; of the first ``most`` prefixes if given."""
    deg = graph.degrees(edges).select("node", "vol")
    return graph.sweep(edges, vectors.join(deg, "node").select("seed_id", "node", (F.col(value) / F.col("vol")).alias("value")), most=most)


def seeds_by_hash(edges: DataFrame, count: int, seed: int = 0) -> DataFrame:
    """seed_id, node of ``count`` nodes chosen by hash: a sampling operator."""
    from levcut.functions.portable import u01

    nodes = graph.degrees(edges).select("node")
    return nodes.orderBy(u01("node", seed), "node").limit(count).select(F.col("node").alias("seed_id"), "node")
