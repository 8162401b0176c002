"""Work that must stay small or in tasks."""

import random

from levcut.operators import small


def _random_graph(nodes, edges, seed=3):
    rng = random.Random(seed)
    rows = {tuple(sorted(rng.sample(range(nodes), 2))) for _ in range(edges)}
    return small.SmallGraph((a, b, 1.0) for a, b in sorted(rows))


def _plain(g, side, share=0.3, rounds=4):
    """Refinement that sorts all gains for every move."""
    side = set(side)
    for _ in range(rounds):
        gain = {i: sum(w if (j in side) != (i in side) else -w for j, w in g.near[i].items()) for i in range(g.n)}
        vol, cut = float(g.degree[list(side)].sum()), g.cut(side)
        best, best_cut, moves, now = 0, cut, [], set(side)
        for _ in range(min(g.n, 400)):
            size = {i: vol + (g.degree[i] if i not in now else -g.degree[i]) for i in gain}
            fit = [i for i in sorted(gain, key=lambda x: (-gain[x], x))[:50] if share * g.volume <= size[i] <= (1 - share) * g.volume]
            if not fit:
                break
            cut, vol = cut - gain.pop(fit[0]), size[fit[0]]
            now ^= {fit[0]}
            moves.append(fit[0])
            for j, w in g.near[fit[0]].items():
                if j in gain:
                    gain[j] += -2 * w if (j in now) == (fit[0] in now) else 2 * w
            if cut < best_cut - 1e-12:
                best, best_cut = len(moves), cut
        side ^= set(moves[:best])
        if not best:
            break
    return side


def test_refinement_sorts_no_gains(monkeypatch):
    g = _random_graph(1500, 2500)
    start = set(range(0, g.n, 2))
    expected, handled = _plain(g, start), []

    def count(x, **how):
        x = list(x)
        handled.append(len(x))
        return sorted(x, **how)

    monkeypatch.setattr(small, "sorted", count, raising=False)
    assert g.refine(start) == expected
    assert sum(handled) < 10 * g.n


def test_large_pieces_go_to_different_tasks(spark):
    from levcut.operators import probes

    pieces = [list(range(1000 - i)) for i in range(600)]
    dealt = probes._dealt(spark, list(enumerate(pieces))).glom().map(lambda x: [i for i, _ in x]).collect()
    assert sorted(i for part in dealt for i in part) == list(range(600))
    assert max(sum(i < 60 for i in part) for part in dealt) == 1
    g = _random_graph(60, 90)
    found = probes.improvements(spark, g, g.recursive(8))
    assert [x[1] for x in found] == [float(g.improve(p)[0]) for p in g.recursive(8)]


def test_flow_of_pieces_runs_once_for_both_kinds(spark, monkeypatch):
    from levcut.operators import models, probes
    from levcut.plans import graphs

    edges = models.lattice(spark, 8).cache()
    own = {}
    for connected in (False, True):
        for r in probes.flow_pieces(edges, connected=connected).collect():
            own.setdefault((r["method"], r["set_id"]), set()).add(r["node"])
    seen, kinds = [], probes.flow_kinds
    monkeypatch.setattr(probes, "flow_kinds", lambda e, *a: seen.append(a) or kinds(e, *a))
    monkeypatch.setattr(graphs, "_sparse", lambda s, d: edges)
    assert graphs.profile_flow(spark, "").count() > 0 and len(seen) == 1
    both = {}
    for r in kinds(edges, *seen[0]).collect():
        both.setdefault((r["method"], r["set_id"]), set()).add(r["node"])
    assert both == own
    g = small.SmallGraph.of(edges)
    for number, piece in enumerate(sorted({tuple(x) for x in g.recursive(6)})):
        assert both.get(("flow", f"{number}"), set()) == {g.ids[i] for i in g.improve(piece)[1]}


def test_walks_in_tasks_are_those_of_joins(spark, monkeypatch):
    from levcut.operators import local, models

    edges = models.random(spark, 200, 4.0).cache()
    seeds = local.seeds_by_hash(edges, 5)
    for rounds in (3, 200):
        held = {(r["seed_id"], r["node"]): (r["p"], r["r"]) for r in local.ppr(edges, seeds, 0.1, 1e-3, rounds).collect()}
        with monkeypatch.context() as m:
            m.setattr(local, "HELD_EDGES", 0)
            joined = {(r["seed_id"], r["node"]): (r["p"], r["r"]) for r in local.ppr(edges, seeds, 0.1, 1e-3, rounds).collect()}
        assert held.keys() == joined.keys()
        assert all(abs(x - y) < 1e-12 for k in held for x, y in zip(held[k], joined[k], strict=True))
    # A graph that tasks hold takes no join a round.
    monkeypatch.setattr(local, "_steps", None)
    assert local.ppr(edges, seeds, 0.1, 1e-3).count() == len(held)


def test_components_by_stars(spark, monkeypatch):
    from levcut.operators import graph, models

    edges = models.random(spark, 300, 1.2).repartition(5).cache()
    one = {r["node"]: r["component"] for r in graph.components(edges).collect()}
    monkeypatch.setattr(graph, "HELD_STARS", 0)
    assert one == {r["node"]: r["component"] for r in graph.components(edges).collect()}
    g = small.SmallGraph.of(edges)
    assert one == {g.ids[i]: g.ids[part[0]] for part in g.parts() for i in part}
    assert graph.components(edges.filter("w < 0")).count() == 0


def test_first_prefixes_alone(spark):
    from levcut.operators import local, models

    edges = models.random(spark, 200, 4.0).cache()
    vectors = local.ppr(edges, local.seeds_by_hash(edges, 3), 0.05, 1e-4).filter("p > 0")
    whole = {tuple(r) for r in local.sweep(edges, vectors, "p").filter("rank <= 20").collect()}
    assert whole == {tuple(r) for r in local.sweep(edges, vectors, "p", 20).collect()} and len(whole) == 60


def test_graph_on_the_driver_comes_by_columns(spark, monkeypatch):
    import pytest
    from pyspark.sql import DataFrame

    from levcut.runtime import TooLarge

    rows = [(3, 9, 0.5), (9, 3, 2.0), (4, 4, 1.0), (9, 12, 1.0)]
    edges = spark.createDataFrame(rows, "src long, dst long, w double").cache()
    monkeypatch.setattr(DataFrame, "collect", None)
    g, plain = small.SmallGraph.of(edges), small.SmallGraph(rows)
    assert (g.ids, g.near, g.degree.tolist(), g.volume) == (plain.ids, plain.near, plain.degree.tolist(), plain.volume)
    assert small.SmallGraph.of(edges.filter("w > 5")).n == 0
    with pytest.raises(TooLarge):
        small.SmallGraph.of(edges, 3)


def test_block_iteration_in_tasks_is_that_of_joins(spark, monkeypatch):
    import numpy as np

    from levcut.operators import svd

    rng = random.Random(5)
    cells = {(rng.randrange(60), f"c{rng.randrange(40)}"): rng.random() + 0.1 for _ in range(700)}
    a = spark.createDataFrame([(r, c, v * (9 if c < "c2" else 1)) for (r, c), v in sorted(cells.items())], "row_id long, col_id string, value double").cache()

    def found():
        f = svd.topk(a, 3, "subspace", power=12)
        return f.sigma, np.array([list(r)[1:] for r in f.v.orderBy("col_id").collect()])

    exact = svd.topk(a, 3, "gram")
    with monkeypatch.context() as m:
        m.setattr(svd, "multiply", None)
        sigma, v = found()
    monkeypatch.setattr(svd, "HELD_ENTRIES", 0)
    joined = found()
    assert np.allclose(sigma, joined[0]) and np.allclose(v, joined[1], atol=1e-6)
    assert np.allclose(sigma, exact.sigma)
    one = spark.createDataFrame([(1, "a", 2.0), (2, "a", 1.0), (2, "b", 0.5)], a.schema)
    assert np.allclose(svd.topk(one, 5, "subspace").sigma, svd.topk(one, 5, "gram").sigma)


def test_shortest_paths_in_tasks_are_those_of_joins(spark, monkeypatch):
    from levcut.operators import graph, local, models

    edges = models.random(spark, 120, 3.0).cache()
    sources = local.seeds_by_hash(edges, 5).select("node").union(spark.createDataFrame([(10**9,)], "node long"))
    for most in (2, 1000):
        with monkeypatch.context() as m:
            m.setattr(graph, "HELD_EDGES", 0)
            joined = {(r["src"], r["dst"]): r["betweenness"] for r in graph.betweenness(edges, sources, most).collect()}
        with monkeypatch.context() as m:
            m.setattr(graph, "both_ways", None)
            held = {(r["src"], r["dst"]): r["betweenness"] for r in graph.betweenness(edges, sources, most).collect()}
        assert held.keys() == joined.keys() and len(held) == edges.count()
        assert all(abs(held[k] - joined[k]) < 1e-9 for k in held) and sum(held.values()) > 0


def test_components_by_centres_of_stars(spark, monkeypatch):
    from levcut.operators import graph, models

    for degree in (0.8, 1.2, 3.0):
        edges = models.random(spark, 300, degree).repartition(7).cache()
        g = small.SmallGraph.of(edges)
        exact = {g.ids[i]: g.ids[part[0]] for part in g.parts() for i in part}
        for limit in (0, 250):
            monkeypatch.setattr(graph, "HELD_STARS", limit)
            rows = graph.components(edges).collect()
            assert {r["node"]: r["component"] for r in rows} == exact and len(rows) == len(exact)
    # Links between centres fit the driver where the stars themselves don't: no round of joins.
    edges = spark.createDataFrame([(2 * i, 2 * i % 100 + 1, 1.0) for i in range(60, 600)], "src long, dst long, w double").repartition(3)
    monkeypatch.setattr(graph, "_join_components", None)
    assert graph.components(edges).select("component").distinct().count() == 50


def test_vectors_of_a_large_factor_go_in_turn(spark, monkeypatch):
    import numpy as np

    from levcut.operators import svd

    rng = random.Random(8)
    cells = {(rng.randrange(30), f"c{rng.randrange(20)}"): rng.random() for _ in range(200)}
    a = spark.createDataFrame([(r, c, v) for (r, c), v in sorted(cells.items())], "row_id long, col_id string, value double").cache()
    whole = svd.topk(a, 3, "subspace", power=2)
    # Three of the eleven vectors at a time, and still no join a round.
    monkeypatch.setattr(svd, "HELD_ENTRIES", 65)
    monkeypatch.setattr(svd, "multiply", None)
    parts = svd.topk(a, 3, "subspace", power=2)
    assert np.allclose(whole.sigma, parts.sigma)
    assert np.allclose(*[np.array([list(r)[1:] for r in f.v.orderBy("col_id").collect()]) for f in (whole, parts)])


def test_all_ranks_are_compared_at_once(spark, monkeypatch):
    import pandas as pd
    import pytest

    from levcut.operators import leverage, relational, svd

    rng = random.Random(4)
    rows = sorted({(rng.randrange(40), f"c{rng.randrange(12)}") for _ in range(200)})
    a = spark.createDataFrame([(r, c, 1.0) for r, c in rows], "row_id long, col_id string, value double").cache()
    labels = spark.createDataFrame([(r, "ab"[r % 3 == 0]) for r in range(40)], "row_id long, label string")
    v = svd.topk(a, 3).v
    gain = leverage.information_gain(a, labels).toPandas().set_index("col_id")["gain"]
    scores = leverage.by_rank(v).toPandas()
    monkeypatch.setattr(relational, "cut_lineage", None)
    found = {r["k"]: r for r in leverage.vs_information_gain(a, labels, (1, 3)).collect()}
    assert sorted(found) == [1, 3]
    for k, row in found.items():
        score = scores[scores["rank"] == k].set_index("col_id")["score"]
        both = pd.DataFrame({"s": score, "g": gain})
        assert row["pearson"] == pytest.approx(both["s"].corr(both["g"]))
        assert row["spearman"] == pytest.approx(both["s"].rank(method="min").corr(both["g"].rank(method="min")))


def test_bridges_in_one_task_are_those_of_joins(spark, monkeypatch):
    from levcut.operators import models, probes

    for degree, limit in ((1.5, 10**6), (3.0, 10**6), (3.0, 250), (2.2, 0)):
        edges = models.random(spark, 150, degree).repartition(6).cache()
        g = small.SmallGraph.of(edges)
        exact = {(g.ids[i], g.ids[j]) for i, j in g.bridges()}
        with monkeypatch.context() as m:
            m.setattr(probes, "HELD_FORESTS", limit)
            if limit:
                m.setattr(probes, "_join_bridges", None)
            rows = probes.bridges(edges).collect()
        assert {tuple(r) for r in rows} == exact and len(rows) == len(exact)
    # A string, and no edge at all.
    line = spark.range(300).selectExpr("id as src", "id + 1 as dst", "1.0D as w")
    assert probes.bridges(line).count() == 300 and probes.bridges(line.filter("w > 5")).count() == 0


def test_copies_of_columns_are_not_kept(spark, monkeypatch):
    from levcut.operators import svd
    from levcut.plans import studies

    rows = [(r, f"t{r * c % 7}") for r in range(20) for c in range(1, 4)]
    base = spark.createDataFrame(sorted(set(rows)), "row_id long, col_id string").selectExpr("*", "1.0D as value")
    monkeypatch.setattr(studies.t, "term_binary", lambda s, d: base)
    monkeypatch.setattr(studies, "cut_lineage", None)
    seen, topk = [], svd.topk

    def record(a, *rest, **more):
        seen.append((a.count(), a.select("col_id").distinct().count()))
        return topk(a, *rest, **more)

    monkeypatch.setattr(svd, "topk", record)
    found = studies.scale_up_terms(spark, "").collect()
    assert [(r["copies"], r["entries"]) for r in found] == [(n, n * base.count()) for n in (1, 2, 4)]
    columns = base.select("col_id").distinct().count()
    assert seen == [(n * base.count(), n * columns) for n in (1, 2, 4)]


def test_tasks_hold_the_document_term_graph():
    from levcut.operators import local

    # Edges of its largest component at sf0.1.
    assert local.HELD_EDGES >= 2_538_883


def test_dense_coarsest_graphs_are_coarsened_on(spark, monkeypatch):
    from levcut.operators import models, multilevel

    edges = models.random(spark, 120, 60.0).cache()
    monkeypatch.setattr(multilevel, "COARSEST_EDGES", 500)
    e, masses, _ = multilevel.ladder(edges, 2000)[-1]
    assert e.count() <= 500 < edges.count()
    assert masses.agg({"mass": "sum"}).first()[0] == 2 * edges.count()
    assert {r["side"]: r["count"] for r in multilevel.bisect(edges, 2000).groupBy("side").count().collect()}.keys() == {0, 1}


def test_flow_pieces_are_not_made_on_the_driver(spark, monkeypatch):
    from levcut.operators import models, probes

    edges = models.lattice(spark, 8).cache()
    monkeypatch.setattr(small.SmallGraph, "recursive", None)
    assert probes.flow_pieces(edges).select("set_id").distinct().count() > 10


def test_arrays_of_a_walk_take_little_room(spark):
    import tracemalloc

    from levcut.operators import graph, local, models

    edges = models.random(spark, 40_000, 5.0).cache()
    n = edges.count()
    tracemalloc.start()
    ids, first, to, w, vol = local._arrays(edges)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 120 * n, peak / n
    near = {(int(ids[i]), int(ids[j])) for i in range(len(ids)) for j in to[first[i] : first[i + 1]]}
    assert near == {(r["src"], r["dst"]) for r in graph.both_ways(edges).collect()} and w.sum() == vol.sum() == 2 * n
