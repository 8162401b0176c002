"""Every piece of the recursive bisection is improved."""

import pytest

from levcut.operators import models, probes, small
from levcut.plans import graphs


def test_every_piece_is_improved(spark, monkeypatch):
    edges = models.lattice(spark, 24).cache()
    g = small.SmallGraph.of(edges)
    pieces = g.recursive(20)
    assert len(pieces) > 40
    monkeypatch.setattr(graphs, "_sparse", lambda s, d: edges)
    rows = {r["piece"]: r for r in graphs.flow_improvement(spark, "").collect()}
    assert sorted(rows) == list(range(len(pieces)))
    for i in (0, 41, len(pieces) - 1):
        phi, side = g.improve(pieces[i])
        assert rows[i]["improved_phi"] == pytest.approx(phi) and rows[i]["improved_size"] == len(side)
    assert probes.look(edges).first()["small_phi"] <= min(g.improve(p)[0] for p in g.recursive(6)) + 1e-9


def test_pieces_are_of_all_orders(spark):
    from levcut.operators import graph
    from levcut.sources import tables

    d = "/root/testdata/sf0.001"
    nodes = graph.degrees(graph.giant(tables.g_order_part(spark, d))).count()
    sizes = {r["piece"]: r["size"] for r in graphs.flow_improvement(spark, d).collect()}
    assert sizes[0] + sizes[1] == nodes


def test_bisection_in_tasks_is_that_of_the_driver(spark):
    from levcut.runtime import ship

    g = small.SmallGraph.of(models.random(spark, 300, 3.0))
    plain = small.SmallGraph((g.ids[i], g.ids[j], w) for i, j, w in g.edges())
    assert plain.ids == g.ids and list(g.near) == plain.near
    found = probes._bisected(spark, ship(spark, g), g.n, 10, alone=40)
    assert [probes._nodes(x) for _, x in found] == plain.recursive(10) and len(found) > 40
