"""Edges whose loss changes a verdict: summed up in numpy against a judged copy of the neighbourhood per set of edges."""

import numpy as np
from test_implicit import points

from lookalike.apps import errors
from lookalike.models import layers, predict
from lookalike.operators import graph, implicit
from lookalike.operators.graph import AnchoredGraph


def rows(df):
    return sorted((r["node_id"], r["size"], tuple(map(tuple, r["removed"])), r["before"], r["after"]) for r in df.collect())


def test_mask_flip_without_copies(spark, monkeypatch):
    nodes = points(spark, 40).select("node_id", "x")
    w = layers.closed_form(4, 3)
    whole = AnchoredGraph(nodes, graph.epsilon(nodes, 0.6))
    asked = nodes.filter("node_id < 12 or node_id = 40").select("node_id")

    def model(g):
        return predict.head(layers.gcn(g.nodes.select("node_id", "x"), g.both_ways(), w, activation=False), np.eye(3), np.zeros(3)).select("node_id", "verdict")

    want = rows(errors.edge_mask_flip(whole, model, asked, 2, 2))
    assert {r[1] for r in want} == {1, 2}
    monkeypatch.setattr(errors, "_judged", None)  # no copies from here on
    assert rows(errors.gcn_mask_flip(whole, w, asked, 2)) == want
    near = implicit.near_graph(nodes, 0.6)
    with monkeypatch.context() as m:
        m.setattr(implicit.ImplicitGraph, "edges", property(lambda self: 1 / 0))  # nor edges
        assert rows(errors.gcn_mask_flip(near, w, asked, 2)) == want
    monkeypatch.setattr(implicit, "tasks_can_read", lambda path: False)
    assert rows(errors.gcn_mask_flip(implicit.near_graph(nodes, 0.6), w, asked, 2)) == want
