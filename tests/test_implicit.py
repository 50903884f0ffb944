"""Neighbour sums without edges against sums over the edges."""

import random

import numpy as np

from lookalike.models import predict
from lookalike.operators import graph, implicit, similarity
from lookalike.operators.graph import AnchoredGraph


def by_id(df, column):
    return {r["node_id"]: (np.array(r[column]), *([r["deg"]] if "deg" in df.columns else [])) for r in df.collect()}


def same(got, want):
    assert got.keys() == want.keys()
    for k, v in want.items():
        assert np.allclose(got[k][0], v[0], atol=1e-12) and got[k][1:] == v[1:]


def points(spark, n=60):
    rng = random.Random(3)
    rows = [(i, [rng.gauss(0, 1) for _ in range(4)] if i % 9 else [0.0] * 4, rng.choice([1, 2, None]), i % 7, i % 3, "train") for i in range(n)]
    rows.append((n, [1.0, 2.0, 3.0, 4.0], 9, 1, 0, "train"))  # alone under its key
    return spark.createDataFrame(rows, "node_id long, x array<double>, a int, b int, label int, split string")


def test_near_sums_equal_edges(spark):
    nodes = points(spark)
    both = graph.symmetrize(graph.epsilon(nodes, 0.3))
    base = nodes.selectExpr("node_id AS i", "transform(x, v -> v / greatest(1e-300, sqrt(aggregate(x, 0D, (s, w) -> s + w * w)))) AS u")
    moved = nodes.selectExpr("node_id", "transform(x, v -> v * v) AS x")
    for weighted in (True, False):
        want = by_id(similarity.bucket_mean(moved, both, weighted=weighted), "m")
        for block in (None, 11):
            same(by_id(implicit.near_mean(base, moved, 0.3, weighted, block), "m"), want)


def test_key_sums_equal_edges_and_make_none(spark, monkeypatch):
    nodes = points(spark)
    g = implicit.key_graph(nodes.select("node_id", "x", "label", "split"), nodes, "node_id", ["a", "b"])
    edges = graph.shared_key(nodes, "node_id", ["a", "b"])
    for weighted in (True, False):
        same(by_id(g.mean(nodes, weighted), "m"), by_id(similarity.bucket_mean(nodes, graph.symmetrize(edges), weighted=weighted), "m"))
    whole = AnchoredGraph(g.nodes, edges)
    want, rule = by_id(similarity.signatures(whole), "sig"), sorted(map(tuple, predict.centroid_rule(whole).collect()))
    monkeypatch.setattr(graph, "shared_key", None)  # no edges from here on
    same(by_id(similarity.signatures(g), "sig"), want)
    assert sorted(map(tuple, predict.centroid_rule(g).collect())) == rule


def test_repeated_ids_fall_back_to_edges(spark):
    nodes = points(spark)
    twice = nodes.select("node_id", "a", "b").union(spark.createDataFrame([(0, 1, 1)], "node_id long, a int, b int"))
    g = implicit.key_graph(nodes, twice, "node_id", ["a", "b"])
    assert not hasattr(g, "mean") and sorted(map(tuple, g.edges.collect())) == sorted(map(tuple, graph.shared_key(twice, "node_id", ["a", "b"]).collect()))


def test_pairs_of_one_key_are_not_shuffled(spark):
    """Only items are dealt out: no aggregation stands above the join."""
    nodes = points(spark).select("node_id", "a", "b")
    pairs = graph.shared_key(nodes, "node_id", ["a", "b"], block=2)
    rows = [tuple(r) for r in nodes.collect()]
    assert sorted(map(tuple, pairs.collect())) == sorted((i, j) for i, *k in rows for j, *m in rows if i < j and k == m and None not in k)
    plan = pairs._jdf.queryExecution().optimizedPlan().toString()
    assert "Aggregate" not in plan[: plan.index("Join")]


def test_models_over_implicit_graphs_make_no_edges(spark, monkeypatch):
    """A convolution, and a fit on a sample, against the same with all edges; sums over groups that are dealt out too."""
    from lookalike.models import layers, train

    nodes = points(spark)
    plain = nodes.select("node_id", "x", "label", "split")
    w = layers.closed_form(4, 3)
    edges = graph.shared_key(nodes, "node_id", ["a", "b"])
    whole, g = AnchoredGraph(plain, edges), implicit.key_graph(plain, nodes, "node_id", ["a", "b"])
    near = implicit.near_graph(plain, 0.3)
    for made, both in ((g, graph.symmetrize(edges)), (near, graph.symmetrize(graph.epsilon(nodes, 0.3)))):
        same(by_id(layers.gcn_of(made, plain, w), "x"), by_id(layers.gcn(plain, both, w), "x"))
    ids = plain.filter("node_id % 2 = 0")
    assert sorted(map(tuple, g.among(ids).collect())) == sorted(map(tuple, whole.among(ids).collect()))
    assert sorted(map(tuple, near.among(ids).collect())) == sorted(map(tuple, AnchoredGraph(plain, graph.epsilon(nodes, 0.3)).among(ids).collect()))
    model = train.fit("gcn", whole, epochs=5)
    want = {r["node_id"]: r["verdict"] for r in model.predict(whole).collect()}
    sigs = by_id(similarity.signatures(whole), "sig")
    monkeypatch.setattr(implicit.ImplicitGraph, "edges", property(lambda self: 1 / 0))
    assert {r["node_id"]: r["verdict"] for r in train.fit("gcn", g, epochs=5).predict(g).collect()} == want
    monkeypatch.setattr(implicit, "tasks_can_read", lambda path: False)
    same(by_id(similarity.signatures(g), "sig"), sigs)


def test_spread_equals_edge_by_edge(monkeypatch):
    from lookalike.models import train

    rng = np.random.default_rng(1)
    n = 40
    cliques = np.equal.outer(np.arange(n) % 4, np.arange(n) % 4) & ~np.eye(n, dtype=bool)
    loose = rng.random((n, n)) < 0.2
    loose = np.triu(loose, 1) | np.triu(loose, 1).T
    monkeypatch.setattr(train, "GATHER", 50)  # what is gathered at a time is bounded
    for adj, classes in ((cliques, 4), (loose, None), (np.zeros((n, n), bool), n), (cliques & (loose | ~(np.arange(n) < 3)), None)):
        src, dst = np.nonzero(adj & adj.T)
        for times in (1, 2):  # edges that repeat count as often
            none = np.zeros(n, bool)
            s = train.Sample(np.arange(n), rng.standard_normal((n, 5)), np.zeros(n, int), none, none, np.tile(src, times), np.tile(dst, times))
            spread = train.Spread(s)
            assert np.allclose(spread(s.x), train.propagate(s.x, s, 1 / np.sqrt(np.bincount(s.src, minlength=n) + 1.0)))
            assert classes is None or times > 1 or len(spread.a) == classes
