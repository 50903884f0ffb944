"""The methods against numpy, worked fixtures and the invariants that can be proved."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from lookalike.apps import audit, errors
from lookalike.functions import caps
from lookalike.functions import vectors as V
from lookalike.operators import cluster, graph, index, metrics, pairs, relational, scan, search, similarity, wl
from lookalike.operators.cluster import Layers, LayerSpec
from lookalike.operators.graph import AnchoredGraph
from lookalike.plans.planner import plan
from lookalike.session import cut


def numpy_signatures(x, adj, alpha=0.5, hops=2):
    """The aggregate vectors, written with dense matrices."""
    total, now = x.copy(), x.copy()
    for _ in range(hops):
        n = np.linalg.norm(now, axis=1)
        cos = now @ now.T / np.where(np.outer(n, n) > 0, np.outer(n, n), 1)
        w = np.where(adj, cos, 0)
        deg = adj.sum(1, keepdims=True)
        now = alpha * now + np.where(deg > 0, (1 - alpha) / np.maximum(deg, 1) * (w @ now), 0)
        total += now
    n = np.linalg.norm(total, axis=1, keepdims=True)
    return total / np.where(n > 0, n, 1)


@pytest.fixture(scope="module")
def small(spark):
    """Sixty nodes, some isolated, some zero, some repeated; random verdicts."""
    rng = np.random.default_rng(1)
    x = rng.standard_normal((60, 6))
    x[5] = 0
    x[7] = x[8]
    adj = rng.random((60, 60)) < 0.06
    adj = np.triu(adj, 1)
    adj[:, 59] = adj[59] = False
    adj = adj | adj.T
    verdict = rng.integers(0, 3, 60)
    nodes = cut(spark.createDataFrame([(i, x[i].tolist(), int(verdict[i])) for i in range(60)], "node_id long, x array<double>, verdict int"), "nodes")
    edges = cut(spark.createDataFrame([(int(a), int(b)) for a, b in zip(*np.nonzero(np.triu(adj)))], "src long, dst long"), "edges")
    return AnchoredGraph(nodes, edges), x, adj, verdict


@pytest.fixture(scope="module")
def sigs(small):
    return cut(similarity.signatures(small[0]).select("node_id", "verdict", "sig"), "sigs")


@pytest.fixture(scope="module")
def exact(small):
    """All pair similarities by numpy, rounded as the engine does; same verdicts masked."""
    s = numpy_signatures(small[1], small[2])
    m = np.round(s @ s.T, 9)
    m[small[3][:, None] == small[3][None, :]] = -np.inf
    return s, m


def lists(df):
    out = {}
    for r in df.orderBy("v", "rank").collect():
        out.setdefault(r["v"], []).append((r["u"], r["sim"]))
    return out


def best(m, v, k):
    order = sorted((-m[v, u], u) for u in range(len(m)) if np.isfinite(m[v, u]))[:k]
    return [(u, round(-s, 6) + 0.0) for s, u in order]


@pytest.mark.parametrize("engine", ["bucket", "sql"])
def test_signatures_equal_numpy(small, exact, engine):
    got = {r["node_id"]: np.array(r["sig"]) for r in similarity.signatures(small[0], engine=engine).collect()}
    for i in range(60):
        assert np.allclose(got[i], exact[0][i], atol=1e-12)


def test_alpha_one_keeps_raw_features(small):
    g, x, _, _ = small
    for r in similarity.signatures(g, alpha=1.0).select("node_id", "sig").collect():
        n = np.linalg.norm(x[r["node_id"]])
        assert np.allclose(r["sig"], x[r["node_id"]] / n if n else 0)


def test_opposite_neighbour_keeps_its_sign(spark):
    g = AnchoredGraph(spark.createDataFrame([(0, [1.0, 0.0]), (1, [-1.0, 0.0]), (2, [0.0, 3.0])], "node_id long, x array<double>"), spark.createDataFrame([(0, 1)], "src long, dst long"))
    got = {r["node_id"]: r["x"] for r in similarity.refine_once(g.nodes, g.both_ways(), 0.5).collect()}
    assert got == {0: [1.0, 0.0], 1: [-1.0, 0.0], 2: [0.0, 1.5]}


@pytest.mark.parametrize("engine", ["block", "sql"])
def test_exact_scan_all(sigs, exact, engine):
    got = lists(scan.exact_scan_all(sigs, 5, engine))
    assert got == {v: best(exact[1], v, 5) for v in range(60)}


def test_exact_scan_of_one(sigs, exact):
    got = [(r["u"], r["sim"]) for r in scan.exact_scan(sigs, 3, 7).orderBy("rank").collect()]
    assert got == best(exact[1], 3, 7)
    assert scan.exact_scan(sigs, 3, 1000).count() == int(np.isfinite(exact[1][3]).sum())
    assert scan.exact_scan(sigs, 12345, 3).count() == 0
    above = {r["u"] for r in scan.twins_above(sigs, 3, 0.2).collect()}
    assert above == set(np.flatnonzero(exact[1][3] >= 0.2).tolist())


def test_one_class_has_no_twins(sigs):
    same = sigs.withColumn("verdict", F.lit(1))
    assert scan.exact_scan(same, 3, 5).count() == 0
    assert scan.exact_scan_all(same, 5).count() == 0
    assert pairs.twin_pairs(same, 5).count() == 0


def test_blocks_merge_to_the_same_lists(sigs, exact):
    from lookalike.operators.kernels import blocked_topk

    one = sigs.select(F.lit(0).alias("cell"), "node_id", "verdict", "sig")
    assert lists(scan.merge_topk(blocked_topk(one, one, 4, block=7), 4)) == {v: best(exact[1], v, 4) for v in range(60)}


def test_stored_by_verdict_prunes(spark, sigs):
    df = scan.load_by_verdict(spark, scan.store_by_verdict(sigs))
    plan_text = scan._scored(df, 3)._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(verdict" in plan_text
    a = [tuple(r) for r in scan.exact_scan(df, 3, 5).orderBy("rank").collect()]
    assert a == [tuple(r) for r in scan.exact_scan(sigs, 3, 5).orderBy("rank").collect()]


GOLD = {2: (0.083333, 0.25, 0.375, 0.5, 0.75), 3: (0.096184, 0.287541, 0.429025, 0.567306, 0.824520), 8: (0.137137, 0.402909, 0.585922, 0.745556, 0.956892), 27: (0.223709, 0.617003, 0.824392, 0.943018, 0.999465), 64: (0.325454, 0.803313, 0.955420, 0.995368, 1.0)}


def test_cap_overlap():
    assert caps.cap_fraction(math.pi / 3, 3) == pytest.approx(0.25, abs=1e-9)
    for d, want in GOLD.items():
        for phi, w in zip((10, 30, 45, 60, 90), want, strict=True):
            assert 1 - caps.overlap_ratio(math.radians(phi), math.pi / 3, d) == pytest.approx(w, abs=2e-6)
            assert caps.boundary_weight(np.array([math.cos(math.radians(phi))]), math.pi / 3, d)[0] == pytest.approx(w, abs=1e-5)
    flat = caps.boundary_weight(np.cos(np.radians([0, 10, 60, 120, 150])), math.pi / 3, 2)
    assert flat == pytest.approx([0, 1 / 12, 0.5, 1, 1], abs=1e-6)


def test_cap_overlap_by_sampling():
    rng = np.random.default_rng(3)
    p = rng.standard_normal((400_000, 5))
    p /= np.linalg.norm(p, axis=1, keepdims=True)
    theta, phi = math.pi / 3, math.radians(50)
    a, b = p[:, 0] > math.cos(theta), p @ np.array([math.cos(phi), math.sin(phi), 0, 0, 0]) > math.cos(theta)
    assert (a & b).sum() / a.sum() == pytest.approx(caps.overlap_ratio(phi, theta, 5), abs=0.01)


def test_weight_is_monotone():
    for d in (2, 8, 64):
        w = caps.boundary_weight(np.cos(np.linspace(0, math.pi, 500)), math.pi / 3, d)
        assert (np.diff(w) >= -1e-12).all() and w[0] == pytest.approx(0, abs=1e-9) and w[-1] == 1


def test_weighted_rounds_never_lower_the_objective():
    rng = np.random.default_rng(5)
    x = rng.standard_normal((300, 5))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    w = rng.random(300)
    mu, last = x[:6].copy(), -np.inf
    for _ in range(12):
        now = cluster.objective(x, w, mu)
        assert now >= last - 1e-9
        mu, last = cluster.update(x, w, cluster.nearest(x, mu)[0], mu), now


def test_empty_clusters_keep_their_centroids():
    x = np.repeat(np.eye(3), 4, axis=0)
    mu = cluster.spherical_kmeans(x, x[[0, 1, 4, 8, 9]], 3)
    assert np.allclose(mu[1], x[1])
    assert set(cluster.nearest(x, mu)[0]) == {0, 2, 3}


def test_singletons_do_not_break_the_next_layer(spark):
    x = np.eye(4)
    layers = cluster.fit_layers(np.arange(4), x, LayerSpec(p=2, m=4, rounds=2))
    assert len(layers.centroids) == 2 and np.isfinite(layers.centroids[1]).all()


def test_distributed_round_equals_local(sigs):
    ids, x = cluster.sample(sigs)
    mu = cluster.pick_seeds(ids, x, 0, 5)
    want = cluster.update(x, np.ones(len(x)), cluster.nearest(x, mu)[0], mu)
    assert np.allclose(cluster.distributed_round(sigs, mu), want)


def test_border_node_finds_its_twin_in_the_other_layer(spark):
    """On the circle: layer 1 parts the query from its twin, layer 2 has both near one centroid."""
    deg = lambda a: [math.cos(math.radians(a)), math.sin(math.radians(a))]
    angles = [2, 5, 10, 20, 30, 88, 92, 95, 100, 110, 170, 178, 182, 190, 200, 260, 268, 272, 280, 290, 44, 46]
    nodes = spark.createDataFrame([(i, i % 2, deg(a)) for i, a in enumerate(angles)], "node_id long, verdict int, sig array<double>")
    one = np.array([deg(a) for a in (0, 90, 180, 270)])
    two = np.array([deg(a) for a in (45, 135, 225, 315)])
    layers = Layers([one, two], [1, 2], LayerSpec(m=4))
    homes = index.choose_home(cluster.assign(nodes, layers), layers)
    ix = index.TwinIndex(layers, cut(homes, "nodes"))
    assert ix.nodes.filter("node_id = 20").head()["layer"] == 2
    assert search.index_search(ix, 20, 1).head()["u"] == 21
    first = index.TwinIndex(Layers([one], [1], LayerSpec(m=4)), cut(index.choose_home(cluster.assign(nodes, Layers([one], [1], LayerSpec(m=4))), Layers([one], [1], LayerSpec(m=4))), "nodes"))
    assert search.index_search(first, 20, 1).head()["u"] != 21


@pytest.fixture(scope="module")
def ix(sigs):
    return index.build(sigs, LayerSpec(p=3, m=4, rounds=3))


def test_index_lists_are_the_home_clusters(ix, exact):
    rows = {r["node_id"]: r for r in ix.nodes.collect()}
    assert 5 not in rows, "a zero signature is not indexed"
    at = {n: i for i, n in enumerate(ix.layers.numbers)}
    want = {}
    for v, r in rows.items():
        layer = at[r["layer"]]
        assert round(r["weights"][layer], 12) == min(round(w, 12) for w in r["weights"])
        mine = exact[1].copy()
        outside = [u for u in range(60) if u not in rows or rows[u]["clusters"][layer] != r["cluster"]]
        mine[v, outside] = -np.inf
        if best(mine, v, 5):
            want[v] = best(mine, v, 5)
    got = lists(search.index_search_all(ix, 5))
    assert got == want
    for v in (0, 3, 41):
        assert [(r["u"], r["sim"]) for r in search.index_search(ix, v, 5).orderBy("rank").collect()] == want.get(v, [])


def test_index_never_beats_the_scan(ix, exact):
    for v, found in lists(search.index_search_all(ix, 5)).items():
        for (_, a), (_, b) in zip(found, best(exact[1], v, 5), strict=False):
            assert a <= b + 1e-9


def test_one_cluster_is_exact(sigs, exact):
    whole = index.build(sigs, LayerSpec(p=1, m=1, rounds=1))
    assert lists(search.index_search_all(whole, 5)) == {v: [p for p in best(exact[1], v, 6) if p[0] != 5][:5] for v in range(60) if v != 5}


def test_shortage_policies(ix, exact):
    short = lists(search.index_search_all(ix, 12))
    full = lists(search.index_search_all(ix, 12, "exact"))
    wide = lists(search.index_search_all(ix, 12, "next_layer"))
    assert any(len(x) < 12 for x in short.values())
    for v, x in full.items():
        known = [p for p in best(exact[1], v, 13) if p[0] != 5][:12]
        assert x == (short[v] if len(short.get(v, [])) == 12 else known)
    assert all(len(wide[v]) >= len(x) for v, x in short.items())


def test_more_probes_find_more(ix, exact):
    truth = {v: {u for u, _ in best(exact[1], v, 5)} for v in range(60)}
    hits = [sum(len(truth[v] & {u for u, _ in x}) for v, x in lists(search.index_search_all(ix, 5, r=r)).items()) for r in (1, 2, 3)]
    assert hits[0] <= hits[1] <= hits[2]


def test_bounded_is_exact(ix, exact):
    for v in (0, 3, 17):
        want = [p for p in best(exact[1], v, 6) if p[0] != 5][:5]
        assert [(r["u"], r["sim"]) for r in search.bounded_exact(ix, v, 5).orderBy("rank").collect()] == want


def test_saved_index(spark, ix):
    again = index.load(spark, index.save(ix))
    assert lists(search.index_search_all(again, 4)) == lists(search.index_search_all(ix, 4))
    assert again.layers.spec == ix.layers.spec


def test_true_pairs_and_node_best(sigs, exact):
    m = exact[1]
    every = sorted((-m[a, b], a, b) for a in range(60) for b in range(a + 1, 60) if np.isfinite(m[a, b]))
    got = [(r["a"], r["b"], r["sim"]) for r in pairs.twin_pairs(sigs, 15, mode="exact_pairs").orderBy("rank").collect()]
    assert got == [(a, b, round(-s, 6) + 0.0) for s, a, b in every[:15]]
    node_best = [r["sim"] for r in pairs.twin_pairs(sigs, 15).collect()]
    assert np.mean(node_best) <= np.mean([g[2] for g in got]) + 1e-9


def test_a_hub_loses_pairs_to_per_node_best(spark):
    """One hub is everybody's best twin: pairs of the others are offered only by the exact form."""
    nodes = spark.createDataFrame([(0, 0, [1.0, 0.0]), (1, 1, [0.99, 0.141067]), (2, 1, [0.99, -0.141067]), (3, 0, [0.96, 0.28])], "node_id long, verdict int, sig array<double>")
    a = {(r["a"], r["b"]) for r in pairs.twin_pairs(nodes, 4).collect()}
    b = {(r["a"], r["b"]) for r in pairs.twin_pairs(nodes, 4, mode="exact_pairs").collect()}
    assert a < b and (2, 3) in b


@pytest.mark.parametrize("engine", ["block", "sql"])
def test_pairs_above(sigs, exact, engine):
    m = exact[1]
    want = {(a, b) for a in range(60) for b in range(a + 1, 60) if m[a, b] >= 0.3}
    assert {(r["a"], r["b"]) for r in pairs.pairs_above(sigs, 0.3, engine).collect()} == want


def test_near_edges_in_blocks(small):
    from lookalike.operators.kernels import blocked_pairs

    g, x, _, _ = small
    n = np.linalg.norm(x, axis=1, keepdims=True)
    u = x / np.where(n > 0, n, 1)
    want = {(a, b) for a in range(60) for b in range(a + 1, 60) if round(float(u[a] @ u[b]), 9) > 0.5}
    for engine in ("block", "sql"):
        assert {tuple(r) for r in graph.epsilon(g.nodes, 0.5, engine=engine).collect()} == want
    rows = g.nodes.select("node_id", F.lit(None).cast("int").alias("verdict"), V.unit(F.col("x")).alias("sig"))
    assert {(r["a"], r["b"]) for r in blocked_pairs(rows, 0.5, strict=True, block=7).collect()} == want


def test_sample_of_many_is_the_smallest_hashes(spark):
    import hashlib

    rows = spark.range(20000).select(F.col("id").alias("node_id"))
    got = {r[0] for r in cluster.smallest_hashes(rows, 500).collect()}
    assert got == set(sorted(range(20000), key=lambda i: hashlib.md5(str(i).encode()).hexdigest())[:500])


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, sf, sigs):
    """What must hold at any size: pruned columns, pushed filters, partial top-k, group limits before the exchange, no cartesian product."""
    from lookalike.sources.tables import table

    scan_plan = plan_of(table(spark, sf, "part").filter("p_size > 40").select("p_partkey"))
    assert "PushedFilters: [IsNotNull(p_size), GreaterThan(p_size,40)]" in scan_plan and "p_name" not in scan_plan
    assert "TakeOrderedAndProject" in plan_of(scan._scored(sigs, 3).orderBy(F.desc("sim"), "u").limit(5))
    everything = plan_of(scan.exact_scan_all(sigs, 5))
    assert "WindowGroupLimit" in everything and "Partial" in everything
    assert "CartesianProduct" not in everything
    joins = [line.strip(" +-:") for line in everything.splitlines() if "NestedLoopJoin" in line]
    assert all("BuildRight" in j for j in joins), "a join on a constant cell must broadcast the grid's one row, never the vectors"
    one_round = plan_of(similarity.refine_once(sigs.withColumnRenamed("sig", "x"), spark.createDataFrame([(0, 1), (1, 0)], "src long, dst long"), 0.5))
    assert "partial_" in one_round


def test_average_similarity(sigs, exact):
    twins = cut(scan.exact_scan_all(sigs, 10), "twins")
    want = [np.mean([np.sum([s for _, s in best(exact[1], v, k)]) / k for v in range(60)]) for k in range(1, 11)]
    curve = [r["avg_sim"] for r in metrics.similarity_curve(twins, sigs).orderBy("k").collect()]
    assert curve == pytest.approx(want)
    assert all(a >= b - 1e-12 for a, b in zip(curve, curve[1:], strict=False)), "more twins, lower average"
    assert metrics.average_similarity(twins, sigs, 10).head()[0] == pytest.approx(want[-1])
    top = pairs.twin_pairs(sigs, 10, mode="exact_pairs")
    assert metrics.average_pair_similarity(top).head()[0] >= want[-1]


def test_strict_and_found_averages(spark):
    twins = spark.createDataFrame([(1, 2, 1, 0.8)], "v long, u long, rank int, sim double")
    nodes = spark.createDataFrame([(1,), (2,)], "node_id long")
    assert metrics.average_similarity(twins, nodes, 2).head()[0] == pytest.approx(0.2)
    assert metrics.average_similarity(twins, nodes, 2, "found").head()[0] == pytest.approx(0.8)


def test_costs():
    exact_cost, index_cost = metrics.predicted_cost("exact", 10_000, 64, k=10), metrics.predicted_cost("index", 10_000, 64, k=10)
    assert index_cost["time"] < exact_cost["time"]
    assert metrics.predicted_cost("exact", 20_000, 64)["time"] == pytest.approx(2 * metrics.predicted_cost("exact", 10_000, 64)["time"])
    assert metrics.predicted_cost("build", 100, 8, m=2, p=3, overlap=2)["time"] == 6000
    assert plan(1_000_000, 64, 10).engine == "index"
    assert plan(1_000_000, 64, 10, exact_needed=True).engine == "bounded"
    assert plan(1_000_000, 64, 10, has_index=False).engine == "exact"
    assert "* index" in plan(1_000_000, 64, 10).explain()


def test_shared_key_by_blocks(spark):
    rows = spark.createDataFrame([(i, "a" if i % 4 else None, i % 2) for i in range(60)] + [(7, "a", 1)], "i long, s string, p int")
    ids = [i for i in range(60) if i % 4]
    want = sorted((a, b) for a in ids for b in ids if a < b and a % 2 == b % 2)
    assert sorted(map(tuple, graph.shared_key(rows, "i", ["s", "p"], block=5).collect())) == want == sorted(map(tuple, graph.shared_key(rows, "i", ["s", "p"]).collect()))


def test_buckets_grow_with_edges_and_dimensions(spark, monkeypatch):
    nodes = spark.range(10).select(F.col("id").alias("node_id"), F.array_repeat(F.lit(1.0), 4).alias("x"))
    both = spark.range(100).select((F.col("id") % 10).alias("src"), (F.col("id") % 7).alias("dst"))
    few = similarity.buckets_for(nodes, both)
    monkeypatch.setattr(similarity, "BUCKET_NUMBERS", 10)
    assert few == int(spark.conf.get("spark.sql.shuffle.partitions")) and similarity.buckets_for(nodes, both) == 40


def test_discrimination_scores(spark):
    twins = spark.createDataFrame([(1, u, i + 1, 0.9) for i, u in enumerate((2, 3, 4, 5))], "v long, u long, rank int, sim double")
    values = spark.createDataFrame([(1, "race", "a"), (2, "race", "b"), (3, "race", "b"), (4, "race", "a"), (5, "race", "c"), (1, "age", "x"), (2, "age", "x"), (3, "age", "x"), (4, "age", "x"), (5, "age", "x")], "node_id long, feature string, value string")
    got = {(r["node_id"], r["feature"]): r["ds"] for r in audit.discrimination_scores(twins, values, 4).collect()}
    assert got[1, "race"] == 0.75 and got[1, "age"] == 0.0 and got[2, "race"] == 0.0
    card = audit.card(values, 1, 2).collect()
    assert [tuple(r) for r in card] == [("race", "a", "b")]


def test_accuracy_in_pairs_units(spark):
    p = spark.createDataFrame([(1, 2, 1, 0.9), (1, 3, 2, 0.8)], "a long, b long, rank int, sim double")
    pred = spark.createDataFrame([(1, 0), (2, 1), (3, 1)], "node_id long, verdict int")
    lab = spark.createDataFrame([(1, 1), (2, 1), (3, 1)], "node_id long, label int")
    node = {r["k"]: (r["n_nodes"], r["accuracy"]) for r in errors.accuracy_in_pairs(p, pred, lab, [1, 2]).collect()}
    slot = {r["k"]: (r["n_nodes"], r["accuracy"]) for r in errors.accuracy_in_pairs(p, pred, lab, [1, 2], "slot").collect()}
    assert node == {1: (2, 0.5), 2: (3, pytest.approx(2 / 3))} and slot == {1: (2, 0.5), 2: (4, 0.5)}


def test_edge_mask_flip(spark):
    """A node whose verdict is its neighbours' majority flips when the right edge goes."""
    nodes = spark.createDataFrame([(0, [0.0]), (1, [1.0]), (2, [1.0]), (3, [-1.0])], "node_id long, x array<double>")
    edges = spark.createDataFrame([(0, 1), (0, 2), (0, 3)], "src long, dst long")

    def predict(g):
        s = g.both_ways().join(g.nodes.withColumnRenamed("node_id", "dst"), "dst").groupBy(F.col("src").alias("node_id")).agg(F.sum(F.col("x")[0]).alias("s"))
        return g.nodes.join(s, "node_id", "left").select("node_id", (F.coalesce("s", F.lit(0.0)) > 0.5).cast("int").alias("verdict"))

    asked = nodes.filter("node_id in (0, 3)").select("node_id")
    got = errors.edge_mask_flip(AnchoredGraph(nodes, edges), predict, asked, 2).collect()
    assert sorted([tuple(e) for e in r["removed"]] for r in got) == [[(0, 1)], [(0, 2)]] and {(r["node_id"], r["size"], r["before"], r["after"]) for r in got} == {(0, 1, 1, 0)}
    strong = edges.filter("dst <> 3")  # two like neighbours: no single edge flips node 0, both do
    got = errors.edge_mask_flip(AnchoredGraph(nodes, strong), predict, asked, 2).collect()
    assert [[tuple(e) for e in r["removed"]] for r in got] == [[(0, 1), (0, 2)]]


def test_edge_mask_flip_tries_every_edge(spark, small):
    """Against numpy: each node's own edges, one by one and in pairs, under a one-layer convolution."""
    from itertools import combinations

    from lookalike.models import layers, predict

    g, x, adj, _ = small
    w = layers.closed_form(x.shape[1], 3)

    def verdict(a, v):
        c = 1 / np.sqrt(a.sum(1) + 1)
        z = (c[v] * ((a[v] + np.eye(len(a))[v]) * c)) @ x @ w
        return int(np.argmax(z))

    want = set()
    for v in (0, 7, 20):
        mine = [tuple(sorted((v, int(u)))) for u in np.flatnonzero(adj[v])]
        for size in (1, 2):
            found = set()
            for drop in combinations(sorted(mine), size):
                a = adj.astype(float).copy()
                for p, q in drop:
                    a[p, q] = a[q, p] = 0
                if verdict(a, v) != verdict(adj.astype(float), v):
                    found.add((v, size, drop, verdict(adj.astype(float), v), verdict(a, v)))
            if found:
                want |= found
                break

    def model(graph_):
        return predict.head(layers.gcn(graph_.nodes.select("node_id", "x"), graph_.both_ways(), w, activation=False), np.eye(3), np.zeros(3)).select("node_id", "verdict")

    asked = g.nodes.filter("node_id in (0, 7, 20)").select("node_id")
    got = errors.edge_mask_flip(AnchoredGraph(g.nodes.select("node_id", "x"), g.edges), model, asked, 2, 2).collect()
    assert {(r["node_id"], r["size"], tuple(tuple(e) for e in r["removed"]), r["before"], r["after"]) for r in got} == want


def test_saturated_weights_leave_layers_to_the_cosine(spark):
    """At 500 dimensions nearly every weight is 1; homes must still spread over the layers and follow the cosine."""
    rng = np.random.default_rng(4)
    x = rng.standard_normal((300, 500))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    nodes = spark.createDataFrame([(i, i % 2, v.tolist()) for i, v in enumerate(x)], "node_id long, verdict int, sig array<double>")
    made = index.build(nodes, LayerSpec(p=10, m=5, rounds=2)).nodes.collect()
    assert sum(round(w, 12) == 1.0 for r in made for w in r["weights"]) > 0.9 * 3000
    assert len({r["layer"] for r in made}) == 10 and max(np.bincount([r["layer"] for r in made])) < 90
    for r in made:
        tied = [c for c, w in zip(r["cosines"], r["weights"], strict=True) if round(w, 12) == min(round(v, 12) for v in r["weights"])]
        assert r["cosines"][r["layer"] - 1] == pytest.approx(max(tied), abs=1e-11)


def test_a_search_reads_one_cell(spark, ix):
    """The plan prunes folders, and the files read are those of the home cell alone."""
    again = index.load(spark, index.save(ix))
    home = again.shelf().find(3)
    found = search.index_search(again, 3, 5)
    plan = found._jdf.queryExecution().toString()
    assert "PartitionFilters" in plan and f"(layer#" in plan and f" = {home['layer']})" in plan.split("PartitionFilters")[1]
    cell_files = again.shelf().members(home["layer"], [home["cluster"]]).select(F.input_file_name().alias("f")).distinct().collect()
    assert cell_files and all(f"layer={home['layer']}/cluster={home['cluster']}/" in r["f"] for r in cell_files)
    assert len(cell_files) < len(again.shelf().postings.inputFiles()) / 3
    look = again.shelf().lookup.filter(F.col("bucket") == index.bucket_of(F.lit(3).cast("long"), again.shelf().buckets))
    assert "bucket" in look._jdf.queryExecution().toString().split("PartitionFilters")[1][:200]


def test_many_cells_are_joined(spark, ix, monkeypatch):
    whole = lists(search.index_search_all(ix, 5))
    monkeypatch.setattr(index, "SMALL_CELLS", 2)
    from lookalike.operators import kernels

    monkeypatch.setattr(kernels, "GRID_ROWS", 1)
    assert lists(search.index_search_all(ix, 5)) == whole


def test_numbered(spark):
    got = relational.numbered(spark.createDataFrame([(v,) for v in "qwertyuiopasdfghjkl"], "t string").repartition(5), "t", "at").collect()
    assert sorted((r["at"], r["t"]) for r in got) == list(enumerate(sorted("qwertyuiopasdfghjkl"), 1))
    assert relational.numbered(spark.createDataFrame([], "t string"), "t", "at").count() == 0


def test_colours_only_split(spark, small):
    g, _, adj, verdict = small
    nodes = g.nodes.select("node_id", F.col("verdict").alias("color"))
    by = {}
    for r in wl.refine_colors(nodes, g.edges, 3).collect():
        by.setdefault(r["iter"], {})[r["node_id"]] = r["color"]
    for i in range(3):
        for a in range(60):
            for b in range(a):
                if by[i + 1][a] == by[i + 1][b]:
                    assert by[i][a] == by[i][b]
    rank = {(r["iter"], r["node_id"]): r["color"] for r in wl.refine_colors(nodes, g.edges, 3, "dense_rank").collect()}
    for i in (1, 2, 3):
        pairs_of = {(by[i][n], rank[i, n]) for n in range(60)}
        assert len(pairs_of) == len({p[0] for p in pairs_of}) == len({p[1] for p in pairs_of})


def test_canonical_edges(spark):
    e = spark.createDataFrame([(1, 2), (2, 1), (1, 2), (3, 3), (4, 2)], "src long, dst long")
    assert sorted(tuple(r) for r in graph.canonical(e).collect()) == [(1, 2), (2, 4)]
    bad = spark.createDataFrame([([1.0, float("nan")],)], "x array<double>")
    with pytest.raises(Exception, match="is not 2 numbers"):
        graph.assert_dim(bad, 2).collect()


def test_large_groups_can_be_left_out(spark):
    rows = spark.createDataFrame([("a", i) for i in range(10)] + [("b", 1), ("b", 2)], "g string, i long")
    assert graph.co_occurrence(rows, "g", "i").count() == 45
    assert [tuple(r) for r in graph.co_occurrence(rows, "g", "i", max_group=5).collect()] == [(1, 2, 1)]


def test_salted_join(spark):
    big = spark.createDataFrame([(1, i) for i in range(100)] + [(2, 1)], "k long, v long")
    small = spark.createDataFrame([(1, "x"), (3, "y")], "k long, w string")
    assert relational.salted_join(big, small, "k", 4, "v").count() == 100


def test_vector_columns(spark):
    df = spark.createDataFrame([([3.0, 4.0], [4.0, 3.0], [0.0, 0.0])], "a array<double>, b array<double>, z array<double>")
    r = df.select(V.dot("a", "b").alias("d"), V.norm("a").alias("n"), V.cosine("a", "b").alias("c"), V.cosine("a", "z").alias("zc"), V.l2("a", "b").alias("l"), V.unit("z").alias("uz"), V.unit("a").alias("ua")).head()
    assert (r["d"], r["n"], r["c"], r["zc"]) == (24.0, 5.0, 0.96, 0.0)
    assert r["l"] == pytest.approx(math.sqrt(2)) and r["uz"] == [0.0, 0.0] and r["ua"] == pytest.approx([0.6, 0.8])
