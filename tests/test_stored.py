"""Scans and neighbour sums whose tasks read blocks from the shared folder, against the dealt grids and plain sorting."""

import random

import numpy as np
from test_implicit import by_id, points, same

from lookalike.operators import implicit, kernels, scan, similarity
from lookalike.session import drop, noted, store


def signed(spark, n=90):
    rng = random.Random(5)
    vectors = [[rng.choice([-1.0, 0.0, 0.5, 1.0]) for _ in range(3)] for _ in range(n)]  # many ties
    rows = [(i if i % 10 else 10, rng.choice([0, 1, 2, None]), v) for i, v in enumerate(vectors)]  # id 10 has many rows
    return spark.createDataFrame(rows, "node_id long, verdict int, sig array<double>"), rows


def test_stored_scan_is_whole_and_shuffles_no_vector(spark, monkeypatch):
    sigs, rows = signed(spark)
    for k in (1, 4, 200):
        got = {}
        for r in scan.exact_scan_all(sigs, k).orderBy("v", "rank").collect():
            got.setdefault(r["v"], []).append((r["u"], r["sim"]))
        for v, own, x in rows:
            if v != 10:
                far = sorted((-round(float(np.dot(x, y)), 9) + 0.0, u) for u, other, y in rows if None not in (own, other) and own != other)
                assert got.get(v, []) == [(u, round(-s, 6) + 0.0) for s, u in far[:k]]
    plan = scan.exact_scan_all(sigs, 4)._jdf.queryExecution().optimizedPlan().toString()
    assert "Repartition" not in plan  # vectors were dealt out here
    for k in (3, 4):
        want = sorted(map(tuple, scan.exact_scan_all(sigs, k).collect()))
        with monkeypatch.context() as m:
            m.setattr(scan, "tasks_can_read", lambda path: False)
            assert sorted(map(tuple, scan.exact_scan_all(sigs, k).collect())) == want
            assert "Repartition" in scan.exact_scan_all(sigs, k)._jdf.queryExecution().optimizedPlan().toString()


def test_small_blocks_give_the_same_lists(spark):
    sigs, _ = signed(spark)
    path, rows = store(sigs.selectExpr("node_id", "cast(verdict as long) as verdict", "sig").filter("verdict is not null"), "rows")
    want = sorted(map(tuple, scan.exact_scan_all(sigs, 5).collect()))
    assert sorted(map(tuple, scan.merge_topk(kernels.stored_topk(rows, path, 5, block=7), 5).collect())) == want


def test_near_sums_read_or_dealt(spark, monkeypatch):
    nodes = points(spark)
    base = nodes.selectExpr("node_id AS i", "transform(x, v -> v / greatest(1e-300, sqrt(aggregate(x, 0D, (s, w) -> s + w * w)))) AS u")
    read = implicit.near_mean(base, nodes, 0.3)
    assert "Repartition" not in read._jdf.queryExecution().optimizedPlan().toString()
    monkeypatch.setattr(implicit, "tasks_can_read", lambda path: False)
    same(by_id(read, "m"), by_id(implicit.near_mean(base, nodes, 0.3), "m"))


def test_rounds_leave_one_table(spark):
    with noted() as paths:
        sigs = similarity.signatures(implicit.near_graph(points(spark).select("node_id", "x"), 0.3), hops=3)
    kept = [p for p in paths if kernels.tasks_can_read(p)]
    assert sigs.count() == 61 and len(paths) > 3 and sum("/round-" in p or "/rows-" in p for p in kept) == 1
    drop(spark, kept)
    assert not any(map(kernels.tasks_can_read, kept))


def test_small_blocks_of_cells_shuffle_a_vector_once(spark, monkeypatch):
    rng = random.Random(8)
    rows = [(rng.choice([0, 1, 5, 1 << 32]), i, rng.choice([0, 1, 2, None]), [rng.choice([-1.0, 0.0, 0.5, 1.0]) for _ in range(3)]) for i in range(300)]
    members = spark.createDataFrame(rows, "cell long, node_id long, verdict int, sig array<double>")
    queries = members.filter("node_id % 2 = 0 or cell = 5").union(members.limit(1).selectExpr("77L", "900L", "1", "sig"))
    found = kernels.blocked_topk(queries, members, 4, block=7)
    assert "explode" not in found._jdf.queryExecution().optimizedPlan().toString()  # a vector per block was
    want = {}
    for cell, v, own, x in rows:
        far = sorted((-round(float(np.dot(x, y)), 9) + 0.0, u) for there, u, other, y in rows if there == cell and None not in (own, other) and own != other)
        if far and (v % 2 == 0 or cell == 5):
            want[v] = [(u, round(-s, 6) + 0.0) for s, u in far[:4]]
    for readable in (True, False):
        with monkeypatch.context() as m:
            if not readable:
                m.setattr(kernels, "tasks_can_read", lambda path: False)
            got = {}
            for r in scan.merge_topk(kernels.blocked_topk(queries, members, 4, block=7), 4).orderBy("v", "rank").collect():
                got.setdefault(r["v"], []).append((r["u"], r["sim"]))
            assert got == want
