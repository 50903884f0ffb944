"""Layers are fitted on all signatures, however many there are."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from lookalike.operators import cluster
from lookalike.operators.cluster import LayerSpec
from lookalike.plans import method_queries as Q
from lookalike.session import cut

MANY = 101_000  # more than were ever fitted on the driver


@pytest.fixture(scope="module")
def many(spark):
    """Vectors whose last thousand, by the hash of their ids, lie where no other does: a sample by hash misses them."""
    late = F.row_number().over(Window.orderBy(F.md5(F.col("node_id").cast("string")))) > MANY - 1000
    a = F.col("node_id") * 0.7
    sig = F.when(F.col("late"), F.array(F.lit(0.0), F.lit(0.0), F.lit(1.0))).otherwise(F.array(F.cos(a), F.sin(a), F.lit(0.0)))
    rows = spark.range(MANY).withColumnRenamed("id", "node_id").withColumn("late", late)
    return cut(rows.select("node_id", (F.col("node_id") % 3).cast("int").alias("verdict"), sig.alias("sig")), "many")


@pytest.mark.parametrize("change", [{}, {"carry": "min"}, {"carry": "product", "include_seed": True}, {"weight_rule": "unit"}, {"weight_rule": "distance"}, {"p": 0, "include_seed": True}])
def test_stored_fit_equals_the_drivers(spark, change):
    rng = np.random.default_rng(3)
    x = rng.standard_normal((300, 4))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    x[[4, 50]] = 0.0
    rows = spark.createDataFrame([(int(i), 0, v.tolist()) for i, v in enumerate(x)] + [(None, 0, [9.0] * 4)], "node_id long, verdict int, sig array<double>")
    spec = replace(LayerSpec(p=3, m=5, rounds=3), **change)
    got, want = cluster.build_layers(rows, spec, fit_rows=100), cluster.fit_layers(np.arange(300), x, spec)
    assert got.numbers == want.numbers and len(got.numbers) == spec.p + spec.include_seed
    assert np.allclose(got.centroids, want.centroids, rtol=0, atol=1e-12)


@pytest.fixture(scope="module")
def whole(many):
    """The signatures in id order, and the layers that numpy fits on all of them."""
    x = np.array([r["sig"] for r in many.orderBy("node_id").collect()])
    return x, cluster.fit_layers(np.arange(MANY), x, Q.SPEC)


@pytest.fixture
def asked(spark, many, monkeypatch):
    monkeypatch.setattr(Q, "emb_sigs", lambda spark, sf: many)
    return spark


def homes(x, layers):
    """Per layer the clusters, and per node the place of its home layer."""
    found = [cluster.nearest(x, mu) for mu in layers.centroids]
    rank = [list(zip(np.round(cluster.weigh(cos, x.shape[1], layers.spec), 12), -np.round(cos, 12), strict=True)) for _, cos in found]
    return np.stack([at for at, _ in found]), np.array([min(range(len(found)), key=lambda i: (rank[i][v], i)) for v in range(len(x))])


def test_candidates_are_of_layers_fitted_on_all(asked, whole):
    x, layers = whole
    assert np.allclose(Q.emb_index(asked, "").layers.centroids, layers.centroids, rtol=0, atol=1e-9)
    at, home = homes(x, layers)
    verdict = np.arange(MANY) % 3
    held = np.array([[[np.count_nonzero((c == k) & (verdict != w)) for w in range(3)] for k in range(10)] for c in at])
    got = Q.candidates_per_query(asked, "").toArrow().sort_by("v")
    assert got.num_rows == MANY
    assert (got.column("candidates").to_numpy() == held[home, at[home, np.arange(MANY)], verdict]).mean() > 0.999  # the last digit of a sum may part a tie


def test_homes_are_of_layers_fitted_on_all(asked, whole):
    at, home = homes(*whole)
    got = Q.choose_home(asked, "").toArrow().sort_by("node_id")
    assert got.num_rows == MANY
    right = (got.column("layer").to_numpy() == home + 1) & (got.column("cluster").to_numpy() == at[home, np.arange(MANY)])
    assert right.mean() > 0.999


def test_plain_weights_are_of_a_layer_fitted_on_all(asked, whole):
    x = whole[0]
    mu = cluster.fit_layers(np.arange(MANY), x, replace(Q.SPEC, p=0, include_seed=True)).centroids[0]
    got = Q.boundary_weight(asked, "").toArrow().sort_by("node_id")
    want = cluster.weigh(cluster.nearest(x, mu)[1], 3, Q.SPEC)
    assert got.num_rows == MANY and np.allclose(got.column("weight").to_numpy(), want, rtol=0, atol=1e-6)
