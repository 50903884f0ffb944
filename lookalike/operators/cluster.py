"""Spherical k-means, plain and weighted, and the layers of supplementary partitions."""

from __future__ import annotations

import hashlib
import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import vectors as V
from ..functions.caps import boundary_weight
from ..session import cut, drop, noted, ship
from .kernels import matrix

#: Signatures up to this many are fitted on the driver, more by rounds over the stored rows. All are fitted in both cases.
FIT_ROWS = 50_000


def seed_key(node_id: int, layer: int) -> str:
    return hashlib.md5(f"{node_id}:{layer}".encode()).hexdigest()


def pick_seeds(ids: np.ndarray, x: np.ndarray, layer: int, m: int) -> np.ndarray:
    """The vectors of the ``m`` nodes with the smallest md5 of id and layer, in that order."""
    order = sorted(range(len(ids)), key=lambda i: seed_key(int(ids[i]), layer))[:m]
    return x[order].copy()


def nearest(x: np.ndarray, mu: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Cluster of the best cosine (ties: smaller cluster) and that cosine."""
    length = np.linalg.norm(mu, axis=1, keepdims=True)
    s = x @ np.divide(mu, length, out=np.zeros_like(mu), where=length > 0).T
    at = np.argmax(np.round(s, 12), axis=1)
    return at, s[np.arange(len(x)), at]


def update(x: np.ndarray, w: np.ndarray, at: np.ndarray, mu: np.ndarray) -> np.ndarray:
    """Weighted centroids; an empty cluster keeps its old one."""
    m = len(mu)
    total, size = np.zeros_like(mu), np.bincount(at, minlength=m)
    np.add.at(total, at, x * w[:, None])
    return np.where(size[:, None] > 0, total / np.maximum(size, 1)[:, None], mu)


def spherical_kmeans(x: np.ndarray, seeds: np.ndarray, rounds: int, w: np.ndarray | None = None) -> np.ndarray:
    """Centroids after ``rounds`` updates. Zero rows take no part: they have no direction."""
    w = np.ones(len(x)) if w is None else w
    live = np.linalg.norm(x, axis=1) > 0
    mu, x, w = seeds.copy(), x[live], w[live]
    for _ in range(rounds):
        mu = update(x, w, nearest(x, mu)[0], mu)
    return mu


def objective(x: np.ndarray, w: np.ndarray, mu: np.ndarray) -> float:
    """The weighted sum of cosines to the own centroid, which Lloyd's rounds raise."""
    return float((w * nearest(x, mu)[1]).sum())


@dataclass(frozen=True)
class LayerSpec:
    """Parameters of an index; ambiguities of the method are switches.

    ``carry``: weights for the next layer come from the ``last`` layer, the ``min`` so far, or the
    ``product``. ``weight_rule``: ``cap`` overlap, ``distance`` (1 - cos) or ``unit``.
    ``include_seed``: whether the unweighted layer 0 can be a home. Empty clusters keep their
    centroid; weights are floored at ``w_min``, as a node on its centroid has weight 0.
    """

    p: int = 50
    m: int = 10
    theta: float = math.pi / 3
    rounds: int = 5
    carry: str = "last"
    weight_rule: str = "cap"
    include_seed: bool = False
    w_min: float = 1e-9


def weigh(cos: np.ndarray, dim: int, spec: LayerSpec, clustering: bool = False) -> np.ndarray:
    """Boundary weights. ``unit`` makes them 1 for clustering alone: homes are chosen by the overlap all the same."""
    if clustering and spec.weight_rule == "unit":
        return np.ones(len(cos))
    if spec.weight_rule == "distance":
        return 1.0 - cos
    return boundary_weight(cos, spec.theta, dim)


@dataclass
class Layers:
    """Fitted centroids, one m x d array per layer; ``numbers`` names the layers."""

    centroids: list[np.ndarray]
    numbers: list[int]
    spec: LayerSpec = field(default_factory=LayerSpec)


def smallest_hashes(rows: DataFrame, most: int) -> DataFrame:
    """The ``most`` rows with the smallest md5 of ``node_id``.

    Of a large table only the hash range that surely holds them is sorted, so what the tasks send
    to be merged follows ``most`` and not the number of tasks.
    """
    key = F.md5(F.col("node_id").cast("string"))
    n = rows.count()
    share = (most + 10 * math.sqrt(most) + 100) / max(n, 1)
    if share < 1:
        rows = rows.filter(F.substring(key, 1, 12) <= format(int(share * (1 << 48)), "012x"))
    return rows.orderBy(key).limit(most)


def sample(sigs: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """All ids and signatures on the driver, in id order: for tables known to be small."""
    t = sigs.select("node_id", "sig").filter(F.col("node_id").isNotNull()).toArrow()
    ids = t.column(0).to_numpy()
    order = np.argsort(ids, kind="stable")
    return ids[order], (matrix(t.column(1))[order] if len(ids) else np.zeros((0, 0)))


def fit_layers(ids: np.ndarray, x: np.ndarray, spec: LayerSpec) -> Layers:
    """Layer 0 with unit weights, then ``p`` layers whose weights say how badly earlier ones placed a node.

    Without weights every layer must start from seeds of its own, else all would coincide.
    """
    if not len(ids):
        return Layers([], [], spec)
    dim = x.shape[1]
    mus, numbers, carried = [], [], None
    mu = spherical_kmeans(x, pick_seeds(ids, x, 0, spec.m), spec.rounds)
    if spec.include_seed:
        mus.append(mu)
        numbers.append(0)
    w = weigh(nearest(x, mu)[1], dim, spec, clustering=True)
    for layer in range(1, spec.p + 1):
        carried = w if carried is None or spec.carry == "last" else np.minimum(carried, w) if spec.carry == "min" else carried * w
        mu = spherical_kmeans(x, pick_seeds(ids, x, layer, spec.m), spec.rounds, np.maximum(carried, spec.w_min))
        mus.append(mu)
        numbers.append(layer)
        w = weigh(nearest(x, mu)[1], dim, spec, clustering=True)
    return Layers(mus, numbers, spec)


def seeds_of(rows: DataFrame, layer: int, m: int) -> np.ndarray:
    """:func:`pick_seeds` of a table: a partial top ``m`` per task."""
    first = rows.orderBy(F.md5(F.concat_ws(":", F.col("node_id"), F.lit(layer))), "node_id").limit(m).select("sig").collect()
    return np.array([r["sig"] for r in first])


def carried_weights(x: np.ndarray, before: list[np.ndarray], spec: LayerSpec) -> np.ndarray:
    """Weights that rows carry into a layer from the centroids of the layers ``before`` it."""
    w = weigh(nearest(x, before[0])[1], x.shape[1], spec, clustering=True)
    for mu in before[1:]:
        new = weigh(nearest(x, mu)[1], x.shape[1], spec, clustering=True)
        w = np.minimum(w, new) if spec.carry == "min" else w * new
    return np.maximum(w, spec.w_min)


def fit_stored(rows: DataFrame, spec: LayerSpec) -> Layers:
    """What :func:`fit_layers` gives, by rounds over all ``rows`` (node_id, sig), which never reach the driver.

    A task makes the carried weights anew from the earlier centroids, so nothing is stored per layer:
    the last layer's are enough for ``last``, all earlier ones for ``min`` and ``product``.
    """
    length = V.norm("sig")
    live = rows.filter((length > 0) & ~F.isnan(length))
    mus, numbers, before = [], [], []
    for layer in range(spec.p + 1):
        mu = seeds_of(rows, layer, spec.m)
        weights = (lambda x, before=tuple(before): carried_weights(x, before, spec)) if before else None
        for _ in range(spec.rounds):
            mu = distributed_round(live, mu, weights=weights)
        if layer or spec.include_seed:
            mus.append(mu)
            numbers.append(layer)
        before = [mu] if spec.carry == "last" else [*before, mu]
    return Layers(mus, numbers, spec)


def build_layers(sigs: DataFrame, spec: LayerSpec = LayerSpec(), fit_rows: int = FIT_ROWS) -> Layers:
    """Layers fitted on all signatures, on the driver up to ``fit_rows`` of them and else where they lie."""
    rows = sigs.select("node_id", "sig").filter(F.col("node_id").isNotNull())
    if rows.count() <= fit_rows:
        return fit_layers(*sample(rows), spec)
    with noted() as stored:
        layers = fit_stored(cut(rows, "fitted"), spec)
    drop(sigs.sparkSession, stored)
    return layers


WIDE = [("clusters", T.ArrayType(T.IntegerType())), ("cosines", T.ArrayType(T.DoubleType())), ("weights", T.ArrayType(T.DoubleType()))]


def assign(sigs: DataFrame, layers: Layers) -> DataFrame:
    """``node_id, verdict, sig`` with arrays ``clusters, cosines, weights``, one entry per layer.

    One pass over the signatures serves all layers, with no shuffle; p * m * d numbers are shipped.
    """
    ship(sigs.sparkSession)
    mus, spec = layers.centroids, layers.spec
    cols = sigs.select(F.col("node_id").cast("long").alias("node_id"), "verdict", "sig")
    schema = T.StructType([*cols.schema.fields, *[T.StructField(n, t) for n, t in WIDE]])

    def wide(y: np.ndarray) -> pa.ListArray:
        return pa.ListArray.from_arrays(np.arange(0, y.size + 1, y.shape[1], dtype=np.int32), pa.array(y.ravel()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x = matrix(pa.chunked_array([b.column(2)]))
            found = [nearest(x, mu) for mu in mus]
            at = np.stack([f[0] for f in found], axis=1).astype(np.int32)
            cos = np.stack([f[1] for f in found], axis=1)
            w = np.stack([weigh(f[1], x.shape[1], spec) for f in found], axis=1)
            yield pa.RecordBatch.from_arrays([*b.columns, wide(at), wide(cos), wide(w)], names=schema.names)

    return cols.mapInArrow(run, schema)


def long_assignment(assigned: DataFrame, layers: Layers) -> DataFrame:
    """``layer, cluster, node_id, cos, weight``: the wide form, a row per layer."""
    numbers = F.array(*[F.lit(n) for n in layers.numbers])
    return assigned.select("node_id", F.explode(F.arrays_zip(numbers.alias("layer"), "clusters", "cosines", "weights")).alias("a")).select(
        F.col("a.layer").alias("layer"), F.col("a.clusters").alias("cluster"), "node_id", F.col("a.cosines").alias("cos"), F.col("a.weights").alias("weight")
    )


def distributed_round(sigs: DataFrame, mu: np.ndarray, weight_col: str | None = None, weights: Callable[[np.ndarray], np.ndarray] | None = None) -> np.ndarray:
    """One exact Lloyd round over all rows: partial sums per task, an m x d aggregate comes back.

    Weights are a column's, or what ``weights`` makes of a batch's signatures. The driver holds m * d numbers.
    """
    ship(sigs.sparkSession)
    w = F.lit(1.0) if weight_col is None else F.col(weight_col)
    schema = "cluster int, n long, total array<double>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, size = np.zeros_like(mu), np.zeros(len(mu), np.int64)
        for b in batches:
            if b.num_rows:
                x = matrix(pa.chunked_array([b.column(0)]))
                at, _ = nearest(x, mu)
                own = b.column(1).to_numpy(zero_copy_only=False) if weights is None else weights(x)
                np.add.at(total, at, x * own[:, None])
                size += np.bincount(at, minlength=len(mu))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(mu), dtype=np.int32)), pa.array(size), pa.array(total.tolist(), pa.list_(pa.float64()))], names=["cluster", "n", "total"])

    parts = sigs.select("sig", w.cast("double").alias("w")).mapInArrow(run, schema)
    summed = parts.select("cluster", "n", F.posexplode("total").alias("i", "v")).groupBy("cluster", "i").agg(F.sum("v").alias("v"), F.sum("n").alias("n")).collect()
    out, size = np.zeros_like(mu), np.zeros(len(mu))
    for r in summed:
        out[r["cluster"], r["i"]], size[r["cluster"]] = r["v"], r["n"]
    return np.where(size[:, None] > 0, out / np.maximum(size, 1)[:, None], mu)
