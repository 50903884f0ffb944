"""Fitting small graph classifiers: weights from a bounded training sample, inference over all nodes in Spark."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.cluster import smallest_hashes
from ..operators.graph import AnchoredGraph
from ..operators.kernels import matrix
from ..session import cut
from . import layers, predict

#: Nodes that are fitted on at most, with the edges among them; more are sampled by the hash of their id.
MAX_TRAIN_NODES = 20_000
#: Directed edges among them that are fitted on at most; of more, those with the smallest hashes, both directions alike.
MAX_TRAIN_EDGES = 4_000_000


@dataclass
class Gcn:
    """A two-layer model: ``relu(A x W1)``, then ``A h W2 + b``."""

    w1: np.ndarray
    w2: np.ndarray
    b: np.ndarray
    classes: list[int]

    def predict(self, graph: AnchoredGraph) -> DataFrame:
        """``node_id, verdict, score`` of every node."""
        if hasattr(graph, "mean"):
            h = layers.gcn_of(graph, graph.nodes, self.w1)
            z = layers.gcn_of(graph, h, self.w2, activation=False)
        else:
            both = cut(graph.both_ways(), "edges")
            h = layers.gcn(graph.nodes, both, self.w1)
            z = layers.gcn(h, both, self.w2, activation=False)
        out = predict.head(z, np.eye(self.w2.shape[1]), self.b)
        names = F.array(*[F.lit(c) for c in self.classes])
        return out.withColumn("verdict", F.element_at(names, F.col("verdict") + 1))


@dataclass
class Sample:
    ids: np.ndarray
    x: np.ndarray
    y: np.ndarray  # -1 where there is no label
    train: np.ndarray
    valid: np.ndarray
    src: np.ndarray
    dst: np.ndarray


def sample(graph: AnchoredGraph, max_nodes: int = MAX_TRAIN_NODES, max_edges: int = MAX_TRAIN_EDGES, include: DataFrame | None = None) -> Sample:
    """At most ``max_nodes`` nodes, smallest id hash first, and at most about ``max_edges`` of the edges among them.

    ``include`` (node_id) names nodes that are in the sample in any case, such as the few thousand of
    pairs to fine-tune on. Beyond these bounds :class:`LinearPropagation` fits on all nodes and edges.
    """
    cols = ["node_id", "x", F.coalesce(F.col("label").cast("int"), F.lit(-1)).alias("y"), "split"]
    picked = smallest_hashes(graph.nodes, max_nodes).select(*cols)
    if include is not None:
        picked = picked.union(graph.nodes.join(include.select("node_id").distinct(), "node_id", "left_semi").select(*cols)).dropDuplicates(["node_id"])
    t = picked.toArrow()
    ids = t.column(0).to_numpy()
    order = np.argsort(ids)
    split = np.array(t.column(3).to_pylist(), object)[order]
    e = graph.among(graph.nodes.sparkSession.createDataFrame([(int(i),) for i in ids], "node_id long"))
    n = 2 * e.count()
    if n > max_edges:
        e = e.filter(F.pmod(F.xxhash64("src", "dst"), F.lit(1 << 30)) < int(max_edges / n * (1 << 30)))
    e = e.toArrow()
    ids = ids[order]
    a, b = (np.searchsorted(ids, e.column(c).to_numpy()) for c in ("src", "dst"))
    return Sample(ids, matrix(t.column(1))[order], t.column(2).to_numpy()[order], split == "train", split == "valid", np.r_[a, b], np.r_[b, a])


#: Numbers that a sum over a sample's edges gathers at a time (32 MB).
GATHER = 4_000_000


def propagate(x: np.ndarray, s: Sample, norm: np.ndarray) -> np.ndarray:
    """The symmetric-normalised neighbour sum with self loops, edge by edge."""
    y = x * norm[:, None]
    out, step = y.copy(), max(1, GATHER // max(1, x.shape[1]))
    for at in range(0, len(s.src), step):
        np.add.at(out, s.src[at : at + step], y[s.dst[at : at + step]])
    return out * norm[:, None]


class Spread:
    """:func:`propagate` on one sample, prepared once.

    Nodes that have the same neighbours, counting themselves, get the same sum and are summed up first, so a clique costs
    its nodes and not its pairs. That the classes stand for every edge once is checked by counting; else each node is its own.
    """

    def __init__(self, s: Sample):
        n = len(s.ids)
        deg = np.bincount(s.src, minlength=n)
        self.norm = 1 / np.sqrt(deg + 1.0)
        mark = np.random.default_rng(0).integers(1 << 63, size=n, dtype=np.uint64)
        order = np.argsort(s.src, kind="stable")
        closed = mark.copy()
        if len(order):
            held, first = np.unique(s.src[order], return_index=True)
            closed[held] += np.add.reduceat(mark[s.dst[order]], first)
        at = np.unique(closed, return_inverse=True)[1]
        size = np.bincount(at)
        pair, count = np.unique(at[s.src] * len(size) + at[s.dst], return_counts=True)
        a, b = pair // len(size), pair % len(size)
        whole = np.array_equal(count, np.where(a == b, size[a] * (size[a] - 1), size[a] * size[b])) and np.isin(np.flatnonzero(size > 1), a[a == b]).all()
        if not whole:
            at, a, b = np.arange(n), s.src[order], s.dst[order]
        loops = np.arange(at.max() + 1) if n else np.zeros(0, int)
        a, b = (np.r_[a[a != b], loops], np.r_[b[a != b], loops]) if whole else (np.r_[a, loops], np.r_[b, loops])
        by = np.argsort(a, kind="stable")
        self.at, self.a, self.b = at, a[by], b[by]
        self.members = np.argsort(at, kind="stable")
        self.first = np.searchsorted(at[self.members], loops)

    def __call__(self, x: np.ndarray) -> np.ndarray:
        if not len(self.at):
            return x.copy()
        y = np.add.reduceat((x * self.norm[:, None])[self.members], self.first, axis=0)
        out, step = np.zeros_like(y), max(1, GATHER // max(1, x.shape[1]))
        for lo in range(0, len(self.a), step):
            i = self.a[lo : lo + step]
            first = np.flatnonzero(np.r_[True, i[1:] != i[:-1]])
            out[i[first]] += np.add.reduceat(y[self.b[lo : lo + step]], first, axis=0)
        return out[self.at] * self.norm[:, None]


def balanced_accuracy(got: np.ndarray, y: np.ndarray) -> float:
    """Mean over classes of the share of their rows that are right."""
    return float(np.mean([(got[y == c] == c).mean() for c in np.unique(y)]))


def fit_gcn(s: Sample, hidden: int = 16, epochs: int = 100, lr: float = 0.02, seed: int = 0, start: Gcn | None = None, on: np.ndarray | None = None, sensitive: np.ndarray | None = None, strength: float = 0.0, decay: float = 5e-4, balance: bool = True) -> Gcn:
    """Full-batch gradient descent with momentum estimates, a fixed seed and the best validation epoch.

    ``balance`` weighs rows so that every class counts alike. ``start`` continues a model and ``on`` names the rows to fit instead of the training split.
    ``sensitive`` and ``strength`` add the squared covariance between the predicted scores and a
    centred 0/1 value to the loss: a fairness penalty (not an adversarial model).
    """
    rng = np.random.default_rng(seed)
    classes = start.classes if start else sorted(int(c) for c in np.unique(s.y[s.y >= 0]))
    code = {c: i for i, c in enumerate(classes)}
    y = np.array([code.get(int(v), -1) for v in s.y])
    rows = np.flatnonzero((s.train if on is None else on) & (y >= 0))
    valid = np.flatnonzero(s.valid & (y >= 0))
    d, c = s.x.shape[1], len(classes)
    w1 = start.w1.copy() if start else rng.standard_normal((d, hidden)) * np.sqrt(2 / (d + hidden))
    w2 = start.w2.copy() if start else rng.standard_normal((hidden, c)) * np.sqrt(2 / (hidden + c))
    b = start.b.copy() if start else np.zeros(c)
    spread = Spread(s)
    ax = spread(s.x)
    onehot = np.eye(c)[y[rows]]
    share = np.bincount(y[rows], minlength=c)[y[rows]].astype(float) if len(rows) else np.zeros(0)
    weight = (1 / share / (1 / share).sum() if balance else np.full(len(rows), 1 / len(rows))) if len(rows) else share
    moments = [[np.zeros_like(p), np.zeros_like(p)] for p in (w1, w2, b)]
    best, best_acc = (w1.copy(), w2.copy(), b.copy()), -1.0
    centred = None if sensitive is None else sensitive - sensitive.mean()
    for step in range(1, epochs + 1):
        h = np.maximum(ax @ w1, 0)
        ah = spread(h)
        z = ah @ w2 + b
        p = np.exp(z - z.max(1, keepdims=True))
        p /= p.sum(1, keepdims=True)
        g = np.zeros_like(z)
        if len(rows):
            g[rows] = (p[rows] - onehot) * weight[:, None]
        if centred is not None and strength:
            cov = centred @ p / len(p)
            dp = 2 * strength * centred[:, None] * cov[None, :] / len(p)
            g += p * (dp - (p * dp).sum(1, keepdims=True))
        gw2, gb = ah.T @ g + decay * w2, g.sum(0)
        gh = spread(g @ w2.T) * (h > 0)
        gw1 = ax.T @ gh + decay * w1
        for prm, grad, m in zip((w1, w2, b), (gw1, gw2, gb), moments, strict=True):
            m[0] = 0.9 * m[0] + 0.1 * grad
            m[1] = 0.999 * m[1] + 0.001 * grad * grad
            prm -= lr * (m[0] / (1 - 0.9**step)) / (np.sqrt(m[1] / (1 - 0.999**step)) + 1e-8)
        acc = balanced_accuracy(z[valid].argmax(1), y[valid]) if len(valid) and on is None else float(step)
        if acc > best_acc:
            best, best_acc = (w1.copy(), w2.copy(), b.copy()), acc
    return Gcn(*best, classes)


def fit(kind: str, graph: AnchoredGraph, epochs: int = 100, lr: float = 0.02, seed: int = 0, **how):
    """``gcn``, ``cluster_gcn``, ``linear``, ``gat``, ``gin``, ``mpnn`` or ``sage``: a fitted model with ``predict(graph)``."""
    if kind == "linear":
        return LinearPropagation.fit(graph, **how)
    s = sample(graph)
    if kind in ("gat", "gin", "mpnn", "sage"):
        from .gnn import fit_kind

        return fit_kind(kind, s, epochs=epochs, lr=lr, seed=seed, **how)
    if kind == "cluster_gcn":
        return fit_batches(s, epochs=epochs, lr=lr, seed=seed, **how)
    return fit_gcn(s, epochs=epochs, lr=lr, seed=seed, **how)


def fit_batches(s: Sample, blocks: int = 4, epochs: int = 100, lr: float = 0.02, seed: int = 0, rounds: int = 3) -> Gcn:
    """Cluster batches: nodes take the least label of their neighbourhood a few times, are dealt to ``blocks`` by it,
    and each round fits every block's subgraph in turn, dropping edges between blocks."""
    lab = np.arange(len(s.ids))
    for _ in range(3):
        nxt = lab.copy()
        np.minimum.at(nxt, s.src, lab[s.dst])
        lab = nxt
    block = (lab * 2654435761 % (1 << 32)) % blocks
    model = None
    for _ in range(rounds):
        for k in range(blocks):
            inside = block == k
            if not (inside & s.train & (s.y >= 0)).any():
                continue
            place = np.cumsum(inside) - 1
            e = inside[s.src] & inside[s.dst]
            part = Sample(s.ids[inside], s.x[inside], s.y[inside], s.train[inside], s.valid[inside], place[s.src[e]], place[s.dst[e]])
            if model is None:
                classes = sorted(int(c) for c in np.unique(s.y[s.y >= 0]))
                first = fit_gcn(s, epochs=1, lr=lr, seed=seed)
                model = Gcn(first.w1, first.w2, first.b, classes)
            model = fit_gcn(part, epochs=max(1, epochs // rounds), lr=lr, seed=seed, start=model, on=part.train)
    return model or fit_gcn(s, epochs=epochs, lr=lr, seed=seed)


class LinearPropagation:
    """Parameter-free propagation, then a logistic head fitted by Spark ML on all training nodes."""

    def __init__(self, model, hops: int):
        self.model, self.hops = model, hops

    @staticmethod
    def features(graph: AnchoredGraph, hops: int) -> DataFrame:
        from pyspark.ml.functions import array_to_vector

        both, x = cut(graph.both_ways(), "edges"), graph.nodes.select("node_id", "x")
        d = len(x.head()["x"])
        for _ in range(hops):
            x = cut(layers.gcn(x, both, np.eye(d), activation=False), "hop")
        return x.select("node_id", array_to_vector("x").alias("features"))

    @classmethod
    def fit(cls, graph: AnchoredGraph, hops: int = 2, iterations: int = 50):
        from pyspark.ml.classification import LogisticRegression

        f = cls.features(graph, hops)
        lab = graph.nodes.filter((F.col("split") == "train") & F.col("label").isNotNull()).select("node_id", F.col("label").cast("double").alias("label"))
        return cls(LogisticRegression(maxIter=iterations, regParam=1e-3).fit(f.join(lab, "node_id")), hops)

    def predict(self, graph: AnchoredGraph) -> DataFrame:
        return self.model.transform(self.features(graph, self.hops)).select("node_id", F.col("prediction").cast("int").alias("verdict"))
