"""Fitting any of the five layer kinds: two layers and a linear head, gradients by a small tape, inference in Spark.

The fit runs on the bounded sample of :mod:`.train`; ``predict`` runs the same layers over all
nodes as joins. Training repeats each layer's formula in numpy, so both give the same numbers.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.graph import AnchoredGraph
from ..session import cut
from . import layers, predict
from .train import Sample, balanced_accuracy

KINDS = ("gcn", "gat", "gin", "mpnn", "sage")


class Var:
    """An array and, after :meth:`Tape.backward`, what the loss changes by with it."""

    __slots__ = ("v", "g")

    def __init__(self, v: np.ndarray):
        self.v, self.g = v, np.zeros_like(v)


class Groups:
    """Sums of rows by a group number, over rows sorted once."""

    def __init__(self, at: np.ndarray, n: int):
        self.at, self.n = at, n
        self.order = np.argsort(at, kind="stable")
        self.held, self.starts = np.unique(at[self.order], return_index=True)

    def sum(self, rows: np.ndarray) -> np.ndarray:
        out = np.zeros((self.n, *rows.shape[1:]))
        if len(self.at):
            out[self.held] = np.add.reduceat(rows[self.order], self.starts, axis=0)
        return out

    def max(self, rows: np.ndarray) -> np.ndarray:
        out = np.zeros(self.n)
        if len(self.at):
            out[self.held] = np.maximum.reduceat(rows[self.order], self.starts)
        return out


class Tape:
    """Records operations; :meth:`backward` walks them in reverse."""

    def __init__(self):
        self.ops = []

    def _out(self, v: np.ndarray, back) -> Var:
        out = Var(v)
        self.ops.append(lambda: back(out.g))
        return out

    def matmul(self, a: Var, b: Var) -> Var:
        def back(g):
            a.g += g @ b.v.T
            b.g += a.v.T @ g

        return self._out(a.v @ b.v, back)

    def add(self, a: Var, b: Var) -> Var:
        def back(g):
            a.g += g
            b.g += g if b.v.shape == g.shape else g.sum(0)

        return self._out(a.v + b.v, back)

    def times(self, a: Var, c: np.ndarray) -> Var:
        """By a constant, which broadcasts."""

        def back(g):
            a.g += g * c

        return self._out(a.v * c, back)

    def outer(self, c: np.ndarray, b: Var) -> Var:
        """Constant numbers times a row of weights."""

        def back(g):
            b.g += c @ g

        return self._out(c[:, None] * b.v, back)

    def weigh(self, a: Var, w: Var) -> Var:
        """Rows of ``a`` times a number each."""

        def back(g):
            a.g += g * w.v[:, None]
            w.g += (g * a.v).sum(1)

        return self._out(a.v * w.v[:, None], back)

    def relu(self, a: Var, slope: float = 0.0) -> Var:
        by = np.where(a.v > 0, 1.0, slope)
        return self.times(a, by)

    def take(self, a: Var, groups: Groups) -> Var:
        """Rows of ``a`` by the groups' numbers."""

        def back(g):
            a.g += groups.sum(g)

        return self._out(a.v[groups.at], back)

    def sum(self, a: Var, groups: Groups) -> Var:
        def back(g):
            a.g += g[groups.at]

        return self._out(groups.sum(a.v), back)

    def softmax(self, s: Var, groups: Groups) -> Var:
        e = np.exp(s.v - groups.max(s.v)[groups.at])
        p = e / groups.sum(e)[groups.at]

        def back(g):
            s.g += p * (g - groups.sum(p * g)[groups.at])

        return self._out(p, back)

    def backward(self, out: Var, g: np.ndarray) -> None:
        out.g += g
        for op in reversed(self.ops):
            op()


class Frame:
    """What a sample's edges give each layer kind, made once."""

    def __init__(self, s: Sample, fanout: int = 5):
        n = self.n = len(s.ids)
        loops = np.arange(n)
        self.src, self.dst = Groups(s.src, n), Groups(s.dst, n)
        self.all_src, self.all_dst = Groups(np.r_[s.src, loops], n), Groups(np.r_[s.dst, loops], n)
        c = 1 / np.sqrt(np.bincount(s.src, minlength=n) + 1.0)
        self.norm = (c[self.all_src.at] * c[self.all_dst.at])[:, None]
        picked = []  # the sampled neighbours: as the Spark layer has them, by md5 of the edge
        if len(s.src):
            key = np.array([hashlib.md5(f"{a}:{b}:0".encode()).hexdigest() for a, b in zip(s.ids[s.src].tolist(), s.ids[s.dst].tolist(), strict=True)])
            order = np.lexsort((key, s.src))
            first = np.searchsorted(s.src[order], s.src[order])
            picked = order[np.arange(len(order)) - first < fanout]
        self.few_src, self.few_dst = Groups(s.src[picked] if len(picked) else s.src, n), Groups(s.dst[picked] if len(picked) else s.dst, n)
        self.share = 1 / np.maximum(np.bincount(self.few_src.at, minlength=n), 1)[:, None]


def _shapes(kind: str, d: int, h: int) -> dict[str, tuple[int, ...]]:
    more = {"gat": {"a": (h, 1), "b": (h, 1)}, "mpnn": {"e": (h,)}, "sage": {"m": (d, h)}}
    return {"w": (d, h), **more.get(kind, {})}


def _layer(t: Tape, kind: str, f: Frame, x: Var, p: dict[str, Var]) -> Var:
    """One layer's formula: see :mod:`.layers`."""
    h = t.matmul(x, p["w"])
    if kind == "gcn":
        return t.relu(t.sum(t.times(t.take(h, f.all_dst), f.norm), f.all_src))
    if kind == "gat":
        s = t.add(t.take(t.matmul(h, p["a"]), f.all_src), t.take(t.matmul(h, p["b"]), f.all_dst))
        flat = t._out(s.v[:, 0], lambda g: s.g.__iadd__(g[:, None]))
        return t.relu(t.sum(t.weigh(t.take(h, f.all_dst), t.softmax(t.relu(flat, 0.2), f.all_src)), f.all_src))
    if kind == "gin":
        return t.relu(t.add(t.times(h, np.float64(1.1)), t.sum(t.take(h, f.dst), f.src)))
    if kind == "mpnn":  # the edge feature is the cosine of the layer's input, taken as given
        size = np.linalg.norm(x.v, axis=1)
        both = size[f.src.at] * size[f.dst.at]
        cos = np.divide((x.v[f.src.at] * x.v[f.dst.at]).sum(1), both, out=np.zeros(len(both)), where=both > 0)
        return t.sum(t.relu(t.add(t.take(h, f.dst), t.outer(cos, p["e"]))), f.src)
    mean = t.times(t.sum(t.take(t.matmul(x, p["m"]), f.few_dst), f.few_src), f.share)
    return t.relu(t.add(h, mean))


@dataclass
class Fitted:
    """A fitted model of one kind: parameters of two layers, and of the head."""

    kind: str
    layers: list[dict[str, np.ndarray]]
    w: np.ndarray
    b: np.ndarray
    classes: list[int]

    def hidden(self, nodes: DataFrame, both: DataFrame, p: dict[str, np.ndarray]) -> DataFrame:
        if self.kind == "gcn":
            return layers.gcn(nodes, both, p["w"])
        if self.kind == "gat":
            return layers.gat(nodes, both, p["w"], p["a"][:, 0], p["b"][:, 0]).select("node_id", layers.relu("x").alias("x"))
        if self.kind == "gin":
            return layers.gin(nodes, both, p["w"], 0.1)
        if self.kind == "mpnn":
            return layers.mpnn(nodes, both, p["w"], p["e"])
        return layers.sage(nodes, both, p["w"], p["m"])

    def predict(self, graph: AnchoredGraph) -> DataFrame:
        """``node_id, verdict, score`` of every node."""
        both, x = cut(graph.both_ways(), "edges"), graph.nodes.select("node_id", "x")
        for p in self.layers:
            x = cut(self.hidden(x, both, p), "hidden")
        out = predict.head(x, self.w, self.b)
        return out.withColumn("verdict", F.element_at(F.array(*[F.lit(c) for c in self.classes]), F.col("verdict") + 1))


def outputs(s: Sample, model: Fitted) -> np.ndarray:
    """The head's numbers for a sample's nodes, in numpy."""
    t, f, x = Tape(), Frame(s), Var(s.x.astype(float))
    for p in model.layers:
        x = _layer(t, model.kind, f, x, {k: Var(v) for k, v in p.items()})
    return x.v @ model.w + model.b


def fit_kind(kind: str, s: Sample, hidden: int = 16, epochs: int = 80, lr: float = 0.02, seed: int = 0, decay: float = 5e-4) -> Fitted:
    """Full-batch gradient descent with moment estimates and a fixed seed; the epoch best on the validation nodes is kept.

    Classes count alike. A sample without labelled training nodes gives the starting weights.
    """
    if kind not in KINDS:
        raise ValueError(f"no model of kind {kind!r}")
    rng = np.random.default_rng(seed)
    classes = sorted(int(c) for c in np.unique(s.y[s.y >= 0])) or [0]
    code = {c: i for i, c in enumerate(classes)}
    y = np.array([code.get(int(v), -1) for v in s.y])
    rows, valid = np.flatnonzero(s.train & (y >= 0)), np.flatnonzero(s.valid & (y >= 0))
    f, x, c = Frame(s), s.x.astype(float), len(classes)
    init = lambda shape: rng.standard_normal(shape) * np.sqrt(2 / (shape[0] + shape[-1]))
    params = [{k: init(v) for k, v in _shapes(kind, d, hidden).items()} for d in (x.shape[1], hidden)]
    flat = [*params[0].values(), *params[1].values(), init((hidden, c)), np.zeros(c)]
    names = [list(p) for p in params]
    share = np.bincount(y[rows], minlength=c)[y[rows]].astype(float)
    weight = (1 / share / (1 / share).sum())[:, None] if len(rows) else None
    moments = [(np.zeros_like(p), np.zeros_like(p)) for p in flat]
    best, best_acc = [p.copy() for p in flat], -1.0
    for step in range(1, epochs + 1 if len(rows) else 1):
        t, vs = Tape(), [Var(p) for p in flat]
        one, two = dict(zip(names[0], vs)), dict(zip(names[1], vs[len(names[0]) :]))
        z = t.add(t.matmul(_layer(t, kind, f, _layer(t, kind, f, Var(x), one), two), vs[-2]), vs[-1])
        e = np.exp(z.v - z.v.max(1, keepdims=True))
        g = np.zeros_like(e)
        g[rows] = (e[rows] / e[rows].sum(1, keepdims=True) - np.eye(c)[y[rows]]) * weight
        acc = balanced_accuracy(z.v[valid].argmax(1), y[valid]) if len(valid) else float(step)
        if acc > best_acc:
            best, best_acc = [p.copy() for p in flat], acc
        t.backward(z, g)
        for p, v, (m1, m2) in zip(flat, vs, moments, strict=True):
            grad = v.g + decay * p
            m1 += 0.1 * (grad - m1)
            m2 += 0.001 * (grad * grad - m2)
            p -= lr * (m1 / (1 - 0.9**step)) / (np.sqrt(m2 / (1 - 0.999**step)) + 1e-8)
    k = len(names[0])
    return Fitted(kind, [dict(zip(names[0], best)), dict(zip(names[1], best[k:]))], best[-2], best[-1], classes)
