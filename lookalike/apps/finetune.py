"""Fine-tuning on the nodes of the most similar pairs."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..models.train import Gcn, Sample, fit_gcn
from ..operators.graph import AnchoredGraph
from ..session import cut


def pair_nodes(pairs: DataFrame, k: int) -> DataFrame:
    """``node_id`` of the first ``k`` pairs, once each."""
    return pairs.filter(F.col("rank") <= k).select(F.explode(F.array("a", "b")).alias("node_id")).distinct()


def remaining_accuracy(predictions: DataFrame, labels: DataFrame, used: DataFrame) -> DataFrame:
    """``accuracy`` over labelled nodes outside ``used``."""
    left = predictions.select("node_id", "verdict").join(used, "node_id", "left_anti").join(labels.select("node_id", "label"), "node_id")
    return left.agg(F.avg((F.col("verdict") == F.col("label")).cast("double")).alias("accuracy"))


def tune(model: Gcn, s: Sample, used: list[int], mode: str = "continue", epochs: int = 40, lr: float = 0.02) -> Gcn:
    """``continue`` trains on with the pairs' labels beside the training split; ``select`` refits a few
    seeds and takes the one that is best on the pairs' nodes. At most a few thousand ids arrive here."""
    mine = np.isin(s.ids, np.array(used))
    if mode == "continue":
        return fit_gcn(s, epochs=epochs, lr=lr, start=model, on=s.train | mine)
    picked = Sample(s.ids, s.x, s.y, s.train, mine, s.src, s.dst)
    return max((fit_gcn(picked, epochs=epochs, seed=i) for i in range(3)), key=lambda m: _accuracy(m, s, mine))


def _accuracy(model: Gcn, s: Sample, rows: np.ndarray) -> float:
    from ..models.train import propagate

    deg = np.bincount(s.src, minlength=len(s.ids)) + 1.0
    norm = 1 / np.sqrt(deg)
    z = propagate(np.maximum(propagate(s.x, s, norm) @ model.w1, 0), s, norm) @ model.w2 + model.b
    known = rows & (s.y >= 0)
    return float((np.array(model.classes)[z[known].argmax(1)] == s.y[known]).mean()) if known.any() else 0.0


def sweep(graph: AnchoredGraph, model: Gcn, s: Sample, pairs: DataFrame, labels: DataFrame, ks: list[int], mode: str = "continue") -> DataFrame:
    """``k, before, after``: accuracy on the remaining nodes when the first ``k`` pairs are used, for each k."""
    before = cut(model.predict(graph).select("node_id", "verdict"), "before")
    out = None
    for k in ks:
        used = pair_nodes(pairs, k)
        after = tune(model, s, [r[0] for r in used.collect()], mode).predict(graph)
        row = remaining_accuracy(before, labels, used).withColumnRenamed("accuracy", "before").crossJoin(remaining_accuracy(after, labels, used).withColumnRenamed("accuracy", "after"))
        row = row.select(F.lit(k).alias("k"), "before", "after")
        out = row if out is None else out.union(row)
    return out


def fixed(graph: AnchoredGraph, model: Gcn, s: Sample, pairs: DataFrame, labels: DataFrame, k_fix: int, ks: list[int], mode: str = "continue") -> DataFrame:
    """``k, before, after``: the first ``k_fix`` pairs are used once; accuracy on the nodes of the next ``k`` pairs without them."""
    used = cut(pair_nodes(pairs, k_fix), "used")
    before = cut(model.predict(graph).select("node_id", "verdict"), "before")
    after = cut(tune(model, s, [r[0] for r in used.collect()], mode).predict(graph).select("node_id", "verdict"), "after")
    rest = pairs.filter(F.col("rank") > k_fix).withColumn("rank", F.col("rank") - k_fix)
    out = None
    for k in ks:
        shown = pair_nodes(rest, k).join(used, "node_id", "left_anti")
        acc = lambda p: p.join(shown, "node_id", "left_semi").join(labels.select("node_id", "label"), "node_id").agg(F.avg((F.col("verdict") == F.col("label")).cast("double")).alias("a"))  # noqa: B023, E731
        row = acc(before).withColumnRenamed("a", "before").crossJoin(acc(after).withColumnRenamed("a", "after")).select(F.lit(k).alias("k"), "before", "after")
        out = row if out is None else out.union(row)
    return out
