"""Verdict tables: ``node_id, verdict``. The engine takes any; these are the built-in providers."""

from __future__ import annotations

import numpy as np
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.ml.stat import Summarizer
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.graph import AnchoredGraph
from ..operators.kernels import matmul
from ..operators.similarity import bucket_mean
from ..session import cut


def from_column(nodes: DataFrame, column: str) -> DataFrame:
    return nodes.select("node_id", F.col(column).cast("int").alias("verdict"))


def hop_mean(graph: AnchoredGraph) -> DataFrame:
    """``node_id, h``: mean of the own and the neighbours' vectors, which travel once per bucket."""
    own = graph.nodes.select("node_id", "x")
    mean = getattr(graph, "mean", None)
    m = mean(own, False) if mean else bucket_mean(own, graph.both_ways(), weighted=False)
    d = F.size("x")
    mixed = F.zip_with(F.zip_with("x", F.zip_with("m", F.array_repeat("deg", d), lambda v, n: v * n), lambda v, w: v + w), F.array_repeat("deg", d), lambda v, n: v / (n + 1))
    return own.join(m, "node_id", "left").select("node_id", F.when(F.col("m").isNull(), F.col("x")).otherwise(mixed).alias("h"))


def centroid_rule(graph: AnchoredGraph, split: str | None = "train") -> DataFrame:
    """The class whose training mean is nearest (squared distance, rounded to 9; ties: smaller class) after one hop of averaging.

    Class means are one row per class and dimension, so they are collected as literals.
    """
    h = cut(hop_mean(graph), "hop")
    lab = graph.nodes.filter(F.col("label").isNotNull())
    lab = lab.filter(F.col("split") == split) if split else lab
    means = h.join(lab.select("node_id", "label"), "node_id").groupBy("label").agg(vector_to_array(Summarizer.mean(array_to_vector("h"))).alias("m")).orderBy("label").collect()
    if not means:
        return graph.nodes.select("node_id", F.lit(None).cast("int").alias("verdict"))
    # the squared distance without the part that is the same for all classes: |m|^2 - 2 h.m
    w = -2.0 * np.array([r["m"] for r in means]).T
    bias = np.array([sum(v * v for v in r["m"]) for r in means])
    s = matmul(h.select("node_id", F.col("h").alias("x")), w, bias=bias)
    r = F.transform("x", lambda v: F.round(v, 9))
    classes = F.array(*[F.lit(int(m["label"])) for m in means])
    return s.select("node_id", F.element_at(classes, F.array_position(r, F.array_min(r)).cast("int")).alias("verdict"))


def head(h: DataFrame, w: np.ndarray, b: np.ndarray) -> DataFrame:
    """``node_id, verdict, score``: softmax of ``x W + b``, the largest wins, ties to the smaller class."""
    z = matmul(h.select("node_id", "x"), w, bias=b)
    top = F.array_max("x")
    z = z.withColumn("top", top)
    e = F.zip_with("x", F.array_repeat(F.col("top"), w.shape[1]), lambda v, t: F.exp(v - t))
    z = z.select("node_id", (F.array_position("x", F.col("top")) - 1).cast("int").alias("verdict"), e.alias("e"))
    total = F.aggregate("e", F.lit(0.0), lambda s, v: s + v)
    return z.select("node_id", "verdict", F.zip_with("e", F.array_repeat(total, w.shape[1]), lambda v, t: v / t).alias("score"))


def assert_deterministic(make) -> None:
    """Raises if two runs of ``make()`` differ in a verdict."""
    a, b = make().select("node_id", "verdict"), make().select("node_id", "verdict")
    if not a.exceptAll(b).isEmpty() or not b.exceptAll(a).isEmpty():
        raise AssertionError("verdicts differ between runs")
