"""Quality and cost measures."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def average_similarity(twins: DataFrame, nodes: DataFrame, k: int, missing: str = "strict") -> DataFrame:
    """``avg_sim``: mean over all nodes of the mean similarity of their ``k`` twins.

    ``strict`` divides by ``k`` whatever was found and counts a node without twins as 0; ``found``
    divides by what was found and leaves such nodes out.
    """
    per = twins.filter(F.col("rank") <= k).groupBy("v").agg(F.sum("sim").alias("s"), F.count("*").alias("n"))
    if missing == "found":
        return per.agg(F.avg(F.col("s") / F.col("n")).alias("avg_sim"))
    total = nodes.agg(F.count("*").alias("nodes"))
    return per.agg(F.sum(F.col("s") / k).alias("s")).crossJoin(total).select((F.coalesce("s", F.lit(0.0)) / F.col("nodes")).alias("avg_sim"))


def similarity_curve(twins: DataFrame, nodes: DataFrame) -> DataFrame:
    """``k, avg_sim`` for every k at once: totals per rank, then a running sum over the few ranks."""
    per = twins.groupBy("rank").agg(F.sum("sim").alias("s"))
    run = F.sum("s").over(Window.orderBy("rank").rowsBetween(Window.unboundedPreceding, 0))
    total = nodes.agg(F.count("*").alias("nodes"))
    return per.withColumn("c", run).crossJoin(total).select(F.col("rank").alias("k"), (F.col("c") / F.col("rank") / F.col("nodes")).alias("avg_sim"))


def average_pair_similarity(pairs: DataFrame) -> DataFrame:
    return pairs.agg(F.avg("sim").alias("avg_sim"))


def accuracy(predictions: DataFrame, labels: DataFrame) -> DataFrame:
    """``accuracy``: correct verdicts over all labelled nodes."""
    return predictions.join(labels, "node_id").agg(F.avg((F.col("verdict") == F.col("label")).cast("double")).alias("accuracy"))


def recall_at_k(found: DataFrame, exact: DataFrame, k: int) -> DataFrame:
    """``avg_recall``: share of each node's exact twins that were found, over nodes that have any."""
    want = exact.filter(F.col("rank") <= k).select("v", "u")
    got = found.filter(F.col("rank") <= k).select("v", "u", F.lit(1).alias("hit"))
    return want.join(got, ["v", "u"], "left").groupBy("v").agg(F.avg(F.coalesce("hit", F.lit(0)).cast("double")).alias("r")).agg(F.avg("r").alias("avg_recall"))


def candidates_per_query(nodes: DataFrame, numbers: list[int]) -> DataFrame:
    """``v, candidates``: nodes of another verdict in each node's home cluster, counted without pairing them."""
    wide = nodes.select("verdict", F.explode(F.arrays_zip(F.array(*[F.lit(n) for n in numbers]).alias("layer"), F.col("clusters").alias("cluster"))).alias("a"))
    by = wide.groupBy(F.col("a.layer").alias("layer"), F.col("a.cluster").alias("cluster"), "verdict").agg(F.count("*").alias("n"))
    all_of = by.groupBy("layer", "cluster").agg(F.sum("n").alias("n_all"))
    q = nodes.select(F.col("node_id").alias("v"), "verdict", "layer", "cluster")
    return q.join(all_of, ["layer", "cluster"]).join(by, ["layer", "cluster", "verdict"]).select("v", (F.col("n_all") - F.col("n")).alias("candidates"))


def predicted_cost(kind: str, n: int, d: int, layers: int = 2, edges: int = 0, degree: int = 0, classes: int = 2, k: int = 1, m: int = 10, p: int = 50, overlap: int = 1) -> dict[str, float]:
    """Unit operations and stored numbers that the method's formulas predict.

    ``exact``: inference, aggregation and a scan of all nodes; ``index``: the same over a cluster
    of n/m nodes plus p for the home; ``build``: the offline cost of p layers.
    """
    if kind == "build":
        return {"time": m * p * n * (d + overlap), "space": p * n}
    c = n if kind == "exact" else n / m
    return {"time": layers * d * (edges + c * (classes + degree)) + k * c + (0 if kind == "exact" else p), "space": d * degree * n + edges + k}


def timed(fn: Callable[[], object], repeats: int = 3) -> float:
    """The least seconds of ``repeats`` runs."""
    best = float("inf")
    for _ in range(repeats):
        t = time.perf_counter()
        fn()
        best = min(best, time.perf_counter() - t)
    return best
