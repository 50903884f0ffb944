"""One layer of each message-passing model: neighbour work as joins and partial sums, weights in Arrow kernels.

Weights are applied before vectors travel wherever the layer allows it (they shrink d to h), so an
edge carries h numbers.
"""

from __future__ import annotations

import numpy as np
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.ml.stat import Summarizer
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import vectors as V
from ..operators.kernels import matmul
from ..session import cut


def closed_form(rows: int, cols: int, a: int = 7, b: int = 3, by: float = 8.0) -> np.ndarray:
    """Weights that SQL can repeat: ``sin(i * a + j * b) / by``."""
    i, j = np.meshgrid(np.arange(rows), np.arange(cols), indexing="ij")
    return np.sin(i * a + j * b) / by


def relu(c) -> F.Column:
    return F.transform(c, lambda v: F.greatest(v, F.lit(0.0)))


def vector_sum(df: DataFrame, key: str, vec: str, out: str = "x") -> DataFrame:
    """Partial and final sums of a vector column per key."""
    return df.groupBy(key).agg(vector_to_array(Summarizer.sum(array_to_vector(vec))).alias(out))


def gcn(nodes: DataFrame, both: DataFrame, w: np.ndarray, activation: bool = True) -> DataFrame:
    """Symmetric-normalised neighbour sum with self loops, then weights and a rectifier. ``node_id, x``."""
    deg = both.groupBy(F.col("src").alias("node_id")).agg(F.count("*").alias("deg"))
    h = matmul(nodes.select("node_id", "x"), w).join(deg, "node_id", "left")
    h = cut(h.select("node_id", (1.0 / F.sqrt(F.coalesce("deg", F.lit(0)) + 1.0)).alias("c"), "x"), "gcn")
    scaled = h.select("node_id", V.scale("x", F.col("c")).alias("x"))
    msg = both.join(scaled.withColumnRenamed("node_id", "dst"), "dst").select(F.col("src").alias("node_id"), "x").union(scaled)
    total = vector_sum(msg, "node_id", "x").join(h.select("node_id", "c"), "node_id")
    y = V.scale("x", F.col("c"))
    return total.select("node_id", (relu(y) if activation else y).alias("x"))


def gcn_of(graph, nodes: DataFrame, w: np.ndarray, activation: bool = True) -> DataFrame:
    """:func:`gcn` over a graph that gives sums over neighbours and makes no edges: degrees once, then one sum."""
    deg = graph.degrees()
    h = matmul(nodes.select("node_id", "x"), w).join(deg, "node_id", "left")
    c = 1.0 / F.sqrt(F.coalesce("deg", F.lit(0)) + 1.0)
    h = cut(h.select("node_id", c.alias("c"), V.scale("x", c).alias("x")), "gcn")
    total = h.join(graph.mean(h.select("node_id", "x"), False), "node_id", "left")
    y = V.scale(F.when(F.col("m").isNull(), F.col("x")).otherwise(V.add("x", V.scale("m", F.col("deg").cast("double")))), F.col("c"))
    return total.select("node_id", (relu(y) if activation else y).alias("x"))


def gat(nodes: DataFrame, both: DataFrame, w: np.ndarray, a_self: np.ndarray, a_other: np.ndarray, slope: float = 0.2) -> DataFrame:
    """Attention over neighbours and the node itself; the softmax subtracts each node's largest score."""
    h = cut(matmul(nodes.select("node_id", "x"), w), "gat")
    lit = lambda v: F.array(*[F.lit(float(t)) for t in v])
    h = h.select("node_id", "x", V.dot("x", lit(a_self)).alias("p"), V.dot("x", lit(a_other)).alias("q"))
    pairs = both.select("src", "dst").union(h.select(F.col("node_id").alias("src"), F.col("node_id").alias("dst")))
    e = pairs.join(h.select(F.col("node_id").alias("src"), "p"), "src").join(h.select(F.col("node_id").alias("dst"), "q", "x"), "dst")
    s = F.col("p") + F.col("q")
    e = cut(e.select("src", "x", F.when(s > 0, s).otherwise(s * slope).alias("s")), "scores")
    top = e.groupBy("src").agg(F.max("s").alias("top"))
    e = e.join(top, "src").select("src", F.exp(F.col("s") - F.col("top")).alias("z"), "x")
    num = e.select("src", "z", V.scale("x", F.col("z")).alias("x")).groupBy(F.col("src").alias("node_id")).agg(vector_to_array(Summarizer.sum(array_to_vector("x"))).alias("x"), F.sum("z").alias("z"))
    return num.select("node_id", V.scale("x", 1.0 / F.col("z")).alias("x"))


def gin(nodes: DataFrame, both: DataFrame, w: np.ndarray, eps: float = 0.1) -> DataFrame:
    """``relu(((1 + eps) x + neighbour sum) W)``; the sum commutes with the weights, so they go first."""
    h = cut(matmul(nodes.select("node_id", "x"), w), "gin")
    own = h.select("node_id", V.scale("x", F.lit(1.0 + eps)).alias("x"))
    msg = both.join(h.withColumnRenamed("node_id", "dst"), "dst").select(F.col("src").alias("node_id"), "x").union(own)
    return vector_sum(msg, "node_id", "x").select("node_id", relu("x").alias("x"))


def mpnn(nodes: DataFrame, both: DataFrame, w: np.ndarray, edge_w: np.ndarray) -> DataFrame:
    """Sum over neighbours of ``relu(x_u W + e b)``, where the edge feature ``e`` is the cosine of the ends."""
    raw = nodes.select("node_id", "x", V.norm("x").alias("n"))
    e = both.join(raw.select(F.col("node_id").alias("src"), F.col("x").alias("xs"), F.col("n").alias("ns")), "src").join(raw.select(F.col("node_id").alias("dst"), F.col("x").alias("xd"), F.col("n").alias("nd")), "dst")
    n = F.col("ns") * F.col("nd")
    e = cut(e.select("src", "dst", F.when(n > 0, V.dot("xs", "xd") / n).otherwise(F.lit(0.0)).alias("e")), "edge-features")
    h = cut(matmul(nodes.select("node_id", "x"), w), "mpnn")
    b = F.array(*[F.lit(float(t)) for t in edge_w])
    msg = e.join(h.withColumnRenamed("node_id", "dst"), "dst").select(F.col("src").alias("node_id"), relu(V.add("x", V.scale(b, F.col("e")))).alias("x"))
    zero = nodes.select("node_id", F.array_repeat(F.lit(0.0), w.shape[1]).alias("x"))
    return vector_sum(msg.union(zero), "node_id", "x")


def sage(nodes: DataFrame, both: DataFrame, w_self: np.ndarray, w_mean: np.ndarray, fanout: int = 5, seed: int = 0) -> DataFrame:
    """``relu(x W1 + mean of sampled neighbours W2)``; the sample is the ``fanout`` smallest hashes of the edge."""
    w = Window.partitionBy("src").orderBy(F.md5(F.concat_ws(":", "src", "dst", F.lit(seed))))
    picked = both.withColumn("r", F.row_number().over(w)).filter(F.col("r") <= fanout).select("src", "dst")
    far = cut(matmul(nodes.select("node_id", "x"), w_mean), "sage")
    mean = picked.join(far.withColumnRenamed("node_id", "dst"), "dst").groupBy(F.col("src").alias("node_id")).agg(vector_to_array(Summarizer.mean(array_to_vector("x"))).alias("m"))
    own = matmul(nodes.select("node_id", "x"), w_self)
    y = F.when(F.col("m").isNull(), F.col("x")).otherwise(V.add("x", "m"))
    return own.join(mean, "node_id", "left").select("node_id", relu(y).alias("x"))
