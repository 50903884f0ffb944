"""Error checks: accuracy among the nodes of the most similar pairs, and explanations by removed edges."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import vectors as V
from ..operators.graph import AnchoredGraph, khop
from ..operators.kernels import groups_in_order, matmul, matrix
from ..operators.relational import numbered
from ..session import cut, ship


def accuracy_in_pairs(pairs: DataFrame, predictions: DataFrame, labels: DataFrame, ks: list[int], unit: str = "node") -> DataFrame:
    """``k, n_nodes, accuracy`` over the nodes of the first ``k`` pairs, for each k of ``ks``.

    A node counts once per k at its best rank (``node``) or once per pair it is in (``slot``).
    """
    slots = pairs.select("rank", F.explode(F.array("a", "b")).alias("node_id"))
    if unit == "node":
        slots = slots.groupBy("node_id").agg(F.min("rank").alias("rank"))
    ok = slots.join(predictions.select("node_id", "verdict"), "node_id").join(labels.select("node_id", "label"), "node_id").select("rank", (F.col("verdict") == F.col("label")).cast("double").alias("ok"))
    per = ok.groupBy("rank").agg(F.sum("ok").alias("ok"), F.count("*").alias("n"))  # one row per rank
    grid = pairs.sparkSession.createDataFrame([(k,) for k in ks], "k int")
    return grid.join(per, F.col("rank") <= F.col("k")).groupBy("k").agg(F.sum("n").alias("n_nodes"), (F.sum("ok") / F.sum("n")).alias("accuracy"))


def edge_mask_flip(graph: AnchoredGraph, predict, queries: DataFrame, max_edges: int = 1, hops: int = 3) -> DataFrame:
    """``node_id, size, removed, before, after``: the smallest sets of a node's edges whose removal changes its verdict.

    ``queries`` has ``node_id``; ``predict(graph)`` gives verdicts that depend on ``hops`` hops. All
    edges of a node are tried, first one by one, then, for nodes that no single edge flips, in pairs
    and so on to ``max_edges``. Every set is a masked copy of the node's anchored neighbourhood
    under ids of its own, so all copies of a size are judged in one distributed pass; their number
    is the binomial coefficient of the degree, which ``max_edges`` bounds.
    """
    nodes = numbered(graph.nodes, "node_id", "__at").withColumn("__at", F.col("__at").cast("long"))
    nodes = cut(nodes, "nodes")
    around = cut(khop(graph.edges, queries.select("node_id").distinct(), hops).select("seed", "node_id"), "around")
    one = graph.edges.select("src", "dst")
    inner = one.join(around.select("seed", F.col("node_id").alias("src")), "src").join(around.select("seed", F.col("node_id").alias("dst")), ["seed", "dst"])
    inner = cut(inner.select("seed", "src", "dst"), "edges")
    mine = inner.filter((F.col("src") == F.col("seed")) | (F.col("dst") == F.col("seed"))).select("seed", F.struct("src", "dst").alias("e"))
    empty = F.array().cast("array<struct<src:bigint,dst:bigint>>")
    masks = around.select("seed").distinct().withColumn("removed", empty)
    before, left, out = None, around.select("seed").distinct(), None
    for size in range(max_edges + 1):
        if size:
            more = masks.join(mine, "seed").filter((F.size("removed") == 0) | (F.element_at("removed", -1) < F.col("e")))
            masks = more.select("seed", F.concat("removed", F.array("e")).alias("removed")).join(left, "seed", "left_semi")
        masks = cut(numbered(masks.withColumn("__key", F.struct("seed", "removed")), "__key", "mask").drop("__key"), "masks")
        judged = cut(_judged(nodes, around, inner, masks, predict), "judged")
        if size == 0:
            before = judged.select("seed", F.col("verdict").alias("before"))
            continue
        masks = masks.select("seed", "removed")
        flips = judged.join(before, "seed").filter("verdict <> before")
        flips = cut(flips.select(F.col("seed").alias("node_id"), F.lit(size).alias("size"), "removed", "before", F.col("verdict").alias("after")), "flips")
        out = flips if out is None else out.union(flips)
        left = left.join(flips.select(F.col("node_id").alias("seed")).distinct(), "seed", "left_anti")
    return out


def gcn_mask_flip(graph: AnchoredGraph, w: np.ndarray, queries: DataFrame, max_edges: int = 1) -> DataFrame:
    """:func:`edge_mask_flip` for one convolution of weights ``w`` and its largest output (ties: the smaller class).

    Without some of its edges a node's output is its sum less their ends' parts, under its own new norm; other nodes'
    degrees enter by the edges that go. So every set is tried in numpy from one row per neighbour, and no copy of a neighbourhood is made.
    """
    ship(queries.sparkSession)
    asked = cut(queries.select("node_id").distinct(), "asked")
    h = matmul(graph.nodes.select("node_id", "x"), w).join(graph.degrees(), "node_id", "left").select("node_id", "x", F.coalesce("deg", F.lit(0)).alias("deg"))
    h = cut(h, "parts")
    own = h.join(asked, "node_id", "left_semi").select(F.col("node_id").alias("seed"), "node_id", "x")
    near = graph.around(asked).join(h, "node_id").select("seed", "node_id", V.scale("x", 1.0 / F.sqrt(F.col("deg") + 1.0)).alias("x"))
    rows = own.union(near).repartition("seed").sortWithinPartitions("seed", "node_id")
    edge = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())])
    schema = T.StructType([T.StructField("node_id", T.LongType()), T.StructField("size", T.IntegerType()), T.StructField("removed", T.ArrayType(edge)), T.StructField("before", T.IntegerType()), T.StructField("after", T.IntegerType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in groups_in_order(batches):
            seed, ids, x = t.column(0)[0].as_py(), t.column(1).to_numpy(), matrix(t.column(2))
            mine, far, parts = x[ids == seed][0], ids[ids != seed], x[ids != seed]
            ends = np.stack([np.minimum(far, seed), np.maximum(far, seed)], axis=1)
            order = np.lexsort((ends[:, 1], ends[:, 0]))
            ends, parts, total = ends[order], parts[order], parts.sum(0)
            before = int(np.argmax(mine / (len(far) + 1) + total / np.sqrt(len(far) + 1)))
            found = False
            for size in range(1, min(max_edges, len(far)) + 1):
                n = len(far) - size + 1
                for first in combinations(range(len(far)), size - 1):
                    last = np.arange(first[-1] + 1 if first else 0, len(far))
                    after = np.argmax(mine / n + (total - parts[list(first)].sum(0) - parts[last]) / np.sqrt(n), axis=1)
                    hit = np.flatnonzero(after != before)
                    if not len(hit):
                        continue
                    found = True
                    sets = np.concatenate([np.tile(np.array(first, np.int64), (len(hit), 1)), last[hit][:, None]], axis=1)
                    gone = ends[sets.ravel()]
                    gone = pa.StructArray.from_arrays([pa.array(gone[:, 0]), pa.array(gone[:, 1])], names=["src", "dst"])
                    lists = pa.ListArray.from_arrays(np.arange(0, sets.size + 1, size, dtype=np.int32), gone)
                    same = [np.full(len(hit), v) for v in (seed, size, before)]
                    yield pa.RecordBatch.from_arrays([pa.array(same[0]), pa.array(same[1].astype(np.int32)), lists, pa.array(same[2].astype(np.int32)), pa.array(after[hit].astype(np.int32))], names=schema.names)
                if found:
                    break

    return rows.mapInArrow(run, schema)


def _judged(nodes: DataFrame, around: DataFrame, inner: DataFrame, masks: DataFrame, predict) -> DataFrame:
    """``seed, removed, verdict`` of each mask's seed in its masked copy."""
    shift = F.col("mask") * F.lit(1 << 31)  # places of nodes are below it
    place = nodes.select("node_id", "__at")
    copies = masks.join(around, "seed").join(nodes, "node_id")
    n = copies.withColumn("node_id", shift + F.col("__at")).drop("seed", "removed", "mask", "__at")
    e = inner.join(place.select(F.col("node_id").alias("src"), F.col("__at").alias("s")), "src").join(place.select(F.col("node_id").alias("dst"), F.col("__at").alias("d")), "dst")
    e = masks.join(e, "seed").filter(~F.array_contains("removed", F.struct("src", "dst")))
    e = e.select((shift + F.col("s")).alias("src"), (shift + F.col("d")).alias("dst"))
    got = predict(AnchoredGraph(cut(n, "copies"), cut(e, "copied-edges"))).select("node_id", "verdict")
    seeds = masks.join(place.withColumnRenamed("node_id", "seed"), "seed").select("seed", "removed", (shift + F.col("__at")).alias("node_id"))
    return seeds.join(got, "node_id").select("seed", "removed", "verdict")
