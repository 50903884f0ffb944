"""Signatures: iterated, cosine-weighted neighbour aggregation, and the similarity of two of them."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.ml.stat import Summarizer
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..session import cut, drop, free_shuffles, noted, ship, store
from .graph import AnchoredGraph
from .kernels import matrix


def neighbour_mean(nodes: DataFrame, both: DataFrame) -> DataFrame:
    """``node_id, m``: mean over neighbours of cosine times the neighbour's vector.

    Norms are stored per node, so an edge costs one dot product; sums are partial before the
    exchange, so what is shuffled to ``src`` is a vector per node and task, not one per edge.
    """
    x = nodes.select("node_id", "x", V.norm("x").alias("nx"))
    far = x.select(F.col("node_id").alias("dst"), F.col("x").alias("xu"), F.col("nx").alias("nu"))
    near = x.select(F.col("node_id").alias("src"), F.col("x").alias("xv"), F.col("nx").alias("nv"))
    msg = both.join(far, "dst").join(near, "src")
    n = F.col("nu") * F.col("nv")
    cos = F.when(n > 0, V.dot("xu", "xv") / n).otherwise(F.lit(0.0))
    msg = msg.select("src", V.scale("xu", cos).alias("m"))
    return msg.groupBy(F.col("src").alias("node_id")).agg(vector_to_array(Summarizer.mean(array_to_vector("m"))).alias("m"))


#: Edges that a bucket's kernel works on at a time.
EDGE_CHUNK = 100_000
#: Numbers that a bucket receives on average, at most (256 MB of doubles).
BUCKET_NUMBERS = 32_000_000


def buckets_for(nodes: DataFrame, both: DataFrame) -> int:
    """Buckets that hold ``BUCKET_NUMBERS`` each even if no two edges of a bucket share a neighbour; one per shuffle partition at least."""
    width = nodes.agg(F.max(F.size("x"))).head()[0] or 1
    least = int(nodes.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return max(least, -(-both.count() * width // BUCKET_NUMBERS))


def bucket_mean(nodes: DataFrame, both: DataFrame, buckets: int | None = None, weighted: bool = True) -> DataFrame:
    """:func:`neighbour_mean` (without ``weighted`` the plain mean), and ``deg``, with one vector per neighbour *and bucket* of receivers on the wire.

    Edges are first gathered per (neighbour, bucket of the receiving node), ids only. A neighbour's
    vector then travels once to every bucket that needs it, not once per edge, and meets its
    receivers in an Arrow kernel. ``buckets`` grow with edges times dimensions unless given, so that a
    bucket's vectors fit a task. The neighbours of one receiver meet in one task: where a
    node may have millions, :func:`neighbour_mean` sums in parts.
    """
    spark = nodes.sparkSession
    ship(spark)
    b = buckets or buckets_for(nodes, both)
    bucket = lambda c: F.pmod(F.xxhash64(c), F.lit(b)).cast("int")
    lists = both.groupBy(F.col("dst").alias("node_id"), bucket("src").alias("bucket")).agg(F.collect_list("src").alias("srcs"))
    sent = lists.join(nodes.select("node_id", "x"), "node_id").select(F.col("bucket").alias("to"), F.col("x").alias("y"), "srcs")
    own = nodes.select(bucket("node_id").alias("bucket"), F.col("node_id").alias("node_id"), F.col("x").alias("x"))

    def run(key, left: pa.Table, right: pa.Table) -> pa.Table:
        ids = left.column("node_id").to_numpy()
        order = np.argsort(ids, kind="stable")
        ids, schema = ids[order], pa.schema([("node_id", pa.int64()), ("m", pa.list_(pa.float64())), ("deg", pa.int64())])
        if not len(ids) or not right.num_rows:
            return schema.empty_table()
        x, y = matrix(left.column("x"))[order], matrix(right.column("y"))
        nx, ny = np.linalg.norm(x, axis=1), np.linalg.norm(y, axis=1)
        lens = np.concatenate([c.value_lengths().to_numpy(zero_copy_only=False) for c in right.column("srcs").chunks])
        to = np.searchsorted(ids, np.concatenate([c.flatten().to_numpy(zero_copy_only=False) for c in right.column("srcs").chunks]))
        frm = np.repeat(np.arange(len(y)), lens)
        by = np.argsort(to, kind="stable")
        to, frm = to[by], frm[by]
        total, deg = np.zeros_like(x), np.bincount(to, minlength=len(ids))
        for at in range(0, len(to), EDGE_CHUNK):
            i, j = to[at : at + EDGE_CHUNK], frm[at : at + EDGE_CHUNK]
            if weighted:
                n = nx[i] * ny[j]
                cos = np.divide(np.einsum("ij,ij->i", x[i], y[j]), n, out=np.zeros(len(i)), where=n > 0)
            else:
                cos = np.ones(len(i))
            first = np.flatnonzero(np.concatenate(([True], i[1:] != i[:-1])))
            total[i[first]] += np.add.reduceat(cos[:, None] * y[j], first, axis=0)
        has = np.flatnonzero(deg)
        m = (total[has] / deg[has, None]).ravel()
        return pa.Table.from_arrays([pa.array(ids[has]), pa.ListArray.from_arrays(np.arange(0, len(m) + 1, x.shape[1], dtype=np.int32), pa.array(m)), pa.array(deg[has].astype(np.int64))], schema=schema)

    return own.groupBy("bucket").cogroup(sent.groupBy("to")).applyInArrow(run, "node_id long, m array<double>, deg long")


def refine_once(nodes: DataFrame, both: DataFrame | None, alpha: float, engine: str = "sql", mean=None, beside=None) -> DataFrame:
    """One round: ``alpha`` of the own vector and the rest of the neighbours' mean; without neighbours that part is 0.

    ``sql`` stays in the JVM and moves a vector per edge; ``bucket`` moves one per neighbour and bucket.
    ``mean`` of an implicit graph needs no edges, ``beside`` no join either.
    """
    m = None if beside else mean(nodes, True) if mean else neighbour_mean(nodes, both) if engine == "sql" else bucket_mean(nodes, both)
    keep = [c for c in nodes.columns if c != "x"]
    mixed = F.when(F.col("m").isNull(), V.scale("x", F.lit(float(alpha)))).otherwise(
        F.zip_with("x", "m", lambda a, b: a * F.lit(float(alpha)) + b * F.lit(1.0 - alpha))
    )
    return (beside(nodes) if beside else nodes.join(m, "node_id", "left")).select(*keep, mixed.alias("x"))


def signatures(graph: AnchoredGraph, alpha: float = 0.5, hops: int = 2, normalize: bool = True, engine: str = "bucket") -> DataFrame:
    """``graph.nodes`` with ``sig``: the sum of the vectors of rounds 0 to ``hops``, at unit length unless told otherwise.

    Every round is cut to the shared folder; the running sum rides along, so each round is one plan.
    """
    mean = getattr(graph, "mean", None) if engine == "bucket" else None
    beside = getattr(graph, "beside", None) if mean else None
    both = None if mean else cut(graph.both_ways(), "edges")
    now, before = graph.nodes.withColumn("total", F.col("x")), []
    for _ in range(hops):
        with noted() as stored:
            now = refine_once(now, both, alpha, engine, mean, beside)
            path, now = store(now.withColumn("total", V.add("total", "x")), "round")
        free_shuffles(now.sparkSession)
        drop(now.sparkSession, [*before, *(p for p in stored if p != path)])  # the last round, and what this one was made from
        before = [path]
    sig = V.unit(F.col("total")) if normalize else F.col("total")
    return now.withColumn("norm", V.norm("total")).withColumn("sig", sig).drop("x", "total")


def sim(a, b) -> Column:
    """Anchored similarity of two signatures that are already at unit length."""
    return V.dot(a, b)
