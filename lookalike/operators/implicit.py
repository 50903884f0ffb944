"""Graphs whose edges follow from the nodes: neighbours are summed up without a row per edge."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.ml.stat import Summarizer
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.vectors import unit
from ..session import cut, ship, store
from . import graph as G
from .graph import AnchoredGraph
from .kernels import BLOCK, BLOCK_NUMBERS, groups_in_order, matrix, stored_blocks, tasks_can_read

#: Blocks that a small table is dealt to at most: a vector travels once per block of the other side.
FEW = 4
#: Tasks that share a group of equal keys.
SALTS = 8


class ImplicitGraph(AnchoredGraph):
    """A graph that makes its edges only when asked; ``mean(nodes, weighted)`` is what refinement needs of them.

    ``beside(nodes)``, where a graph has it, is ``nodes`` with the weighted mean beside its columns.
    ``make_edges(ids)`` gives all edges, or those between nodes of ``ids`` (node_id).
    """

    def __init__(self, nodes: DataFrame, make_edges: Callable[[DataFrame | None], DataFrame], mean: Callable[[DataFrame, bool], DataFrame], beside: Callable[[DataFrame], DataFrame] | None = None):
        self.nodes, self.mean, self.beside, self._make, self._edges, self._degrees = nodes, mean, beside, make_edges, None, None

    @property
    def edges(self) -> DataFrame:
        if self._edges is None:
            self._edges = cut(self._make(None), "edges")
        return self._edges

    def with_nodes(self, nodes: DataFrame) -> ImplicitGraph:
        return ImplicitGraph(nodes, lambda ids: self.edges if ids is None else self.among(ids), self.mean, self.beside)

    def among(self, ids: DataFrame) -> DataFrame:
        return self._make(ids)

    def degrees(self) -> DataFrame:
        """``node_id, deg`` of nodes that have neighbours."""
        if self._degrees is None:
            self._degrees = cut(self.mean(self.nodes.select("node_id", F.array(F.lit(0.0)).alias("x")), False).select("node_id", "deg"), "degrees")
        return self._degrees


def _lists(m: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(np.arange(0, m.size + 1, m.shape[1], dtype=np.int32), pa.array(np.ascontiguousarray(m).ravel()))


def _at_unit(x: np.ndarray) -> np.ndarray:
    n = np.linalg.norm(x, axis=1, keepdims=True)
    return np.divide(x, n, out=np.zeros_like(x), where=n > 0)


def _above(s: np.ndarray, tau: float) -> np.ndarray:
    """Whether ``s`` exceeds ``tau`` after rounding to nine digits; only what is close is rounded."""
    a = s > tau
    close = np.abs(s - tau) <= 2e-9
    a[close] = np.round(s[close], 9) > tau
    return a


def near_mean(base: DataFrame, nodes: DataFrame, tau: float, weighted: bool = True, block: int | None = None) -> DataFrame:
    """``node_id, m, deg`` over the neighbours whose cosine by ``base`` (``i, u`` at unit length) exceeds ``tau``.

    What :func:`similarity.bucket_mean` gives over ``graph.epsilon``'s edges. Vectors are stored once and every
    task sums over blocks that it reads from there, so disk grows with the nodes. Where only Spark reads the shared
    folder, every pair of blocks meets in a group and sends one sum per node: disk grows with nodes times blocks.
    """
    ship(nodes.sparkSession)
    path, rows = store(nodes.select("node_id", "x").join(base, F.col("node_id") == F.col("i")).select("node_id", "u", "x").repartition("node_id"), "rows")
    return _stored_mean(rows, path, tau, weighted, block or BLOCK) if tasks_can_read(path) else _dealt_mean(rows, tau, weighted, block)


def _stored_mean(rows: DataFrame, path: str, tau: float, weighted: bool, block: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            ids, u, x = b.column(0).to_numpy(), matrix(pa.chunked_array([b.column(1)])), matrix(pa.chunked_array([b.column(2)]))
            c = _at_unit(x) if weighted else None
            total, deg = np.zeros_like(x), np.zeros(len(ids), np.int64)
            for t in stored_blocks(path, ["node_id", "u", "x"], block):
                far_ids, far_u, far = t.column(0).to_numpy(), matrix(pa.chunked_array([t.column(1)])), matrix(pa.chunked_array([t.column(2)]))
                far_c = _at_unit(far) if weighted else None
                same = weighted and np.allclose(c, u, rtol=0, atol=1e-14) and np.allclose(far_c, far_u, rtol=0, atol=1e-14)  # as in the first round
                for at in range(0, len(ids), 512):
                    i = slice(at, at + 512)
                    s = u[i] @ far_u.T
                    a = _above(s, tau)
                    if np.isin(ids[i], far_ids).any():
                        a &= ids[i, None] != far_ids[None, :]
                    w = np.where(a, (s if same else c[i] @ far_c.T) if weighted else 1.0, 0.0)
                    total[i] += w @ far
                    deg[i] += np.count_nonzero(a, axis=1)
            has = np.flatnonzero(deg)
            if len(has):
                yield pa.RecordBatch.from_arrays([pa.array(ids[has]), _lists(total[has] / deg[has, None]), pa.array(deg[has])], names=["node_id", "m", "deg"])

    return rows.mapInArrow(run, "node_id long, m array<double>, deg long")


def _dealt_mean(rows: DataFrame, tau: float, weighted: bool, block: int | None) -> DataFrame:
    n, dim = rows.agg(F.count("*"), F.max(F.size("x"))).first()
    nb = max(1, -(-n // block) if block else max(-(-2 * n * (dim or 1) // BLOCK_NUMBERS), min(-(-n // BLOCK), FEW)))
    r = rows.withColumn("own", F.pmod(F.xxhash64("node_id"), F.lit(nb)).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(nb - 1))))
    r = r.select((F.least("own", "other") * nb + F.greatest("own", "other")).cast("long").alias("grp"), "own", "node_id", "u", "x")
    dealt = r.repartition("grp").sortWithinPartitions("grp", "own", "node_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in groups_in_order(batches):
            own, ids = t.column(1).to_numpy(), t.column(2).to_numpy()
            u, x = matrix(t.column(3)), matrix(t.column(4))
            c = _at_unit(x) if weighted else None
            first = int((own == own[0]).sum())
            right = slice(0, first) if first == len(own) else slice(first, len(own))
            total, deg = np.zeros_like(x), np.zeros(len(ids), np.int64)
            for at in range(0, first, 512):
                i = slice(at, min(first, at + 512))
                a = _above(u[i] @ u[right].T, tau)
                a &= ids[i, None] != ids[None, right]
                w = np.where(a, c[i] @ c[right].T, 0.0) if weighted else a.astype(np.float64)
                total[i] += w @ x[right]
                deg[i] += a.sum(1)
                if right.start:
                    total[right] += w.T @ x[i]
                    deg[right] += a.sum(0)
            has = np.flatnonzero(deg)
            if len(has):
                yield pa.RecordBatch.from_arrays([pa.array(ids[has]), _lists(total[has]), pa.array(deg[has])], names=["node_id", "total", "deg"])

    sums = dealt.mapInArrow(run, "node_id long, total array<double>, deg long")
    return _mean_of(sums.groupBy("node_id").agg(vector_to_array(Summarizer.sum(array_to_vector("total"))).alias("total"), F.sum("deg").alias("deg")))


def _mean_of(sums: DataFrame) -> DataFrame:
    return sums.select("node_id", F.zip_with("total", F.array_repeat(F.col("deg").cast("double"), F.size("total")), lambda v, n: v / n).alias("m"), "deg")


def clique_mean(keyed: DataFrame, nodes: DataFrame, weighted: bool = True) -> DataFrame:
    """``node_id, m, deg`` where all nodes of one ``key`` are neighbours; ``keyed`` is ``i, key``, an id once."""
    return clique_beside(keyed, nodes.select("node_id", "x"), weighted).filter("deg is not null").select("node_id", "m", "deg")


def clique_beside(keyed: DataFrame, nodes: DataFrame, weighted: bool = True) -> DataFrame:
    """``nodes`` with ``m, deg`` beside their columns, null without neighbours, so that no vector is joined afterwards.

    A neighbour's vector x counts cosine times x, which is x (x / |x|)' applied to the own unit
    vector. So the sum over a group is one matrix, made in one pass, less the node's own part: exact, and linear
    in the nodes. A group costs its dimensions squared, so groups should be few or large.
    """
    ship(nodes.sparkSession)
    held_by = nodes.join(keyed, F.col("node_id") == F.col("i"), "left").select("key", "x", *[c for c in nodes.columns if c != "x"])
    rows = held_by.filter("key is not null").select("key", "node_id", "x")

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, list] = {}

        def out():
            keys = list(held)
            return pa.RecordBatch.from_arrays([pa.array(keys), _lists(np.array([held[k][0].ravel() for k in keys])), pa.array([held[k][1] for k in keys], pa.int64())], names=["key", "part", "n"])

        for b in batches:
            if not b.num_rows:
                continue
            keys, at = np.unique(b.column(0).to_numpy(zero_copy_only=False).astype(str), return_inverse=True)
            x = matrix(pa.chunked_array([b.column(2)]))
            for k, key in enumerate(keys.tolist()):
                own = x[at == k]
                part = own.T @ _at_unit(own) if weighted else own.sum(0)
                if key in held:
                    held[key] = [held[key][0] + part, held[key][1] + len(own)]
                else:
                    held[key] = [part, len(own)]
            if sum(v[0].size for v in held.values()) > BLOCK_NUMBERS:
                yield out()
                held.clear()
        if held:
            yield out()

    parts = rows.mapInArrow(sums, "key string, part array<double>, n long")
    path, whole = store(parts.groupBy("key").agg(vector_to_array(Summarizer.sum(array_to_vector("part"))).alias("part"), F.sum("n").alias("n")).filter("n > 1"), "groups")
    numbers = whole.agg(F.coalesce(F.sum(F.size("part")), F.lit(0))).head()[0]
    if numbers <= BLOCK_NUMBERS and tasks_can_read(path):
        return _stored_groups(held_by, path, weighted)
    return nodes.join(_dealt_groups(rows, whole, weighted), "node_id", "left")


def _of_group(x: np.ndarray, part: np.ndarray, n: int, weighted: bool) -> np.ndarray:
    """The neighbours' mean of each row of one group, whose sums are ``part`` over ``n`` nodes."""
    if not weighted:
        return (part - x) / (n - 1)
    u = _at_unit(x)
    return (u @ part.reshape(x.shape[1], -1).T - x * (u * u).sum(1, keepdims=True)) / (n - 1)


def _stored_groups(rows: DataFrame, path: str, weighted: bool) -> DataFrame:
    """Every task reads the sums of all groups from the shared folder; no vector is shuffled."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = {}
        for t in stored_blocks(path, ["key", "part", "n"]):
            parts = matrix(pa.chunked_array([t.column(1)]))
            held.update((k, (parts[i], n)) for i, (k, n) in enumerate(zip(t.column(0).to_pylist(), t.column(2).to_pylist(), strict=True)))
        for b in batches:
            if not b.num_rows:
                continue
            codes = b.column(0).dictionary_encode()
            names, at = codes.dictionary.to_pylist(), codes.indices.fill_null(-1).to_numpy(zero_copy_only=False)
            x = matrix(pa.chunked_array([b.column(1)]))
            m, deg = np.zeros_like(x), np.zeros(len(x), np.int64)
            for k, key in enumerate(names):
                if key in held:
                    own, (part, n) = at == k, held[key]
                    m[own], deg[own] = _of_group(x[own], part, n, weighted), n - 1
            alone = deg == 0
            lists = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(~alone) * m.shape[1]].astype(np.int32), mask=np.r_[alone, False]), pa.array(m[~alone].ravel()))
            yield pa.RecordBatch.from_arrays([*b.columns[1:], lists, pa.array(deg, mask=alone)], schema=pa.schema([*list(b.schema)[1:], ("m", lists.type), ("deg", pa.int64())]))

    schema = T.StructType([*rows.schema.fields[1:], T.StructField("m", T.ArrayType(T.DoubleType())), T.StructField("deg", T.LongType())])
    return rows.mapInArrow(run, schema)


def _dealt_groups(rows: DataFrame, whole: DataFrame, weighted: bool) -> DataFrame:
    whole = whole.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    rows = rows.withColumn("salt", F.pmod(F.xxhash64("node_id"), F.lit(SALTS)).cast("int"))

    def apply(key, left: pa.Table, right: pa.Table) -> pa.Table:
        schema = pa.schema([("node_id", pa.int64()), ("m", pa.list_(pa.float64())), ("deg", pa.int64())])
        if not left.num_rows or not right.num_rows:
            return schema.empty_table()
        x, n = matrix(left.column("x")), right.column("n")[0].as_py()
        m = _of_group(x, matrix(right.column("part"))[0], n, weighted)
        return pa.Table.from_arrays([pa.concat_arrays(left.column("node_id").chunks), _lists(m), pa.array(np.full(len(x), n - 1))], schema=schema)

    return rows.groupBy("key", "salt").cogroup(whole.groupBy("key", "salt")).applyInArrow(apply, "node_id long, m array<double>, deg long")


def near_around(base: DataFrame, ids: DataFrame, tau: float) -> DataFrame | None:
    """``seed, node_id``: nodes near to each node of ``ids``, whose vectors every task reads; None where tasks cannot."""
    ship(base.sparkSession)
    path, _ = store(base.join(ids.select(F.col("node_id").alias("i")), "i", "left_semi").select("i", "u"), "asked")
    if not tasks_can_read(path):
        return None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            own, u = b.column(0).to_numpy(), matrix(pa.chunked_array([b.column(1)]))
            for t in stored_blocks(path, ["i", "u"], 512):
                seeds, far = t.column(0).to_numpy(), matrix(pa.chunked_array([t.column(1)]))
                i, j = np.nonzero(_above(u @ far.T, tau) & (own[:, None] != seeds[None, :]))
                if len(i):
                    yield pa.RecordBatch.from_arrays([pa.array(seeds[j]), pa.array(own[i])], names=["seed", "node_id"])

    return base.select("i", "u").mapInArrow(run, "seed long, node_id long")


class NearGraph(ImplicitGraph):
    """Nodes near in ``base`` (``i, u`` at unit length) are neighbours."""

    base, tau = None, 0.0

    def around(self, ids: DataFrame) -> DataFrame:
        found = near_around(self.base, ids, self.tau)
        return super().around(ids) if found is None else found


def near_graph(nodes: DataFrame, tau: float) -> ImplicitGraph:
    """The graph of ``graph.epsilon`` over the vectors ``x`` of ``nodes``."""
    base = cut(nodes.select(F.col("node_id").alias("i"), unit(F.col("x")).alias("u")), "unit")
    some = lambda ids: nodes if ids is None else nodes.join(ids.select("node_id"), "node_id", "left_semi")
    g = NearGraph(nodes, lambda ids: G.epsilon(some(ids), tau), lambda now, weighted: near_mean(base, now, tau, weighted))
    g.base, g.tau = base, tau
    return g


def key_graph(nodes: DataFrame, rows: DataFrame, item: str, keys: list[str]) -> AnchoredGraph:
    """The graph of ``graph.shared_key``; where an id has several rows its edges are made after all."""
    full = rows.dropna(subset=[item, *keys])
    keyed = full.select(F.col(item).alias("i"), F.to_json(F.struct(*keys)).alias("key"))
    if not keyed.groupBy("i").count().filter("count > 1").isEmpty():
        return AnchoredGraph(nodes, cut(G.shared_key(rows, item, keys), "edges"))
    keyed = cut(keyed, "keys")
    some = lambda ids: rows if ids is None else rows.join(ids.select(F.col("node_id").alias(item)), item, "left_semi")
    return ImplicitGraph(nodes, lambda ids: G.shared_key(some(ids), item, keys), lambda now, weighted: clique_mean(keyed, now, weighted), lambda now: clique_beside(keyed, now))
