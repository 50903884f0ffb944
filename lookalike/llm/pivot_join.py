"""Near-duplicate vectors through a pivot-permutation index.

Each vector is described by its nearest reference points in order. An inverted list per label and
pivot holds the vectors that have the pivot among their nearest; inside a list, the vectors' other
pivots make lists again, which give the pairs that share at least two pivots and how many they
share. Only such pairs are verified, by cosine in double precision, and a pair is verified in the
list of the smallest pivot that both have, so it counts once. Pivots grow with the rows of a
label, so a vector meets about as many candidates in a large table as in a small one. Equal
vectors travel as one with a count.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, name_components, ship, sorted_groups

#: Fewest reference points, and the rows of one label that they are meant for.
PIVOTS, PIVOT_ROWS = 256, 1000
#: Nearest pivots kept (two more for each fourfold number of pivots above 1,024), and common ones that make a candidate.
NEAREST, SHARED = 8, 2
#: Rows of a block of an inverted list; a longer list becomes one task's group per pair of blocks.
BLOCK = 1024
#: Lists up to this many have their sizes broadcast.
SMALL_COUNTS = 200_000


def pivots(dim: int, n: int = PIVOTS) -> np.ndarray:
    """``n`` unit vectors from a fixed seed: they depend on nothing in the data."""
    p = np.random.default_rng(20240229).standard_normal((n, dim))
    return p / np.linalg.norm(p, axis=1, keepdims=True)


def plan_pivots(rows: int) -> tuple[int, int]:
    """Number of pivots and of nearest ones for the largest label's ``rows``.

    The share of unlike pairs with two pivots in common falls a little faster than the number of
    pivots to the power 1.7, so a power of 0.6 keeps a vector's candidates level.
    """
    n = max(PIVOTS, 64 * math.ceil(PIVOTS * (max(rows, 1) / PIVOT_ROWS) ** 0.6 / 64))
    return n, NEAREST + 2 * max(0, math.ceil(math.log(n / 1024, 4)))


def describe(x: np.ndarray, p: np.ndarray, nearest: int) -> np.ndarray:
    """The ordered nearest pivots of unit rows ``x``; ties by number."""
    s = np.round(x @ p.T, 12)
    if nearest >= s.shape[1]:
        return np.argsort(-s, axis=1, kind="stable").astype(np.int32)
    floor = -np.partition(-s, nearest - 1, axis=1)[:, nearest - 1]
    out = np.empty((len(x), nearest), np.int32)
    for i, (row, least) in enumerate(zip(s, floor, strict=True)):
        at = np.flatnonzero(row >= least)
        out[i] = at[np.argsort(-row[at], kind="stable")[:nearest]]
    return out


def pack(x: np.ndarray) -> list[bytes]:
    """Rows as bytes, in four bytes a number where nothing is lost."""
    with np.errstate(over="ignore"):
        short = x.astype("<f4")
    fits = (short == x).all(1)
    return [(short[i] if fits[i] else x[i].astype("<f8")).tobytes() for i in range(len(x))]


def unpack(vectors, dim: int) -> np.ndarray:
    """Unit rows in double precision of packed vectors."""
    x = np.array([np.frombuffer(v, "<f4" if len(v) == 4 * dim else "<f8") for v in vectors], np.float64).reshape(len(vectors), dim)
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


ROWS = T.StructType([T.StructField("id", T.LongType()), T.StructField("label", T.LongType()), T.StructField("dim", T.IntegerType()), T.StructField("vector", T.BinaryType())])


def packed(vectors: DataFrame, id_col: str, vec_col: str, label_col: str) -> DataFrame:
    """Every row, ``vector`` null where it cannot be compared: null, zero or not finite throughout, or without label or id."""
    ship(vectors.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, by = b.column(2).to_pylist(), {}
            for i, (d, lab, v) in enumerate(zip(b.column(0).to_pylist(), b.column(1).to_pylist(), raw, strict=True)):
                if d is not None and lab is not None and v and None not in v:
                    by.setdefault(len(v), []).append(i)
            out, dims = [None] * len(raw), [None] * len(raw)
            for dim, at in by.items():
                x = np.array([raw[i] for i in at], np.float64)
                size = np.abs(x).max(axis=1)
                ok = np.flatnonzero(np.isfinite(size) & (size > 0))
                for k, v in zip(ok, pack(x[ok]), strict=True):
                    out[at[k]], dims[at[k]] = v, dim
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(dims, pa.int32()), pa.array(out, pa.binary())], names=ROWS.names)

    rows = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(label_col).cast("long").alias("label"), F.col(vec_col).cast("array<double>").alias("v"))
    return rows.mapInArrow(run, ROWS)


LISTED = T.StructType([T.StructField("node", T.LongType()), T.StructField("label", T.LongType()), T.StructField("dim", T.IntegerType()), T.StructField("vector", T.BinaryType()), T.StructField("copies", T.LongType()), T.StructField("perm", T.ArrayType(T.IntegerType()))])


def described(reps: DataFrame, n_pivots: int, nearest: int) -> DataFrame:
    """``reps`` (node, label, dim, vector, copies) with ``perm``, the ordered nearest pivots."""
    ship(reps.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables: dict[int, np.ndarray] = {}
        for b in batches:
            dims, raw = b.column(2).to_numpy(), b.column(3).to_pylist()
            for dim in np.unique(dims).tolist():
                if dim not in tables:
                    tables[dim] = pivots(dim, n_pivots)
                at = np.flatnonzero(dims == dim)
                for s in range(0, len(at), 512):
                    some = at[s : s + 512]
                    perm = describe(unpack([raw[i] for i in some], dim), tables[dim], min(nearest, n_pivots))
                    flat = pa.ListArray.from_arrays(np.arange(0, perm.size + 1, perm.shape[1], dtype=np.int32), pa.array(perm.ravel()))
                    take = pa.array(some)
                    yield pa.RecordBatch.from_arrays([*(b.column(i).take(take) for i in range(5)), flat], names=LISTED.names)

    return reps.mapInArrow(run, LISTED)


def _met(keys_a: np.ndarray, keys_b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``(key, row of a, row of b)`` of all equal keys of two row lists (n x k): an inverted list joined with itself."""
    ka, kb = keys_a.ravel(), keys_b.ravel()
    ra, rb = np.repeat(np.arange(len(keys_a)), keys_a.shape[1]), np.repeat(np.arange(len(keys_b)), keys_b.shape[1])
    order = np.argsort(kb, kind="stable")
    kb, rb = kb[order], rb[order]
    lo, hi = np.searchsorted(kb, ka, "left"), np.searchsorted(kb, ka, "right")
    n = hi - lo
    at = np.repeat(lo - np.cumsum(n) + n, n) + np.arange(n.sum())
    return np.repeat(ka, n), np.repeat(ra, n), rb[at]


def candidates(perm: np.ndarray, a: np.ndarray, b: np.ndarray, pivot: int, shared: int, within: bool) -> tuple[np.ndarray, np.ndarray] | None:
    """Pairs of rows of one pivot's list that share ``shared`` pivots, this one being the smallest; None where so
    many pairs share that a product of all is cheaper than their lists."""
    wide = int(perm.max()) + 1
    size_a, size_b = np.bincount(perm[a].ravel(), minlength=wide), np.bincount(perm[b].ravel(), minlength=wide)
    size_a[pivot] = 0
    if shared <= 1 or int(size_a @ size_b) > len(a) * len(b):
        return None
    other = perm[a] != pivot, perm[b] != pivot  # every row has the pivot once
    q, i, j = _met(perm[a][other[0]].reshape(len(a), -1), perm[b][other[1]].reshape(len(b), -1))
    if within:
        up = a[i] < b[j]
        q, i, j = q[up], i[up], j[up]
    key, count = np.unique(i * len(b) + j, return_counts=True)
    earlier = np.unique((i * len(b) + j)[q < pivot])
    key = key[(count >= shared - 1) & ~np.isin(key, earlier, assume_unique=True)]
    return a[key // len(b)], b[key % len(b)]


def dense(perm: np.ndarray, x: np.ndarray, a: np.ndarray, b: np.ndarray, pivot: int, shared: int, within: bool, similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """The same pairs, verified, by products of whole blocks: for lists of vectors that are mostly alike."""
    names, place = np.unique(perm, return_inverse=True)
    mark = np.zeros((len(perm), len(names)), np.float32)
    np.put_along_axis(mark, place.reshape(perm.shape), 1, axis=1)
    first = int(np.searchsorted(names, pivot))
    left, right = [], []
    for s in range(0, len(a), 256):
        some = a[s : s + 256]
        ok = (x[some] @ x[b].T >= similarity) & (mark[some] @ mark[b].T >= shared)
        if first:
            ok &= mark[some, :first] @ mark[b, :first].T == 0
        if within:
            ok &= some[:, None] < b[None, :]
        i, j = np.nonzero(ok)
        left.append(some[i])
        right.append(b[j])
    return np.concatenate(left), np.concatenate(right)


def joined(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """The smallest row that each of ``n`` rows reaches over the pairs."""
    root = np.arange(n)
    while True:
        low = np.minimum(root[i], root[j])
        nxt = root.copy()
        np.minimum.at(nxt, i, low)
        np.minimum.at(nxt, j, low)
        nxt = nxt[nxt]
        if (nxt == root).all():
            return root
        root = nxt


FOUND = T.StructType([T.StructField("node", T.LongType()), T.StructField("links", T.LongType()), T.StructField("centre", T.LongType())])


def verified(listed: DataFrame, similarity: float, shared: int) -> DataFrame:
    """``node, links, centre``: per inverted list, how many vectors each one links with there, and a star edge that keeps it connected."""
    posted = listed.withColumn("pivot", F.explode("perm"))
    counts = cut(posted.groupBy("label", "dim", "pivot").agg(F.count("*").alias("members")).filter("members > 1"), "counts")
    if counts.limit(SMALL_COUNTS + 1).count() <= SMALL_COUNTS:  # a row per list, not per vector
        counts = F.broadcast(counts)
    nb = F.ceil(F.col("members") / BLOCK).cast("int")
    rows = posted.join(counts, ["label", "dim", "pivot"]).withColumn("nb", nb).withColumn("own", F.pmod(F.xxhash64("node"), F.col("nb")).cast("int"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("nb") - 1)))
    grp = F.xxhash64("label", "dim", "pivot", F.least("own", "other"), F.greatest("own", "other"))
    rows = rows.select(grp.alias("grp"), "node", "pivot", "dim", "copies", "vector", "perm", (F.col("own") <= F.col("other")).alias("left"), (F.col("own") >= F.col("other")).alias("right"))
    dealt = rows.repartition("grp").sortWithinPartitions("grp")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in sorted_groups(batches):
            ids, pivot, dim, copies = t.column(1).to_numpy(), t.column(2)[0].as_py(), t.column(3)[0].as_py(), t.column(4).to_numpy()
            perm = t.column(6).combine_chunks().flatten().to_numpy().reshape(len(ids), -1)
            side = t.column(7).to_numpy(), t.column(8).to_numpy()
            within = bool((side[0] & side[1]).all())
            a, b = (np.arange(len(ids)),) * 2 if within else (np.flatnonzero(side[0]), np.flatnonzero(side[1]))
            pairs = candidates(perm, a, b, pivot, shared, within)
            if pairs is None:
                i, j = dense(perm, unpack(t.column(5).to_pylist(), dim), a, b, pivot, shared, within, similarity)
            else:
                i, j = pairs
                if not len(i):
                    continue
                used, place = np.unique(np.concatenate((i, j)), return_inverse=True)
                x = unpack([t.column(5)[k].as_py() for k in used.tolist()], dim)
                p, q = place[: len(i)], place[len(i) :]
                close = np.concatenate([np.einsum("ij,ij->i", x[p[s : s + 65536]], x[q[s : s + 65536]]) for s in range(0, len(i), 65536)]) >= similarity
                i, j = i[close], j[close]
            if len(i):
                n = len(ids)
                links = (np.bincount(i, copies[j], n) + np.bincount(j, copies[i], n)).astype(np.int64)
                keep, root = np.flatnonzero(links), joined(n, i, j)
                yield pa.RecordBatch.from_arrays([pa.array(ids[keep]), pa.array(links[keep]), pa.array(ids[root[keep]])], names=FOUND.names)

    return dealt.mapInArrow(run, FOUND)


def near_duplicates(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", label_col: str = "label", similarity: float = 0.98, n_pivots: int | None = None, nearest: int | None = None, shared: int = SHARED) -> DataFrame:
    """``id_col, n_links, component_id, kept`` for every row.

    Rows of equal, non-null label and dimension are linked when their cosine in double precision
    is at least ``similarity``. A vector that is null, zero, or holds null or non-finite components
    links with nothing. A row with a null id links with nothing and has a null component. Rows that
    repeat an id keep a row, a vector and links each (also with one another), and share one
    component. An empty table gives no rows; other columns are not read. ``n_pivots`` and
    ``nearest`` follow the largest label's rows unless given.
    """
    rows = packed(vectors, id_col, vec_col, label_col).withColumn("same", F.sha2("vector", 256)).withColumn("rid", F.monotonically_increasing_id())
    rows = cut(rows, "vectors")
    can = rows.filter("vector is not null")
    classes = cut(can.groupBy("label", "dim", "same").agg(F.min("rid").alias("node"), F.count("*").alias("copies")), "classes")
    reps = can.select("label", "dim", "vector", F.col("rid").alias("node")).join(classes.select("node", "copies"), "node").select("node", "label", "dim", "vector", "copies")
    largest = classes.groupBy("label", "dim").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 0
    planned = plan_pivots(largest)
    listed = cut(described(reps, n_pivots or planned[0], nearest or planned[1]), "listed")
    found = cut(verified(listed, similarity, shared), "found")
    links = found.groupBy("node").agg(F.sum("links").alias("links"))
    linked = classes.join(links, "node", "left").select("label", "dim", "same", "node", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"))
    known = can.select("id", "label", "dim", "same").join(linked, ["label", "dim", "same"]).select("id", "node", "n_links")
    alone = rows.filter("vector is null and id is not null").select("id", F.col("rid").alias("node"), F.lit(0).cast("long").alias("n_links"))
    named = name_components(known.union(alone), found.filter("node <> centre").select(F.col("centre").alias("a"), F.col("node").alias("b")))
    nameless = rows.filter("id is null").select("id", F.lit(0).cast("long").alias("n_links"), F.lit(None).cast("long").alias("component_id"))
    return named.select("id", "n_links", "component_id").union(nameless).select(
        F.col("id").alias(id_col), F.col("n_links").cast("long").alias("n_links"), "component_id", F.coalesce(F.col("id") == F.col("component_id"), F.lit(False)).alias("kept")
    )
