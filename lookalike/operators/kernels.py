"""Arrow kernels: blocks of vectors meet in numpy, never rows in Python."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import ship, store

#: Rows of a small block, and numbers of a large one (64 MB of doubles).
BLOCK, BLOCK_NUMBERS = 4096, 8_000_000
#: Groups that a grid should have before its blocks grow, and rows of a grid that may be broadcast.
GRID, GRID_ROWS = 64, 100_000

FOUND = T.StructType([T.StructField("v", T.LongType()), T.StructField("u", T.LongType()), T.StructField("sim", T.DoubleType())])


def groups_in_order(batches: Iterator[pa.RecordBatch], key: int = 0) -> Iterator[pa.Table]:
    """Runs of equal integer keys from batches that arrive sorted by that column, a run in memory at a time."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        if not b.num_rows:
            continue
        k = b.column(key).to_numpy(zero_copy_only=False)
        if held and held[0].column(key)[0].as_py() != k[0]:
            yield pa.Table.from_batches(held)
            held = []
        at = 0
        for e in (np.flatnonzero(k[1:] != k[:-1]) + 1).tolist():
            held.append(b.slice(at, e - at))
            yield pa.Table.from_batches(held)
            held, at = [], e
        held.append(b.slice(at))
    if held:
        yield pa.Table.from_batches(held)


def matrix(column: pa.ChunkedArray) -> np.ndarray:
    """A list column of equal lengths as an n x d array without a Python object per number."""
    flat = np.concatenate([c.flatten().to_numpy(zero_copy_only=False) for c in column.chunks]) if column.num_chunks else np.zeros(0)
    return flat.reshape(len(column), -1)


def topk_rows(s: np.ndarray, ids_v: np.ndarray, ids_u: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The best ``k`` of each row of a masked (-inf) score matrix, ties by the smaller ``u``."""
    order = np.argsort(ids_u, kind="stable")
    s, ids_u = s[:, order], ids_u[order]
    k = min(k, s.shape[1])
    if k < s.shape[1]:  # all that equal the k-th best stay, so ties are cut by id and not by place
        floor = np.partition(s, s.shape[1] - k, axis=1)[:, s.shape[1] - k]
    else:
        floor = np.full(len(s), -np.inf)
    i, j = np.nonzero((s >= floor[:, None]) & np.isfinite(s))
    sim = s[i, j]
    best = np.lexsort((j, -sim, i))
    i, j, sim = i[best], j[best], sim[best]
    place = np.arange(len(i)) - np.searchsorted(i, i)
    keep = place < k
    return ids_v[i[keep]], ids_u[j[keep]], sim[keep]


def blocks_of(rows, dim, block: int | None = None):
    """How many blocks ``rows`` vectors of ``dim`` numbers are dealt to.

    A vector travels once per block of the other side, so blocks are as large as 64 MB allows; as
    long as a grid of them would leave cores idle they are smaller. ``block`` fixes the rows.
    """
    if block:
        return F.ceil(rows / block).cast("int")
    large = F.ceil(rows * dim / BLOCK_NUMBERS)
    return F.greatest(large, F.least(F.ceil(rows / BLOCK), F.lit(math.isqrt(GRID)))).cast("int")


def blocked_topk(queries: DataFrame, members: DataFrame, k: int, block: int | None = None) -> DataFrame:
    """``v, u, sim``: for each query and block of members of its ``cell``, the best ``k`` of another verdict.

    Both have ``cell, node_id, verdict, sig``. Cells are counted first; a cell of several blocks on
    either side becomes a grid of block pairs, each its own group, so no cell is gathered in one
    task. Inside a group the rows lie by verdict, and products of one verdict with itself
    are left out, as its rows cannot be twins. Merge the lists with ``scan.merge_topk``.

    A vector travels once per block of the other side. Where that is more than to store the members
    once, and tasks can read them, they are stored by cell and :func:`stored_topk` meets them block by block.
    """
    ship(members.sparkSession)
    dim = F.coalesce(F.max(F.size("sig")), F.lit(1))
    nq = queries.groupBy("cell").agg(blocks_of(F.count("*"), dim, block).alias("nq"), F.count("*").alias("cq"))
    nm = members.groupBy("cell").agg(blocks_of(F.count("*"), dim, block).alias("nm"), F.count("*").alias("cm"))
    at, grid = store(nq.join(nm, "cell"), "grid")  # a row per cell
    travel, once = grid.agg(F.sum(F.col("cq") * F.col("nm") + F.col("cm") * F.col("nq")), F.sum(F.col("cq") + 2 * F.col("cm"))).head()
    if (travel or 0) > (once or 0) and tasks_can_read(at):
        laid = lambda df: df.select("cell", "node_id", "verdict", "sig").filter("verdict is not null and cell is not null").repartitionByRange("cell", "verdict", "node_id")
        path, _ = store(laid(members), "cells")
        return stored_topk(laid(queries), path, k, block or BLOCK, by_cell=True)
    grid = grid.select("cell", "nq", "nm")
    if grid.limit(GRID_ROWS + 1).count() <= GRID_ROWS:
        grid = F.broadcast(grid)
    salt = F.xxhash64("node_id")

    def dealt(df: DataFrame, own: str, other: str, role: int) -> DataFrame:
        r = df.filter("verdict is not null").join(grid, "cell").withColumn("own", F.pmod(salt, F.col(own)).cast("int"))
        r = r.withColumn("other", F.explode(F.sequence(F.lit(0), F.col(other) - 1)))
        i, j = ("own", "other") if role == 0 else ("other", "own")
        return r.select(F.xxhash64("cell", i, j).alias("grp"), F.lit(role).alias("role"), "node_id", "verdict", "sig")

    rows = dealt(queries, "nq", "nm", 0).union(dealt(members, "nm", "nq", 1)).repartition("grp").sortWithinPartitions("grp", "role", "verdict", "node_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in groups_in_order(batches):
            role, ids, verdict = (t.column(c).to_numpy() for c in (1, 2, 3))
            x = matrix(t.column(4))
            n = int((role == 0).sum())
            if not n or n == len(ids):
                continue
            far_ids, far_verdict, far = ids[n:], verdict[n:], x[n:]
            cuts = np.flatnonzero(verdict[1:n] != verdict[: n - 1]) + 1
            for lo, hi in zip(np.r_[0, cuts], np.r_[cuts, n], strict=True):  # queries of one verdict
                other = far_verdict != verdict[lo]
                if not other.any():
                    continue
                there, u_ids = far[other], far_ids[other]
                for at in range(lo, hi, 512):
                    stop = min(hi, at + 512)
                    s = np.round(x[at:stop] @ there.T, 9)
                    s[ids[at:stop, None] == u_ids[None, :]] = -np.inf
                    v, u, sim = topk_rows(s, ids[at:stop], u_ids, k)
                    if len(v):
                        yield pa.RecordBatch.from_arrays([pa.array(v), pa.array(u), pa.array(sim)], names=FOUND.names)

    return rows.mapInArrow(run, FOUND)


def tasks_can_read(path: str) -> bool:
    """Whether Arrow reaches the store that ``path`` is in, as Spark does."""
    from pyarrow import fs

    try:
        files, at = fs.FileSystem.from_uri(path)
        return files.get_file_info(at).type == fs.FileType.Directory
    except (OSError, pa.ArrowException):
        return False


def stored_blocks(path: str, columns: list[str], rows: int = BLOCK, within: tuple[str, int, int] | None = None) -> Iterator[pa.RecordBatch]:
    """The Parquet files of a folder in the shared store, at most ``rows`` rows at a time; ``within`` names a column and its least and largest value."""
    import pyarrow.dataset as ds
    from pyarrow import fs

    files, at = fs.FileSystem.from_uri(path)
    found = ds.dataset(at, filesystem=files, format="parquet")
    only = None if within is None else (ds.field(within[0]) >= within[1]) & (ds.field(within[0]) <= within[2])
    for b in found.to_batches(columns=columns, filter=only, batch_size=rows, use_threads=False, batch_readahead=1, fragment_readahead=1):
        if b.num_rows:
            yield b


def keep_best(s: np.ndarray, ids_v: np.ndarray, ids_u: np.ndarray, u: np.ndarray, sim: np.ndarray) -> None:
    """Take the scores ``s`` of ``ids_u`` into the lists ``u, sim`` of each row's best so far, in place.

    Only scores that can still enter a list are rounded and sorted, which are few after the first block.
    """
    k = sim.shape[1]
    if np.isin(ids_v, ids_u).any():
        s[ids_v[:, None] == ids_u[None, :]] = -np.inf
    floor = sim[:, -1].copy()
    short = np.flatnonzero(np.isneginf(floor))
    if len(short) and s.shape[1] > k:
        floor[short] = np.partition(s[short], s.shape[1] - k, axis=1)[:, s.shape[1] - k]
    i, j = np.nonzero(s >= (floor - 1e-9)[:, None])
    score = np.round(s[i, j], 9)
    real = np.isfinite(score)
    i, j, score = i[real], j[real], score[real]
    if not len(i):
        return
    rows = np.unique(i)
    r, c = np.nonzero(np.isfinite(sim[rows]))
    r = rows[r]
    at, them, got = np.r_[r, i], np.r_[u[r, c], ids_u[j]], np.r_[sim[r, c], score]
    order = np.lexsort((them, -got, at))
    at, them, got = at[order], them[order], got[order]
    place = np.arange(len(at)) - np.searchsorted(at, at)
    at, them, got, place = (a[place < k] for a in (at, them, got, place))
    u[at, place], sim[at, place] = them, got


def stored_topk(queries: DataFrame, path: str, k: int, block: int = BLOCK, by_cell: bool = False) -> DataFrame:
    """``v, u, sim``: the best ``k`` of another verdict of each query, of all rows (node_id, verdict, sig) stored in ``path``.

    A task reads the stored rows block by block from the shared folder and holds ``k`` rows a query. No
    vector is shuffled, so disk grows with the rows, not with rows times blocks. ``by_cell``: both have
    a ``cell``, and rows of one cell meet; a batch reads from its least cell to its largest, so cells should lie together.
    """
    ship(queries.sparkSession)
    columns = ["node_id", "verdict", "sig", *["cell"] * by_cell]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            verdict = b.column(1).to_numpy(zero_copy_only=False)
            cell = b.column(3).to_numpy(zero_copy_only=False) if by_cell else np.zeros(b.num_rows, np.int64)
            order = np.lexsort((verdict, cell))
            cell = cell[order]
            ids, verdict, x = b.column(0).to_numpy(zero_copy_only=False)[order], verdict[order], matrix(pa.chunked_array([b.column(2)]))[order]
            n = len(ids)
            u, sim = np.zeros((n, k), np.int64), np.full((n, k), -np.inf)
            cuts = np.flatnonzero((verdict[1:] != verdict[:-1]) | (cell[1:] != cell[:-1])) + 1
            for t in stored_blocks(path, columns, block, ("cell", int(cell[0]), int(cell[-1])) if by_cell else None):
                far_ids, far_verdict, far = t.column(0).to_numpy(zero_copy_only=False), t.column(1).to_numpy(zero_copy_only=False), matrix(pa.chunked_array([t.column(2)]))
                finite = np.isfinite(far).all(1)
                for lo, hi in zip(np.r_[0, cuts], np.r_[cuts, n], strict=True):  # queries of one verdict, and cell
                    other = (far_verdict != verdict[lo]) & finite
                    if by_cell:
                        other &= t.column(3).to_numpy(zero_copy_only=False) == cell[lo]
                    if not other.any():
                        continue
                    there, there_ids = far[other], far_ids[other]
                    for at in range(lo, hi, 512):
                        i = slice(at, min(hi, at + 512))
                        keep_best(x[i] @ there.T, ids[i], there_ids, u[i], sim[i])
            has, place = np.nonzero(np.isfinite(sim))
            if len(has):
                yield pa.RecordBatch.from_arrays([pa.array(ids[has]), pa.array(u[has, place]), pa.array(sim[has, place])], names=FOUND.names)

    return queries.select(*columns).mapInArrow(run, FOUND)


PAIRS = T.StructType([T.StructField("a", T.LongType()), T.StructField("b", T.LongType()), T.StructField("sim", T.DoubleType())])


def blocked_pairs(rows: DataFrame, least: float, strict: bool = False, block: int | None = None) -> DataFrame:
    """``a, b, sim`` with a < b: pairs of ``rows`` (node_id, verdict, sig) whose dot product, rounded to nine digits, reaches ``least``.

    Pairs of equal verdicts are left out; where verdicts are null no pair is. Rows are dealt to
    blocks by hash, every pair of blocks is one group, and the upper half of the grid is enough.
    """
    ship(rows.sparkSession)
    nb = F.greatest(blocks_of(F.count("*"), F.coalesce(F.max(F.size("sig")), F.lit(1)), block), F.lit(1))
    r = rows.select("node_id", F.col("verdict").cast("int").alias("verdict"), "sig").crossJoin(F.broadcast(rows.agg(nb.alias("nb"))))  # one row
    r = r.withColumn("own", F.pmod(F.xxhash64("node_id"), F.col("nb")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("nb") - 1)))
    r = r.select(F.xxhash64(F.least("own", "other"), F.greatest("own", "other")).alias("grp"), "own", "node_id", "verdict", "sig")
    dealt = r.repartition("grp").sortWithinPartitions("grp", "own", "node_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in groups_in_order(batches):
            own, ids = t.column(1).to_numpy(), t.column(2).to_numpy()
            verdict = t.column(3).fill_null(-(1 << 31)).to_numpy()
            x = matrix(t.column(4))
            n = int((own == own[0]).sum())
            left, right = (np.arange(n),) * 2 if n == len(own) else (np.arange(n), np.arange(n, len(own)))
            for at in range(0, n, 512):
                i = left[at : at + 512]
                s = np.round(x[i] @ x[right].T, 9)
                ok = (s > least) if strict else (s >= least)
                ok &= (verdict[i, None] != verdict[None, right]) | (verdict[i, None] == -(1 << 31))
                if n == len(own):
                    ok &= i[:, None] < right[None, :]
                p, q = np.nonzero(ok)
                if len(p):
                    u, v = ids[i[p]], ids[right[q]]
                    yield pa.RecordBatch.from_arrays([pa.array(np.minimum(u, v)), pa.array(np.maximum(u, v)), pa.array(s[p, q])], names=PAIRS.names)

    return dealt.mapInArrow(run, PAIRS)


def matmul(df: DataFrame, weights: np.ndarray, vec_col: str = "x", bias: np.ndarray | None = None, activation: str | None = None) -> DataFrame:
    """``df`` with ``vec_col`` times ``weights`` (d x h, shipped once per task in the closure), batch by batch."""
    ship(df.sparkSession)
    at = df.columns.index(vec_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            y = matrix(pa.chunked_array([b.column(at)])) @ weights
            if bias is not None:
                y = y + bias
            if activation == "relu":
                y = np.maximum(y, 0.0)
            rows = pa.ListArray.from_arrays(np.arange(0, y.size + 1, y.shape[1], dtype=np.int32), pa.array(y.ravel()))
            yield pa.RecordBatch.from_arrays([rows if i == at else b.column(i) for i in range(b.num_columns)], names=b.schema.names)

    schema = T.StructType([T.StructField(f.name, T.ArrayType(T.DoubleType()) if f.name == vec_col else f.dataType) for f in df.schema])
    return df.mapInArrow(run, schema)
