"""Packing by concatenate and cut: prefix sums give every document its place in one id stream.

Pass 1 encodes each document and notes its offset inside its partition. The totals of the
partitions, one number each, are summed in order to the partitions' bases. Pass 2 adds base and
offset and cuts the stream into fixed windows, with no shuffle of ids: a window that spans two
tasks leaves a boundary record in each, and only those are merged by key.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, ship
from .token_ids import token_ids

L = T.LongType()
PLACED = T.StructType([T.StructField("part", L), T.StructField("at", L), T.StructField("doc_id", L), T.StructField("n", L), T.StructField("ids", T.BinaryType())])
PIECE = ("doc_id", "start", "length", "doc_tokens", "offset")
PIECES = T.StructType([T.StructField(n, L) for n in ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")])
FRAGMENTS = T.StructType([T.StructField("sequence_id", L), T.StructField("offset", L), T.StructField("n_tokens", L), T.StructField("ids", T.BinaryType()), T.StructField("pieces", T.ArrayType(T.StructType([T.StructField(n, L) for n in PIECE])))])


def place(docs: DataFrame, tokenizer: str, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pass 1: ``part, at, doc_id, n, ids``, cut to the shared folder so that nothing is encoded twice.

    Ids are stored in two bytes where the vocabulary allows it.
    """
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, part, at = token_ids(tokenizer), TaskContext.get().partitionId(), 0
        kind = f"<u{enc.width}"
        for b in batches:
            for i in range(0, b.num_rows, 256):
                s = b.slice(i, 256)
                ids = [np.append(enc.encode(t.as_py() or ""), np.uint32(end_id)).astype(kind) for t in s.column(1)]
                n = np.array([len(x) for x in ids], np.int64)
                starts = at + np.cumsum(n) - n
                at += int(n.sum())
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(n), part, np.int64)), pa.array(starts), s.column(0), pa.array(n), pa.array([x.tobytes() for x in ids], pa.binary())], names=PLACED.names)

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return cut(rows.mapInArrow(run, PLACED), "placed")


def bases(placed: DataFrame) -> dict[int, int]:
    """Ids before each partition: one row per partition of pass 1 comes to the driver."""
    out, total = {}, 0
    for r in placed.groupBy("part").agg(F.sum("n").alias("n")).orderBy("part").collect():
        out[r["part"]] = total
        total += r["n"]
    return out


def _runs(batches, base, window, width):
    """Each document as ``(doc_id, n, global start, ids)``."""
    for b in batches:
        part, at, doc, n, ids = (b.column(i) for i in range(5))
        for i in range(b.num_rows):
            yield doc[i].as_py(), n[i].as_py(), base[part[i].as_py()] + at[i].as_py(), np.frombuffer(ids[i].as_buffer(), f"<u{width}")


def _fragments(rows: list[tuple]) -> pa.RecordBatch:
    """A batch of ``(sequence, offset, n, ids, pieces)``, the pieces' numbers laid out flat."""
    flat = [x for r in rows for x in r[4]]
    numbers = [pa.array([x[i] for x in flat], pa.int64()) for i in range(len(PIECE))]
    ends = np.concatenate(([0], np.cumsum([len(r[4]) for r in rows]))).astype(np.int32)
    pieces = pa.ListArray.from_arrays(pa.array(ends), pa.StructArray.from_arrays(numbers, names=list(PIECE)))
    cols = [pa.array([r[i] for r in rows], k) for i, k in enumerate((pa.int64(), pa.int64(), pa.int64(), pa.binary()))]
    return pa.RecordBatch.from_arrays([*cols, pieces], names=FRAGMENTS.names)


def sequences(placed: DataFrame, tokenizer: str, window: int = 1024, pad_id: int = 0) -> DataFrame:
    """Pass 2: ``sequence_id, n_tokens, ids, pieces``, every window padded to ``window``, ids as little-endian unsigned 32-bit.

    ``pieces`` says what lies where: document, its ids before the piece, length, the document's ids,
    place in the sequence. Windows that lie in one task are finished there; the fragments at its ends are boundary
    records, merged by key (a window has at most ``window`` ids, so a group is small).
    """
    spark = placed.sparkSession
    base, width = spark.sparkContext.broadcast(bases(placed)), token_ids(tokenizer).width

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple] = []
        open_seq, open_off, have, parts, inside = -1, 0, 0, [], []
        for doc, n, g, ids in _runs(batches, base.value, window, width):
            start = 0
            while start < n:
                seq, off = divmod(g + start, window)
                k = min(n - start, window - off)
                if seq != open_seq or off != open_off + have:
                    if have:
                        out.append((open_seq, open_off, have, b"".join(parts), inside))
                    open_seq, open_off, have, parts, inside = seq, off, 0, [], []
                parts.append(ids[start : start + k].astype("<u4").tobytes())
                inside.append((doc, start, k, n, off))
                have += k
                start += k
                if len(out) >= 512:
                    yield _fragments(out)
                    out = []
        if have:
            out.append((open_seq, open_off, have, b"".join(parts), inside))
        if out:
            yield _fragments(out)

    found = cut(placed.mapInArrow(run, FRAGMENTS), "fragments")
    whole = found.filter(F.col("n_tokens") == window).select("sequence_id", "n_tokens", "ids", "pieces")
    pad = pad_id.to_bytes(4, "little").hex().upper()
    merged = (
        found.filter(F.col("n_tokens") < window)
        .groupBy("sequence_id")
        .agg(F.array_sort(F.collect_list(F.struct("offset", F.hex("ids").alias("ids"), "pieces"))).alias("p"), F.sum("n_tokens").alias("n_tokens"))
        .select("sequence_id", "n_tokens", F.unhex(F.rpad(F.array_join(F.transform("p", lambda x: x["ids"]), ""), window * 8, pad)).alias("ids"), F.flatten(F.transform("p", lambda x: x["pieces"])).alias("pieces"))
    )
    return whole.union(merged)


def pieces(packed: DataFrame) -> DataFrame:
    """One row per piece, read from finished sequences: ``doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset``."""
    p = packed.select("sequence_id", "ids", F.explode("pieces").alias("p")).select("sequence_id", "ids", "p.*")
    mine = F.substring(F.col("ids"), (F.col("offset") * 4 + 1).cast("int"), (F.col("length") * 4).cast("int"))
    return p.select("doc_id", "start", "length", F.crc32(mine).alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


def pack(docs: DataFrame, tokenizer: str, window: int = 1024, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: ``doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset``.

    Null text is empty and packs as its end id alone; a null id is packed with a null ``doc_id``;
    repeated rows are packed once each; an empty table gives no rows. All windows but the last are
    full, so at most ``window - 1`` ids of padding arise in all. Rows are read from the padded
    sequences, so what they say is what a trainer would get.
    """
    return pieces(sequences(place(docs, tokenizer, end_id, id_col, text_col), tokenizer, window))
