"""Substring dedup: content-defined chunks by a gear rolling hash, duplicates by digest.

A chunk ends where the gear hash of the last 8 bytes falls below a bound, moved on to the next white
space, so boundaries follow content and an insertion shifts nothing. What is looked up is a passage:
from each chunk on, as many chunks as hold ``min_words`` words, in their order. A passage that also
stands in a document with a smaller id is cut out. So all that goes lies, passage by passage, in one
earlier document each; phrases that are known one by one never make a known text. Passages are
compared by 96 bits of digest: among the 4 * 10^12 of 100 TB, one chance in ten thousand of a single collision.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ship, spare

#: A cut where the 8-bit gear hash is below this: every 26 bytes on average. Short chunks and a
#: short window leave little of a repeated passage at its two ends.
BELOW = 10
#: Words of a passage: what must be known from an earlier document, in one piece, to be cut out.
MIN_WORDS = 25
#: Where the next white space is further than this, a chunk ends in mid-word.
REACH = 64


def gear_table() -> np.ndarray:
    """One 8-bit value per byte, from a fixed rule."""
    return np.array([xxhash.xxh3_64_intdigest(bytes((b,)), 11) & 0xFF for b in range(256)], np.uint8)


GEAR = gear_table()


def gear_hash(raw: np.ndarray) -> np.ndarray:
    """The rolling gear hash after each byte: sum of ``GEAR[byte] << age``, ages 0 to 7, by doubling the window."""
    h = GEAR[raw]
    for w in (1, 2, 4):
        older = h[:-w] << np.uint8(w)
        h = h.copy()
        h[w:] += older
    return h


def boundaries(raw: bytes) -> np.ndarray:
    """Ends of the chunks of ``raw``, the last being its length."""
    n = len(raw)
    if not n:
        return np.zeros(0, np.int64)
    b = np.frombuffer(raw, np.uint8)
    hits = np.flatnonzero(gear_hash(b) < BELOW)
    if not len(hits):
        return np.array([n], np.int64)
    blank = np.append(np.flatnonzero(b <= 32), n)
    ends = blank[np.searchsorted(blank, hits)]
    far = ends - hits > REACH
    if far.any():
        own = hits[far] + 1
        for _ in range(3):  # not inside a character
            own = np.where((own < n) & ((b[np.minimum(own, n - 1)] & 0xC0) == 0x80), own + 1, own)
        ends[far] = own
    ends = np.unique(ends)
    ends = ends[(ends > 0) & (ends < n)]
    return np.append(ends, n)


def chunk_words(raw: bytes, ends: np.ndarray) -> np.ndarray:
    """Words that begin in each chunk; one that a cut parted counts on both sides."""
    b = np.frombuffer(raw, np.uint8) > 32
    begin = b & ~np.concatenate(([False], b[:-1]))
    total = np.concatenate(([0], np.cumsum(begin)))
    starts = np.concatenate(([0], ends[:-1]))
    return total[ends] - total[starts] + (b[starts] & ~begin[starts])


def passage_ends(words: np.ndarray, min_words: int) -> np.ndarray:
    """For each chunk the number of the chunk after the passage that starts there; -1 where the text is too short."""
    total = np.concatenate(([0], np.cumsum(words)))
    at = np.searchsorted(total, total[:-1] + min_words)
    return np.where(at < len(total), at, -1)


_POLY = (0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93)


def _powers(m: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first ``n`` powers of odd ``m`` and of its inverse, modulo 2^64."""
    up, down = np.full(n, m, np.uint64), np.full(n, pow(m, -1, 1 << 64), np.uint64)
    up[0] = down[0] = 1
    return np.multiply.accumulate(up), np.multiply.accumulate(down)


def passages(raw: bytes, min_words: int) -> tuple[np.ndarray, np.ndarray]:
    """``(first chunk, digest)`` of every passage: two 64-bit words each, made from its chunks' digests in order.

    Chunks are hashed once, without the white space around them; a passage's digest is a difference
    of running polynomials.
    """
    ends = boundaries(raw)
    if not len(ends):
        return np.zeros(0, np.int64), np.zeros((0, 2), np.int64)
    upto = passage_ends(chunk_words(raw, ends), min_words)
    first = np.flatnonzero(upto >= 0)
    if not len(first):
        return first, np.zeros((0, 2), np.int64)
    at, parts, digest = 0, [], xxhash.xxh3_128_digest
    for e in ends.tolist():
        parts.append(digest(raw[at:e].strip()))
        at = e
    d = np.frombuffer(b"".join(parts), "<u8").reshape(-1, 2)
    out = np.empty((len(first), 2), np.uint64)
    for k, m in enumerate(_POLY):
        up, down = _powers(m, len(d))
        run = np.concatenate((np.zeros(1, np.uint64), np.cumsum(d[:, k] * up, dtype=np.uint64)))
        out[:, k] = (run[upto[first]] - run[first]) * down[first]
    return first, out.view(np.int64)


def cut_runs(raw: bytes, ends: np.ndarray, duplicate: np.ndarray) -> tuple[bytes, list[tuple[int, int]]]:
    """``raw`` without its duplicate chunks, and the byte spans taken out."""
    starts = np.concatenate(([0], ends[:-1]))
    marks = np.flatnonzero(np.diff(np.concatenate(([0], duplicate.astype(np.int8), [0]))))
    spans = [(int(starts[i]), int(ends[j - 1])) for i, j in marks.reshape(-1, 2).tolist()]
    kept, at = [], 0
    for lo, hi in spans:
        kept.append(raw[at:lo])
        at = hi
    kept.append(raw[at:])
    return b"".join(kept), spans


PASSAGES = T.StructType([T.StructField("d1", T.LongType()), T.StructField("d2", T.IntegerType()), T.StructField("doc_id", T.LongType()), T.StructField("nth", T.IntegerType())])


def all_passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS) -> DataFrame:
    """``d1, d2, doc_id, nth`` of every passage of every whole text; ``nth`` is its first chunk."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                digests, ids, nth = [], [], []
                for d, t in zip(part.column(0).to_pylist(), part.column(1), strict=True):
                    if d is None:
                        continue
                    first, got = passages((t.as_py() or "").encode(), min_words)
                    digests.append(got)
                    ids.append(np.full(len(first), d, np.int64))
                    nth.append(first.astype(np.int32))
                if ids:
                    d = np.concatenate(digests)
                    cols = [np.ascontiguousarray(d[:, 0]), d[:, 1].astype(np.int32), np.concatenate(ids), np.concatenate(nth)]
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in cols], names=PASSAGES.names)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, PASSAGES)


def known_passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS) -> DataFrame:
    """``doc_id, known``: place and first digest word of the passages of each document that also stand in one with a smaller id.

    The first aggregation keeps two ids per digest and combines on the map side, so a passage that
    a third of the documents share leaves each task once; the join back is an equi join whose
    skew AQE splits.
    """
    found = all_passages(docs, id_col, text_col, min_words)
    shared = found.groupBy("d1", "d2").agg(F.min("doc_id").alias("first_id"), F.max("doc_id").alias("last_id")).filter("first_id < last_id").select("d1", "d2", "first_id")
    return found.join(shared, ["d1", "d2"]).filter("doc_id > first_id").groupBy("doc_id").agg(F.collect_set(F.struct("nth", "d1")).alias("known"))


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS) -> DataFrame:
    """``docs`` with ``text_col`` replaced, plus ``n_chunks, n_duplicate, removed_bytes``.

    Passages of ``min_words`` words and more stay in the document with the smallest id that has
    them. Null texts stay null, empty ones empty; a row with a null id is neither cut nor a reason
    to cut; rows that repeat an id with the same text are one document, and are cut alike; with different texts,
    each is cut where its own text has a known passage; a passage repeated inside one document only
    stays. Extra columns pass through; should they carry the names of the three counts, the counts win.
    """
    spark = docs.sparkSession
    ship(spark)
    counts = ("n_chunks", "n_duplicate", "removed_bytes")
    base = docs.drop(*[c for c in counts if c in docs.columns])
    theirs, known = spare(base.columns, "marked_id"), spare(base.columns, "marked_known")
    marked = known_passages(base, id_col, text_col, min_words).select(F.col("doc_id").alias(theirs), F.col("known").alias(known))
    joined = base.join(marked, base[id_col] == marked[theirs], "left").drop(theirs)
    at, where = base.columns.index(text_col), len(base.columns)
    schema = T.StructType([*[T.StructField(f.name, T.StringType() if f.name == text_col else f.dataType) for f in base.schema], *[T.StructField(c, T.LongType()) for c in counts]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, 256):
                part = b.slice(i, 256)
                texts, stats = [], []
                for t, found in zip(part.column(at), part.column(where), strict=True):
                    text, marks = t.as_py(), found.as_py()
                    raw = (text or "").encode()
                    ends = boundaries(raw)
                    flag = np.zeros(len(ends) + 1, np.int64)
                    gone = 0
                    if marks and len(ends):
                        first, digests = passages(raw, min_words)  # marks of another row with this id do not fit
                        mine = np.isin(first, [m["nth"] for m in marks]) & np.isin(digests[:, 0], [m["d1"] for m in marks])
                        upto = passage_ends(chunk_words(raw, ends), min_words)
                        np.add.at(flag, first[mine], 1)
                        np.add.at(flag, upto[first[mine]], -1)
                        short, spans = cut_runs(raw, ends, np.cumsum(flag[:-1]) > 0)
                        gone = sum(hi - lo for lo, hi in spans)
                        text = short.decode("utf-8", "replace") if spans else text
                    texts.append(text)
                    stats.append((len(ends), int((np.cumsum(flag[:-1]) > 0).sum()), gone))
                cols = [pa.array(texts, pa.string()) if k == at else part.column(k) for k in range(where)]
                cols += [pa.array(c, pa.int64()) for c in zip(*stats, strict=True)]
                yield pa.RecordBatch.from_arrays(cols, names=schema.names)

    return joined.mapInArrow(run, schema)
