"""Token shards with keyed access: raw ids, and a minimal perfect hash from key to place.

A shard is two files. ``.ids`` holds the ids of its documents back to back, two or four bytes
each, little-endian. ``.idx`` holds a JSON header and arrays: the hash's displacements, and per
slot a 64-bit fingerprint of the key, the first id and the number of ids; then the keys in order,
for scans. A key is looked up with one hash and one compare, whatever the shard's size. Shards
follow each other in key order; the manifest lists them with their key ranges and the ids before each.
"""

from __future__ import annotations

import bisect
import json
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import fresh_path, ship
from .perfect_hash import bucket_of, displacements, place_of, slot_of
from .token_ids import token_ids

MAGIC = b"TOKIDX01"
L = T.LongType()
MANIFEST = T.StructType([T.StructField("shard", L), T.StructField("file", T.StringType()), T.StructField("n_docs", L), T.StructField("n_tokens", L), T.StructField("width", L), T.StructField("least", L), T.StructField("most", L), T.StructField("nameless", T.BooleanType())])
ENTRIES = T.StructType([T.StructField(n, L) for n in ("doc_id", "start", "n_tokens", "ids_crc32")])


def filesystem(path: str):
    """Arrow's filesystem for a URI or a plain path; works on executors for any store Arrow knows."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if ":/" in path else (fs.LocalFileSystem(), path)


def key_bytes(doc_id: int | None, nth: int = 0) -> bytes:
    """The key of the ``nth`` row (from 0) that carries ``doc_id``, so repeated ids stay apart."""
    return (b"\0" * 9 if doc_id is None else b"\1" + struct.pack("<q", doc_id)) + struct.pack("<I", nth)


def _hash(key: bytes) -> int:
    return xxhash.xxh3_64_intdigest(key)


def fingerprint(key: bytes) -> int:
    return xxhash.xxh64_intdigest(key, 7)


def _index(keys: list[bytes], starts: np.ndarray, lengths: np.ndarray) -> bytes:
    n = len(keys)
    h = np.fromiter(map(_hash, keys), np.uint64, n)
    shift = displacements(h)
    slots = np.fromiter((slot_of(int(x), shift, len(shift), n) for x in h), np.int64, n)
    fp, at, ln = np.zeros(n, "<u8"), np.zeros(n, "<u8"), np.zeros(n, "<u8")
    fp[slots] = np.fromiter(map(fingerprint, keys), np.uint64, n)
    at[slots], ln[slots] = starts, lengths
    head = json.dumps({"n": n, "buckets": len(shift)}).encode()
    return b"".join((MAGIC, struct.pack("<I", len(head)), head, shift.astype("<u4").tobytes(), fp.tobytes(), at.tobytes(), ln.tobytes(), b"".join(keys)))


class ShardReader:
    """Keyed and ordered access to one shard.

    A lookup reads the header once and then a few numbers: the bucket's displacement, the slot's
    fingerprint, place and length. ``bulk`` loads the index whole, for scans.
    """

    def __init__(self, file: str, width: int, bulk: bool = False):
        fs, path = filesystem(file)
        self.index = fs.open_input_file(path + ".idx")
        self.raw = self.index.read() if bulk else None
        if self._bytes(0, 8) != MAGIC:
            raise ValueError(f"{file}: not a token index")
        (size,) = struct.unpack("<I", self._bytes(8, 4))
        head = json.loads(self._bytes(12, size))
        self.n, self.buckets, self.width = head["n"], head["buckets"], width
        self.shift_at = 12 + size
        self.slots_at = self.shift_at + 4 * self.buckets
        self.keys_at = self.slots_at + 24 * self.n
        self.payload = fs.open_input_file(path + ".ids")

    def _bytes(self, at: int, n: int) -> bytes:
        return self.index.read_at(n, at) if self.raw is None else self.raw[at : at + n]

    def _number(self, column: int, slot: int) -> int:
        return struct.unpack("<Q", self._bytes(self.slots_at + 8 * (self.n * column + slot), 8))[0]

    def find(self, key: bytes) -> int | None:
        """The slot of ``key``, or None where the fingerprint says it is not here."""
        if not self.n:
            return None
        h = _hash(key)
        bucket = bucket_of(h, self.buckets)
        (shift,) = struct.unpack("<I", self._bytes(self.shift_at + 4 * bucket, 4))
        s = place_of(h, shift, self.n)
        return s if self._number(0, s) == fingerprint(key) else None

    def get(self, key: bytes) -> tuple[int, np.ndarray] | None:
        """``(first id's place in the shard, ids)`` by one hash and one read of the payload."""
        s = self.find(key)
        if s is None:
            return None
        at, n = self._number(1, s), self._number(2, s)
        return at, np.frombuffer(self.payload.read_at(n * self.width, at * self.width), f"<u{self.width}")

    def keys(self) -> Iterator[bytes]:
        for i in range(self.n):
            yield self._bytes(self.keys_at + 13 * i, 13)

    def close(self) -> None:
        self.payload.close()
        self.index.close()


def shard_of(manifest: list[dict], doc_id: int | None) -> dict | None:
    """The one shard that can hold ``doc_id``: shards follow each other in key order."""
    if doc_id is None:
        return next((m for m in manifest if m["nameless"]), None)
    named = [m for m in manifest if m["least"] is not None]
    i = bisect.bisect_right([m["least"] for m in named], doc_id) - 1
    return named[i] if i >= 0 and doc_id <= named[i]["most"] else None


def lookup(manifest: list[dict], doc_id: int | None, nth: int = 0) -> np.ndarray | None:
    """The ids of the ``nth`` row with ``doc_id``, from the one shard whose range holds it; None if there is none."""
    m = shard_of(manifest, doc_id)
    if m is None:
        return None
    shard = ShardReader(m["file"], m["width"])
    try:
        got = shard.get(key_bytes(doc_id, nth))
    finally:
        shard.close()
    return None if got is None else got[1].astype("<u4")


FETCHED = T.StructType([T.StructField("doc_id", L), T.StructField("n_tokens", L), T.StructField("ids", T.BinaryType())])


def fetch(keys: DataFrame, manifest: list[dict], id_col: str = "doc_id") -> DataFrame:
    """``doc_id, n_tokens, ids`` (little-endian unsigned 32-bit) of the documents that ``keys`` names and the shards hold.

    Keys are dealt by range like the shards, so a task opens few; the manifest, a row per shard, is what travels.
    """
    spark = keys.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(manifest)
    rows = keys.select(F.col(id_col).cast("long").alias("doc_id")).repartitionByRange("doc_id").sortWithinPartitions("doc_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, shard = None, None
        for b in batches:
            out = []
            for d in b.column(0).to_pylist():
                m = shard_of(shared.value, d)
                if m is None:
                    continue
                if m is not now:
                    if shard is not None:
                        shard.close()
                    now, shard = m, ShardReader(m["file"], m["width"])
                nth = 0
                while (got := shard.get(key_bytes(d, nth))) is not None:
                    out.append((d, len(got[1]), got[1].astype("<u4").tobytes()))
                    nth += 1
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), (pa.int64(), pa.int64(), pa.binary()), strict=True)], names=FETCHED.names)
        if shard is not None:
            shard.close()

    return rows.mapInArrow(run, FETCHED)


def write(docs: DataFrame, tokenizer: str, path: str | None = None, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> tuple[str, list[dict]]:
    """Write all documents in ascending id order; returns the folder and the manifest.

    One range shuffle of the texts puts them in order; every task then encodes and writes its own
    shard as a stream. A task names its file freshly and reports it, so a second attempt after a
    lost executor leaves a file that no manifest names. The manifest has one row per shard.
    Null text is written as its end id; a null id sorts first; rows that repeat an id are kept in
    text order under keys of their own. An empty table has an empty manifest.
    """
    spark = docs.sparkSession
    ship(spark)
    folder = path or fresh_path(spark, "tokens")
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    ordered = rows.repartitionByRange("doc_id").sortWithinPartitions("doc_id", F.xxhash64("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        enc, shard = token_ids(tokenizer), TaskContext.get().partitionId()
        kind = f"<u{enc.width}"
        fs, base = filesystem(folder)
        fs.create_dir(base, recursive=True)
        name = f"shard-{shard:06d}-{uuid.uuid4().hex[:12]}"
        keys, lengths, last, nth = [], [], object(), 0
        least = most = None
        nameless = False
        out = None
        for b in batches:
            ids_col, text = b.column(0), b.column(1)
            for i in range(b.num_rows):
                d = ids_col[i].as_py()
                nth = nth + 1 if d == last else 0
                last = d
                nameless = nameless or d is None
                least, most = (d, d) if least is None else (least, d)
                ids = np.append(enc.encode(text[i].as_py() or ""), np.uint32(end_id)).astype(kind)
                if out is None:
                    out = fs.open_output_stream(f"{base}/{name}.ids", buffer_size=1 << 20)
                out.write(ids.tobytes())
                keys.append(key_bytes(d, nth))
                lengths.append(len(ids))
        if out is None:
            return
        out.close()
        ln = np.array(lengths, np.int64)
        with fs.open_output_stream(f"{base}/{name}.idx") as f:
            f.write(_index(keys, np.cumsum(ln) - ln, ln))
        yield pa.RecordBatch.from_arrays([pa.array([shard]), pa.array([f"{folder}/{name}"]), pa.array([len(keys)]), pa.array([int(ln.sum())]), pa.array([enc.width]), pa.array([least], pa.int64()), pa.array([most], pa.int64()), pa.array([nameless])], names=MANIFEST.names)

    manifest, total = [], 0
    for r in sorted(ordered.mapInArrow(run, MANIFEST).collect(), key=lambda r: r["shard"]):  # one row per shard
        manifest.append(r.asDict() | {"first_token": total})
        total += r["n_tokens"]
    spark.createDataFrame([(json.dumps(m),) for m in manifest], "value string").coalesce(1).write.mode("overwrite").text(f"{folder}/manifest")
    return folder, manifest


def read_manifest(spark, folder: str) -> list[dict]:
    return sorted((json.loads(r["value"]) for r in spark.read.text(f"{folder}/manifest").collect()), key=lambda m: m["shard"])


def read(spark, manifest: list[dict]) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` of every document, each fetched from its shard by key."""
    ship(spark)
    schema = T.StructType([*MANIFEST.fields, T.StructField("first_token", L)])
    rows = spark.createDataFrame([tuple(m[f] for f in schema.names) for m in manifest], schema).repartition(max(1, len(manifest)), "shard")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for m in b.to_pylist():
                shard, out = ShardReader(m["file"], m["width"], bulk=True), []
                for key in shard.keys():
                    at, ids = shard.get(key)
                    out.append((None if key[0] == 0 else struct.unpack_from("<q", key, 1)[0], m["first_token"] + at, len(ids), zlib.crc32(ids.astype("<u4"))))
                    if len(out) >= 8192:
                        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out)], names=ENTRIES.names)
                        out = []
                shard.close()
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out)], names=ENTRIES.names)

    return rows.mapInArrow(run, ENTRIES)
