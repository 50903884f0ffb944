"""Byte-level BPE, two tiers: a minimal perfect hash for whole pre-tokens, a heap for the rest."""

from __future__ import annotations

import base64
import hashlib
import heapq
import json
from array import array
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ship
from .perfect_hash import PerfectHash

#: Pre-tokens a worker remembers before it starts again; bounds its memory.
MEMO = 400_000


def read_ranks(path: str) -> dict[bytes, int]:
    """Token bytes to id from a ``.tiktoken`` rank file, or from a byte-level ``.json`` whose merges are in id order."""
    if path.endswith(".json"):
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        back = {c: b for b, c in byte_alphabet().items()}
        vocab = {bytes(back[c] for c in tok): i for tok, i in model["vocab"].items() if all(c in back for c in tok)}
        last = -1
        for m in model["merges"]:
            left, right = m.split(" ") if isinstance(m, str) else m
            made = model["vocab"][left + right]
            if made <= last:
                raise ValueError("merges are not in the order of ids, so ids cannot serve as ranks")
            last = made
        return vocab
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def byte_alphabet() -> dict[int, str]:
    """The printable stand-in of each byte in byte-level vocabularies: Latin-1's printable ones stand for themselves, the rest follow from 256."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}


class Codec:
    """Encodes and decodes with one rank table; ``memo`` pre-tokens are remembered."""

    def __init__(self, ranks: dict[bytes, int], pattern: str, memo: int = MEMO):
        import regex

        self.ranks = ranks
        self.find = regex.compile(pattern).findall
        words = sorted(ranks)
        self.index = PerfectHash.build(words)
        self.slot_id = array("I", bytes(4 * len(words)))
        for w in words:
            self.slot_id[self.index.slot(w)] = ranks[w]
        self.slot_bytes: list[bytes] = [b""] * len(words)
        for w in words:
            self.slot_bytes[self.index.slot(w)] = w
        self.by_id = [b""] * (max(ranks.values()) + 1 if ranks else 0)
        for w, i in ranks.items():
            self.by_id[i] = w
        self.memo = _Memo(self._encode_piece, memo)

    def lookup(self, word: bytes) -> int:
        """The id of a whole pre-token that is in the vocabulary, else -1: one hash, one compare."""
        s = self.index.slot(word)
        return self.slot_id[s] if self.slot_bytes[s] == word else -1

    def _encode_piece(self, piece: str) -> bytes:
        raw = piece.encode("utf-8", "surrogatepass")
        i = self.lookup(raw)
        return array("I", (i,)).tobytes() if i >= 0 else array("I", self.merge(raw)).tobytes()

    def merge(self, raw: bytes) -> list[int]:
        """Ids of ``raw``: neighbours in a linked list of parts, candidates in a heap by (rank, place); stale entries are skipped."""
        n, rank = len(raw), self.ranks.get
        end = list(range(1, n + 1))  # a part at i spans raw[i:end[i]]; 0 marks a part merged away
        before = list(range(-1, n - 1))
        heap = []
        for i in range(n - 1):
            r = rank(raw[i : i + 2])
            if r is not None:
                heap.append((r, i, i + 2))
        heapq.heapify(heap)
        while heap:
            r, i, stop = heapq.heappop(heap)
            mid = end[i]
            if not mid or mid >= n or end[mid] != stop:
                continue
            end[i], end[mid] = stop, 0
            if stop < n:
                before[stop] = i
                r = rank(raw[i : end[stop]])
                if r is not None:
                    heapq.heappush(heap, (r, i, end[stop]))
            p = before[i]
            if p >= 0:
                r = rank(raw[p:stop])
                if r is not None:
                    heapq.heappush(heap, (r, p, stop))
        out, i = [], 0
        while i < n:
            out.append(self.ranks[raw[i : end[i]]])
            i = end[i]
        return out

    def encode_bytes(self, text: str) -> bytes:
        """The ids as little-endian unsigned 32-bit integers."""
        self.memo.trim()
        return b"".join(map(self.memo.__getitem__, self.find(text)))

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.by_id.__getitem__, np.frombuffer(ids, "<u4").tolist()))


class _Memo(dict):
    def __init__(self, make, most: int):
        super().__init__()
        self.make, self.most = make, most

    def __missing__(self, key):
        v = self.make(key)
        if len(key) <= 64:
            self[key] = v
        return v

    def trim(self) -> None:
        if len(self) > self.most:
            self.clear()


@lru_cache(maxsize=2)
def codec(path: str, pattern: str) -> Codec:
    """One codec per worker process and vocabulary file."""
    return Codec(read_ranks(path), pattern)


ENCODED = T.StructType(
    [
        T.StructField("doc_id", T.LongType()),
        T.StructField("n_tokens", T.LongType()),
        T.StructField("ids", T.BinaryType()),
    ]
)


def encode(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col, n_tokens, ids`` (little-endian unsigned 32-bit) of every whole text.

    Null text is empty and gives no ids. The vocabulary file at ``path`` must be readable on
    executors. Repeated rows and null ids pass through; other columns are not read; an empty table
    gives no rows. Each text is encoded by itself, so memory follows the longest text only.
    """
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = codec(path, pattern)
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                ids = [enc.encode_bytes(t.as_py() or "") for t in part.column(1)]
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(ids, pa.binary())], names=["doc_id", "n_tokens", "ids"]
                )

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, ENCODED).withColumnRenamed("doc_id", id_col)


def decode(encoded: DataFrame, path: str, pattern: str, ids_col: str = "ids") -> DataFrame:
    """``encoded`` with a binary column ``decoded``: the bytes of each row's ids. Null ids give null."""
    ship(encoded.sparkSession)
    at = encoded.columns.index(ids_col)
    schema = T.StructType([*encoded.schema.fields, T.StructField("decoded", T.BinaryType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = codec(path, pattern)
        for b in batches:
            for i in range(0, b.num_rows, 256):
                part = b.slice(i, 256)
                raw = [None if (x := v.as_py()) is None else enc.decode(x) for v in part.column(at)]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(raw, pa.binary())], names=[*part.schema.names, "decoded"])

    return encoded.mapInArrow(run, schema)


def sha256_hex(raw: bytes) -> str:
    return hashlib.sha256(raw).hexdigest()
