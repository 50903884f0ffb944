"""A minimal perfect hash: n keys to n slots by one displacement per bucket."""

from __future__ import annotations

import numpy as np
import xxhash

#: Keys per bucket on average; more makes the table smaller and the search for displacements longer.
LOAD = 3


class PerfectHash:
    """``slot(key)`` is a bijection of the keys it was built from to 0..n-1; other keys get any slot, so store the key or a fingerprint beside it."""

    __slots__ = ("n", "shift", "buckets")

    def __init__(self, n: int, shift: np.ndarray):
        self.n, self.shift = n, shift.tolist()
        self.buckets = len(self.shift)

    @staticmethod
    def _hashes(keys: list[bytes]) -> np.ndarray:
        return np.fromiter((xxhash.xxh3_64_intdigest(k) for k in keys), np.uint64, len(keys))

    @classmethod
    def build(cls, keys: list[bytes]) -> PerfectHash:
        """Raises ValueError on equal keys. Buckets are placed from the fullest down; each tries displacements until its keys fall on free slots."""
        return cls(len(keys), displacements(cls._hashes(keys)))

    def slot(self, key: bytes) -> int:
        if not self.n:
            return 0
        return slot_of(xxhash.xxh3_64_intdigest(key), self.shift, self.buckets, self.n)


_M = (1 << 64) - 1
_ODD, _MUL = 0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9


def bucket_of(h: int, buckets: int) -> int:
    return (h >> 40) % buckets


def place_of(h: int, shift: int, n: int) -> int:
    """The slot of hash ``h`` under its bucket's displacement."""
    z = (h ^ (shift * _ODD & _M)) * _MUL & _M
    z = (z ^ z >> 32) * _MUL & _M
    return (z >> 29) % n


def slot_of(h: int, shift, buckets: int, n: int) -> int:
    return place_of(h, int(shift[bucket_of(h, buckets)]), n)


def displacements(h: np.ndarray) -> np.ndarray:
    """The displacement of each bucket for distinct 64-bit hashes ``h``."""
    n = len(h)
    buckets = max(1, n // LOAD)
    if len(np.unique(h)) != n:
        raise ValueError("keys repeat, or their 64-bit hashes do")
    where = ((h >> np.uint64(40)) % np.uint64(buckets)).astype(np.int64)
    order = np.argsort(where, kind="stable")
    starts = np.searchsorted(where[order], np.arange(buckets + 1))
    size = np.diff(starts)
    shift, used = np.zeros(buckets, np.uint32), np.zeros(n, bool)
    with np.errstate(over="ignore"):
        for b in np.argsort(-size, kind="stable"):
            k = h[order[starts[b] : starts[b + 1]]]
            if not len(k):
                break
            first = 0
            while True:
                ds = np.arange(first, first + 64, dtype=np.uint64)
                # exclusive or, then two rounds: displacements must move two keys apart, not just along
                z = (k[None, :] ^ (ds[:, None] * np.uint64(_ODD))) * np.uint64(_MUL)
                z = (z ^ (z >> np.uint64(32))) * np.uint64(_MUL)
                s = ((z >> np.uint64(29)) % np.uint64(n)).astype(np.int64)
                ok = ~used[s].any(1)
                if len(k) > 1:
                    t = np.sort(s, 1)
                    ok &= (t[:, 1:] != t[:, :-1]).all(1)
                hit = np.flatnonzero(ok)
                if len(hit):
                    shift[b] = first + hit[0]
                    used[s[hit[0]]] = True
                    break
                first += 64
                if first > 1 << 26:
                    raise ValueError("no displacement found")
    return shift
