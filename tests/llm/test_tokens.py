"""BPE, packing and token shards against the libraries, and exact round trips."""

import hashlib
import random
import zlib

import numpy as np
import public_tokenizers as P
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from lookalike.llm import bpe, packing, token_file
from lookalike.llm.perfect_hash import PerfectHash
from lookalike.llm.token_ids import token_ids

RANKS, JSON = P.path("byte_bpe_50k.tiktoken"), P.path("byte_bpe_50k.json")
ODD = ["", " ", "a", "\n\n \t", "It's we'll they'd", "<|endoftext|>", "日本語テキスト", "🙂🙂 é́ ß", "x" * 5000, "ab" * 3000 + " 123456789", "\x00\x1c\x85\xa0", "'S 's 'LL", "word " * 20000]


@pytest.fixture(scope="module")
def reference():
    import tiktoken

    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=bpe.read_ranks(RANKS), special_tokens={})


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(JSON)
    return lambda text: t.encode_batch([text], add_special_tokens=False)[0].ids


def test_perfect_hash_is_a_bijection():
    keys = [f"key-{i}".encode() for i in range(5000)]
    h = PerfectHash.build(keys)
    assert sorted(h.slot(k) for k in keys) == list(range(5000))
    assert PerfectHash.build([]).slot(b"x") == 0
    for n in range(1, 200):
        few = [f"{n}/{i}".encode() for i in range(n)]
        small = PerfectHash.build(few)
        assert sorted(small.slot(k) for k in few) == list(range(n))
    with pytest.raises(ValueError):
        PerfectHash.build([b"a", b"a"])


def test_odd_texts(reference, library):
    codec, ids = bpe.codec(RANKS, P.PATTERN), token_ids(JSON)
    for t in ODD:
        want = reference.encode_ordinary(t)
        assert np.frombuffer(codec.encode_bytes(t), "<u4").tolist() == want
        assert codec.decode(codec.encode_bytes(t)) == t.encode()
        assert ids.encode(t).tolist() == library(t)
        if not any(a in t for a in ids.added):
            assert library(t) == want


def test_strings_of_special_tokens_are_the_library_s(library):
    """The plain library reads an added token's string as that token; so do the ids here, and nothing else changes."""
    ids = token_ids(JSON)
    assert ids.added and ids.fast is not None
    for t in ["a <|endoftext|> b", "<|endoftext|>", "<|endoftext|><|endoftext|> x", "<|endoftext| >", "x" * 3000 + "<|endoftext|>"]:
        assert ids.encode(t).tolist() == library(t)
    assert 50256 in ids.encode("a <|endoftext|> b").tolist()


@settings(max_examples=300, deadline=None)
@given(st.text(max_size=80))
def test_any_text(text):
    import tiktoken

    ref = test_any_text.__dict__.setdefault("ref", tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=bpe.read_ranks(RANKS), special_tokens={}))
    codec = bpe.codec(RANKS, P.PATTERN)
    raw = codec.encode_bytes(text)
    assert np.frombuffer(raw, "<u4").tolist() == ref.encode_ordinary(text)
    assert codec.decode(raw) == text.encode()


def test_memo_is_bounded():
    c = bpe.Codec(bpe.read_ranks(RANKS), P.PATTERN, memo=50)
    text = " ".join(f"word{i}" for i in range(400))
    first = c.encode_bytes(text)
    assert c.encode_bytes(text) == first
    c.encode_bytes("a")
    assert len(c.memo) <= 2


def docs(spark):
    rng = random.Random(1)
    data = [(i * 3 % 101, " ".join(rng.choice(ODD[:11]) for _ in range(rng.randrange(0, 4)))) for i in range(101)]
    data += [(500, None), (501, ""), (502, "w " * 9000), (None, "null id"), (3, "again"), (3, "again")]
    return data, spark.createDataFrame([(i, t, "s", 4) for i, t in data], "doc_id long, text string, ids string, n long")


def test_encode_decode_on_spark(spark, reference):
    data, df = docs(spark)
    got = bpe.decode(bpe.encode(df, RANKS, P.PATTERN), RANKS, P.PATTERN).collect()
    want = sorted((str(i), hashlib.sha256(np.array(reference.encode_ordinary(t or ""), "<u4").tobytes()).hexdigest()) for i, t in data)
    assert sorted((str(r["doc_id"]), bpe.sha256_hex(bytes(r["ids"]))) for r in got) == want
    assert sorted(bytes(r["decoded"]) for r in got) == sorted((t or "").encode() for _, t in data)
    assert bpe.encode(df.limit(0), RANKS, P.PATTERN).count() == 0


def test_packing_covers_every_id_once(spark, library):
    data, df = docs(spark)
    placed = packing.place(df.repartition(5), JSON)
    rows = packing.pieces(packing.sequences(placed, JSON, window=64)).collect()
    want = {}
    for i, t in data:
        want.setdefault(i, []).append([*library(t or ""), 0])
    for i, found in want.items():
        mine = sorted((r["sequence_id"], r["offset"], r["start"], r["length"], r["ids_crc32"], r["doc_tokens"]) for r in rows if r["doc_id"] == i)
        at = 0
        for ids in sorted(found, key=len) if len(found) == 1 else [None]:
            if ids is None:
                assert sum(m[3] for m in mine) == sum(map(len, found))
                continue
            for _, _, start, length, crc, total in mine:
                assert start == at and total == len(ids)
                assert crc == zlib.crc32(np.array(ids[start : start + length], "<u4"))
                at += length
            assert at == len(ids)
    by = {}
    for r in rows:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert sorted(by) == list(range(len(by)))
    for s, parts in by.items():
        at = 0
        for off, n in sorted(parts):
            assert off == at
            at += n
        assert at == 64 or s == len(by) - 1
    seqs = packing.sequences(placed, JSON, window=64).collect()
    assert len(seqs) == len(by) and all(len(r["ids"]) == 256 for r in seqs)
    assert sum(r["n_tokens"] for r in seqs) == sum(len(x) for v in want.values() for x in v)
    whole = b"".join(bytes(r["ids"])[: r["n_tokens"] * 4] for r in sorted(seqs, key=lambda r: r["sequence_id"]))
    for r in rows:
        a = (r["sequence_id"] * 64 + r["offset"]) * 4
        assert zlib.crc32(whole[a : a + r["length"] * 4]) == r["ids_crc32"]
    assert packing.pack(df.limit(0), JSON).count() == 0


def test_token_files(spark, library):
    data, df = docs(spark)
    folder, manifest = token_file.write(df, JSON)
    assert token_file.read_manifest(spark, folder) == manifest
    got = token_file.read(spark, manifest).collect()
    assert len(got) == len(data)
    order = sorted(got, key=lambda r: r["start"])
    keys = [(-1 if r["doc_id"] is None else r["doc_id"]) for r in order]
    assert keys == sorted(keys)
    at = 0
    for r in order:
        assert r["start"] == at
        at += r["n_tokens"]
    want = sorted((str(i), len(library(t or "")) + 1, zlib.crc32(np.array([*library(t or ""), 0], "<u4"))) for i, t in data)
    assert sorted((str(r["doc_id"]), r["n_tokens"], r["ids_crc32"]) for r in got) == want
    for i, t in data:
        if [d for d, _ in data].count(i) == 1:
            assert token_file.lookup(manifest, i).tolist() == [*library(t or ""), 0]
    assert token_file.lookup(manifest, 10**12) is None and token_file.lookup(manifest, -5) is None and token_file.lookup([], 1) is None
    assert token_file.lookup(manifest, 3, 9) is None
    three = sorted(tuple(token_file.lookup(manifest, 3, k)) for k in range(3))
    assert three == sorted((*library(t), 0) for i, t in data if i == 3)
    asked = spark.createDataFrame([(500,), (3,), (None,), (987654,), (9,)], "doc_id long")
    fetched = sorted((str(r["doc_id"]), bytes(r["ids"])) for r in token_file.fetch(asked, manifest).collect())
    assert fetched == sorted((str(i), np.array([*library(t or ""), 0], "<u4").tobytes()) for i, t in data if i in (500, 3, None, 9))
    m = manifest[-1]
    shard = token_file.ShardReader(m["file"], m["width"])
    assert shard.get(token_file.key_bytes(987654321)) is None
    for k in shard.keys():
        assert shard.find(k) is not None
    assert token_file.read(spark, token_file.write(df.limit(0), JSON)[1]).count() == 0
