"""Exact dedup, near dedup of documents and vectors, substring dedup: edge cases and brute force."""

import hashlib
import itertools
import random

import numpy as np
import pytest

from lookalike.llm import exact_dedup, pivot_join, set_join, substring
from lookalike.llm.common import connected_components

DOC = "doc_id long, text string, kept boolean, digest string"


def rows(df, *cols):
    return {r[cols[0]]: tuple(r[c] for c in cols[1:]) for r in df.collect()}


def components(ids, links):
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for a, b in links:
        ra, rb = find(a), find(b)
        root[max(ra, rb)] = min(ra, rb)
    return {i: find(i) for i in ids}


def test_components(spark):
    rng = random.Random(3)
    links = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(1000 + i, 1001 + i) for i in range(60)]
    df = spark.createDataFrame([*links, (None, 4), (5, 5)], "a long, b long")
    got = {r["id"]: r["component_id"] for r in connected_components(df).collect()}
    used = {x for e in links if e[0] != e[1] for x in e}
    want = components(used, links)
    assert got == want


def test_components_of_large_ids(spark):
    big = 6 * 10**18
    df = spark.createDataFrame([(big + i, big + i + 1) for i in range(70)], "a long, b long")
    assert {r["component_id"] for r in connected_components(df).collect()} == {big}


def test_components_of_nothing(spark):
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_exact_dedup(spark):
    long = "Word " * 60000
    data = [(1, "Abc", True, "x"), (2, "aBC", None, None), (3, None, None, None), (4, "", None, None), (5, "É", None, None), (6, "é", None, None), (7, long, None, None), (8, long.lower(), None, None), (8, long, None, None), (None, "abc", None, None)]
    df = spark.createDataFrame(data, DOC)
    got = sorted(exact_dedup.exact_dedup(df, keep="max").collect(), key=lambda r: (r["doc_id"] is None, r["doc_id"]))
    assert [(r["doc_id"], r["keep_id"], r["group_size"], r["kept"]) for r in got] == [(1, 2, 3, False), (2, 2, 3, True), (3, 4, 2, False), (4, 4, 2, True), (5, 5, 1, True), (6, 6, 1, True), (7, 8, 3, False), (8, 8, 3, True), (8, 8, 3, True), (None, 2, 3, False)]
    assert got[0]["text_sha256"] == hashlib.sha256(b"abc").hexdigest()
    kept = exact_dedup.keep_first(df)
    assert kept.columns == df.columns
    assert sorted(r["doc_id"] for r in kept.collect()) == [1, 3, 5, 6, 7]
    assert exact_dedup.exact_dedup(df.limit(0)).count() == 0
    lone = spark.createDataFrame([(None, "q")], "doc_id long, text string")
    assert exact_dedup.keep_first(lone).count() == 1


def shingles(text, w=5):
    words = text.encode().lower().split() if text else []
    if not words:
        return set()
    return {tuple(words)} if len(words) < w else {tuple(words[i : i + w]) for i in range(len(words) - w + 1)}


def brute_near(docs, percent):
    sets = {i: shingles(t) for i, t in docs}
    links = [(a, b) for a, b in itertools.combinations(sets, 2) if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]
    comp = components(sets, links)
    return {i: (len(sets[i]), comp[i], comp[i] == i) for i in sets}


def planted(seed=1, families=25):
    rng = random.Random(seed)
    vocab = [f"w{i}" for i in range(2000)]
    docs = []
    for _ in range(families):
        base = [rng.choice(vocab) for _ in range(rng.randrange(3, 300))]
        docs.append(base)
        for _ in range(rng.randrange(0, 6)):
            copy = list(base)
            for _ in range(rng.randrange(0, max(1, len(copy) // 40) + 1)):
                copy[rng.randrange(len(copy))] = rng.choice(vocab)
            docs.append(copy)
    texts = [(i, " ".join(d)) for i, d in enumerate(docs)]
    n = len(texts)
    texts += [(n, ""), (n + 1, None), (n + 2, "\t \n"), (n + 3, "One two"), (n + 4, "oNE\ttwo"), (n + 5, texts[0][1].upper()), (n + 6, "a b " * 30000)]
    return texts


def test_near_duplicates_equal_brute_force(spark):
    docs = planted()
    df = spark.createDataFrame([(i, t, False, "z") for i, t in docs], DOC)
    got = rows(set_join.near_duplicates(df), "doc_id", "n_shingles", "component_id", "kept")
    assert got == brute_near(docs, 85)
    got = rows(set_join.near_duplicates(df, similarity=0.8), "doc_id", "n_shingles", "component_id", "kept")
    assert got == brute_near(docs, 80)


def test_large_nodes_and_blocks(spark, monkeypatch):
    """Small leaves and blocks force branching and pairs of blocks."""
    for name in ("SKETCH_ROWS", "TEXT_ROWS", "PAIR_ROWS"):
        monkeypatch.setattr(set_join, name, 8)
    docs = planted(7, 12)
    base = docs[0][1].split() if docs[0][1] else []
    base = (base + [f"x{i}" for i in range(200)])[:200]
    docs += [(1000 + i, " ".join(base[:i] + [f"new{i}"] + base[i + 1 :])) for i in range(40)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = rows(set_join.near_duplicates(df), "doc_id", "n_shingles", "component_id", "kept")
    assert got == brute_near(docs, 85)


def test_large_groups_meet_block_by_block(spark, monkeypatch):
    """A chain of texts, each like the next alone, in one group: hubs reach few, so the second pass must find the rest."""
    for name in ("SKETCH_ROWS", "TEXT_ROWS", "PAIR_ROWS"):
        monkeypatch.setattr(set_join, name, 5)
    monkeypatch.setattr(set_join, "HUBS", 1)
    words = [f"w{i}" for i in range(400)]
    chain = [(i, " ".join(words[i : i + 80])) for i in range(0, 120)]
    chain += [(500 + i, " ".join(words[7 * i : 7 * i + 80])) for i in range(20)]
    df = spark.createDataFrame(chain, "doc_id long, text string")
    got = rows(set_join.near_duplicates(df, similarity=0.97), "doc_id", "n_shingles", "component_id", "kept")
    assert got == brute_near(chain, 97)


def test_search_groups_equals_brute_force(spark):
    """Any predicate, any group sizes: the same components as all pairs give."""
    rng = random.Random(6)
    data = [(g, g * 1000 + i, rng.randrange(200)) for g, n in ((1, 90), (2, 4), (3, 33), (4, 1)) for i in range(n)]

    def make_near(t):
        v = t.column("v").to_numpy()
        return lambda i, rest: np.abs(v[rest] - v[i]) <= 1

    df = spark.createDataFrame(data, "g long, rid long, v long")
    got = {r["id"]: r["component_id"] for r in connected_components(set_join.search_groups(df, "g", make_near, 4, 6)).collect()}
    want = components([r for _, r, _ in data], [(a, b) for (g, a, v), (h, b, w) in itertools.combinations(data, 2) if g == h and abs(v - w) <= 1])
    assert {i: got.get(i, i) for i in want} == want


def test_payloads_join_each_row_once(spark):
    """Ids are grouped and dealt without the payload, which then joins a row once, a hub of many blocks too."""
    data = [(g, g * 100 + i, i // 2) for g, n in ((1, 60), (2, 5)) for i in range(n)]
    df = spark.createDataFrame(data, "g long, rid long, v long")
    asked = []

    def attach(r):
        asked.append(sorted(x["rid"] for x in r.select("rid").collect()))
        assert "v" not in r.columns
        return r.join(df.select("rid", "v"), "rid")

    def make_near(t):
        v = t.column("v").to_numpy()
        return lambda i, rest: np.abs(v[rest] - v[i]) <= 1

    found = set_join.search_groups(df.select("g", "rid"), "g", make_near, 4, 6, attach, ["v"])
    got = {r["id"]: r["component_id"] for r in connected_components(found).collect()}
    assert got == {r: g * 100 for g, r, _ in data} and asked[0] == sorted(r for _, r, _ in data)


def test_repeated_and_large_ids_of_texts(spark):
    big, a, b = 6 * 10**18, "p q r s t u v", "a b c d e f g"
    data = [(5, a), (5, b), (3, a), (9, b), (big + 1, "x y"), (big + 2, "x y"), (big + 3, "X Y"), (7, None), (7, "one two three"), (8, "one two three")]
    df = spark.createDataFrame([(*d, 1, "z") for d in data], "doc_id long, text string, n long, digest string")
    got = {(r["doc_id"], r["component_id"], r["kept"]) for r in set_join.near_duplicates(df).collect()}
    assert got == {(5, 3, False), (3, 3, True), (9, 3, False), (big + 1, big + 1, True), (big + 2, big + 1, False), (big + 3, big + 1, False), (7, 7, True), (8, 7, False)}
    kept = set_join.keep_one(df)
    assert kept.columns == df.columns
    assert sorted((r["doc_id"], r["text"] or "") for r in kept.collect()) == sorted([(3, a), (5, b), (big + 1, "x y"), (7, ""), (7, "one two three")])


def test_exact_dedup_of_repeated_ids(spark):
    df = spark.createDataFrame([(1, "q", 0), (1, "q", 0), (1, "B", 0), (2, "b", 0), (None, "z", 1), (None, "Z", 2), (None, "q", 3), (6 * 10**18, "z9", 0)], "doc_id long, text string, h128 long")
    kept = exact_dedup.keep_first(df)
    assert kept.columns == df.columns
    assert sorted(str((r["doc_id"], r["text"].lower())) for r in kept.collect()) == sorted(map(str, [(1, "q"), (1, "b"), (None, "z"), (6 * 10**18, "z9")]))
    assert exact_dedup.keep_first(df.limit(0)).count() == 0


def test_near_duplicates_odd_rows(spark):
    df = spark.createDataFrame([(None, "a b c"), (1, "a b c"), (1, "a b c"), (2, None)], "doc_id long, text string")
    got = sorted(map(str, (tuple(r) for r in set_join.near_duplicates(df).collect())))
    assert got == sorted(map(str, [(None, 1, None, True), (1, 1, 1, True), (1, 1, 1, True), (2, 0, 2, True)]))
    assert set_join.near_duplicates(df.limit(0)).count() == 0


def brute_vectors(data, least):
    ok = {}
    for i, v, lab in data:
        if lab is None or v is None or None in v or not np.isfinite(v).all() or not np.any(v):
            continue
        x = np.array(v, np.float64)
        ok[i] = (x / np.linalg.norm(x), lab)
    links = [(a, b) for a, b in itertools.combinations(ok, 2) if ok[a][1] == ok[b][1] and float(ok[a][0] @ ok[b][0]) >= least]
    comp = components([d[0] for d in data], links)
    deg = {d[0]: 0 for d in data}
    for a, b in links:
        deg[a] += 1
        deg[b] += 1
    return {i: (deg[i], comp[i], comp[i] == i) for i in deg}


@pytest.mark.parametrize("block", [1024, 7])
def test_vectors_equal_brute_force(spark, monkeypatch, block):
    monkeypatch.setattr(pivot_join, "BLOCK", block)
    rng = np.random.default_rng(5)
    data = []
    for c in range(30):
        centre = rng.standard_normal(16)
        for _ in range(rng.integers(1, 9)):
            data.append((len(data), (centre + rng.standard_normal(16) * rng.choice([0.02, 0.06, 0.3])).astype(np.float32).tolist(), int(c % 3)))
        if c % 4 == 0:
            data += [(len(data) + k, data[-1][1], data[-1][2]) for k in range(3)]
    n = len(data)
    data += [(n, None, 1), (n + 1, [0.0] * 16, 1), (n + 2, [float("nan")] + [1.0] * 15, 1), (n + 3, data[0][1], None), (n + 4, [None] + [1.0] * 15, 1), (n + 5, [float("inf")] * 16, 1), (n + 6, [1.0, 2.0], 0), (n + 7, [2.0, 4.0], 0), (n + 8, [], 0)]
    df = spark.createDataFrame(data, "vec_id long, embedding array<float>, label int")
    small = [d for d in data if d[1] is None or len(d[1]) in (0, 16)]
    want = brute_vectors(small, 0.98) | {n + 6: (1, n + 6, True), n + 7: (1, n + 6, False)}
    got = rows(pivot_join.near_duplicates(df), "vec_id", "n_links", "component_id", "kept")
    assert got == want


@pytest.mark.parametrize("rows", [1000, 50_000, 1_000_000])
def test_vector_recall_on_random_pairs(rows):
    """Pairs at the threshold share two pivots, however many pivots the table's size asks for."""
    rng = np.random.default_rng(11)
    n, nearest = pivot_join.plan_pivots(rows)
    p = pivot_join.pivots(64, n)
    a = rng.standard_normal((3000, 64))
    a /= np.linalg.norm(a, axis=1, keepdims=True)
    b = rng.standard_normal(a.shape)
    b -= (a * b).sum(1, keepdims=True) * a
    b /= np.linalg.norm(b, axis=1, keepdims=True)
    b = 0.98 * a + np.sqrt(1 - 0.98**2) * b
    da, db = (np.concatenate([pivot_join.describe(x[i : i + 200], p, nearest) for i in range(0, 3000, 200)]) for x in (a, b))
    hit = (da[:, :, None] == db[:, None, :]).sum((1, 2)) >= pivot_join.SHARED
    assert hit.mean() >= 0.999


def test_vector_recall_on_the_table():
    """Each vector of the given table and one at the threshold from it are candidates; few unlike pairs are looked at."""
    import pyarrow.parquet as pq

    t = pq.read_table("/root/testdata/sf0.1/embeddings.parquet")
    x, labels = np.array(t["embedding"].to_pylist(), np.float64), np.array(t["label"].to_pylist())
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    b = np.random.default_rng(3).standard_normal(x.shape)
    b -= (x * b).sum(1, keepdims=True) * x
    y = 0.98 * x + np.sqrt(1 - 0.98**2) * b / np.linalg.norm(b, axis=1, keepdims=True)
    n, nearest = pivot_join.plan_pivots(int(np.bincount(labels).max()))
    p = pivot_join.pivots(64, n)
    mark = np.zeros((2, len(x), n), np.float32)
    for m, v in zip(mark, (x, y), strict=True):
        np.put_along_axis(m, pivot_join.describe(v, p, nearest), 1, axis=1)
    assert ((mark[0] * mark[1]).sum(1) >= pivot_join.SHARED).mean() >= 0.999
    same = (labels[:, None] == labels[None, :]) & ~np.eye(len(x), dtype=bool)
    assert (mark[0] @ mark[0].T >= pivot_join.SHARED)[same].mean() < 0.06


def test_repeated_and_large_ids(spark):
    """An id with two vectors is one thing with two rows; ids near 2**63 do not overflow."""
    big = 6 * 10**18
    v, w, u = [1.0, 0.0, 0.0], [0.0, 1.0, 0.0], [0.0, 0.0, 1.0]
    near = lambda x: [a + 0.01 for a in x]
    data = [(1, v, 0), (1, w, 0), (2, near(v), 0), (3, near(w), 0), (4, u, 0), (4, None, 0), (4, u, 0), (big + 1, v, 1), (big + 2, near(v), 1), (big + 3, [1.0, 0.02, 0.0], 1), (None, v, 0)]
    got = sorted(pivot_join.near_duplicates(spark.createDataFrame(data, "vec_id long, embedding array<double>, label int")).collect(), key=str)
    want = [(1, 1, 1, True), (1, 1, 1, True), (2, 1, 1, False), (3, 1, 1, False), (4, 1, 4, True), (4, 0, 4, True), (4, 1, 4, True), (big + 1, 2, big + 1, True), (big + 2, 2, big + 1, False), (big + 3, 2, big + 1, False), (None, 0, None, False)]
    assert sorted(map(str, map(tuple, got))) == sorted(map(str, want))


def test_vectors_of_nothing(spark):
    df = spark.createDataFrame([], "vec_id long, embedding array<float>, label int")
    assert pivot_join.near_duplicates(df).count() == 0


def words(rng, n):
    return " ".join("".join(rng.choice("abcdefghijklmnoprstu") for _ in range(rng.randrange(2, 9))) for _ in range(n))


def test_gear_hash_rolls():
    raw = np.frombuffer(np.random.default_rng(2).bytes(500), np.uint8)
    h, want = substring.gear_hash(raw), 0
    for i, b in enumerate(raw):
        want = ((want << 1) + int(substring.GEAR[b])) & 0xFF
        assert int(h[i]) == want


def test_chunks_resist_shifts():
    rng = random.Random(4)
    text = words(rng, 800)
    cut = lambda t: {t.encode()[a:b].strip() for a, b in itertools.pairwise([0, *substring.boundaries(t.encode()).tolist()])}
    a, b = cut(text), cut("inserted words " + text)
    assert len(a & b) > 0.97 * len(a)
    assert b"".join(text.encode()[x:y] for x, y in itertools.pairwise([0, *substring.boundaries(text.encode()).tolist()])) == text.encode()


def test_substring_dedup_finds_planted_passages(spark):
    rng = random.Random(9)
    data, passages = [], []
    for p in range(20):
        passage = words(rng, rng.randrange(51, 90))
        passages.append(passage)
        for k in range(3):
            data.append((p * 10 + k, f"{words(rng, 60)}\n{passage} {words(rng, 60)}"))
    clean = [(1000 + i, words(rng, 200)) for i in range(20)]
    df = spark.createDataFrame(data + clean + [(5000, None), (5001, ""), (None, passages[0]), (5002, "é" * 5000), (5003, "a b c. " * 20000)], "doc_id long, text string")
    got = {r["doc_id"]: r for r in substring.dedup(df).collect()}
    before = dict(data)
    for p, passage in enumerate(passages):
        assert got[p * 10]["text"] == before[p * 10]
        middle = " ".join(passage.split()[9:-9])
        for k in (1, 2):
            assert middle not in got[p * 10 + k]["text"]
            assert len(got[p * 10 + k]["text"].split()) >= 116
    for i, t in clean:
        assert got[i]["text"] == t
    assert got[5000]["text"] is None and got[5001]["text"] == "" and got[None]["text"] == passages[0]


def brute_substring(data, min_words=25):
    """Plain Python over tuples of chunk texts: which chunks lie in a passage that an earlier document has."""
    cuts = {}
    for k, (i, t) in enumerate(data):
        raw, at, parts = (t or "").encode(), 0, []
        for e in substring.boundaries(raw).tolist():
            parts.append(raw[at:e])
            at = e
        cuts[k] = (i, parts)
    where, spans = {}, {}
    for k, (i, parts) in cuts.items():
        for a in range(len(parts)):
            n = 0
            for b in range(a, len(parts)):
                n += len(parts[b].split())
                if n >= min_words:
                    key = tuple(p.strip() for p in parts[a : b + 1])
                    spans.setdefault(k, []).append((a, b, key))
                    if i is not None:
                        where.setdefault(key, set()).add(i)
                    break
    out, gone = [], []
    for k, (i, parts) in cuts.items():
        drop = set()
        for a, b, key in spans.get(k, ()):
            if i is not None and min(where[key]) < i:
                drop |= set(range(a, b + 1))
                gone.append((i, key))
        text = data[k][1]
        out.append((i, text if not drop else b"".join(p for j, p in enumerate(parts) if j not in drop).decode("utf-8", "replace")))
    return out, gone


def test_substring_dedup_equals_brute_force(spark):
    """Stitched, shifted, nested and side-by-side passages, repeated ids; and all that goes lies in one earlier text."""
    rng = random.Random(12)
    texts = [words(rng, 120) for _ in range(30)]
    data = list(enumerate(texts))
    phrases = [" ".join(t.split()[k : k + 8]) for t in texts for k in (3, 40)]
    stitched = " ".join(rng.sample(phrases, 40))
    data += [(100, stitched), (101, f"{texts[3]} {texts[4]}"), (102, " ".join(texts[5].split()[10:80]) + " " + words(rng, 20)), (103, words(rng, 7) + " " + " ".join(texts[6].split()[20:47])), (104, texts[7].replace(" ", "\n ")), (105, "ß é 日本 " * 40), (106, "ß é 日本 " * 40)]
    data += [(110, texts[8]), (110, words(rng, 150)), (110, texts[8]), (111, words(rng, 30) + " " + texts[9] + " " + texts[9]), (None, texts[1]), (112, None), (113, "")]
    df = spark.createDataFrame(data, "doc_id long, text string")
    got = [(r["doc_id"], r["text"]) for r in substring.dedup(df).collect()]
    want, gone = brute_substring(data)
    assert sorted(map(str, got)) == sorted(map(str, want))
    assert (100, stitched) in got, "a text made of many documents' phrases is no copy"
    squeezed = [(i, b" ".join((t or "").encode().split())) for i, t in data if i is not None]
    for i, key in gone:
        piece = b" ".join(b" ".join(key).split())
        assert any(j < i and piece.replace(b" ", b"") in t.replace(b" ", b"") for j, t in squeezed)


def test_substring_dedup_on_the_table(spark, sf):
    data = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    got = [(r["doc_id"], r["text"]) for r in substring.dedup(spark.createDataFrame(data, "doc_id long, text string")).collect()]
    assert sorted(map(str, got)) == sorted(map(str, brute_substring(data)[0]))


def test_substring_dedup_empty_and_clashing_columns(spark):
    df = spark.createDataFrame([(1, "x", 5)], "doc_id long, text string, n_chunks long")
    assert substring.dedup(df).columns == ["doc_id", "text", "n_chunks", "n_duplicate", "removed_bytes"]
    assert substring.dedup(df.limit(0)).count() == 0
