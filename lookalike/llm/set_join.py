"""Near-duplicate documents by a chosen-path set similarity join.

Every document's set of word shingles is sketched by minwise hashes. A tree sends documents down
branches named by the minwise tokens that they hold: the root branches on one coordinate, a node
with more than ``leaf`` documents on two more, chosen by the node itself, if that thins it. Two sets of similarity
s meet under one coordinate with probability s, so independent trees reach any recall. Leaves are
searched exhaustively on sketches, which yields candidate groups; inside a group every link is
then confirmed on the full sets. Both searches walk breadth first: what is already known to be
connected is not compared again, so a group of near copies costs a pass, not a square. A group of
many rows is dealt to blocks of rows: each block first searches itself beside a few members that
all blocks get, then only rows that this has not yet joined to the group's largest part meet the
others, block by block.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import connected_components, cut, drop_cut, free_shuffles, name_components, ship, sorted_groups

WIDTH = 5
#: Coordinates of a sketch, 16 bits each.
COORDS = 128
#: Independent trees. A pair at 0.85 is missed by one tree with about 0.18 even below deep nodes: 0.18**6 < 4e-5.
TREES = 6
#: Documents of a node that are searched exhaustively; larger nodes branch again, to this depth.
LEAF, DEPTH = 512, 3
#: Rows of one block: of a node's sketches; of a candidate group's texts, in the first pass and in the second.
SKETCH_ROWS, TEXT_ROWS, PAIR_ROWS = 4096, 64, 512
#: Members of a group of several blocks that every block gets.
HUBS = 4
#: Standard deviations of the estimate by which a candidate may fall short of the threshold.
SLACK = 4.5
#: Words that a worker remembers the hashes of.
MEMO = 500_000

_MULT = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5, 0x85EBCA77C2B2AE63], np.uint64)


class _Words(dict):
    def __missing__(self, w):
        v = xxhash.xxh3_64_intdigest(w)
        if len(self) >= MEMO:
            self.clear()
        self[w] = v
        return v


_words = _Words()


def _mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x7FB5D329728EA185)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


def shingle_set(text: str | None, width: int = WIDTH) -> np.ndarray:
    """Sorted 64-bit hashes of the distinct ``width``-word shingles of a whole text.

    Words are what ASCII white space leaves, lower-cased in A-Z only. A text of fewer words is one
    shingle; null, or no word, is the empty set.
    """
    words = text.encode().lower().split() if text else ()
    n = len(words)
    if not n:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(_words.__getitem__, words), np.uint64, n)
    if n < width:
        s = np.add.reduce(h * _mix(np.arange(1, n + 1, dtype=np.uint64)), keepdims=True) + np.uint64(n)
        return _mix(s)
    s = h[: n - width + 1] * _mult(width)[0]
    for j in range(1, width):
        s = s + h[j : n - width + 1 + j] * _mult(width)[j]
    return np.unique(_mix(s))


def _mult(width: int) -> np.ndarray:
    return _MULT if width == len(_MULT) else _mix(np.arange(101, 101 + width, dtype=np.uint64)) | np.uint64(1)


def _family(coords: int) -> tuple[np.ndarray, np.ndarray]:
    x = _mix(np.arange(1, 2 * coords + 1, dtype=np.uint64))
    return (x[:coords].astype(np.uint32) | np.uint32(1))[:, None], x[coords:].astype(np.uint32)[:, None]


_A, _B = _family(COORDS)


def sketch(s: np.ndarray) -> np.ndarray:
    """The low 16 bits of each coordinate's minwise hash."""
    x = (s >> np.uint64(32)).astype(np.uint32)
    low = np.full(COORDS, 0xFFFFFFFF, np.uint32)
    for i in range(0, len(x), 512):
        low = np.minimum(low, ((x[None, i : i + 512] + _B) * _A).min(axis=1))
    return ((low ^ (low >> np.uint32(16))) & np.uint32(0xFFFF)).astype(np.uint16)


SKETCH = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("n", T.LongType()), T.StructField("digest", T.BinaryType()), T.StructField("text_md5", T.BinaryType()), T.StructField("sketch", T.BinaryType())])


def set_digest(s: np.ndarray) -> bytes:
    """128 bits that name a shingle set."""
    return hashlib.blake2b(s, digest_size=16).digest()


def sketches(docs: DataFrame, id_col: str, text_col: str, width: int) -> DataFrame:
    """``doc_id, n, digest, text_md5, sketch``: set size, 128-bit digests of the set and of the text, minwise sketch."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                texts = [t.as_py() or "" for t in part.column(1)]
                sets = [shingle_set(t, width) for t in texts]
                yield pa.RecordBatch.from_arrays(
                    [
                        part.column(0),
                        pa.array([len(s) for s in sets], pa.int64()),
                        pa.array(map(set_digest, sets), pa.binary()),
                        pa.array([hashlib.md5(t.encode()).digest() for t in texts], pa.binary()),
                        pa.array([sketch(s).tobytes() for s in sets], pa.binary()),
                    ],
                    names=SKETCH.names,
                )

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, SKETCH)


def _token(coord) -> F.Column:
    """A coordinate's 16-bit token as hex, straight from the binary sketch."""
    return F.hex(F.substring("sketch", coord * 2 + 1, 2))


def _components(n: int, near) -> np.ndarray:
    """Roots of the graph whose edges ``near(i, rest)`` reveals: a mask over ``rest``; breadth first over what is left."""
    root = np.full(n, -1, np.int64)
    rest = np.arange(n)
    while len(rest):
        first, rest = rest[0], rest[1:]
        root[first] = first
        queue = [first]
        while queue and len(rest):
            hit = near(queue.pop(), rest)
            found = rest[hit]
            root[found] = first
            queue.extend(found.tolist())
            rest = rest[~hit]
    return root


def _bridges(comp: np.ndarray, left: np.ndarray, right: np.ndarray, near) -> list[tuple[int, int]]:
    """Edges between rows of different ``comp``, from ``left`` to ``right``, one for each pair of parts that they join."""
    part, out = comp.copy(), []
    for i in left.tolist():
        rest = right[part[right] != part[i]]
        if not len(rest):
            continue
        hits = rest[near(i, rest)]
        for j in hits.tolist():
            if part[j] != part[i]:
                out.append((i, j))
                part[part == part[j]] = part[i]
    return out


EDGES = T.StructType([T.StructField("a", T.LongType()), T.StructField("b", T.LongType())])


def _edges_of(ids: np.ndarray, root: np.ndarray) -> pa.RecordBatch | None:
    """Stars from the smallest id of each component of two and more."""
    order = np.lexsort((ids, root))
    r, i = root[order], ids[order]
    first = np.concatenate(([True], r[1:] != r[:-1]))
    centre = np.repeat(i[first], np.diff(np.append(np.flatnonzero(first), len(r))))
    keep = ~first
    if not keep.any():
        return None
    return pa.RecordBatch.from_arrays([pa.array(centre[keep]), pa.array(i[keep])], names=EDGES.names)


def search_groups(rows: DataFrame, key: str, make_near, block: int, pair_block: int, attach=None, payload: list[str] | None = None) -> DataFrame:
    """Edges ``a, b`` that connect all rows of a group which the predicate links; ``rows`` has ``key``, ``rid`` and payload.

    ``make_near(table)`` builds ``near(i, rest)`` over an Arrow table of payload columns. Where those
    are wide, ``attach`` adds the columns ``payload`` to rows that have been dealt, so that ids alone are
    grouped and a payload travels to its row and to its block, no more often. Groups up
    to ``block`` rows are one task's; a larger one is dealt to such blocks by hash. In the first pass a
    block also gets the group's hubs, the ``HUBS`` rows with the smallest hashes. In the second,
    rows outside the group's largest part so far meet each other and that part, in pairs of blocks of ``pair_block`` rows;
    parts that the first pass joined are not compared again. No link is lost: two linked rows lie in
    one part after the first pass, or meet in the second.
    """
    light = [c for c in rows.columns if c not in (key, "rid")]
    payload, attach = payload or light, attach or (lambda r: r)
    order = [F.min(F.struct(F.xxhash64("rid", F.lit(h)), "rid"))["rid"] for h in range(HUBS)]
    sized = cut(rows.groupBy(key).agg(F.count("*").alias("members"), F.array(*order).alias("hubs")).filter("members > 1"), "groups")
    nb = F.ceil(F.col("members") / block).cast("int")
    r = rows.join(sized, key).withColumn("nb", nb).withColumn("own", F.pmod(F.xxhash64("rid", F.lit(5)), F.col("nb")).cast("int"))
    where = F.when((F.col("nb") > 1) & F.array_contains("hubs", F.col("rid")), F.sequence(F.lit(0), F.col("nb") - 1)).otherwise(F.array("own"))
    r = r.select(F.transform(where, lambda b: F.xxhash64(F.col(key), b)).alias("grps"), "rid", *light)
    r = attach(r).select(F.explode("grps").alias("grp"), "rid", *payload)

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in sorted_groups(batches):
            if (e := _edges_of(t.column(1).to_numpy(), _components(t.num_rows, make_near(t.select(payload))))) is not None:
                yield e

    edges = cut(r.repartition("grp").sortWithinPartitions("grp").mapInArrow(first, EDGES).distinct(), "edges")
    free_shuffles(rows.sparkSession)
    big = sized.filter(F.col("members") > block).select(key)
    if big.isEmpty():
        return edges
    part = connected_components(edges).select(F.col("id").alias("__i"), F.col("component_id").alias("part"))
    ids = rows.select(key, "rid").join(big, key, "left_semi").join(part, F.col("rid") == F.col("__i"), "left").select(key, "rid", F.coalesce("part", "rid").alias("part"))
    ids = cut(ids, "parts")
    sizes = ids.groupBy(key, "part").agg(F.count("*").alias("n"))
    about = sizes.groupBy(key).agg(F.max_by("part", F.struct("n", "part")).alias("main"), F.sum("n").alias("all"), F.max("n").alias("most")).filter("most < all")
    about = about.select(key, "main", F.ceil(F.col("most") / pair_block).cast("int").alias("ng"), F.ceil((F.col("all") - F.col("most")) / pair_block).cast("int").alias("nl"))
    if about.isEmpty():
        return edges
    # of the rows outside the main part the blocks meet each other and, block by block, the main part
    m = ids.join(about, key).withColumn("outer", F.col("part") != F.col("main"))
    own = F.pmod(F.xxhash64("rid", F.lit(7)), F.when(F.col("outer"), F.col("nl")).otherwise(F.col("ng"))).cast("int")
    m = m.withColumn("own", own)
    each = lambda n: F.sequence(F.lit(0), F.col(n) - 1)
    among = F.transform(each("nl"), lambda o: F.xxhash64(F.col(key), F.lit(1), F.least(o, F.col("own")), F.greatest(o, F.col("own"))))
    to_main = F.transform(each("ng"), lambda o: F.xxhash64(F.col(key), F.lit(2), F.col("own"), o))
    to_outer = F.transform(each("nl"), lambda o: F.xxhash64(F.col(key), F.lit(2), o, F.col("own")))
    kind = F.when(F.col("outer"), F.concat(F.transform(among, lambda g: F.struct(g.alias("grp"), F.lit(1).alias("kind"))), F.transform(to_main, lambda g: F.struct(g.alias("grp"), F.lit(2).alias("kind"))))).otherwise(F.transform(to_outer, lambda g: F.struct(g.alias("grp"), F.lit(2).alias("kind"))))
    m = m.select(F.col(key).alias("__k"), F.col("rid").alias("__r"), "part", "outer", kind.alias("__gs"))
    r = rows.join(m, (F.col(key) == F.col("__k")) & (F.col("rid") == F.col("__r"))).drop(key, "__k", "__r")
    r = attach(r).select(F.explode("__gs").alias("__g"), "rid", "part", "outer", *payload).select("__g.grp", "__g.kind", "rid", "part", "outer", *payload)

    def second(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in sorted_groups(batches):
            kinds, ids, parts, outer = (t.column(i).to_numpy() for i in (1, 2, 3, 4))
            left = np.flatnonzero(outer)
            right = left if kinds[0] == 1 else np.flatnonzero(~outer)
            if len(left) and len(right):
                found = _bridges(parts, left, right, make_near(t.select(payload)))
                if found:
                    i, j = np.array(found).T
                    yield pa.RecordBatch.from_arrays([pa.array(ids[i]), pa.array(ids[j])], names=EDGES.names)

    return edges.union(cut(r.repartition("grp").sortWithinPartitions("grp").mapInArrow(second, EDGES), "bridges"))


def candidate_edges(reps: DataFrame, similarity: float, trees: int = TREES, leaf: int = LEAF, depth: int = DEPTH) -> DataFrame:
    """Edges that connect what the trees hold similar by its sketch; ``reps`` has ``rid, n, sketch``."""
    spark = reps.sparkSession
    least = max(1, math.floor(COORDS * (similarity - SLACK * math.sqrt(similarity * (1 - similarity) / COORDS))))

    def with_tokens(rows: DataFrame) -> DataFrame:
        """``node, rid`` and the tokens at the two coordinates that the node chooses: the sketch stays behind."""
        at = lambda b: _token(F.pmod(F.xxhash64("node", F.lit(b)), F.lit(COORDS)).cast("int"))
        return cut(rows.select("node", "rid", at(1).alias("t1"), at(2).alias("t2")), "level")

    roots = F.explode(F.array(*[F.xxhash64(F.lit(t), _token(F.lit(t))) for t in range(trees)]))
    level, leaves, made = with_tokens(reps.select(roots.alias("node"), "rid", "sketch")), [], []
    for d in range(depth + 1):
        made.append(level)
        sized = cut(level.groupBy("node").agg(F.count("*").alias("members")).filter("members > 1"), "nodes")
        made.append(sized)
        large = sized.filter(F.col("members") > leaf)
        if d == depth or large.isEmpty():
            leaves.append(level.join(sized, "node").select("node", "rid"))
            break
        # two branches thin a node only where no token is held by half of it; near copies are a leaf of any size
        top = level.join(large, "node").groupBy("node", "members", "t1").agg(F.count("*").alias("holders"))
        thick = top.groupBy("node", "members").agg(F.max("holders").alias("most")).filter("2 * most > members").select("node")
        split = cut(large.join(thick, "node", "left_anti").select("node"), "split")
        leaves.append(level.join(sized.join(split, "node", "left_anti"), "node").select("node", "rid"))
        if split.isEmpty():
            break
        branches = F.array(*[F.xxhash64("node", F.lit(b), F.col(f"t{b}")) for b in (1, 2)])
        level = with_tokens(level.join(split, "node").select(F.explode(branches).alias("node"), "rid").join(reps.select("rid", "sketch"), "rid"))
    found = leaves[0]
    for more in leaves[1:]:
        found = found.union(more)
    found = cut(found, "found")
    for old in made:
        drop_cut(old)
    free_shuffles(spark)

    def make_near(t: pa.Table):
        n = t.column("n").to_numpy()
        sk = np.frombuffer(b"".join(t.column("sketch").to_pylist()), np.uint16).reshape(-1, COORDS)

        def near(i, rest):
            a, b = np.minimum(n[rest], n[i]), np.maximum(n[rest], n[i])
            hit = a >= similarity * b - 1e-9
            at = np.flatnonzero(hit)
            hit[at] = (sk[rest[at]] == sk[i]).sum(1) >= least
            return hit

        return near

    edges = cut(search_groups(found, "node", make_near, SKETCH_ROWS, SKETCH_ROWS, lambda r: r.join(reps.select("rid", "n", "sketch"), "rid"), ["n", "sketch"]).distinct(), "candidates")
    drop_cut(found)
    free_shuffles(spark)
    return edges


def confirmed_edges(docs: DataFrame, members: DataFrame, similarity: float, id_col: str, text_col: str, width: int) -> DataFrame:
    """Edges inside candidate groups, each confirmed on the full shingle sets.

    ``members`` has ``rid, doc_id, digest, group_id``; texts of members alone travel. Rows that repeat an id
    are told apart by the digest of their set: a text that is not the member's has no set here.
    """
    percent = round(similarity * 100)
    texts = docs.select(F.col(id_col).cast("long").alias("__id"), F.col(text_col).cast("string").alias("text"))
    none = np.zeros(0, np.uint64)

    def make_near(t: pa.Table):
        sets = [shingle_set(x.as_py(), width) for x in t.column("text")]
        sets = [s if set_digest(s) == d.as_py() else none for s, d in zip(sets, t.column("digest"), strict=True)]
        n = np.array([len(s) for s in sets], np.int64)
        flat = np.concatenate(sets)
        lo = np.concatenate(([0], np.cumsum(n)))

        def near(i, rest):
            mine = sets[i]
            if not len(mine):
                return np.zeros(len(rest), bool)
            hit = (np.minimum(n[rest], n[i]) * 100 >= percent * np.maximum(n[rest], n[i])) & (n[rest] > 0)
            at = np.flatnonzero(hit)
            if not len(at):
                return hit
            if len(at) < len(n) // 2:
                shared = np.array([len(np.intersect1d(mine, sets[j], assume_unique=True)) for j in rest[at]], np.int64)
            else:
                place = np.searchsorted(mine, flat)
                same = mine[np.minimum(place, len(mine) - 1)] == flat
                total = np.concatenate(([0], np.cumsum(same)))
                shared = (total[lo[1:]] - total[lo[:-1]])[rest[at]]
            hit[at] = 100 * shared >= percent * (n[rest[at]] + n[i] - shared)
            return hit

        return near

    attach = lambda r: r.join(texts, F.col("doc_id") == F.col("__id"))
    return search_groups(members.select("group_id", "rid", "doc_id", "digest"), "group_id", make_near, TEXT_ROWS, PAIR_ROWS, attach, ["text", "digest"])


def row_classes(docs: DataFrame, id_col: str, text_col: str, similarity: float, width: int, trees: int) -> tuple[DataFrame, DataFrame]:
    """Rows ``id, n, text_md5, node`` and links ``a, b`` between nodes.

    A node stands for all rows of one shingle set, and is the number of one of them; a row with the
    empty set, or without an id, is a node of its own.
    """
    sk = cut(sketches(docs, id_col, text_col, width).withColumn("rid", F.monotonically_increasing_id()), "sketches")
    named = sk.filter("doc_id is not null and n > 0")
    classes = cut(named.groupBy("digest").agg(F.min("rid").alias("node")), "classes")
    reps = cut(named.join(classes.select("node"), F.col("rid") == F.col("node"), "left_semi").select("rid", "doc_id", "n", "digest", "sketch"), "reps")
    groups = cut(connected_components(candidate_edges(reps.select("rid", "n", "sketch"), similarity, trees)), "groups")
    members = cut(groups.select(F.col("id").alias("rid"), F.col("component_id").alias("group_id")).join(reps.select("rid", "doc_id", "digest"), "rid"), "members")
    drop_cut(reps)
    free_shuffles(docs.sparkSession)
    links = cut(confirmed_edges(docs, members, similarity, id_col, text_col, width), "links")
    free_shuffles(docs.sparkSession)
    rows = sk.select(F.col("doc_id").alias("id"), "n", "digest", "text_md5", "rid")
    known = rows.join(classes.withColumnRenamed("node", "__n"), "digest", "left")
    node = F.when((F.col("n") > 0) & F.col("id").isNotNull(), F.col("__n")).otherwise(F.col("rid"))
    return known.select("id", "n", "text_md5", node.alias("node")), links


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", similarity: float = 0.85, width: int = WIDTH, trees: int = TREES) -> DataFrame:
    """``id_col, n_shingles, component_id, kept`` for every row.

    Documents are linked when their distinct shingles overlap by at least ``similarity`` of the
    union (in whole percent); ``component_id`` is the smallest id that links reach and the row
    with that id is kept. Null text and text without words have the empty set and no link. A row
    with a null id takes part in no link, has a null component and is kept. Rows that repeat an id
    are one document, whatever their texts: they share the component that any of them reaches. An
    empty table gives no rows; other columns are not read.
    """
    rows, links = row_classes(docs, id_col, text_col, similarity, width, trees)
    rows = cut(rows, "rows")
    named = name_components(rows.filter("id is not null").select("id", "node", "n"), links).select("id", "n", "component_id")
    nameless = rows.filter("id is null").select("id", "n", F.lit(None).cast("long").alias("component_id"))
    return named.union(nameless).select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), "component_id").withColumn(
        "kept", F.coalesce(F.col(id_col) == F.col("component_id"), F.lit(True))
    )


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", similarity: float = 0.8, width: int = WIDTH, trees: int = TREES) -> DataFrame:
    """``docs`` without near copies: of each group of linked rows the one with the smallest id stays, with all its columns.

    Rows count by themselves here: one that repeats an id with another text stays or goes by its own
    text alone. Rows that repeat both id and text are one. Rows with a null id, and those
    without words, stay.
    """
    rows, links = row_classes(docs, id_col, text_col, similarity, width, trees)
    rows = cut(rows.filter("id is not null and n > 0"), "rows")
    found = connected_components(links).select(F.col("id").alias("node"), F.col("component_id").alias("__c"))
    rows = rows.join(found, "node", "left").withColumn("__c", F.coalesce("__c", "node"))
    first = rows.groupBy("__c").agg(F.min(F.struct("id", "text_md5")).alias("first"))
    gone = rows.join(first, "__c").filter(F.struct("id", "text_md5") != F.col("first")).select(F.col("id").alias("__gone"), F.col("text_md5").alias("__md5"))
    gone = cut(gone.distinct(), "gone")
    here = F.unhex(F.md5(F.coalesce(docs[text_col].cast("string"), F.lit(""))))
    return docs.join(gone, (docs[id_col].cast("long") == gone["__gone"]) & (here == gone["__md5"]), "left_anti")
