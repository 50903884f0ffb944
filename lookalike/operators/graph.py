"""Graphs as two relations: nodes and canonical edges (src < dst, no loops, no repeats)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import dot, unit
from ..session import cut
from .kernels import blocked_pairs


@dataclass
class AnchoredGraph:
    """``nodes(node_id, x array<double>, label, ...)`` and ``edges(src, dst)`` with src < dst."""

    nodes: DataFrame
    edges: DataFrame

    def both_ways(self) -> DataFrame:
        return symmetrize(self.edges)

    def with_nodes(self, nodes: DataFrame) -> AnchoredGraph:
        """The same edges between nodes with other columns."""
        return AnchoredGraph(nodes, self.edges)

    def among(self, ids: DataFrame) -> DataFrame:
        """``src, dst``: the edges between nodes of ``ids`` (node_id)."""
        src, dst = (ids.select(F.col("node_id").alias(c)) for c in ("src", "dst"))
        return self.edges.join(src, "src", "left_semi").join(dst, "dst", "left_semi").select("src", "dst")

    def around(self, ids: DataFrame) -> DataFrame:
        """``seed, node_id``: the neighbours of each node of ``ids`` (node_id)."""
        return self.both_ways().join(ids.select(F.col("node_id").alias("src")), "src", "left_semi").select(F.col("src").alias("seed"), F.col("dst").alias("node_id"))

    def degrees(self) -> DataFrame:
        """``node_id, deg`` of nodes that have neighbours."""
        return self.both_ways().groupBy(F.col("src").alias("node_id")).agg(F.count("*").alias("deg"))


def canonical(pairs: DataFrame, a: str = "src", b: str = "dst") -> DataFrame:
    """Unordered pairs once each, without loops."""
    return pairs.select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst")).filter("src < dst").distinct()


def symmetrize(edges: DataFrame) -> DataFrame:
    """Both directions of canonical edges: no distinct is needed."""
    return edges.select("src", "dst").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


def pairs_in_groups(r: DataFrame, group: str, block: int | None = None) -> DataFrame:
    """``src, dst`` for every pair of items ``i`` of a group, once per group; ``r`` has an item of a group once."""
    ends = F.least("a.i", "b.i").alias("src"), F.greatest("a.i", "b.i").alias("dst")
    if block:
        blocks = r.groupBy(group).agg(F.ceil(F.count("*") / block).cast("int").alias("nb"))
        r = r.join(blocks, group).withColumn("own", F.pmod(F.xxhash64("i"), F.col("nb")).cast("int"))
        a = r.select(group, "i", F.col("own").alias("lo"), F.explode(F.sequence("own", F.col("nb") - 1)).alias("hi")).alias("a")
        b = r.select(group, "i", F.explode(F.sequence(F.lit(0), F.col("own"))).alias("lo"), F.col("own").alias("hi")).alias("b")
        met = (F.col(f"a.{group}") == F.col(f"b.{group}")) & (F.col("a.lo") == F.col("b.lo")) & (F.col("a.hi") == F.col("b.hi"))
        return a.join(b, met & ((F.col("a.lo") < F.col("a.hi")) | (F.col("a.i") < F.col("b.i")))).select(*ends)
    a, b = r.alias("a"), r.alias("b")
    return a.join(b, (F.col(f"a.{group}") == F.col(f"b.{group}")) & (F.col("a.i") < F.col("b.i"))).select(*ends)


def co_occurrence(rows: DataFrame, group: str, item: str, min_support: int = 1, max_group: int | None = None, block: int | None = None) -> DataFrame:
    """Pairs of items that share at least ``min_support`` groups: ``src, dst, support``.

    A group's pairs are made inside the join on the group key. ``max_group`` leaves out groups
    with more items, whose pairs grow with the square; None leaves out none. With ``block``, a group
    of more items than that is joined as pairs of blocks, so that no task makes all pairs of a large group.
    """
    r = rows.select(group, F.col(item).alias("i")).distinct()
    if max_group:
        small = r.groupBy(group).agg(F.count("*").alias("n")).filter(F.col("n") <= max_group)
        r = r.join(small, group, "left_semi")
    pairs = pairs_in_groups(r, group, block)
    return pairs.groupBy("src", "dst").agg(F.count("*").alias("support")).filter(F.col("support") >= min_support)


#: Buckets of word counts that are broadcast, whatever the table's size.
COUNTED = 1 << 17


def alike_sets(rows: DataFrame, item: str, elements: str, above: tuple[int, int]) -> DataFrame:
    """``src, dst``: items whose element sets have a Jaccard similarity above ``above`` (a fraction in integers), all of them and exactly.

    Two such sets share one of the first elements of each in any one order of all elements, so only
    pairs that share such an element are compared. The order puts rare elements first, by counts per
    hash bucket; a bucket of several elements costs candidates, never a pair. An empty set is like none.
    """
    num, den = above
    sets = cut(rows.select(F.col(item).alias("i"), F.array_distinct(elements).alias("s")).withColumn("n", F.size("s")).filter("n > 0"), "sets")
    at = F.pmod(F.xxhash64("w"), F.lit(COUNTED)).alias("at")
    counts = cut(sets.select(F.explode("s").alias("w")).groupBy(at).agg(F.count("*").alias("d")), "counts")  # COUNTED rows at most
    words = sets.repartition("i").select("i", "n", F.explode("s").alias("w")).withColumn("at", at).join(F.broadcast(counts), "at")
    ranked = words.groupBy("i", "n").agg(F.array_sort(F.collect_list(F.struct("d", "w"))).alias("o"))
    first = F.expr(f"slice(o, 1, n - CAST(floor(({num} * n + {den - 1}) / {den}) AS INT) + 1)")
    posted = ranked.select(F.struct("i", "n").alias("set"), F.explode(first).alias("p")).select("set", "p.w")
    near = co_occurrence(posted, "w", "set", block=1024).filter(den * F.least("src.n", "dst.n") > num * F.greatest("src.n", "dst.n"))
    a, b = sets.select(F.col("i").alias("src"), F.col("s").alias("s1")), sets.select(F.col("i").alias("dst"), F.col("s").alias("s2"))
    pairs = near.select(F.col("src.i").alias("src"), F.col("dst.i").alias("dst")).join(a, "src").join(b, "dst")
    both = F.size(F.array_intersect("s1", "s2"))
    return pairs.filter(den * both > num * (F.size("s1") + F.size("s2") - both)).select("src", "dst")


def shared_key(rows: DataFrame, item: str, keys: list[str], block: int = 4096) -> DataFrame:
    """Items that agree on all of ``keys``, none of them null; groups of more than ``block`` items are joined as pairs of blocks.

    Where every item has one key a pair is made once, so pairs are neither counted nor shuffled.
    """
    full = rows
    for c in (item, *keys):
        full = full.filter(F.col(c).isNotNull())
    full = full.select(F.struct(*keys).alias("group"), F.col(item).alias("i"))
    if full.groupBy("i").agg(F.min("group").alias("lo"), F.max("group").alias("hi")).filter("lo <> hi").isEmpty():
        return pairs_in_groups(full.distinct(), "group", block).select("src", "dst")
    return co_occurrence(full, "group", "i", block=block).select("src", "dst")


def epsilon(nodes: DataFrame, tau: float, id_col: str = "node_id", vec_col: str = "x", engine: str = "block") -> DataFrame:
    """Pairs whose cosine exceeds ``tau``: ``src, dst``.

    Unit vectors are stored first, so a pair costs one dot product; ``block`` multiplies blocks of
    them, ``sql`` is the theta join.
    """
    u = cut(nodes.select(F.col(id_col).alias("i"), unit(F.col(vec_col)).alias("u")), "unit")
    if engine == "block":
        rows = u.select(F.col("i").alias("node_id"), F.lit(None).cast("int").alias("verdict"), F.col("u").alias("sig"))
        return blocked_pairs(rows, tau, strict=True).select(F.col("a").alias("src"), F.col("b").alias("dst"))
    n = max(1, int(u.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    a, b = u.repartition(n, "i").alias("a"), u.alias("b")
    return a.join(b, F.col("a.i") < F.col("b.i")).filter(F.round(dot("a.u", "b.u"), 9) > tau).select(F.col("a.i").alias("src"), F.col("b.i").alias("dst"))


def degree(edges: DataFrame) -> DataFrame:
    return symmetrize(edges).groupBy(F.col("src").alias("node_id")).agg(F.count("*").alias("degree"))


def khop(edges: DataFrame, seeds: DataFrame, hops: int) -> DataFrame:
    """``seed, node_id, hop``: nodes within ``hops`` of each seed, at their least distance."""
    both = symmetrize(edges)
    seen = seeds.select(F.col("node_id").alias("seed"), F.col("node_id"), F.lit(0).alias("hop"))
    front = seen
    for h in range(1, hops + 1):
        step = front.join(both, front["node_id"] == both["src"]).select("seed", F.col("dst").alias("node_id")).distinct()
        front = cut(step.join(seen.select("seed", "node_id"), ["seed", "node_id"], "left_anti").withColumn("hop", F.lit(h)), "khop")
        seen = seen.union(front)
    return seen


def one_hot(column: Column, values: list[str]) -> list[Column]:
    return [F.when(column == v, 1.0).otherwise(0.0) for v in values]


def assert_dim(df: DataFrame, dim: int, vec_col: str = "x") -> DataFrame:
    """Fails the job on a vector of another length or with a NaN."""
    bad = (F.size(vec_col) != dim) | F.exists(vec_col, lambda v: F.isnan(v) | v.isNull())
    return df.withColumn(vec_col, F.when(bad, F.raise_error(F.lit(f"{vec_col} is not {dim} numbers"))).otherwise(F.col(vec_col)))
