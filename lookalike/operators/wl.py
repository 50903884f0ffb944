"""Classic colour refinement on one attribute, and the subtree kernel over its colours."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import cut
from .graph import symmetrize
from .relational import numbered


def refine_colors(nodes: DataFrame, edges: DataFrame, rounds: int, how: str = "md5") -> DataFrame:
    """``node_id, iter, color``; ``nodes`` has ``node_id, color``.

    A round's colour names the own colour and the sorted colours of the neighbours *before* the
    round. ``md5`` needs no agreement between tasks; ``dense_rank`` numbers the distinct pairs in order, by ranges;
    ``multiset`` sums hashes of the neighbours' colours, so a hub's neighbours are never gathered.
    """
    both = cut(symmetrize(edges), "edges")
    now = nodes.select("node_id", F.col("color").cast("string").alias("color"))
    out = now.withColumn("iter", F.lit(0))
    for i in range(1, rounds + 1):
        if how == "multiset":
            far = both.join(now.withColumnRenamed("node_id", "dst"), "dst")
            around = [F.sum(F.xxhash64("color", F.lit(salt)).cast("decimal(38,0)")).alias(f"h{salt}") for salt in (1, 2)]
            seen = far.groupBy(F.col("src").alias("node_id")).agg(*around)
            color = F.md5(F.concat_ws("|", "color", F.coalesce("h1", F.lit(0)), F.coalesce("h2", F.lit(0))))
            now = cut(now.join(seen, "node_id", "left").select("node_id", color.alias("color")), "colors")
            out = out.union(now.withColumn("iter", F.lit(i)))
            continue
        seen = both.join(now.withColumnRenamed("node_id", "dst"), "dst").groupBy(F.col("src").alias("node_id")).agg(F.array_join(F.array_sort(F.collect_list("color")), ",").alias("around"))
        text = F.concat(F.col("color"), F.lit("|"), F.coalesce("around", F.lit("")))
        nxt = now.join(seen, "node_id", "left").select("node_id", text.alias("text"))
        if how == "md5":
            nxt = nxt.select("node_id", F.md5("text").alias("color"))
        else:
            names = numbered(nxt.select("text").distinct(), "text", "place").select("text", F.col("place").cast("string").alias("color"))
            nxt = nxt.join(names, "text").select("node_id", "color")
        now = cut(nxt, "colors")
        out = out.union(now.withColumn("iter", F.lit(i)))
    return out.select("node_id", F.col("iter").cast(T.IntegerType()).alias("iter"), "color")


def kernel(colors: DataFrame, around: DataFrame, queries: DataFrame | None = None) -> DataFrame:
    """``a, b, kernel``: cosine of the colour counts of two anchored neighbourhoods.

    ``around`` is ``seed, node_id`` as ``khop`` gives it; counts over all rounds, multiplied where colours agree.
    With ``queries`` (node_id), those seeds against all others; without, each unordered pair of seeds.
    """
    hist = around.join(colors, "node_id").groupBy("seed", "iter", "color").agg(F.count("*").alias("n"))
    size = hist.groupBy("seed").agg(F.sqrt(F.sum(F.col("n") * F.col("n")).cast("double")).alias("size"))
    mine, mine_size, meet = hist, size, F.col("a.seed") < F.col("b.seed")
    if queries is not None:
        asked = queries.select(F.col("node_id").alias("seed"))
        mine, mine_size, meet = hist.join(asked, "seed", "left_semi"), size.join(asked, "seed", "left_semi"), F.col("a.seed") != F.col("b.seed")
    a, b = mine.alias("a"), hist.alias("b")
    shared = a.join(b, (F.col("a.iter") == F.col("b.iter")) & (F.col("a.color") == F.col("b.color")) & meet)
    shared = shared.groupBy(F.col("a.seed").alias("a"), F.col("b.seed").alias("b")).agg(F.sum(F.col("a.n") * F.col("b.n")).alias("shared"))
    a, b = mine_size.alias("a"), size.alias("b")
    pairs = a.join(b, meet).select(F.col("a.seed").alias("a"), F.col("b.seed").alias("b"), F.col("a.size").alias("sa"), F.col("b.size").alias("sb")).join(shared, ["a", "b"], "left")
    return pairs.select("a", "b", (F.coalesce("shared", F.lit(0)) / (F.col("sa") * F.col("sb"))).alias("kernel"))
