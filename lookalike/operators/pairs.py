"""Twin pairs over all nodes: the best of all local twins, or the truly best pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import vectors as V
from .cluster import LayerSpec
from .index import TwinIndex, build
from .kernels import blocked_pairs
from .scan import exact_scan_all
from .search import index_search_all


def canonical(twins: DataFrame) -> DataFrame:
    """``a, b, sim`` with a < b, each unordered pair once."""
    return twins.select(F.least("v", "u").alias("a"), F.greatest("v", "u").alias("b"), "sim").dropDuplicates(["a", "b"])


def top(pairs: DataFrame, k: int) -> DataFrame:
    """``a, b, rank, sim``: partial top-k per task, k rows merged."""
    best = pairs.orderBy(F.desc("sim"), "a", "b").limit(k)
    return best.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("sim"), "a", "b"))).select("a", "b", "rank", "sim")


def local_twins(sigs: DataFrame, k: int, local: str = "exact", spec: LayerSpec | None = None, index: TwinIndex | None = None) -> DataFrame:
    """Local twins by the inner method: ``exact``, ``index``, ``flat_weights`` or ``single_layer``."""
    if local == "exact":
        return exact_scan_all(sigs, k)
    return index_search_all(index or build(sigs, variant(spec or LayerSpec(), local)), k)


def variant(spec: LayerSpec, name: str) -> LayerSpec:
    """The full index, or one with a part left out."""
    from dataclasses import replace

    return {"index": spec, "flat_weights": replace(spec, weight_rule="unit"), "single_layer": replace(spec, p=1)}[name]


def twin_pairs(sigs: DataFrame, k: int = 1, local: str = "exact", mode: str = "per_node_best", dedupe: bool = True, **how) -> DataFrame:
    """``a, b, rank, sim``: the ``k`` most similar pairs of different verdicts.

    ``per_node_best`` lets every node offer its best twin only, as the method's bucket does;
    ``exact_pairs`` lets it offer ``k``, which misses no pair of the true top ``k``. A pair found
    from both ends counts once unless ``dedupe`` is off.
    """
    twins = local_twins(sigs, k if mode == "exact_pairs" else 1, local, **how)
    pairs = canonical(twins) if dedupe else twins.select(F.least("v", "u").alias("a"), F.greatest("v", "u").alias("b"), "sim")
    return top(pairs, k)


def pairs_above(sigs: DataFrame, min_sim: float, engine: str = "block") -> DataFrame:
    """``a, b, sim`` of all pairs at or above ``min_sim``: each unordered pair is scored once."""
    if engine == "block":
        return blocked_pairs(sigs.select("node_id", "verdict", "sig"), min_sim).withColumn("sim", V.r6("sim"))
    a, b = sigs.alias("a"), sigs.alias("b")
    pairs = a.join(b, (F.col("a.node_id") < F.col("b.node_id")) & (F.col("a.verdict") != F.col("b.verdict")))
    return pairs.select(F.col("a.node_id").alias("a"), F.col("b.node_id").alias("b"), F.round(V.dot("a.sig", "b.sig"), 9).alias("sim")).filter(F.col("sim") >= min_sim).select("a", "b", V.r6("sim").alias("sim"))
