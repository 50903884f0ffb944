"""Twin search through the index: one node, all nodes, several probes, shortage policies, exact pruning."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut
from .index import TwinIndex, by_preference, cell
from .kernels import blocked_topk
from .scan import exact_scan_all, merge_topk, ranked, scored_against


def index_search(index: TwinIndex, query_id: int, k: int = 1) -> DataFrame:
    """``u, rank, sim`` from the query's home cluster alone.

    Two small reads of the stored index: the folder that the id hashes to, then the folder of the
    home cell. Nothing else of the nodes is read, so the cost follows n / m and not n.
    """
    shelf = index.shelf()
    home = shelf.find(query_id)
    if home is None:
        return ranked(shelf.postings.filter(F.lit(False)).select(F.col("node_id").alias("u"), F.lit(0.0).alias("sim")), k)
    cell_rows = shelf.members(home["layer"], [home["cluster"]])
    return ranked(scored_against(cell_rows, home["verdict"], home["sig"]), k)


def _search(index: TwinIndex, queries: DataFrame, k: int) -> DataFrame:
    """Top ``k`` of ``queries`` (node_id, verdict, sig, layer, cluster) in their cells, unmerged."""
    return blocked_topk(queries.select(cell().alias("cell"), "node_id", "verdict", "sig"), index.postings().select("cell", "node_id", "verdict", "sig"), k)


def probes(index: TwinIndex, r: int) -> DataFrame:
    """``node_id, verdict, sig, layer, cluster, nth``: the ``r`` best layers of each node, best first."""
    best = index.nodes.select("node_id", "verdict", "sig", F.slice(F.array_sort(by_preference(index.layers)), 1, r).alias("best"))
    return best.select("node_id", "verdict", "sig", F.posexplode("best").alias("nth", "b")).select("node_id", "verdict", "sig", F.col("b.layer").alias("layer"), F.col("b.cluster").alias("cluster"), "nth")


def _postings_of(index: TwinIndex, cells: DataFrame) -> DataFrame:
    """Postings of the given ``layer, cluster`` cells."""
    return index.postings(cells.select(cell().alias("cell"))).select("cell", "node_id", "verdict", "sig")


def index_search_all(index: TwinIndex, k: int, on_shortage: str = "return_short", r: int = 1) -> DataFrame:
    """``v, u, rank, sim`` for every node.

    A node's home may hold fewer than ``k`` nodes of another verdict. ``return_short`` leaves it
    at that; ``next_layer`` searches its second-best layer as well; ``exact`` scans all nodes for
    the short ones. ``r`` probes the best ``r`` layers and drops repeats.
    """
    if r > 1:
        wanted = cut(probes(index, r), "probes")
        found = blocked_topk(wanted.select(cell().alias("cell"), "node_id", "verdict", "sig"), _postings_of(index, wanted.select("layer", "cluster")), k)
        return merge_topk(found.dropDuplicates(["v", "u"]), k)
    found = merge_topk(_search(index, index.nodes, k), k)
    if on_shortage == "return_short":
        return found
    found = cut(found, "found")
    full = found.filter(F.col("rank") == k).select(F.col("v").alias("node_id"))
    short = cut(index.nodes.join(full, "node_id", "left_anti").select("node_id", "verdict", "sig"), "short")
    kept = found.join(short.select(F.col("node_id").alias("v")), "v", "left_anti")
    if on_shortage == "exact":
        more = exact_scan_all(index.nodes, k, queries=short)
    else:
        second = probes(index, 2).join(short.select("node_id"), "node_id", "left_semi")
        more = merge_topk(blocked_topk(second.select(cell().alias("cell"), "node_id", "verdict", "sig"), _postings_of(index, second.select("layer", "cluster")), k).dropDuplicates(["v", "u"]), k)
    return kept.unionByName(more)


def cluster_bounds(index: TwinIndex) -> list[tuple[int, np.ndarray, float, int]]:
    """Per cluster of the first layer: number, unit centroid, the widest angle of a member, members. m rows reach the driver."""
    mu = index.layers.centroids[0]
    length = np.linalg.norm(mu, axis=1, keepdims=True)
    unit = np.divide(mu, length, out=np.zeros_like(mu), where=length > 0)
    return [(c, unit[c], math.acos(max(-1.0, min(1.0, low))), n) for c, low, n in index.shelf().bounds]


def bounded_exact(index: TwinIndex, query_id: int, k: int) -> DataFrame:
    """The exact answer from as few clusters as the triangle inequality on angles allows.

    Clusters of the first layer are read in the order of the best cosine that they could hold, one,
    then two, then four at a time, each once; those whose bound is below the k-th best so far are
    never read. The driver keeps the ``k`` best rows.
    """
    shelf = index.shelf()
    q = shelf.find(query_id)
    if q is None:
        return index_search(index, query_id, k)
    x = np.array(q["sig"])
    bounds = sorted(((math.cos(max(0.0, math.acos(max(-1.0, min(1.0, float(x @ mu)))) - radius)), c) for c, mu, radius, _ in cluster_bounds(index)), reverse=True)
    best: list[tuple[float, int]] = []
    at, step = 0, 1
    while at < len(bounds):
        if len(best) == k and bounds[at][0] < -best[-1][0] - 1e-9:
            break
        wave = [c for b, c in bounds[at : at + step] if len(best) < k or b >= -best[-1][0] - 1e-9]
        found = scored_against(shelf.members(shelf.first, wave), q["verdict"], q["sig"]).orderBy(F.desc("sim"), "u").limit(k)
        best = sorted(best + [(-r["sim"], r["u"]) for r in found.collect()])[:k]
        at, step = at + step, step * 2
    rows = [(u, i, round(-s, 6) + 0.0) for i, (s, u) in enumerate(best, 1)]
    return index.nodes.sparkSession.createDataFrame(rows, "u long, rank int, sim double")


def lsh_search(sigs: DataFrame, k: int, min_sim: float = 0.15, bucket: float = 0.5, tables: int = 16, seed: int = 42) -> DataFrame:
    """A baseline: Euclidean LSH on unit signatures, where squared distance is 2 - 2 cos.

    Only pairs of at least ``min_sim`` are kept. Unit vectors project to a spread of 1 / sqrt(d), so
    buckets are ``bucket`` of four such spreads: a handful of buckets a table, not one that holds all.
    """
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    first = sigs.select(F.size("sig").alias("d")).head()
    width = bucket * 4 / math.sqrt(first["d"] if first else 1)
    v = sigs.select("node_id", "verdict", "sig", array_to_vector("sig").alias("features"))
    model = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=width, numHashTables=tables, seed=seed).fit(v)
    pairs = model.approxSimilarityJoin(v, v, math.sqrt(2 - 2 * min_sim) + 1e-9, distCol="dist").filter("datasetA.verdict <> datasetB.verdict")
    return merge_topk(pairs.select(F.col("datasetA.node_id").alias("v"), F.col("datasetB.node_id").alias("u"), F.round(1 - F.col("dist") * F.col("dist") / 2, 9).alias("sim")), k)
