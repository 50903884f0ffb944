"""Exact twin search: of one node, of all nodes, by threshold."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import vectors as V
from ..session import fresh_path, store
from .kernels import blocked_topk, stored_topk, tasks_can_read


def _query(sigs: DataFrame, query_id: int) -> tuple[int, list[float]] | None:
    """Verdict and signature of one node: the only row that the driver reads."""
    r = sigs.filter(F.col("node_id") == query_id).select("verdict", "sig").head()
    return None if r is None else (r["verdict"], r["sig"])


def _scored(sigs: DataFrame, query_id: int) -> DataFrame:
    """Every node that is judged otherwise, with its similarity. The verdict filter reaches the scan;
    rows of the query's own verdict are never scored. Scores are rounded to 9 digits, so equal
    vectors tie and the smaller id wins."""
    q = _query(sigs, query_id)
    if q is None:
        return sigs.filter(F.lit(False)).select(F.col("node_id").alias("u"), F.lit(0.0).alias("sim"))
    return scored_against(sigs, *q)


def scored_against(sigs: DataFrame, verdict: int, sig: list[float]) -> DataFrame:
    """``u, sim`` of the rows of ``sigs`` that are judged otherwise than ``verdict``."""
    literal = F.array(*[F.lit(float(x)) for x in sig])
    return sigs.filter(F.col("verdict") != F.lit(verdict)).select(F.col("node_id").alias("u"), F.round(V.dot("sig", literal), 9).alias("sim"))


def ranked(scored: DataFrame, k: int) -> DataFrame:
    """The best ``k`` rows of ``u, sim`` with their rank: partial top-k per task, merged at the end."""
    best = scored.orderBy(F.desc("sim"), "u").limit(k)
    return best.select("u", F.row_number().over(Window.orderBy(F.desc("sim"), "u")).alias("rank"), V.r6("sim").alias("sim"))


def exact_scan(sigs: DataFrame, query_id: int, k: int = 1) -> DataFrame:
    """``u, rank, sim``: the ``k`` most similar nodes of another verdict; no rows if there is none."""
    return ranked(_scored(sigs, query_id), k)


def twins_above(sigs: DataFrame, query_id: int, min_sim: float) -> DataFrame:
    return _scored(sigs, query_id).filter(F.col("sim") >= min_sim).select("u", V.r6("sim").alias("sim"))


def store_by_verdict(sigs: DataFrame, path: str | None = None) -> str:
    """Signatures partitioned by verdict on disk: a query's verdict filter then prunes its own class's files."""
    path = path or fresh_path(sigs.sparkSession, "by-verdict")
    sigs.select("node_id", "sig", "verdict").repartition("verdict").write.mode("overwrite").partitionBy("verdict").parquet(path)
    return path


def load_by_verdict(spark, path: str) -> DataFrame:
    return spark.read.parquet(path)


def merge_topk(found: DataFrame, k: int) -> DataFrame:
    """``v, u, rank, sim`` of partial lists; the group limit cuts each task's rows to ``k`` per node before the exchange."""
    w = Window.partitionBy("v").orderBy(F.desc("sim"), "u")
    return found.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).select("v", "u", "rank", V.r6("sim").alias("sim"))


def exact_scan_all(sigs: DataFrame, k: int, engine: str = "block", queries: DataFrame | None = None) -> DataFrame:
    """Top ``k`` of every node (or of ``queries``, the same columns): ``v, u, rank, sim``.

    ``sql`` is the theta join that a database would run. ``block`` stores the signatures once, and every
    task multiplies its queries with blocks that it reads from there. Where only Spark reads the
    shared folder, a grid of block pairs is dealt out instead. A task's memory is two blocks whatever the table's size.
    """
    q = sigs if queries is None else queries
    if engine == "sql":
        a, b = q.alias("a"), sigs.alias("b")
        pairs = a.join(b, F.col("a.verdict") != F.col("b.verdict"))
        return merge_topk(pairs.select(F.col("a.node_id").alias("v"), F.col("b.node_id").alias("u"), F.round(V.dot("a.sig", "b.sig"), 9).alias("sim")), k)
    path, rows = store(sigs.select(F.col("node_id").cast("long").alias("node_id"), F.col("verdict").cast("long").alias("verdict"), "sig").filter("verdict is not null").repartition("node_id"), "scanned")
    if tasks_can_read(path):
        asked = rows if queries is None else q.select(F.col("node_id").cast("long").alias("node_id"), F.col("verdict").cast("long").alias("verdict"), "sig").filter("verdict is not null")
        return merge_topk(stored_topk(asked, path, k), k)
    one = F.lit(0).alias("cell")
    sigs, q = rows, rows if queries is None else q
    return merge_topk(blocked_topk(q.select(one, "node_id", "verdict", "sig"), sigs.select(one, "node_id", "verdict", "sig"), k), k)
