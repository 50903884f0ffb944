"""Unfairness audits: which feature values twins of another verdict lack."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..operators.graph import khop


def discrimination_scores(twins: DataFrame, values: DataFrame, k: int = 10) -> DataFrame:
    """``node_id, feature, value, ds``: the share of a node's ``k`` twins that lack a value it holds.

    Twins that hold it are counted by one equi join; the share is over ``k``, as missing twins
    cannot lack anything. Values that a node lacks have score 0 and no row.
    """
    t = twins.filter(F.col("rank") <= k).select("v", "u")
    per = t.groupBy("v").agg(F.count("*").alias("n"))
    held = t.join(values.withColumnRenamed("node_id", "v"), "v").join(values.select(F.col("node_id").alias("u"), "feature", "value"), ["u", "feature", "value"])
    held = held.groupBy("v", "feature", "value").agg(F.count("*").alias("same"))
    out = values.withColumnRenamed("node_id", "v").join(per, "v", "left").join(held, ["v", "feature", "value"], "left")
    return out.select(F.col("v").alias("node_id"), "feature", "value", ((F.coalesce("n", F.lit(0)) - F.coalesce("same", F.lit(0))) / F.lit(float(k))).alias("ds"))


def rank_features(ds: DataFrame, top: int = 10, over: str = "holders", nodes: int | None = None) -> DataFrame:
    """``feature, value, ds, rank``: mean score of each value, over its holders or over ``nodes`` nodes in all."""
    agg = F.avg("ds") if over == "holders" else F.sum("ds") / F.lit(float(nodes or 1))
    mean = ds.groupBy("feature", "value").agg(F.round(agg, 9).alias("ds"))
    w = Window.orderBy(F.desc("ds"), "feature", "value")  # one row per value of a feature
    return mean.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= top)


def inconsistency(twins: DataFrame, nodes: DataFrame, s: float) -> DataFrame:
    """``share``: nodes whose best twin is at least ``s`` similar, of all nodes."""
    best = twins.filter((F.col("rank") == 1) & (F.col("sim") >= s)).agg(F.count("*").alias("c"))
    return best.crossJoin(nodes.agg(F.count("*").alias("n"))).select((F.col("c") / F.col("n")).alias("share"))


def card(values: DataFrame, v: int, u: int) -> DataFrame:
    """``feature, v_value, u_value`` where two nodes differ."""
    a = values.filter(F.col("node_id") == v).select("feature", F.col("value").alias("v_value"))
    b = values.filter(F.col("node_id") == u).select("feature", F.col("value").alias("u_value"))
    return a.join(b, "feature", "full").filter(~F.col("v_value").eqNullSafe(F.col("u_value")))


def neighbourhoods(edges: DataFrame, v: int, u: int, hops: int = 2) -> DataFrame:
    """Both anchored neighbourhoods of a twin pair: ``seed, node_id, hop``."""
    return khop(edges, edges.sparkSession.createDataFrame([(v,), (u,)], "node_id long"), hops)
