"""The index: fitted layers, every node's home, and the postings that homes need."""

from __future__ import annotations

import json
import math
from dataclasses import asdict, dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import cut, fresh_path
from .cluster import FIT_ROWS, Layers, LayerSpec, assign, build_layers


#: Up to this many cells are literals of one plan or are broadcast; more are a table to join.
SMALL_CELLS = 4096
#: Rows of one file of postings, and nodes of one folder of the lookup by id.
FILE_ROWS, LOOKUP_ROWS = 250_000, 100_000


@dataclass
class TwinIndex:
    """``nodes``: node_id, verdict, sig, clusters, cosines, weights, layer, cluster (the home)."""

    layers: Layers
    nodes: DataFrame
    path: str | None = None
    _shelf: Shelf | None = None

    def home_cells(self) -> DataFrame:
        """``cell``: those that are somebody's home, p * m at most."""
        return self.nodes.select(cell().alias("cell")).distinct()

    def postings(self, cells: DataFrame | None = None) -> DataFrame:
        """``layer, cluster, node_id, verdict, sig, cell`` for the given ``cell``s, by default those that are somebody's home.

        Memberships in other cells are filtered while they are still numbers, so a node's vector is
        repeated only for cells that will be searched. A few cells become literals; many (a large m)
        stay a table, which ids alone are joined with before vectors are fetched.
        """
        wanted = cut((self.home_cells() if cells is None else cells).select("cell").distinct(), "cells")
        mine = F.zip_with(F.array(*[F.lit(n).cast("long") for n in self.layers.numbers]), "clusters", lambda a, c: a * F.lit(1 << 32) + c)
        few = [r[0] for r in wanted.limit(SMALL_CELLS + 1).collect()]
        if len(few) <= SMALL_CELLS:
            held = F.array_intersect(mine, F.array(*[F.lit(c).cast("long") for c in sorted(few)]).cast("array<long>"))
            rows = self.nodes.select("node_id", "verdict", "sig", F.explode(held).alias("cell"))
        else:
            ids = self.nodes.select("node_id", F.explode(mine).alias("cell")).join(wanted, "cell", "left_semi")
            rows = self.nodes.select("node_id", "verdict", "sig").join(ids, "node_id")
        layer = F.floor(F.col("cell") / F.lit(1 << 32)).cast("int")
        return rows.select(layer.alias("layer"), F.pmod("cell", F.lit(1 << 32)).cast("int").alias("cluster"), "node_id", "verdict", "sig", "cell")

    def shelf(self) -> Shelf:
        """The index on disk, written at first use, for searches of single nodes."""
        if self._shelf is None:
            self.path = self.path or save(self)
            self._shelf = Shelf.open(self.nodes.sparkSession, self.path)
        return self._shelf


@dataclass
class Shelf:
    """A stored index: ``lookup`` by folders of hashed ids, ``postings`` by folders of layer and cluster.

    The folders are listed once, when it is opened; a search then reads one of each kind.
    ``bounds`` holds cluster, least cosine and members of the first layer, m rows.
    """

    lookup: DataFrame
    postings: DataFrame
    bounds: list[tuple[int, float, int]]
    buckets: int
    first: int

    @classmethod
    def open(cls, spark: SparkSession, path: str) -> Shelf:
        about = json.loads(spark.read.text(f"{path}/manifest").head()[0])
        node = T.StructType.fromJson(about["node"])
        posted = T.StructType([*node.fields, T.StructField("layer", T.IntegerType()), T.StructField("cluster", T.IntegerType())])
        looked = T.StructType([*posted.fields, T.StructField("bucket", T.IntegerType())])
        bounds = [tuple(r) for r in spark.read.parquet(f"{path}/bounds").select("cluster", "low", "members").collect()]
        return cls(spark.read.schema(looked).parquet(f"{path}/lookup"), spark.read.schema(posted).parquet(f"{path}/postings"), bounds, about["buckets"], about["first"])

    def find(self, node_id: int):
        """The row of one node (verdict, sig, layer, cluster), from one folder; None if it is not indexed."""
        at = bucket_of(F.lit(node_id).cast("long"), self.buckets)
        return self.lookup.filter((F.col("bucket") == at) & (F.col("node_id") == node_id)).select("verdict", "sig", "layer", "cluster").head()

    def members(self, layer: int, clusters: list[int]) -> DataFrame:
        """Postings of some clusters of one layer; the filter prunes folders."""
        return self.postings.filter((F.col("layer") == layer) & F.col("cluster").isin(clusters))


def bucket_of(node_id, buckets: int):
    return F.pmod(F.xxhash64(node_id), F.lit(buckets)).cast("int")


def cell(layer="layer", cluster="cluster"):
    """One number for a layer and a cluster."""
    return F.col(layer).cast("long") * F.lit(1 << 32) + F.col(cluster).cast("long")


def by_preference(layers: Layers, rule: str = "weight"):
    """``[(weight, -cos, layer, cluster)]`` of a node; the least is the best: the smallest weight, then the largest cosine, then the earlier layer.

    In many dimensions most weights are 1 to the last digit; the cosine, which weight falls with,
    then still tells the layers apart. ``cos`` goes by the cosine alone.
    """
    numbers = F.array(*[F.lit(n) for n in layers.numbers]).cast("array<int>")
    weight = F.transform("weights", lambda w: F.round(w, 12) if rule == "weight" else F.lit(0.0))
    packed = F.arrays_zip(weight.alias("weight"), F.transform("cosines", lambda c: -F.round(c, 12)).alias("far"), numbers.alias("layer"), F.col("clusters").alias("cluster"))
    return packed


def choose_home(assigned: DataFrame, layers: Layers, rule: str = "weight") -> DataFrame:
    """Adds ``layer, cluster``: the node's best layer by :func:`by_preference`.

    The layers are arrays on the node's row, so this is a projection: no shuffle.
    """
    best = F.array_min(by_preference(layers, rule))
    return assigned.withColumn("best", best).withColumn("layer", F.col("best.layer")).withColumn("cluster", F.col("best.cluster")).drop("best")


def build(sigs: DataFrame, spec: LayerSpec = LayerSpec(), fit_rows: int = FIT_ROWS, home_rule: str = "weight") -> TwinIndex:
    """Fit, assign and choose homes; signatures of length zero have no direction and are not indexed."""
    layers = build_layers(sigs, spec, fit_rows)
    live = sigs.filter(F.exists("sig", lambda v: v != 0))
    return TwinIndex(layers, cut(choose_home(assign(live, layers), layers, home_rule), "index"))


def save(index: TwinIndex, path: str | None = None) -> str:
    """Nodes, lookup, postings, bounds, centroids and a manifest, all in open formats.

    A vector is stored once per cell that is a home (p times at most): that buys a search which reads
    one cell, a share 1/m of the nodes. All cells of the first layer are stored too, for bounded
    search. A cell of many rows is dealt to several files, so none is written by one task.
    """
    spark, first = index.nodes.sparkSession, (index.layers.numbers or [0])[0]
    path = path or fresh_path(spark, "twin-index")
    index.nodes.write.mode("overwrite").parquet(f"{path}/nodes")
    nodes = spark.read.schema(index.nodes.schema).parquet(f"{path}/nodes")
    buckets = max(1, math.ceil(nodes.count() / LOOKUP_ROWS))
    lookup = nodes.select("node_id", "verdict", "sig", "layer", "cluster", bucket_of(F.col("node_id"), buckets).alias("bucket"))
    lookup.repartition("bucket").sortWithinPartitions("bucket", "node_id").write.mode("overwrite").partitionBy("bucket").parquet(f"{path}/lookup")
    if index.layers.numbers:
        whole = nodes.select((F.lit(first * (1 << 32)).cast("long") + F.col("clusters")[0]).alias("cell"))
        posted = TwinIndex(index.layers, nodes).postings(nodes.select(cell().alias("cell")).union(whole).distinct())
        bounds = nodes.groupBy(F.col("clusters")[0].alias("cluster")).agg(F.min(F.col("cosines")[0]).alias("low"), F.count("*").alias("members"))
    else:
        posted = nodes.select("layer", "cluster", "node_id", "verdict", "sig", cell().alias("cell"))
        bounds = spark.createDataFrame([], "cluster int, low double, members long")
    sizes = posted.groupBy("cell").agg(F.ceil(F.count("*") / FILE_ROWS).cast("int").alias("files"))
    dealt = posted.join(sizes, "cell").withColumn("file", F.pmod(F.xxhash64("node_id"), F.col("files")))
    dealt.repartition("cell", "file").drop("cell", "files", "file").write.mode("overwrite").partitionBy("layer", "cluster").parquet(f"{path}/postings")
    bounds.coalesce(1).write.mode("overwrite").parquet(f"{path}/bounds")
    rows = [(n, c, mu[c].tolist()) for n, mu in zip(index.layers.numbers, index.layers.centroids, strict=True) for c in range(len(mu))]
    spark.createDataFrame(rows, "layer int, cluster int, mu array<double>").coalesce(1).write.mode("overwrite").parquet(f"{path}/centroids")
    node = nodes.select("node_id", "verdict", "sig").schema.jsonValue()
    about = {"spec": asdict(index.layers.spec), "buckets": buckets, "first": first, "node": node}
    spark.createDataFrame([(json.dumps(about),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")
    return path


def load(spark: SparkSession, path: str) -> TwinIndex:
    spec = LayerSpec(**json.loads(spark.read.text(f"{path}/manifest").head()[0])["spec"])
    by: dict[int, dict[int, list[float]]] = {}
    for r in spark.read.parquet(f"{path}/centroids").collect():  # p * m rows
        by.setdefault(r["layer"], {})[r["cluster"]] = r["mu"]
    numbers = sorted(by)
    layers = Layers([np.array([by[n][c] for c in sorted(by[n])]) for n in numbers], numbers, spec)
    return TwinIndex(layers, spark.read.parquet(f"{path}/nodes"), path)
