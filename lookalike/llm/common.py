"""What the training-data operators share: shipping code, cut lineage, connected components."""

from __future__ import annotations

import gc
import io
import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_SHIPPED = "lookalike.shipped"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The input table ``name``; only Spark's reader touches the path, so any store works."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spare(columns: list[str], name: str) -> str:
    """``name``, with underscores before it until no column is called so."""
    while name in columns:
        name = f"_{name}"
    return name


def ship(spark: SparkSession) -> None:
    """Give executors this package, once per application.

    Python workers import the package by name; a cluster whose workers lack the driver's
    PYTHONPATH gets it as a zip through Spark's own file server.
    """
    sc = spark.sparkContext
    if getattr(sc, "_lookalike_shipped", False):
        return
    root = Path(__file__).resolve().parents[1]
    folder = tempfile.mkdtemp(prefix="lookalike-")
    target = os.path.join(folder, "lookalike_pkg.zip")
    blob = io.BytesIO()
    with zipfile.ZipFile(blob, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, f"{root.name}/{p.relative_to(root)}")
    Path(target).write_bytes(blob.getvalue())
    sc.addPyFile(target)
    sc._lookalike_shipped = True


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Only where it is unset (tests, one machine) a temporary folder is made and set.
    """
    sc = spark.sparkContext
    named = sc.getConf().get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    there = sc._jsc.sc().getCheckpointDir()
    if there.isDefined():
        return str(there.get()).rstrip("/")
    if not sc.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    sc.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="lookalike-shared-"))
    return str(sc._jsc.sc().getCheckpointDir().get()).rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/lookalike/{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame, name: str) -> DataFrame:
    """Materialise ``df`` as a Parquet table in the shared folder and read it again.

    Cuts the lineage durably: a lost executor costs a re-read, never a re-run of what is above.
    """
    spark = df.sparkSession
    path = fresh_path(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._lookalike_path = path
    return out


def drop_cut(df: DataFrame) -> None:
    """Delete a table made by :func:`cut` that nothing reads any more."""
    path = getattr(df, "_lookalike_path", None)
    if path:
        spark = df.sparkSession
        p = spark._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def free_shuffles(spark: SparkSession) -> None:
    """Let Spark's cleaner delete the shuffle files that no plan needs any more; by itself it waits until the driver's heap is full."""
    gc.collect()
    spark._jvm.System.gc()


def connected_components(edges: DataFrame) -> DataFrame:
    """``edges(a, b)`` → ``(id, component_id)``: the smallest id that each node reaches.

    Alternates large-star and small-star until no edge changes; each round is cut to the shared
    folder. Star centres only ever shrink, so rounds grow with the logarithm of the longest path.
    Each min is a partial aggregation, and the join back is an equi join that AQE can split, so a
    hub that a third of the rows touch is not gathered in one task. Nothing reaches the driver but
    a count and two digests per round, made of hashes alone, so ids of any size do. Null ends and
    loops are ignored; nodes without an edge do not appear.
    """
    e = (
        edges.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b"))
        .filter("a is not null and b is not null and a <> b")
        .distinct()
    )
    e = cut(e, "cc")
    seen = None
    while True:
        both = e.select("a", "b").union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(low, "a").filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = large.filter("a <> b").distinct()
        low2 = large.groupBy("a").agg(F.min("b").alias("m"))
        small = (
            large.join(low2, "a")
            .select(F.explode(F.array(F.struct("a", F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("e"))
            .select("e.a", "e.b")
            .filter("a <> b")
            .distinct()
        )
        nxt = cut(small, "cc")
        state = tuple(nxt.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b")), F.sum(F.xxhash64("b", "a").cast("decimal(38,0)"))).first())
        drop_cut(e)
        e = nxt
        if state == seen:
            break
        seen = state
    return e.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("component_id")).union(
        e.select(F.col("b").alias("id"), F.col("b").alias("component_id")).distinct()
    )


def name_components(rows: DataFrame, links: DataFrame) -> DataFrame:
    """``rows(id, node, ...)`` with ``component_id``: the smallest id that links between nodes reach.

    Rows that share an id are one thing, whatever their nodes: their nodes are linked as well. Rows
    without an id must not be among ``rows``.
    """
    spread = rows.groupBy("id").agg(F.min("node").alias("first"), F.max("node").alias("last")).filter("first < last").select("id", "first")
    same_id = rows.select("id", "node").join(spread, "id").select(F.col("first").alias("a"), F.col("node").alias("b"))
    found = cut(connected_components(links.select("a", "b").union(same_id)).select(F.col("id").alias("node"), F.col("component_id").alias("__c")), "components")
    named = cut(rows.join(found, "node", "left").withColumn("__c", F.coalesce("__c", "node")), "named")
    least = named.groupBy("__c").agg(F.min("id").alias("component_id"))
    return named.join(least, "__c").drop("__c")


def sorted_groups(batches, key: int = 0, least: int = 2):
    """Runs of equal keys in batches that arrive sorted by integer column ``key``, as Arrow tables.

    Holds one run at a time; runs of fewer than ``least`` rows are passed over without Python work.
    """
    import numpy as np
    import pyarrow as pa

    carry: list = []

    def flush():
        t = pa.Table.from_batches(carry)
        return t if t.num_rows >= least else None

    for b in batches:
        if not b.num_rows:
            continue
        k = b.column(key).to_numpy(zero_copy_only=False)
        edges = np.flatnonzero(k[1:] != k[:-1]) + 1
        first = 0
        if carry and carry[0].column(key)[0].as_py() != k[0]:
            if (t := flush()) is not None:
                yield t
            carry = []
        if not len(edges):
            carry.append(b)
            continue
        if carry:
            carry.append(b.slice(0, int(edges[0])))
            if (t := flush()) is not None:
                yield t
            carry, first = [], 1
        starts = np.concatenate(([0], edges))[first:]
        ends = np.concatenate((edges, [b.num_rows]))[first:]
        for s, e in zip(starts[:-1][ends[:-1] - starts[:-1] >= least], ends[:-1][ends[:-1] - starts[:-1] >= least], strict=True):
            yield pa.Table.from_batches([b.slice(int(s), int(e - s))])
        carry = [b.slice(int(starts[-1]))]
    if carry and (t := flush()) is not None:
        yield t
