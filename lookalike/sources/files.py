"""Edge lists in open formats, there and back."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..session import fresh_path

SCHEMA = "src BIGINT, dst BIGINT"


def write_edges(edges: DataFrame, path: str, fmt: str = "csv") -> None:
    w = edges.select("src", "dst").write.mode("overwrite")
    (w.option("header", True).csv(path) if fmt == "csv" else w.format(fmt).save(path))


def read_edges(spark: SparkSession, path: str, fmt: str = "csv") -> DataFrame:
    """With a declared schema: no pass to infer one."""
    r = spark.read.schema(SCHEMA)
    return r.option("header", True).csv(path) if fmt == "csv" else r.format(fmt).load(path)


def roundtrip(edges: DataFrame, fmt: str) -> DataFrame:
    path = fresh_path(edges.sparkSession, f"edges-{fmt}")
    write_edges(edges, path, fmt)
    return read_edges(edges.sparkSession, path, fmt)


def bucketed(df: DataFrame, name: str, key: str, buckets: int = 8) -> DataFrame:
    """A table bucketed and sorted by ``key``: joins of two such tables on it need no exchange.

    Its files lie in the shared folder under a fresh name, so runs do not meet.
    """
    path = fresh_path(df.sparkSession, name)
    name = path.rsplit("/", 1)[1].replace("-", "_")
    df.write.option("path", path).bucketBy(buckets, key).sortBy(key).saveAsTable(name)
    return df.sparkSession.table(name)
