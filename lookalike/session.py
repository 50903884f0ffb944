"""Session settings that may change at run time, shared folders, and cutting lineage."""

from __future__ import annotations

import gc
import os
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


def local_session(cpus: str = "*", shuffle: int = 8, name: str = "lookalike") -> SparkSession:
    """A session for one machine: tests and the bench."""
    return (
        SparkSession.builder.master(f"local[{cpus}]")
        .appName(name)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.shuffle.partitions", str(shuffle))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "8g")
        .getOrCreate()
    )


def ship(spark: SparkSession) -> None:
    """Give Python workers this package through Spark's file server, once per application."""
    sc = spark.sparkContext
    if getattr(sc, "_lookalike_shipped", False):
        return
    root = Path(__file__).resolve().parent
    target = os.path.join(tempfile.mkdtemp(prefix="lookalike-"), "lookalike_pkg.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, f"{root.name}/{p.relative_to(root)}")
    sc.addPyFile(target)
    sc._lookalike_shipped = True


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` as the session names it; a temporary folder only on one machine without it."""
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


def free_shuffles(spark: SparkSession) -> None:
    """Let Spark's cleaner delete the shuffle files that no plan needs any more; by itself it waits until the driver's heap is full."""
    gc.collect()
    spark._jvm.System.gc()


def store(df: DataFrame, name: str) -> tuple[str, DataFrame]:
    """``df`` written to the shared folder, as a path and as a table."""
    path = fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    for paths in _noted:
        paths.append(path)
    return path, df.sparkSession.read.schema(df.schema).parquet(path)


def cut(df: DataFrame, name: str) -> DataFrame:
    """``df`` written to the shared folder and read again: lineage ends there, and an executor may be lost."""
    return store(df, name)[1]


_noted: list[list[str]] = []


@contextmanager
def noted() -> Iterator[list[str]]:
    """The paths that are stored inside, for :func:`drop` once no table reads them."""
    paths: list[str] = []
    _noted.append(paths)
    try:
        yield paths
    finally:
        _noted[:] = [p for p in _noted if p is not paths]


def drop(spark: SparkSession, paths: list[str]) -> None:
    """Delete what :func:`store` wrote there."""
    jvm, conf = spark._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for path in paths:
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(conf).delete(at, True)
