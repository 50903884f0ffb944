"""Joins that Spark has no operator for, as compositions that scale."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import cut


def band_join(left: DataFrame, right: DataFrame, on_left: str, on_right: str, width: float) -> DataFrame:
    """Pairs with ``|on_left - on_right| <= width``: bands of that width make it an equi join; the left side visits three."""
    band = lambda c: F.floor(F.col(c) / F.lit(width)).cast("long")
    l = left.withColumn("__band", F.explode(F.array(band(on_left) - 1, band(on_left), band(on_left) + 1)))  # noqa: E741
    r = right.withColumn("__rband", band(on_right))
    return l.join(r, (F.col("__band") == F.col("__rband")) & (F.abs(F.col(on_left) - F.col(on_right)) <= width)).drop("__band", "__rband")


def interval_join(points: DataFrame, spans: DataFrame, at: str, start: str, end: str, bucket_seconds: int, cond: Column | None = None) -> DataFrame:
    """Points inside spans: a span is dealt to every time bucket that it touches, a point to its own."""
    sec = lambda c: F.floor(F.unix_micros(F.col(c).cast("timestamp")) / F.lit(bucket_seconds * 1_000_000)).cast("long")
    s = spans.withColumn("__b", F.explode(F.sequence(sec(start), sec(end))))
    p = points.withColumn("__pb", sec(at))
    on = (F.col("__b") == F.col("__pb")) & (F.col(at) >= F.col(start)) & (F.col(at) <= F.col(end))
    return p.join(s, on if cond is None else on & cond).drop("__b", "__pb")


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, value: str, order: str) -> DataFrame:
    """``left`` with the last ``value`` of ``right`` at or before each row's ``at`` and key: one shuffle, no pairs.

    Rows of both sides are sorted together; a running last value carries over. On equal times the
    right row comes first; equal right rows are ordered by ``order``.
    """
    l = left.select(*left.columns).withColumn("__side", F.lit(1)).withColumn("__v", F.lit(None).cast(right.schema[value].dataType)).withColumn("__o", F.lit(0).cast("long"))  # noqa: E741
    blank = [F.lit(None).cast(f.dataType).alias(f.name) if f.name not in (key, at) else F.col(f.name) for f in left.schema]
    r = right.select(*blank, F.lit(0).alias("__side"), F.col(value).alias("__v"), F.col(order).cast("long").alias("__o"))
    w = Window.partitionBy(key).orderBy(at, "__side", "__o").rowsBetween(Window.unboundedPreceding, 0)
    both = l.unionByName(r).withColumn(value, F.last("__v", ignorenulls=True).over(w))
    return both.filter("__side = 1").drop("__side", "__v", "__o")


def salted_join(big: DataFrame, small: DataFrame, key: str, salts: int = 8, salt_by: str | None = None) -> DataFrame:
    """An equi join whose hot keys are spread: the big side draws one of ``salts``, the small side has all of them."""
    b = big.withColumn("__salt", F.pmod(F.xxhash64(salt_by or F.monotonically_increasing_id()), F.lit(salts)).cast("int"))
    s = small.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return b.join(s, [key, "__salt"]).drop("__salt")


def numbered(rows: DataFrame, order: str, name: str) -> DataFrame:
    """``rows`` with ``name``: their place, from 1, in the order of ``order``, whose values are distinct.

    Ranges are sorted side by side; only one count per range meets on the driver, so no task holds all rows.
    """
    part, nth = "__part", "__nth"
    dealt = cut(rows.repartitionByRange(order).sortWithinPartitions(order).withColumn(part, F.spark_partition_id()), "ranges")
    before, total = [], 0
    for r in dealt.groupBy(part).agg(F.count("*").alias("n")).orderBy(part).collect():  # a row per range
        before.append((r[part], total))
        total += r["n"]
    base = F.create_map(*[F.lit(v) for pair in before for v in pair]) if before else F.create_map(F.lit(0), F.lit(0))
    nthed = dealt.withColumn(nth, F.row_number().over(Window.partitionBy(part).orderBy(order)))
    return nthed.withColumn(name, (F.col(nth) + F.element_at(base, F.col(part))).cast("long")).drop(part, nth)
