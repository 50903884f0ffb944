"""Exact dedup: one row of each set of equal texts stays. DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import spare

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def fold_ascii(text: Column) -> Column:
    """A-Z to a-z and nothing else; ``lower`` does just that where every character is one byte."""
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, UPPER.lower()))


def content_key(text: Column) -> Column:
    """A 128-bit content hash."""
    return F.md5(text)


def text_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min") -> DataFrame:
    """One row per distinct normalised text: h128, text_sha256, keep_id, group_size.

    Grouping by the 128-bit hash *and* the text makes the aggregation compare bytes inside each
    hash group, so a collision gives two groups. Copies collapse before the shuffle: a text that a
    third of the rows share leaves each task once.
    """
    best = {"min": F.min, "max": F.max}[keep]
    norm = docs.select(F.col(id_col).alias("id"), fold_ascii(F.coalesce(F.col(text_col), F.lit(""))).alias("norm"))
    return (
        norm.withColumn("h128", content_key(F.col("norm")))
        .groupBy("h128", "norm")
        .agg(best("id").alias("keep_id"), F.count("*").alias("group_size"))
        .select("h128", F.sha2("norm", 256).alias("text_sha256"), "keep_id", "group_size")
    )


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min") -> DataFrame:
    """Every input row with the id that stays for it.

    Returns ``id_col, keep_id, group_size, kept, text_sha256``. Null text counts as empty; texts
    are equal when identical after lower-casing A-Z only. ``keep`` says whether the smallest
    (default) or largest id of equal texts stays. A row with a null id never stays while an equal
    text has an id, and is returned with ``kept`` false; repeated rows each come back and count in
    ``group_size``. An empty table gives no rows; other columns are not read.
    """
    groups = text_groups(docs, id_col, text_col, keep)
    norm = fold_ascii(F.coalesce(F.col(text_col), F.lit("")))
    rows = docs.select(F.col(id_col).alias("id"), norm.alias("norm")).select(
        "id", content_key(F.col("norm")).alias("h128"), F.sha2("norm", 256).alias("text_sha256")
    )
    return rows.join(groups, ["h128", "text_sha256"]).select(
        F.col("id").alias(id_col), "keep_id", "group_size", F.coalesce(F.col("id") == F.col("keep_id"), F.lit(False)).alias("kept"), "text_sha256"
    )


def keep_first(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min") -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns: one of each set of equal texts.

    The row with the smallest (``max``: largest) id stays. Rows count by themselves: where an id
    repeats with different texts, each row stays or goes by its own text; where id and text
    repeat, one row stays, any one. Texts of rows without an id stay once if no row with an id has them.
    """
    key, norm = spare(docs.columns, "h128"), spare(docs.columns, "norm")
    groups = text_groups(docs, id_col, text_col, keep).select(F.col("h128").alias("__h"), F.col("keep_id").alias("__keep"))
    folded = fold_ascii(F.coalesce(F.col(text_col), F.lit("")))
    rows = docs.withColumn(key, content_key(folded))
    first = rows.join(groups.filter("__keep is not null"), (F.col(id_col) == F.col("__keep")) & (F.col(key) == F.col("__h")), "left_semi")
    # ids that repeat, and rows without one, ask for more passes over the table: only where there are any
    again = docs.groupBy(F.col(id_col).alias("__again")).agg(F.count("*").alias("n")).filter("n > 1 or __again is null").select("__again")
    odd = again.agg(F.count("__again").alias("repeated"), F.count("*").alias("all")).first()
    if not odd["all"]:
        return first.drop(key)
    once = first.join(again, F.col(id_col) == F.col("__again"), "left_anti").drop(key)
    more = first.join(again, F.col(id_col) == F.col("__again"), "left_semi").dropDuplicates([id_col, key]).drop(key)
    out = once.unionByName(more) if odd["repeated"] else first.drop(key)
    if odd["all"] == odd["repeated"]:
        return out
    nameless = rows.filter(F.col(id_col).isNull()).join(groups.filter("__keep is null"), F.col(key) == F.col("__h"), "left_semi")
    nameless = nameless.withColumn(norm, folded).dropDuplicates([key, norm]).drop(key, norm)
    return out.unionByName(nameless)
