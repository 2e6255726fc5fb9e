"""Exact deduplication by URL over releases and by content over URLs; only keys are shuffled."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def dedup_url(captures: DataFrame, keep: str = "latest") -> DataFrame:
    """One capture per URL: of the latest (or earliest) release, then least archive and offset."""
    sign = {"latest": -1, "earliest": 1}[keep]
    order = F.struct((F.col("release") * sign).alias("r"), "archive", "offset")
    kept = captures.groupBy("url").agg(F.min(F.struct(order.alias("o"), "release", "length")).alias("x"))
    return kept.select("url", "x.release", "x.o.archive", "x.o.offset", "x.length")


def url_overlap(captures: DataFrame) -> DataFrame:
    per = captures.groupBy("url").agg(F.count_distinct("release").alias("n"))
    return per.agg(F.count("*").alias("urls"), F.count_if(F.col("n") > 1).alias("in_several"), F.round(F.count_if(F.col("n") > 1) / F.count("*"), 6).alias("share"))


def content_key(text: Column, key: str = "sha256") -> Column:
    if key == "sha256":
        return F.sha2(text, 256)
    if key == "normalised":
        return F.sha2(F.trim(F.regexp_replace(F.lower(text), r"[ \n\r\t]+", " ")), 256)
    raise ValueError(f"unknown key {key!r}")


def dedup_content(rows: DataFrame, id_col: str, key: Column) -> DataFrame:
    """Least id of each group of equal contents, and the size of the group."""
    return rows.groupBy(key.alias("key")).agg(F.min(id_col).alias(id_col), F.count("*").alias("copies")).drop("key")


def keep_first(rows: DataFrame, id_col: str, key: Column) -> DataFrame:
    """The rows of :func:`dedup_content`, all columns, by a semi join on the id."""
    return rows.join(dedup_content(rows, id_col, key).select(id_col), id_col, "left_semi")


def older_captures(pointers: DataFrame, id_col: str, key: str = "url") -> DataFrame:
    """Ids of the captures that a later one of the same ``key`` replaces (ties: least archive, offset, id); only keys move."""
    order = F.struct((-F.col("release")).alias("r"), "archive", "offset", id_col)
    best = pointers.where(F.col(key).isNotNull()).groupBy(key).agg(F.min(order)[id_col].alias("_best"))
    return pointers.join(best, key).where(F.col(id_col) != F.col("_best")).select(id_col)


def later_copies(rows: DataFrame, id_col: str, key: str) -> DataFrame:
    """Ids of all rows but the first of each key; a missing key has no copies."""
    least = rows.groupBy(key).agg(F.min(id_col).alias("_least"), F.count("*").alias("_n")).where("_n > 1")
    return rows.select(id_col, key).join(least, key).where(F.col(id_col) != F.col("_least")).select(id_col)
