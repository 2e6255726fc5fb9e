"""The columnar URL index: explicit schema, partition pruning, five columns."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

INDEX_SCHEMA = "release string, part int, url string, mime_detected string, archive string, offset bigint, length bigint"


def scan_index(spark: SparkSession, root: str, releases: list[str] | None = None, parts: list[int] | None = None) -> DataFrame:
    """Index rows under ``root``, partitioned by release; ``parts`` keeps some parts (a preview)."""
    df = spark.read.schema(INDEX_SCHEMA).parquet(root)
    if releases is not None:
        df = df.where(F.col("release").isin(releases))
    return df if parts is None else df.where(F.col("part").isin(parts))
