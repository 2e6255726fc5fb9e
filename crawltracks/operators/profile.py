"""Statistics of the result: ranks, ranges, medians, histograms, extrapolation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def length_stats(rows: DataFrame, value: Column, digits: int = 2, exact: bool = True) -> DataFrame:
    """Count, least, greatest, mean and median; a KLL sketch stands in for the exact median on raw sets."""
    x = value.cast("double")
    middle = F.percentile(x, 0.5) if exact else F.percentile_approx(x, 0.5, 10_000)
    return rows.agg(F.count("*").alias("n"), F.round(F.min(x), digits).alias("least"), F.round(F.max(x), digits).alias("greatest"), F.round(F.avg(x), digits).alias("mean"), F.round(middle, digits).alias("median"))


def top(rows: DataFrame, key: str, k: int | None = None) -> DataFrame:
    """Counts by key, ties by name; ``k`` keeps the first."""
    counts = rows.groupBy(key).agg(F.count("*").alias("n"))
    return counts if k is None else counts.orderBy(F.desc("n"), F.asc_nulls_last(key)).limit(k)


def histogram(rows: DataFrame, value: Column, low: float, high: float, bins: int) -> DataFrame:
    """Counts of every bin of [low, high), empty ones too; what lies outside is in bins 0 and bins + 1."""
    spark = rows.sparkSession
    counts = rows.groupBy(F.width_bucket(value.cast("double"), F.lit(float(low)), F.lit(float(high)), F.lit(bins)).cast("long").alias("bin")).agg(F.count("*").alias("n"))
    every = spark.range(0, bins + 2).withColumnRenamed("id", "bin")
    start = F.round(low + (F.col("bin") - 1) * (high - low) / bins, 6)
    return every.join(F.broadcast(counts), "bin", "left").select("bin", start.alias("start"), F.coalesce("n", F.lit(0)).alias("n"))


def domain_count(rows: DataFrame, host: Column, exact: bool = True) -> DataFrame:
    return rows.agg((F.count_distinct(host) if exact else F.approx_count_distinct(host, 0.01)).alias("domains"))


def extrapolate(per_release: DataFrame, kept: str, wanted: int) -> DataFrame:
    """Releases needed for ``wanted`` rows at the mean yield of a release."""
    y = F.avg(kept)
    return per_release.agg(F.round(y, 6).alias("yield_per_release"), F.ceil(F.lit(wanted) / y).cast("long").alias("releases_needed"))
