"""Selection of tracks: pure predicates, each usable as a flag or as a filter."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from crawltracks.config import DEFAULT, PipelineConfig
from crawltracks.functions import geo


def measured(tracks: DataFrame) -> DataFrame:
    """Adds n_points, n_segments and len2d once, so that no gate computes them again."""
    return tracks.withColumns({"n_points": geo.n_points(F.col("segments")).cast("long"), "n_segments": F.size("segments").cast("long"), "len2d": geo.length_2d(F.col("segments"))})


def ok_length(cfg: PipelineConfig = DEFAULT) -> Column:
    return F.col("len2d").between(cfg.min_len_m, cfg.max_len_m)


def ok_density(cfg: PipelineConfig = DEFAULT) -> Column:
    """At least so many points for 100 m on average; written without a division."""
    return F.col("n_points") * 100 >= F.col("len2d") * cfg.min_points_per_100m


def ok_description(text: Column, cfg: PipelineConfig = DEFAULT) -> Column:
    return F.length(text).between(cfg.desc_min, cfg.desc_max)


def single_track(tracks: DataFrame, id_col: str = "file_id") -> DataFrame:
    """Rows of files with one track (input: one row per track)."""
    one = tracks.groupBy(id_col).agg(F.count("*").alias("n")).where("n = 1").select(id_col)
    return tracks.join(one, id_col, "left_semi")


def density_pass_rate(tracks: DataFrame, cfg: PipelineConfig = DEFAULT) -> DataFrame:
    return tracks.agg(F.count("*").alias("tracks"), F.count_if(ok_density(cfg)).alias("dense"), F.round(F.count_if(ok_density(cfg)) / F.count("*"), 6).alias("rate"))


def sweep(tracks: DataFrame, metric: Column, thresholds: list[float]) -> DataFrame:
    """How many rows reach each threshold, all thresholds in one pass."""
    counts = tracks.agg(*[F.count_if(metric >= t).alias(f"t{i}") for i, t in enumerate(thresholds)])
    return counts.select(F.explode(F.array(*[F.struct(F.lit(float(t)).alias("threshold"), F.col(f"t{i}").alias("passing")) for i, t in enumerate(thresholds)])).alias("x")).select("x.*")


def language_support(rows: DataFrame, lang: str = "lang", cfg: PipelineConfig = DEFAULT, plan: str = "semi") -> DataFrame:
    """Rows of languages that more than ``lang_more_than`` rows have.

    "semi" counts first (a dozen groups) and filters by a semi join; "window" is the twin that
    moves all rows to their language and so suffers from a frequent one.
    """
    if plan == "window":
        n = F.count("*").over(Window.partitionBy(lang))
        return rows.withColumn("_n", n).where(F.col("_n") > cfg.lang_more_than).drop("_n")
    common = rows.groupBy(lang).agg(F.count("*").alias("n")).where(F.col("n") > cfg.lang_more_than).select(lang)
    return rows.join(common, lang, "left_semi")
