"""Discovery of candidate files in the URL index."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crawltracks.functions.url import url_ext


def is_mime(mime: Column, token: str) -> Column:
    return F.lower(mime).contains(token.lower())


def is_ext(url: Column, ext: str | list[str]) -> Column:
    return url_ext(url).isin([ext] if isinstance(ext, str) else ext)


def discover(index: DataFrame, mime_token: str, ext: str | list[str], mode: str = "either") -> DataFrame:
    """Captures whose detected type holds the token, whose path has the extension, either or both."""
    mime, named = is_mime(F.col("mime_detected"), mime_token), is_ext(F.col("url"), ext)
    return index.where({"either": mime | named, "mime": mime, "ext": named, "both": mime & named}[mode])


def dictionary_in(index: DataFrame, mime_token: str, limit: int = 10_000) -> list[str]:
    """The few distinct detected types that hold the token, so that the scan can push IN (..) down.

    Detected types come from a fixed registry; more than ``limit`` of them is an error, not a cut.
    """
    found = index.select("mime_detected").distinct().where(is_mime(F.col("mime_detected"), mime_token)).limit(limit + 1).collect()
    if len(found) > limit:
        raise ValueError(f"more than {limit} detected types; use discover() instead")
    return [r[0] for r in found]


def discover_pushed(index: DataFrame, mime_token: str, ext: str) -> DataFrame:
    """As ``discover(mode="either")``, with a first condition that Parquet row groups can be tested against."""
    values = dictionary_in(index, mime_token)
    near = F.col("url").contains(f".{ext}") | F.col("mime_detected").isin(values) if values else F.col("url").contains(f".{ext}")
    return index.where(near).where(is_ext(F.col("url"), ext) | F.col("mime_detected").isin(values)) if values else index.where(near).where(is_ext(F.col("url"), ext))


def discovery_agreement(index: DataFrame, mime_token: str, ext: str) -> DataFrame:
    flags = index.select(is_mime(F.col("mime_detected"), mime_token).alias("is_mime"), is_ext(F.col("url"), ext).alias("is_ext"))
    return flags.groupBy("is_mime", "is_ext").agg(F.count("*").alias("n"))


def pointers(candidates: DataFrame) -> DataFrame:
    return candidates.select("url", F.struct("archive", "offset", "length").alias("pointer"))
