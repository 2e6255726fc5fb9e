"""Writers for the result: partitioned Parquet, JSON lines, and GeoJSON-shaped lines."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def write_final(final: DataFrame, path: str) -> None:
    """Parquet by language; rows are dealt by language and salted, so a frequent one is not one file of one task."""
    final.repartition("desc_lang", F.pmod(F.xxhash64("file_id"), F.lit(8))).write.mode("overwrite").partitionBy("desc_lang").parquet(path)


def write_json_lines(rows: DataFrame, path: str) -> None:
    rows.write.mode("overwrite").option("ignoreNullFields", "false").json(path)


def geojson_line(segments: Column, properties: Column) -> Column:
    """One feature as JSON text; this format puts the longitude first."""
    point = lambda p: F.array(p["lon"], p["lat"], p["ele"])
    geometry = F.struct(F.lit("LineString").alias("type"), F.transform(F.flatten(segments), point).alias("coordinates"))
    return F.to_json(F.struct(F.lit("Feature").alias("type"), geometry.alias("geometry"), properties.alias("properties")))
