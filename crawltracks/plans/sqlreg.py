"""SQL functions for users who write SQL; Catalyst inlines each into a plain projection, but for the table function."""

from __future__ import annotations

from pyspark.sql import SparkSession

from crawltracks.functions import text as tx
from crawltracks.functions.url import PATH
from crawltracks.operators.parse import segment_points


def _quoted(pattern: str) -> str:
    return "r'" + pattern + "'"


def register_sql(spark: SparkSession) -> list[str]:
    """Create the temporary functions; returns their names."""
    bodies = {
        "track_step_m": ("lat1 DOUBLE, lon1 DOUBLE, lat2 DOUBLE, lon2 DOUBLE", "DOUBLE", "2 * 6371000 * asin(sqrt(pow(sin(radians(lat2 - lat1) / 2), 2) + cos(radians(lat1)) * cos(radians(lat2)) * pow(sin(radians(lon2 - lon1) / 2), 2)))"),
        "url_ext": ("url STRING", "STRING", rf"lower(regexp_extract(regexp_extract(url, {_quoted(PATH)}, 1), r'\.([A-Za-z0-9]+)$', 1))"),
        "is_dense": ("n_points INT, metres DOUBLE", "BOOLEAN", "n_points * 100 >= metres"),
        "mask_pii": (
            "t STRING", "STRING",
            f"regexp_replace(regexp_replace(regexp_replace(t, {_quoted(tx.URL_PATTERN)}, '{tx.URL}'), {_quoted(tx.EMAIL_PATTERN)}, '{tx.EMAIL}'), {_quoted(tx.POSSIBLE_PATTERN)}, '{tx.TELEPHONE}')",
        ),
        "clean_desc": ("t STRING", "STRING", rf"trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(t, {_quoted(tx.TAG)}, ''), r'[\n\r\t\x0B\f]+', ' '), r'\[[^\[\]]*\]|\{{[^{{}}]*\}}', ''), ' {{2,}}', ' '))"),
    }
    for name, (args, kind, body) in bodies.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
    spark.udtf.register("segment_points", segment_points)
    return [*bodies, "segment_points"]
