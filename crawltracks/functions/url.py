"""Parts of URLs by expressions that do not fail on dirty input."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

PATH = r"^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*([^?#]*)"
HOST = r"^[A-Za-z][A-Za-z0-9+.-]*://([^/?#:]+)"


def url_path(url: Column) -> Column:
    return F.regexp_extract(url, PATH, 1)


def url_ext(url: Column) -> Column:
    """Lower-case extension of the path's last part; query and fragment do not count."""
    return F.lower(F.regexp_extract(url_path(url), r"\.([A-Za-z0-9]+)$", 1))


def url_host(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, HOST, 1))
