"""Track files: XML text to nested tracks, and back to flat points."""

from __future__ import annotations

import xml.etree.ElementTree as ET
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: What from_xml reads; timestamps are not in it, so they are never parsed.
XML_SCHEMA = (
    "trk array<struct<desc: string, trkseg: array<struct<trkpt: array<struct<_lat: double, _lon: double, ele: double>>>>>>, "
    "wpt array<struct<_lat: double>>, rte array<struct<desc: string>>"
)
TRACKS = "array<struct<desc: string, segments: array<array<struct<lat: double, lon: double, ele: double>>>>>"
_POINT = pa.struct([("lat", pa.float64()), ("lon", pa.float64()), ("ele", pa.float64())])
_TRACKS = pa.list_(pa.struct([("desc", pa.string()), ("segments", pa.list_(pa.list_(_POINT)))]))


def parse_tracks(files: DataFrame, mode: str = "native", max_bytes: int | None = None) -> DataFrame:
    """Adds ``tracks`` and ``parse_status`` (ok, empty, malformed, oversized) and drops ``content``.

    Way-points and planned routes are not tracks; they are not looked at. The native mode leaves files whose
    root it cannot see at both ends (comments, a byte order mark or a second instruction around it, or
    malformed ones) to the other. ``max_bytes``, where it is given, sets longer files aside as oversized.
    """
    if mode == "arrow":
        return _arrow(files, max_bytes)
    if mode != "native":
        raise ValueError(f"unknown mode {mode!r}")
    parsed = _native(files.where(_whole()), max_bytes)
    rest = _arrow(files.where(~_whole()), max_bytes)
    return parsed.unionByName(rest.select(parsed.columns))


def _whole() -> Column:
    """The quick test: the text begins with its root and ends with the root's end; a cut file would still parse up to the cut."""
    root = F.regexp_extract("content", r"^\s*(?:<\?[^>]*>\s*)?<([A-Za-z0-9:]+)", 1)
    return F.coalesce(F.endswith(F.rtrim(F.translate("content", "\n\r\t", "   ")), F.concat(F.lit("</"), root, F.lit(">"))), F.lit(False))


def _native(files: DataFrame, max_bytes: int | None) -> DataFrame:
    fits = F.lit(True) if max_bytes is None else F.octet_length("content") <= max_bytes
    doc = F.from_xml(F.when(fits, F.col("content")), XML_SCHEMA, {"mode": "PERMISSIVE", "rowTag": "gpx"})
    point = lambda p: F.struct(p["_lat"].alias("lat"), p["_lon"].alias("lon"), p["ele"].alias("ele"))
    seg = lambda s: F.transform(F.coalesce(s["trkpt"], F.array().cast("array<struct<_lat:double,_lon:double,ele:double>>")), point)
    trk = lambda t: F.struct(t["desc"].alias("desc"), F.transform(F.coalesce(t["trkseg"], F.array().cast("array<struct<trkpt:array<struct<_lat:double,_lon:double,ele:double>>>>")), seg).alias("segments"))
    rows = files.withColumn("doc", doc).withColumn("tracks", F.transform("doc.trk", trk))
    status = F.when(~fits, "oversized").when(F.col("doc").isNull(), "malformed").when(F.coalesce(F.size("tracks"), F.lit(0)) < 1, "empty").otherwise("ok")
    return rows.withColumn("parse_status", status).drop("doc", "content")


def _local(tag: str) -> str:
    return tag.rpartition("}")[2]


def _tracks_of(content: str | None) -> tuple[str, list[dict] | None]:
    if content is None:
        return "malformed", None
    if "<!DOCTYPE" in content or "<!ENTITY" in content:
        return "malformed", None
    try:
        root = ET.fromstring(content.lstrip("\ufeff \t\r\n"))
    except ET.ParseError:
        return "malformed", None
    found = []
    for trk in (x for x in root if _local(x.tag) == "trk"):
        desc = next((x.text for x in trk if _local(x.tag) == "desc"), None)
        segments = []
        for seg in (x for x in trk if _local(x.tag) == "trkseg"):
            points = []
            for p in (x for x in seg if _local(x.tag) == "trkpt"):
                ele = next((x.text for x in p if _local(x.tag) == "ele"), None)
                points.append({"lat": float(p.get("lat")), "lon": float(p.get("lon")), "ele": float(ele) if ele else None})
            segments.append(points)
        found.append({"desc": desc, "segments": segments})
    return ("ok" if found else "empty"), found


def _arrow(files: DataFrame, max_bytes: int | None) -> DataFrame:
    kept = [c for c in files.columns if c != "content"]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in files.schema if f.name != "content") + f", tracks {TRACKS}, parse_status string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            status, tracks = [], []
            for content in batch.column("content").to_pylist():
                if max_bytes is not None and content is not None and len(content.encode()) > max_bytes:
                    s, t = "oversized", None
                else:
                    s, t = _tracks_of(content)
                status.append(s)
                tracks.append(t)
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.array(tracks, _TRACKS), pa.array(status, pa.string())], [*kept, "tracks", "parse_status"])

    return files.mapInArrow(run, schema)


def shape(parsed: DataFrame, id_col: str = "file_id") -> DataFrame:
    """Tracks, segments and points of each file."""
    segments = F.aggregate("tracks", F.lit(0), lambda acc, t: acc + F.size(t["segments"]))
    points = F.aggregate("tracks", F.lit(0), lambda acc, t: acc + F.aggregate(t["segments"], F.lit(0), lambda a, s: a + F.size(s)))
    return parsed.select(id_col, F.size("tracks").cast("long").alias("n_tracks"), segments.cast("long").alias("n_segments"), points.cast("long").alias("n_points"))


def shape_by_path(files: DataFrame, id_col: str = "file_id") -> DataFrame:
    """The same counts by path expressions, one document tree an expression, and way-points and routes beside them.

    Path expressions fail on malformed text, so files whose root cannot be seen at both ends have no counts.
    """
    paths = {"n_tracks": "trk", "n_segments": "trk/trkseg", "n_points": "trk/trkseg/trkpt", "n_waypoints": "wpt", "n_routes": "rte"}
    return files.select(id_col, *[F.when(_whole(), F.xpath_long("content", F.lit(f"count(/*/{p})"))).alias(c) for c, p in paths.items()])


class SegmentPoints:
    """Table function: the points of a file's text, with the numbers of track, segment and point."""

    def eval(self, content: str):
        for t, track in enumerate(_tracks_of(content)[1] or []):
            for s, points in enumerate(track["segments"]):
                for i, p in enumerate(points):
                    yield t, s, i, p["lat"], p["lon"], p["ele"]


segment_points = F.udtf(SegmentPoints, returnType="track int, segment int, seq int, lat double, lon double, ele double")


def explode_tracks(parsed: DataFrame) -> DataFrame:
    """One row per track: the rejected option of keeping files with several."""
    return parsed.select("*", F.posexplode("tracks").alias("track_no", "track")).select(*[c for c in parsed.columns if c != "tracks"], "track_no", "track.desc", "track.segments")
