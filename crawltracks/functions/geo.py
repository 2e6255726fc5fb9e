"""Geometry on nested points: lengths, climbs, extremes, bearings, well-known text.

A segment is ``array<struct<lat, lon, ele>>``; a track is an array of segments. All helpers are
row-local higher-order functions, so none of them shuffles.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

EARTH_RADIUS_M = 6_371_000.0


def step_m(lat1: Column, lon1: Column, lat2: Column, lon2: Column, radius: float = EARTH_RADIUS_M) -> Column:
    """Great-circle distance of two points in metres; null where a coordinate is."""
    a = F.pow(F.sin(F.radians(lat2 - lat1) / 2), 2) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.pow(F.sin(F.radians(lon2 - lon1) / 2), 2)
    return 2 * radius * F.asin(F.sqrt(F.when(a > 1, 1.0).otherwise(a)))


def flat_step_m(lat1: Column, lon1: Column, lat2: Column, lon2: Column, radius: float = EARTH_RADIUS_M) -> Column:
    """Distance on a local flat projection; close to :func:`step_m` for short steps."""
    x = F.radians(lon2 - lon1) * F.cos(F.radians((lat1 + lat2) / 2))
    return radius * F.sqrt(x * x + F.pow(F.radians(lat2 - lat1), 2))


def pairs(points: Column, f: Callable[[Column, Column], Column]) -> Column:
    """f over each two consecutive points of a segment."""
    n = F.greatest(F.size(points) - 1, F.lit(0))
    return F.zip_with(F.slice(points, F.lit(1), n), F.slice(points, F.lit(2), n), f)


def total(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda acc, x: acc + x)


def per_segment(segments: Column, f: Callable[[Column, Column], Column]) -> Column:
    """Sum of f over the consecutive points of every segment; gaps between segments do not count."""
    return total(F.transform(segments, lambda s: total(pairs(s, f))))


def _plane(metric: str) -> Callable[[Column, Column], Column]:
    step = {"haversine": step_m, "equirect": flat_step_m}[metric]
    return lambda a, b: step(a["lat"], a["lon"], b["lat"], b["lon"])


def length_2d(segments: Column, metric: str = "haversine", across_segments: bool = False) -> Column:
    if across_segments:
        return total(pairs(F.flatten(segments), _plane(metric)))
    return per_segment(segments, _plane(metric))


def length_3d(segments: Column) -> Column:
    """As :func:`length_2d` with the height of each step; an unknown height difference is flat."""
    flat = _plane("haversine")

    def step(a: Column, b: Column) -> Column:
        rise = F.coalesce(b["ele"] - a["ele"], F.lit(0.0))
        return F.sqrt(F.pow(flat(a, b), 2) + rise * rise)

    return per_segment(segments, step)


def max_step_m(segments: Column) -> Column:
    """Longest single step inside a segment."""
    return F.coalesce(F.array_max(F.flatten(F.transform(segments, lambda s: pairs(s, _plane("haversine"))))), F.lit(0.0))


def n_points(segments: Column) -> Column:
    return F.aggregate(segments, F.lit(0), lambda acc, s: acc + F.size(s))


def _smoothed(points: Column, smooth: str, band: float) -> Column:
    if smooth == "none":
        return F.transform(points, lambda p: p["ele"])
    if smooth == "mean3":
        near = lambda p, i: F.slice(points, F.greatest(i, F.lit(1)), F.lit(2) + (i > 0).cast("int"))
        mean = lambda a: F.aggregate(a, F.lit(0.0), lambda acc, q: acc + q["ele"]) / F.size(a)
        return F.transform(points, lambda p, i: mean(near(p, i)))
    if smooth == "hyst":  # heights move only when they leave a band around the last one
        last = lambda acc: F.element_at(acc, -1)
        return F.aggregate(
            F.slice(points, F.lit(2), F.greatest(F.size(points) - 1, F.lit(0))),
            F.array(F.get(points, F.lit(0))["ele"]),
            lambda acc, p: F.concat(acc, F.array(F.when(F.abs(p["ele"] - last(acc)) >= band, p["ele"]).otherwise(last(acc)))),
        )
    raise ValueError(f"unknown smoothing {smooth!r}")


def gain(segments: Column, sign: int = 1, smooth: str = "none", band: float = 5.0) -> Column:
    """Sum of rising steps (sign 1) or of falling ones (sign -1) as a magnitude."""
    return total(F.transform(segments, lambda s: total(pairs(_smoothed(s, smooth, band), lambda a, b: F.greatest(F.coalesce((b - a) * sign, F.lit(0.0)), F.lit(0.0))))))


def highest(segments: Column) -> Column:
    return F.array_max(F.transform(F.flatten(segments), lambda p: p["ele"]))


def lowest(segments: Column) -> Column:
    return F.array_min(F.transform(F.flatten(segments), lambda p: p["ele"]))


def first_point(segments: Column) -> Column:
    return F.get(F.flatten(segments), F.lit(0))


def last_point(segments: Column) -> Column:
    return F.element_at(F.flatten(segments), -1)


def end_distance_m(segments: Column) -> Column:
    a, b = first_point(segments), last_point(segments)
    return step_m(a["lat"], a["lon"], b["lat"], b["lon"])


def is_circular(segments: Column, within_m: float = 350.0) -> Column:
    return end_distance_m(segments) <= within_m


def elevation_class(segments: Column) -> Column:
    """'full', 'none' or 'partial' by how many points have a height."""
    points = F.flatten(segments)
    return (
        F.when(F.forall(points, lambda p: p["ele"].isNotNull()), "full").when(F.forall(points, lambda p: p["ele"].isNull()), "none").otherwise("partial")
    )


def bearing_deg(a: Column, b: Column) -> Column:
    """Initial bearing from a to b in -180..180."""
    dlon, p, q = F.radians(b["lon"] - a["lon"]), F.radians(a["lat"]), F.radians(b["lat"])
    return F.degrees(F.atan2(F.sin(dlon) * F.cos(q), F.cos(p) * F.sin(q) - F.sin(p) * F.cos(q) * F.cos(dlon)))


def turns_deg(points: Column) -> Column:
    """Change of bearing at each inner point, in 0..180."""
    turn = lambda a, b: F.lit(180.0) - F.abs(F.abs(a - b) % 360 - 180)
    return pairs(pairs(points, bearing_deg), turn)


def drop_times(segments: Column) -> Column:
    """Points without anything but position and height."""
    return F.transform(segments, lambda s: F.transform(s, lambda p: F.struct(p["lat"].alias("lat"), p["lon"].alias("lon"), p["ele"].alias("ele"))))


def trim_ends(segments: Column, metres: float) -> Column:
    """Segments without the points nearer than ``metres`` to the first or the last point of the track."""
    a, b = first_point(segments), last_point(segments)
    far = lambda p, q: step_m(p["lat"], p["lon"], q["lat"], q["lon"]) >= metres
    return F.filter(F.transform(segments, lambda s: F.filter(s, lambda p: far(p, a) & far(p, b))), lambda s: F.size(s) > 0)


def to_wkt_z(segments: Column, axis: str = "latlon", digits: int = 6, multi: bool = False) -> Column:
    """Well-known text of one 3-D line over all segments, or with ``multi`` of a line a segment; ``axis`` orders the first two numbers."""
    one, two = ("lat", "lon") if axis == "latlon" else ("lon", "lat")
    number = lambda c, d: F.format_string(f"%.{d}f", c)
    point = lambda p: F.concat_ws(" ", number(p[one], digits), number(p[two], digits), number(F.coalesce(p["ele"], F.lit(float("nan"))), 2))
    line = lambda points: F.concat(F.lit("("), F.array_join(F.transform(points, point), ", "), F.lit(")"))
    if multi:
        return F.concat(F.lit("MULTILINESTRING Z ("), F.array_join(F.transform(segments, line), ", "), F.lit(")"))
    return F.concat(F.lit("LINESTRING Z "), line(F.flatten(segments)))


def in_ring(lat: Column, lon: Column, ring: Column) -> Column:
    """Even-odd ray casting against a closed ring (array of lat/lon structs, the first repeated at the end)."""

    def crosses(a: Column, b: Column) -> Column:
        spans = (a["lat"] > lat) != (b["lat"] > lat)
        at = a["lon"] + (lat - a["lat"]) / F.nullif(b["lat"] - a["lat"], F.lit(0.0)) * (b["lon"] - a["lon"])
        return F.when(spans & (lon < at), 1).otherwise(0)

    return F.aggregate(pairs(ring, crosses), F.lit(0), lambda acc, x: acc + x) % 2 == 1
