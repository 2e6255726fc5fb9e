"""Country of a track: the polygon that its first point lies in."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crawltracks.functions import geo

#: Corners that may be sent to all tasks; beyond it the call fails instead of growing.
MAX_CORNERS = 100_000


def cover_cells(polygons: DataFrame, degrees: float = 2.0) -> DataFrame:
    """Each polygon once for every grid cell that its bounding box touches."""
    lat, lon = F.transform("ring", lambda p: p["lat"]), F.transform("ring", lambda p: p["lon"])
    cell = lambda x: F.floor(x / degrees)
    rows = F.explode(F.sequence(cell(F.array_min(lat)), cell(F.array_max(lat)))).alias("cell_lat")
    cols = F.explode(F.sequence(cell(F.array_min(lon)), cell(F.array_max(lon)))).alias("cell_lon")
    return polygons.select("*", rows).select("*", cols)


def assign_country(tracks: DataFrame, polygons: DataFrame, degrees: float = 2.0) -> DataFrame:
    """Adds ``country`` (and ``region`` where polygons have one): NULL outside all of them.

    An equi-join on the grid cell finds the few polygons near a point, ray casting decides; a
    point that several hold goes to the first by name.
    """
    p = geo.first_point(F.col("segments"))
    rows = tracks.withColumns({"_lat": p["lat"], "_lon": p["lon"]})
    rows = rows.withColumns({"cell_lat": F.floor(F.col("_lat") / degrees), "cell_lon": F.floor(F.col("_lon") / degrees)})
    extra = [c for c in ("region",) if c in polygons.columns]
    cells = cover_cells(polygons, degrees).select("cell_lat", "cell_lon", "country", "ring", *extra)
    side = cells.groupBy("cell_lat", "cell_lon").agg(F.sort_array(F.collect_list(F.struct("country", *extra, "ring"))).alias("near"))
    joined = rows.join(side, ["cell_lat", "cell_lon"], "left")
    hit = F.get(F.filter("near", lambda c: geo.in_ring(F.col("_lat"), F.col("_lon"), c["ring"])), F.lit(0))
    return joined.withColumn("_hit", hit).select(*tracks.columns, F.col("_hit.country").alias("country"), *[F.col(f"_hit.{c}").alias(c) for c in extra])


def nearest_country(points: DataFrame, polygons: DataFrame) -> DataFrame:
    """For points without a country: the polygon with the nearest corner; all corners go to every task as one checked array."""
    corners = polygons.select("country", F.explode("ring").alias("c")).select("country", "c.lat", "c.lon").where("lat is not null and lon is not null").distinct()
    known = corners.limit(MAX_CORNERS + 1).collect()
    if len(known) > MAX_CORNERS:
        raise ValueError(f"more than {MAX_CORNERS} corners to send to all tasks")
    side = points.sparkSession.createDataFrame([(sorted(known),)], "corners array<struct<country: string, lat: double, lon: double>>")
    near = F.array_min(F.transform("corners", lambda c: F.struct(geo.step_m(F.col("lat"), F.col("lon"), c["lat"], c["lon"]).alias("m"), c["country"].alias("country"))))
    placed = F.when(F.col("lat").isNotNull() & F.col("lon").isNotNull(), near["country"])
    return points.withColumn("_one", F.lit(1)).join(F.broadcast(side.withColumn("_one", F.lit(1))), "_one").select(*points.columns, placed.alias("country"))
