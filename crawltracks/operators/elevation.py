"""Heights from a raster where a track has none of its own."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crawltracks.functions import geo

CELLS = 8
SOUTH, COLUMNS = 40, 10
FILL_SCALE, FILL_BASE = 1000.0, 600.0


def tile_id(lat_u: Column, lon_u: Column) -> Column:
    return (F.floor(lat_u / 1_000_000) - SOUTH) * COLUMNS + F.floor(lon_u / 1_000_000)


def _cell(u: Column) -> Column:
    return F.floor((u % 1_000_000) * CELLS / 1_000_000).cast("int")


def _micro(x: Column) -> Column:
    return F.round(x * 1_000_000).cast("long")


def height(cells: Column, row: Column, col: Column) -> Column:
    return F.get(cells, row * CELLS + col).cast("double") * FILL_SCALE + FILL_BASE


def lookup(points: DataFrame, tiles: DataFrame, interp: str = "nearest") -> DataFrame:
    """Adds ``dem`` to points with lat_u and lon_u; NULL where no tile covers them.

    An equi-join on the tile: the engine broadcasts a small tile table and shuffles a large one.
    "bilinear" weighs the four nearest cell centres of the point's tile (clamped at its border).
    """
    rows = points.withColumn("tile_id", tile_id(F.col("lat_u"), F.col("lon_u"))).join(tiles, "tile_id", "left")
    if interp == "nearest":
        dem = height(F.col("cells"), _cell(F.col("lat_u")), _cell(F.col("lon_u")))
    elif interp == "bilinear":
        at = lambda u: F.greatest(F.least((u % 1_000_000) * CELLS / 1_000_000 - 0.5, F.lit(CELLS - 1.0)), F.lit(0.0))
        y, x = at(F.col("lat_u")), at(F.col("lon_u"))
        y0, x0 = F.floor(y).cast("int"), F.floor(x).cast("int")
        y1, x1 = F.least(y0 + 1, F.lit(CELLS - 1)), F.least(x0 + 1, F.lit(CELLS - 1))
        fy, fx = y - y0, x - x0
        c = F.col("cells")
        dem = height(c, y0, x0) * (1 - fy) * (1 - fx) + height(c, y0, x1) * (1 - fy) * fx + height(c, y1, x0) * fy * (1 - fx) + height(c, y1, x1) * fy * fx
    else:
        raise ValueError(f"unknown interpolation {interp!r}")
    return rows.withColumn("dem", dem).drop("cells", "tile_id")


def fill_elevation(tracks: DataFrame, tiles: DataFrame, keys: list[str], interp: str = "nearest", policy: str = "track") -> DataFrame:
    """Tracks with heights everywhere and ``elev_source``; complete tracks never leave their row.

    policy: "track" takes all heights from the raster unless all are recorded; "gaps" takes
    only the missing ones; "linear" bridges gaps between recorded neighbours and takes the rest.
    """
    rows = tracks.withColumn("elev_class", geo.elevation_class(F.col("segments")))
    full = rows.where("elev_class = 'full'").withColumn("elev_source", F.lit("GPS")).drop("elev_class")
    lacking = rows.where("elev_class <> 'full'")
    flat = lacking.select(*keys, F.posexplode("segments").alias("seg", "points")).select(*keys, "seg", F.posexplode("points").alias("seq", "p"))
    flat = flat.select(*keys, "seg", "seq", "p.lat", "p.lon", "p.ele", _micro(F.col("p.lat")).alias("lat_u"), _micro(F.col("p.lon")).alias("lon_u"))
    flat = lookup(flat, tiles, interp)
    if policy == "track":
        ele = F.col("dem")
    elif policy == "gaps":
        ele = F.coalesce("ele", "dem")
    elif policy == "linear":
        from pyspark.sql.window import Window

        w = Window.partitionBy(*keys, "seg").orderBy("seq")
        back, ahead = w.rowsBetween(Window.unboundedPreceding, 0), w.rowsBetween(0, Window.unboundedFollowing)
        known = F.when(F.col("ele").isNotNull(), F.col("seq"))
        a, b = F.last(known, ignorenulls=True).over(back), F.first(known, ignorenulls=True).over(ahead)
        ea, eb = F.last("ele", ignorenulls=True).over(back), F.first("ele", ignorenulls=True).over(ahead)
        bridged = F.when(a == b, ea).otherwise(ea + (eb - ea) * (F.col("seq") - a) / (b - a))
        ele = F.coalesce("ele", bridged, "dem")
    else:
        raise ValueError(f"unknown policy {policy!r}")
    point = F.struct("seq", "lat", "lon", ele.alias("ele"))
    flat = flat.withColumn("point", point) if policy != "linear" else flat.withColumn("ele2", ele).withColumn("point", F.struct("seq", "lat", "lon", F.col("ele2").alias("ele")))
    plain = F.transform(F.sort_array(F.collect_list("point")), lambda p: F.struct(p["lat"].alias("lat"), p["lon"].alias("lon"), p["ele"].alias("ele")))
    segs = flat.groupBy(*keys, "seg").agg(plain.alias("points"))
    whole = segs.groupBy(*keys).agg(F.transform(F.sort_array(F.collect_list(F.struct("seg", "points"))), lambda s: s["points"]).alias("segments"))
    filled = lacking.drop("segments", "elev_class").join(whole, keys).withColumn("elev_source", F.lit("DEM"))
    full = full.withColumn("segments", geo.drop_times(F.col("segments")))
    return full.unionByName(filled.select(full.columns))
