"""Registered queries of parsing, selection, elevation and track properties."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from crawltracks.config import DEFAULT as CFG
from crawltracks.functions import geo
from crawltracks.operators import gates, parse
from crawltracks.operators.country import assign_country
from crawltracks.operators.elevation import fill_elevation, lookup
from crawltracks.plans.registry import query
from crawltracks.plans.sqlviews import sql
from crawltracks.sources import fixtures as fx

KEYS = ["file_id", "track_no"]


def banded(spark: SparkSession, sf: str) -> DataFrame:
    return gates.measured(gates.single_track(fx.tracks(spark, sf))).where(gates.ok_length())


def dense(spark: SparkSession, sf: str) -> DataFrame:
    return banded(spark, sf).where(gates.ok_density())


def filled(spark: SparkSession, sf: str, **how) -> DataFrame:
    return fill_elevation(fx.tracks(spark, sf).withColumn("segments", geo.drop_times(F.col("segments"))), fx.tiles(spark, sf), KEYS, **how)


_SHAPE = "SELECT file_id, count(DISTINCT track_no) AS n_tracks, count(DISTINCT (track_no, seg_no)) AS n_segments, count(*) AS n_points FROM pts GROUP BY file_id"


@query(sql("pts", _SHAPE))
def b1_parse(spark: SparkSession, sf: str) -> DataFrame:
    """Counts of nested parts after the way through XML text."""
    return parse.shape(parse.parse_tracks(fx.track_xml(spark, sf)))


@query(sql("pts", _SHAPE))
def b1a_parse_arrow(spark: SparkSession, sf: str) -> DataFrame:
    return parse.shape(parse.parse_tracks(fx.track_xml(spark, sf), mode="arrow"))


@query(sql("pts", _SHAPE))
def b1b_parse_paths(spark: SparkSession, sf: str) -> DataFrame:
    return parse.shape_by_path(fx.track_xml(spark, sf)).select("file_id", "n_tracks", "n_segments", "n_points")


@query("SELECT CASE WHEN user_id % 40 = 0 THEN 'malformed' ELSE 'ok' END AS parse_status, count(DISTINCT user_id) AS files FROM events GROUP BY 1")
def b1c_parse_status(spark: SparkSession, sf: str) -> DataFrame:
    return parse.parse_tracks(fx.track_xml(spark, sf, malformed=True)).groupBy("parse_status").agg(F.count("*").alias("files"))


@query(sql("pts", _SHAPE))
def b2_shape(spark: SparkSession, sf: str) -> DataFrame:
    files = fx.tracks(spark, sf).groupBy("file_id").agg(F.collect_list(F.struct(F.lit("").alias("desc"), "segments")).alias("tracks"))
    return parse.shape(files)


@query(sql("one", "SELECT file_id FROM one"))
def b3_single_track(spark: SparkSession, sf: str) -> DataFrame:
    return gates.single_track(fx.tracks(spark, sf)).select("file_id")


@query(sql("trk", "SELECT file_id, CAST(track_no AS INTEGER) AS track_no, n_points FROM trk"))
def b3a_all_tracks(spark: SparkSession, sf: str) -> DataFrame:
    """Through XML: one row per track of every parsed file."""
    rows = parse.explode_tracks(parse.parse_tracks(fx.track_xml(spark, sf)))
    return rows.select("file_id", "track_no", geo.n_points(F.col("segments")).cast("long").alias("n_points"))


@query(sql("trk", "SELECT file_id, track_no, round(len2d, 2) AS len2d FROM trk"))
def b4_len2d(spark: SparkSession, sf: str) -> DataFrame:
    return fx.tracks(spark, sf).select(*KEYS, F.round(geo.length_2d(F.col("segments")), 2).alias("len2d"))


@query(sql("trk", "SELECT file_id, track_no, round(len2d, 2) AS len2d FROM trk"))
def b4a_len2d_window(spark: SparkSession, sf: str) -> DataFrame:
    """The exploded twin: lag over each segment, then a sum."""
    w = Window.partitionBy("file_id", "track_no", "seg_no").orderBy("ts", "event_id")
    p = fx.points(spark, sf).select("*", (F.col("lat_u") / 1e6).alias("lat"), (F.col("lon_u") / 1e6).alias("lon"))
    step = geo.step_m(F.lag("lat").over(w), F.lag("lon").over(w), F.col("lat"), F.col("lon"))
    return p.withColumn("step", step).groupBy(*KEYS).agg(F.round(F.coalesce(F.sum("step"), F.lit(0.0)), 2).alias("len2d"))


@query(sql("pts", """, s AS (SELECT file_id, track_no, lat_u / 1e6 AS lat, lon_u / 1e6 AS lon, lag(lat_u) OVER w / 1e6 AS plat, lag(lon_u) OVER w / 1e6 AS plon FROM pts WINDOW w AS (PARTITION BY file_id, track_no ORDER BY seg_no, ts, event_id))
SELECT file_id, track_no, round(coalesce(sum(2 * 6371000 * asin(sqrt((pow(sin(radians(lat - plat) / 2), 2) + cos(radians(plat)) * cos(radians(lat)) * pow(sin(radians(lon - plon) / 2), 2))))), 0), 2) AS len2d FROM s GROUP BY ALL"""))
def b4b_len_joined(spark: SparkSession, sf: str) -> DataFrame:
    return fx.tracks(spark, sf).select(*KEYS, F.round(geo.length_2d(F.col("segments"), across_segments=True), 2).alias("len2d"))


@query(sql("steps", "SELECT file_id, track_no, round(coalesce(sum(6371000 * sqrt(pow(radians(lon - plon) * cos(radians((lat + plat) / 2)), 2) + pow(radians(lat - plat), 2))), 0), 2) AS len2d FROM steps GROUP BY ALL"))
def b4c_len_flat(spark: SparkSession, sf: str) -> DataFrame:
    return fx.tracks(spark, sf).select(*KEYS, F.round(geo.length_2d(F.col("segments"), metric="equirect"), 2).alias("len2d"))


@query(sql("banded", "SELECT file_id, round(len2d, 2) AS len2d FROM banded"))
def b5_length_band(spark: SparkSession, sf: str) -> DataFrame:
    return banded(spark, sf).select("file_id", F.round("len2d", 2).alias("len2d"))


@query(sql("dense", "SELECT file_id, n_points, n_segments, round(len2d, 2) AS len2d FROM dense"))
def b6_density(spark: SparkSession, sf: str) -> DataFrame:
    return dense(spark, sf).select("file_id", "n_points", "n_segments", F.round("len2d", 2).alias("len2d"))


_RATE = "count(*) AS tracks, count(*) FILTER (n_points * 100 >= len2d) AS dense, round(count(*) FILTER (n_points * 100 >= len2d) / count(*), 6) AS rate"


@query(sql("trk banded", f"SELECT 'all' AS base, {_RATE} FROM trk UNION ALL SELECT 'banded', {_RATE} FROM banded"))
def b6a_density_rate(spark: SparkSession, sf: str) -> DataFrame:
    every = gates.density_pass_rate(gates.measured(fx.tracks(spark, sf))).withColumn("base", F.lit("all"))
    return every.unionByName(gates.density_pass_rate(banded(spark, sf)).withColumn("base", F.lit("banded")))


@query(sql("banded", "SELECT t AS threshold, (SELECT count(*) FROM banded WHERE n_points * 100 / len2d >= t) AS passing FROM (SELECT unnest([0.25, 0.5, 1.0, 2.0, 4.0, 8.0])::DOUBLE AS t)"))
def b6b_density_sweep(spark: SparkSession, sf: str) -> DataFrame:
    return gates.sweep(banded(spark, sf), F.col("n_points") * 100 / F.col("len2d"), [0.25, 0.5, 1, 2, 4, 8])


@query(sql("banded", "SELECT file_id, round(max_step, 2) AS max_step FROM banded WHERE max_step <= 1000"))
def b6c_max_gap(spark: SparkSession, sf: str) -> DataFrame:
    step = geo.max_step_m(F.col("segments"))
    return banded(spark, sf).withColumn("max_step", step).where("max_step <= 1000").select("file_id", F.round("max_step", 2).alias("max_step"))


@query(sql("trk", "SELECT file_id, track_no, CASE WHEN n_ele = n_points THEN 'full' WHEN n_ele = 0 THEN 'none' ELSE 'partial' END AS elev_class FROM trk"))
def e1_elev_class(spark: SparkSession, sf: str) -> DataFrame:
    return fx.tracks(spark, sf).select(*KEYS, geo.elevation_class(F.col("segments")).alias("elev_class"))


@query(sql("filled", "SELECT file_id, track_no, source AS elev_source, count(*) AS n_points, round(sum(ele), 2) AS total FROM filled GROUP BY ALL"))
def e2_dem_fill(spark: SparkSession, sf: str) -> DataFrame:
    flat = filled(spark, sf).select(*KEYS, "elev_source", F.explode(F.flatten("segments")).alias("p"))
    return flat.groupBy(*KEYS, "elev_source").agg(F.count("*").alias("n_points"), F.round(F.sum("p.ele"), 2).alias("total"))


@query(sql("pts", """, a AS (SELECT event_id, lat_u, lon_u, greatest(least((lat_u % 1000000) * 8 / 1000000 - 0.5, 7.0), 0.0) AS y, greatest(least((lon_u % 1000000) * 8 / 1000000 - 0.5, 7.0), 0.0) AS x FROM pts),
b AS (SELECT *, floor(y)::INT AS y0, floor(x)::INT AS x0, least(floor(y)::INT + 1, 7) AS y1, least(floor(x)::INT + 1, 7) AS x1, y - floor(y) AS fy, x - floor(x) AS fx FROM a),
h AS (SELECT b.*, embedding AS c FROM b LEFT JOIN embeddings e ON e.vec_id = (lat_u // 1000000 - 40) * 10 + lon_u // 1000000)
SELECT event_id, round((c[y0*8+x0+1]::DOUBLE*1000+600)*(1-fy)*(1-fx) + (c[y0*8+x1+1]::DOUBLE*1000+600)*(1-fy)*fx + (c[y1*8+x0+1]::DOUBLE*1000+600)*fy*(1-fx) + (c[y1*8+x1+1]::DOUBLE*1000+600)*fy*fx, 4) AS dem FROM h"""))
def e2a_dem_bilinear(spark: SparkSession, sf: str) -> DataFrame:
    return lookup(fx.points(spark, sf), fx.tiles(spark, sf), "bilinear").select("event_id", F.round("dem", 4).alias("dem"))


@query(sql("lit", "SELECT file_id, track_no, count(*) AS n_points, round(sum(coalesce(ele, dem)), 2) AS total FROM lit GROUP BY ALL"))
def e2b_dem_gaps(spark: SparkSession, sf: str) -> DataFrame:
    flat = filled(spark, sf, policy="gaps").select(*KEYS, F.explode(F.flatten("segments")).alias("p"))
    return flat.groupBy(*KEYS).agg(F.count("*").alias("n_points"), F.round(F.sum("p.ele"), 2).alias("total"))


@query(sql("pts", """SELECT file_id, track_no, count(*) AS n_points, count(*) FILTER (e.vec_id IS NULL) AS n_void FROM pts p
LEFT JOIN (SELECT vec_id FROM embeddings WHERE vec_id % 37 <> 0) e ON e.vec_id = (lat_u // 1000000 - 40) * 10 + lon_u // 1000000 GROUP BY ALL"""))
def e2c_dem_void(spark: SparkSession, sf: str) -> DataFrame:
    rows = lookup(fx.points(spark, sf), fx.tiles(spark, sf, voids=True))
    return rows.groupBy(*KEYS).agg(F.count("*").alias("n_points"), F.count_if(F.col("dem").isNull()).alias("n_void"))


@query(sql("filled", "SELECT source AS elev_source, count(DISTINCT (file_id, track_no)) AS tracks FROM filled GROUP BY ALL"))
def e3_elev_source(spark: SparkSession, sf: str) -> DataFrame:
    return filled(spark, sf).groupBy("elev_source").agg(F.count("*").alias("tracks"))


@query(sql("dense idx", 'SELECT file_id, url, archive, "offset", length FROM dense JOIN idx ON page_id = file_id'))
def o1_provenance(spark: SparkSession, sf: str) -> DataFrame:
    index = fx.crawl_index(spark, sf).select(F.col("page_id").alias("file_id"), "url", "archive", "offset", "length")
    return dense(spark, sf).select("file_id").join(index, "file_id")


@query(sql("dense ends cells", """SELECT d.file_id, country FROM dense d JOIN ends e USING (file_id, track_no)
LEFT JOIN cells ON lat1 >= south AND lat1 < south + 2 AND lon1 >= west AND lon1 < west + 2"""))
def o2_country(spark: SparkSession, sf: str) -> DataFrame:
    return assign_country(dense(spark, sf), fx.country_cells(spark, sf)).select("file_id", "country")


@query(sql("pts", """SELECT CASE WHEN (lat < 41 OR lon >= 1) AND lat >= 40 AND lat < 42 AND lon >= 0 AND lon < 2 THEN 'inside' ELSE 'outside' END AS side, count(*) AS points
FROM (SELECT lat_u / 1e6 AS lat, lon_u / 1e6 AS lon FROM pts) GROUP BY ALL"""))
def o2a_ray_cast(spark: SparkSession, sf: str) -> DataFrame:
    """A ring with a notch: the square of two degrees without its upper left quarter."""
    ring = F.array(*[F.struct(F.lit(float(a)).alias("lat"), F.lit(float(b)).alias("lon")) for a, b in ((40, 0), (40, 2), (42, 2), (42, 1), (41, 1), (41, 0), (40, 0))])
    p = fx.points(spark, sf).select((F.col("lat_u") / 1e6).alias("lat"), (F.col("lon_u") / 1e6).alias("lon"))
    return p.groupBy(F.when(geo.in_ring(F.col("lat"), F.col("lon"), ring), "inside").otherwise("outside").alias("side")).agg(F.count("*").alias("points"))


@query(sql("dense props", "SELECT file_id, round(highest, 2) AS highest, round(lowest, 2) AS lowest FROM dense JOIN props USING (file_id, track_no)"))
def o5_extremes(spark: SparkSession, sf: str) -> DataFrame:
    rows = fill_elevation(dense(spark, sf), fx.tiles(spark, sf), KEYS)
    return rows.select("file_id", F.round(geo.highest(F.col("segments")), 2).alias("highest"), F.round(geo.lowest(F.col("segments")), 2).alias("lowest"))


@query(sql("dense props", "SELECT file_id, round(up, 2) AS uphill, round(down, 2) AS downhill FROM dense JOIN props USING (file_id, track_no)"))
def o6_gain_loss(spark: SparkSession, sf: str) -> DataFrame:
    rows = fill_elevation(dense(spark, sf), fx.tiles(spark, sf), KEYS)
    return rows.select("file_id", F.round(geo.gain(F.col("segments")), 2).alias("uphill"), F.round(geo.gain(F.col("segments"), -1), 2).alias("downhill"))


@query(sql("dense filled", """, sm AS (SELECT file_id, track_no, seg_no, ts, event_id, avg(ele) OVER (PARTITION BY file_id, track_no, seg_no ORDER BY ts, event_id ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING) AS e FROM filled),
r AS (SELECT *, e - lag(e) OVER (PARTITION BY file_id, track_no, seg_no ORDER BY ts, event_id) AS rise FROM sm)
SELECT file_id, round(coalesce(sum(greatest(rise, 0)), 0), 3) AS uphill FROM r WHERE file_id IN (SELECT file_id FROM dense) GROUP BY file_id"""))
def o6a_gain_smooth(spark: SparkSession, sf: str) -> DataFrame:
    rows = fill_elevation(dense(spark, sf), fx.tiles(spark, sf), KEYS)
    return rows.select("file_id", F.round(geo.gain(F.col("segments"), smooth="mean3"), 3).alias("uphill"))


@query(sql("dense props", "SELECT file_id, round(len3d, 2) AS len3d FROM dense JOIN props USING (file_id, track_no)"))
def o8_len3d(spark: SparkSession, sf: str) -> DataFrame:
    rows = fill_elevation(dense(spark, sf), fx.tiles(spark, sf), KEYS)
    return rows.select("file_id", F.round(geo.length_3d(F.col("segments")), 2).alias("len3d"))


@query(sql("dense ends", "SELECT file_id, apart <= 350 AS is_circular FROM dense JOIN ends USING (file_id, track_no)"))
def o9_circular(spark: SparkSession, sf: str) -> DataFrame:
    return dense(spark, sf).select("file_id", geo.is_circular(F.col("segments"), CFG.circular_m).alias("is_circular"))


@query(sql("dense filled", """SELECT file_id, md5('LINESTRING Z (' || string_agg(format('{:.6f} {:.6f} {:.2f}', lat_u / 1e6, lon_u / 1e6, ele), ', ' ORDER BY seg_no, ts, event_id) || ')') AS digest, count(*) AS n
FROM filled WHERE file_id IN (SELECT file_id FROM dense) AND n_ele = 0 GROUP BY file_id"""))
def o10_geometry_text(spark: SparkSession, sf: str) -> DataFrame:
    """Lines of the tracks whose heights all come from the raster."""
    bare = dense(spark, sf).where(geo.elevation_class(F.col("segments")) == "none")
    rows = fill_elevation(bare, fx.tiles(spark, sf), KEYS)
    return rows.select("file_id", F.md5(geo.to_wkt_z(F.col("segments"))).alias("digest"), F.size(F.flatten("segments")).cast("long").alias("n"))


@query(sql("trk", "SELECT round(count(*) FILTER (n_ele = n_points) / count(*), 6) AS full_share, round(count(*) FILTER (n_ele > 0) / count(*), 6) AS some_share FROM trk"))
def s13_elev_share(spark: SparkSession, sf: str) -> DataFrame:
    c = fx.tracks(spark, sf).select(geo.elevation_class(F.col("segments")).alias("c"))
    return c.agg(F.round(F.count_if(F.col("c") == "full") / F.count("*"), 6).alias("full_share"), F.round(F.count_if(F.col("c") != "none") / F.count("*"), 6).alias("some_share"))


@query(sql("dense ends", "SELECT round(count(*) FILTER (apart <= 350) / count(*), 6) AS share FROM dense JOIN ends USING (file_id, track_no)"))
def s15_circular_share(spark: SparkSession, sf: str) -> DataFrame:
    return dense(spark, sf).agg(F.round(F.count_if(geo.is_circular(F.col("segments"))) / F.count("*"), 6).alias("share"))


@query(sql("banded", "SELECT t AS min_per_100m, count(*) FILTER (n_points * 100 >= len2d * t) AS kept FROM banded CROSS JOIN (SELECT unnest([0.5, 1.0, 2.0])::DOUBLE AS t) GROUP BY t"))
def abl_density(spark: SparkSession, sf: str) -> DataFrame:
    """The density gate at half and at twice its threshold."""
    rows = banded(spark, sf)
    parts = [rows.where(gates.ok_density(replace(CFG, min_points_per_100m=t))).agg(F.count("*").alias("kept")).select(F.lit(t).alias("min_per_100m"), "kept") for t in (0.5, 1.0, 2.0)]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query("""SELECT count(*) AS files, CAST(sum(n) AS BIGINT) AS points, CAST(max(n) AS BIGINT) AS most FROM (SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY 1)""")
def w3_volume_tracks(spark: SparkSession, sf: str) -> DataFrame:
    """The volume twin through the same nesting and measuring."""
    t = gates.measured(fx.tracks(spark, sf, fx.volume_points(spark, sf)))
    return t.agg(F.count("*").alias("files"), F.sum("n_points").alias("points"), F.max("n_points").alias("most"))
