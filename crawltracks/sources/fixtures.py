"""Stand-in inputs on the given tables (formulas in FIXTURES.md)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Step in micro-degrees by file number modulo 8.
STEPS = (1, 5, 10, 15, 20, 40, 100, 700)
#: Added to a file's number for its older capture, and for its copy elsewhere.
RECAPTURED, COPIED = 1_000_000_000, 2_000_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def crawl_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    """one row per capture, with the pointer into its archive."""
    length = F.octet_length("html").cast("long")
    before = Window.partitionBy("archive").orderBy("page_id").rowsBetween(Window.unboundedPreceding, -1)
    pages = table(spark, sf_dir, "pages").select("page_id", "url", length.alias("length"), F.floor(F.col("page_id") / 50).alias("archive"))
    mime = F.when(F.col("page_id") % 9 == 0, "Application/XHTML+xml").otherwise("text/html")
    return pages.select(
        "page_id", (F.col("page_id") % 6).alias("release"), (F.col("page_id") % 300).alias("part"), "url", mime.alias("mime_detected"), "archive",
        F.coalesce(F.sum("length").over(before), F.lit(0)).cast("long").alias("offset"), "length",
    )


def archives(spark: SparkSession, sf_dir: str) -> DataFrame:
    """the bytes of each archive, its pages one after the other."""
    held = table(spark, sf_dir, "pages").groupBy(F.floor(F.col("page_id") / 50).alias("archive")).agg(F.sort_array(F.collect_list(F.struct("page_id", "html"))).alias("x"))
    return held.select("archive", F.encode(F.array_join(F.transform("x", lambda p: p["html"]), ""), "UTF-8").alias("body"))


def captures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The index with a second capture of every twelfth page in the next release."""
    index = crawl_index(spark, sf_dir)
    return index.unionByName(index.where("page_id % 12 = 0").withColumn("release", (F.col("page_id") + 1) % 6))


def _by_mod(n: Column, values: tuple[int, ...]) -> Column:
    return F.element_at(F.array(*[F.lit(v).cast("long") for v in values]), (n % len(values) + 1).cast("int"))


def points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """one row per point, in micro-degrees, from ``events``."""
    f = F.col("user_id")
    e = table(spark, sf_dir, "events").select(
        f.alias("file_id"),
        F.when((f % 10 == 9) & (F.col("event_id") % 2 == 1), 1).otherwise(0).alias("track_no"),
        F.floor(F.dayofmonth("ts") / 11).cast("int").alias("seg_no"),
        "ts", "event_id", "event_type", _by_mod(f, STEPS).alias("m"),
        F.get_json_object("props", "$.k").cast("long").alias("k"),
        F.when((f % 2 == 1) | ((f % 6 == 0) & (F.col("event_type") == "error")), None).otherwise(F.col("value")).alias("ele"),
    )
    cell = F.col("file_id") % 27
    w = Window.partitionBy("file_id", "track_no").orderBy("ts", "event_id")
    lat = 41_000_000 + 2_000_000 * F.floor(cell / 5) + F.sum((F.col("k") - 50) * F.col("m")).over(w)
    lon = 1_000_000 + 2_000_000 * (cell % 5) + F.sum(((37 * F.col("event_id")) % 101 - 50) * F.col("m")).over(w)
    return e.select("file_id", "track_no", "seg_no", "ts", "event_id", lat.alias("lat_u"), lon.alias("lon_u"), "ele")


def volume_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The volume twin: one file per part of ``lineitem``, with the same columns as :func:`points`."""
    li = table(spark, sf_dir, "lineitem")
    f = F.col("l_partkey")
    w = Window.partitionBy("l_partkey").orderBy("l_shipdate", "l_orderkey", "l_linenumber")
    cell, m = f % 25, _by_mod(f, STEPS)
    lat = 41_000_000 + 2_000_000 * F.floor(cell / 5) + F.sum((F.col("l_orderkey") % 101 - 50) * m).over(w)
    lon = 1_000_000 + 2_000_000 * (cell % 5) + F.sum(((37 * F.col("l_orderkey") + F.col("l_linenumber")) % 101 - 50) * m).over(w)
    return li.select(
        f.alias("file_id"), F.lit(0).alias("track_no"), F.lit(0).alias("seg_no"), F.col("l_shipdate").alias("ts"),
        (F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("event_id"), lat.alias("lat_u"), lon.alias("lon_u"), F.col("l_quantity").alias("ele"),
    )


def tracks(spark: SparkSession, sf_dir: str, source: DataFrame | None = None) -> DataFrame:
    """One row per track with nested segments of points (lat, lon, ele, t)."""
    p = points(spark, sf_dir) if source is None else source
    point = F.struct("ts", "event_id", (F.col("lat_u") / 1e6).alias("lat"), (F.col("lon_u") / 1e6).alias("lon"), "ele")
    segs = p.groupBy("file_id", "track_no", "seg_no").agg(F.sort_array(F.collect_list(point)).alias("p"))
    plain = F.transform("p", lambda x: F.struct(x["lat"].alias("lat"), x["lon"].alias("lon"), x["ele"].alias("ele"), x["ts"].alias("t")))
    whole = segs.groupBy("file_id", "track_no").agg(F.sort_array(F.collect_list(F.struct("seg_no", plain.alias("points")))).alias("s"))
    return whole.select("file_id", "track_no", F.transform("s", lambda s: s["points"]).alias("segments"))


def track_xml(spark: SparkSession, sf_dir: str, malformed: bool = False) -> DataFrame:
    """Files rendered as XML text: file_id, content; with ``malformed`` every 40th is cut short."""
    number = lambda c: c.cast("string")
    node = lambda p: F.concat(
        F.lit('<trkpt lat="'), number(p["lat"]), F.lit('" lon="'), number(p["lon"]), F.lit('">'),
        F.coalesce(F.concat(F.lit("<ele>"), number(p["ele"]), F.lit("</ele>")), F.lit("")),
        F.lit("<time>"), F.date_format(p["t"], "yyyy-MM-dd'T'HH:mm:ss"), F.lit("</time></trkpt>"),
    )
    seg = lambda s: F.concat(F.lit("<trkseg>"), F.array_join(F.transform(s, node), ""), F.lit("</trkseg>"))
    safe = F.replace(F.replace(F.replace(F.col("text"), F.lit("&"), F.lit("&amp;")), F.lit("<"), F.lit("&lt;")), F.lit(">"), F.lit("&gt;"))
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("file_id"), safe.alias("safe"))
    rows = tracks(spark, sf_dir).join(docs, "file_id", "left")
    body = F.concat(F.lit("<trk><desc>"), F.coalesce("safe", F.lit("")), F.lit("</desc>"), F.array_join(F.transform("segments", seg), ""), F.lit("</trk>"))
    files = rows.groupBy("file_id").agg(F.sort_array(F.collect_list(F.struct("track_no", body.alias("x")))).alias("t"))
    content = F.concat(F.lit('<gpx version="1.1">'), F.array_join(F.transform("t", lambda t: t["x"]), ""), F.lit("</gpx>"))
    if malformed:
        content = F.when(F.col("file_id") % 40 == 0, F.substring(content, F.lit(1), F.length(content) - 9)).otherwise(content)
    return files.select("file_id", content.alias("content"))


def captured_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    """F3 with repeats: files 0 mod 12 were captured before, files 5 mod 15 lie at a second place too."""
    files = track_xml(spark, sf_dir)
    f = F.col("file_id")
    numbers = F.array_compact(F.array(f, F.when(f % 12 == 0, f + RECAPTURED), F.when(f % 15 == 5, f + COPIED)))
    return files.select(F.explode(numbers).alias("file_id"), "content")


def descriptions(spark: SparkSession, sf_dir: str, markers: bool = False) -> DataFrame:
    """doc_id, text, lang; with ``markers`` every tenth text has bracketed app markers."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    if markers:
        marked = F.concat(F.lit("[app 1.2] "), F.col("text"), F.lit(" {route: test}"))
        docs = docs.withColumn("text", F.when(F.col("doc_id") % 10 == 0, marked).otherwise(F.col("text")))
    return docs


def tiles(spark: SparkSession, sf_dir: str, voids: bool = False) -> DataFrame:
    """elevation tiles of 8 x 8 cells; with ``voids`` every 37th is withheld."""
    t = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("tile_id"), F.col("embedding").alias("cells"))
    return t.where("tile_id % 37 <> 0") if voids else t


def country_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """nations as cells of two degrees, with ring and region."""
    i = F.col("n_nationkey").cast("long")
    south, west = (40 + 2 * F.floor(i / 5)).cast("double"), (2 * (i % 5)).cast("double")
    corner = lambda a, b: F.struct((south + a).alias("lat"), (west + b).alias("lon"))
    ring = F.array(corner(0, 0), corner(0, 2), corner(2, 2), corner(2, 0), corner(0, 0))
    n = table(spark, sf_dir, "nation").join(F.broadcast(table(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return n.select(F.trim("n_name").alias("country"), F.trim("r_name").alias("region"), south.alias("south"), west.alias("west"), ring.alias("ring"))


def poi(spark: SparkSession, sf_dir: str) -> DataFrame:
    """suppliers as points of interest inside their nation's cell."""
    i, k = F.col("s_nationkey").cast("long"), F.col("s_suppkey")
    lat = (40 + 2 * F.floor(i / 5)) * 1_000_000 + (k * 7919) % 2_000_000
    lon = (2 * (i % 5)) * 1_000_000 + (k * 104_729) % 2_000_000
    return table(spark, sf_dir, "supplier").select(k.alias("poi_id"), (lat / 1e6).alias("lat"), (lon / 1e6).alias("lon"))
