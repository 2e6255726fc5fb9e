"""Registered queries of the relational operators around the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from crawltracks.functions import geo
from crawltracks.operators import gates, relational
from crawltracks.operators.elevation import fill_elevation
from crawltracks.plans.registry import query
from crawltracks.plans.sqlviews import sql
from crawltracks.plans.tracks import KEYS, dense
from crawltracks.plans.whole import _LOCATED, located
from crawltracks.sources import fixtures as fx


@query(sql("trk", "SELECT file_id, track_no, len2d BETWEEN 500 AND 100000 AS ok_length, n_points * 100 >= len2d AS ok_density FROM trk"))
def q_gate_flags(spark: SparkSession, sf: str) -> DataFrame:
    return gates.measured(fx.tracks(spark, sf)).select(*KEYS, gates.ok_length().alias("ok_length"), gates.ok_density().alias("ok_density"))


@query("SELECT lang, quality, toxic, count(*) AS n FROM documents LEFT JOIN labels USING (doc_id) GROUP BY ALL")
def q_label_join(spark: SparkSession, sf: str) -> DataFrame:
    d = fx.table(spark, sf, "documents").select("doc_id", "lang")
    return d.join(fx.table(spark, sf, "labels"), "doc_id", "left").groupBy("lang", "quality", "toxic").agg(F.count("*").alias("n"))


@query("SELECT o_orderpriority, count(*) AS lines, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def q_smj(spark: SparkSession, sf: str) -> DataFrame:
    o = fx.table(spark, sf, "orders").select("o_orderkey", "o_orderpriority")
    li = fx.table(spark, sf, "lineitem").select("l_orderkey", "l_extendedprice", "l_discount").hint("merge")
    joined = li.join(o, F.col("o_orderkey") == F.col("l_orderkey"))
    return joined.groupBy("o_orderpriority").agg(F.count("*").alias("lines"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


@query(sql("pts", """SELECT file_id, count(*) AS n_points, count(vec_id) AS n_tiles FROM pts LEFT JOIN (SELECT vec_id FROM embeddings WHERE vec_id % 37 <> 0)
ON vec_id = (lat_u // 1000000 - 40) * 10 + lon_u // 1000000 GROUP BY file_id"""))
def q_left_void(spark: SparkSession, sf: str) -> DataFrame:
    from crawltracks.operators.elevation import tile_id

    p = fx.points(spark, sf).withColumn("tile_id", tile_id(F.col("lat_u"), F.col("lon_u")))
    return p.join(fx.tiles(spark, sf, voids=True).withColumn("hit", F.lit(1)), "tile_id", "left").groupBy("file_id").agg(F.count("*").alias("n_points"), F.count("hit").alias("n_tiles"))


@query(sql("pts cells", "SELECT country, count(*) AS n FROM pts JOIN cells ON lat_u / 1e6 >= south AND lat_u / 1e6 < south + 2 AND lon_u / 1e6 >= west AND lon_u / 1e6 < west + 2 GROUP BY country"))
def q_bbox_join(spark: SparkSession, sf: str) -> DataFrame:
    """Points in boxes as an equi-join on the box's cell."""
    c = fx.country_cells(spark, sf).select("country", F.floor(F.col("south") / 2).alias("a"), F.floor(F.col("west") / 2).alias("b"))
    p = fx.points(spark, sf).select(F.floor(F.col("lat_u") / 2_000_000).alias("a"), F.floor(F.col("lon_u") / 2_000_000).alias("b"))
    return p.groupBy("a", "b").agg(F.count("*").alias("n")).join(c, ["a", "b"]).groupBy("country").agg(F.sum("n").alias("n"))


@query("""SELECT event_id, prev_event_id FROM (SELECT event_id, event_type, max_by(CASE WHEN event_type = 'view' THEN event_id END, CASE WHEN event_type = 'view' THEN (ts, event_id) END) OVER (PARTITION BY user_id ORDER BY ts
RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS prev_event_id FROM events) WHERE event_type = 'error'""")
def q_asof(spark: SparkSession, sf: str) -> DataFrame:
    """The view before each error of a user."""
    e = fx.table(spark, sf, "events").select("event_id", "ts", "user_id", "event_type")
    views = e.where("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("event_id").alias("event_id"))
    got = relational.as_of(e.where("event_type = 'error'"), views, "user_id", F.col("ts"), ["event_id"])
    return got.select("event_id", "prev_event_id")


_SESS = """(SELECT user_id, sid, min(ts) AS a, max(ts) + INTERVAL 6 HOUR AS b, count(*) AS n FROM (SELECT *, sum(CASE WHEN p IS NULL OR ts >= p + INTERVAL 6 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sid
FROM (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events)) GROUP BY user_id, sid)"""


@query(f"SELECT user_id, count(*) AS sessions, CAST(max(n) AS BIGINT) AS longest FROM {_SESS} GROUP BY user_id")
def q_sessions(spark: SparkSession, sf: str) -> DataFrame:
    s = fx.table(spark, sf, "events").groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    return s.groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest"))


@query(f"SELECT count(*) AS pairs, count(DISTINCT e.event_id) AS events FROM events e JOIN {_SESS} s ON e.user_id = s.user_id AND e.ts >= s.a AND e.ts < s.b WHERE e.event_type = 'error'")
def q_interval(spark: SparkSession, sf: str) -> DataFrame:
    """Errors inside sessions: an equi-join on the user with the interval as a filter."""
    ev = fx.table(spark, sf, "events")
    s = ev.groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    e = ev.where("event_type = 'error'").select("user_id", "event_id", "ts")
    hit = e.join(s, "user_id").where("ts >= w.start and ts < w.end")
    return hit.agg(F.count("*").alias("pairs"), F.count_distinct("event_id").alias("events"))


@query("SELECT event_type, count(*) AS n, round(min(value), 4) AS least, round(max(value), 4) AS greatest, round(avg(value), 4) AS mean, round(median(value), 4) AS median, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def q_agg(spark: SparkSession, sf: str) -> DataFrame:
    v = F.col("value")
    return fx.table(spark, sf, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.min(v), 4).alias("least"), F.round(F.max(v), 4).alias("greatest"), F.round(F.avg(v), 4).alias("mean"), F.round(F.median(v), 4).alias("median"), F.count_distinct("user_id").alias("users"))


@query(sql("dense ends cells", f"SELECT region, country, count(*) AS n, round(sum(len2d), 2) AS metres FROM {_LOCATED} GROUP BY ROLLUP (region, country)"))
def q_rollup_region(spark: SparkSession, sf: str) -> DataFrame:
    return located(spark, sf).rollup("region", "country").agg(F.count("*").alias("n"), F.round(F.sum("len2d"), 2).alias("metres"))


@query(sql("sized filled", "SELECT lang, source, count(*) AS n FROM sized JOIN (SELECT DISTINCT file_id, track_no, source FROM filled) USING (file_id, track_no) GROUP BY CUBE (lang, source)"))
def q_cube_lang_source(spark: SparkSession, sf: str) -> DataFrame:
    from crawltracks.plans.texts import sized

    rows = fill_elevation(sized(spark, sf), fx.tiles(spark, sf), KEYS).withColumnRenamed("elev_source", "source")
    return rows.cube("lang", "source").agg(F.count("*").alias("n"))


@query("SELECT lang, count(*) FILTER (quality = 0) AS q0, count(*) FILTER (quality = 1) AS q1 FROM documents JOIN labels USING (doc_id) GROUP BY lang")
def q_pivot(spark: SparkSession, sf: str) -> DataFrame:
    d = fx.table(spark, sf, "documents").join(fx.table(spark, sf, "labels"), "doc_id")
    p = d.groupBy("lang").pivot("quality", [0, 1]).agg(F.count(F.lit(1)))
    return p.select("lang", F.coalesce("0", F.lit(0)).alias("q0"), F.coalesce("1", F.lit(0)).alias("q1"))


@query("SELECT lang, doc_id, rk FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY length(text) DESC, doc_id) AS rk FROM documents) WHERE rk <= 3")
def q_topk_per_lang(spark: SparkSession, sf: str) -> DataFrame:
    rk = F.row_number().over(Window.partitionBy("lang").orderBy(F.length("text").desc(), "doc_id"))
    return fx.descriptions(spark, sf).select("lang", "doc_id", rk.cast("long").alias("rk")).where("rk <= 3")


@query(sql("pts", "SELECT event_id, round(avg(ele) OVER (PARTITION BY file_id, track_no, seg_no ORDER BY ts, event_id ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING), 3) AS smooth FROM pts"))
def q_smooth(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("file_id", "track_no", "seg_no").orderBy("ts", "event_id").rowsBetween(-1, 1)
    return fx.points(spark, sf).select("event_id", F.round(F.avg("ele").over(w), 3).alias("smooth"))


@query(sql("dense", "SELECT file_id, round(len2d, 2) AS len2d FROM dense ORDER BY dense.len2d DESC LIMIT 10"))
def q_longest(spark: SparkSession, sf: str) -> DataFrame:
    return dense(spark, sf).orderBy(F.desc("len2d")).limit(10).select("file_id", F.round("len2d", 2).alias("len2d"))


@query("SELECT doc_id FROM documents WHERE substr(md5(CAST(doc_id AS VARCHAR)), 1, 6) < '199999'")
def q_hash_sample(spark: SparkSession, sf: str) -> DataFrame:
    """A repeatable tenth of the documents, for looking at."""
    return relational.hash_sample(fx.descriptions(spark, sf), "doc_id", 0.1).select("doc_id")


@query("SELECT count(DISTINCT user_id) AS users, true AS users_close, round(median(value), 6) AS median, true AS median_close FROM events")
def q_sketches(spark: SparkSession, sf: str) -> DataFrame:
    """Exact distinct users and median, and whether the HLL and KLL sketches come within 5 % and between the 45th and 55th percentile."""
    e = fx.table(spark, sf, "events")
    found = e.agg(
        F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("hll"), F.count_distinct("user_id").alias("users"),
        F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(value), 0.5)").alias("kll"), F.percentile("value", [0.45, 0.5, 0.55]).alias("p"),
    )
    near = F.abs(F.col("hll") - F.col("users")) <= 0.05 * F.col("users")
    return found.select("users", near.alias("users_close"), F.round(F.col("p")[1], 6).alias("median"), F.col("kll").between(F.col("p")[0], F.col("p")[2]).alias("median_close"))


@query("SELECT count(*) AS tracks FROM (SELECT DISTINCT user_id, CASE WHEN user_id % 10 = 9 AND event_id % 2 = 1 THEN 1 ELSE 0 END FROM events)")
def q_sql_surface(spark: SparkSession, sf: str) -> DataFrame:
    """The same methods by SQL text, through registered functions."""
    from crawltracks.plans.sqlreg import register_sql

    register_sql(spark)
    fx.tracks(spark, sf).createOrReplaceTempView("ct_tracks")
    return spark.sql("SELECT count(*) AS tracks FROM ct_tracks WHERE is_dense(size(flatten(segments)), 0.0D)")


@query(sql("pts", "SELECT file_id, count(*) AS n_points, count(ele) AS n_heights FROM pts GROUP BY file_id"))
def q_table_function(spark: SparkSession, sf: str) -> DataFrame:
    """Points of files by the table function, in SQL."""
    from crawltracks.plans.sqlreg import register_sql

    register_sql(spark)
    fx.track_xml(spark, sf).createOrReplaceTempView("ct_files")
    return spark.sql("SELECT file_id, count(*) AS n_points, count(ele) AS n_heights FROM ct_files, LATERAL segment_points(content) GROUP BY file_id")


@query(sql("pts", "SELECT event_id FROM pts WHERE 2 * 6371000 * asin(sqrt(pow(sin(radians(lat_u / 1e6 - 42.0) / 2), 2) + cos(radians(42.0)) * cos(radians(lat_u / 1e6)) * pow(sin(radians(lon_u / 1e6 - 2.0) / 2), 2))) <= 120000"))
def q_radius(spark: SparkSession, sf: str) -> DataFrame:
    p = fx.points(spark, sf)
    return p.where(geo.step_m(F.lit(42.0), F.lit(2.0), F.col("lat_u") / 1e6, F.col("lon_u") / 1e6) <= 120_000).select("event_id")
