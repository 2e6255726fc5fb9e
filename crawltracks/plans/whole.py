"""Registered queries of the whole pipeline, its statistics, ablations and workloads."""

from __future__ import annotations

from functools import reduce
from hashlib import md5

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StringType
from pyspark.sql.window import Window

from crawltracks.functions import geo
from crawltracks.functions.url import url_host
from crawltracks.functions.wkb import read_line_z
from crawltracks.materialise import to_table
from crawltracks.operators import profile
from crawltracks.plans import pipeline
from crawltracks.plans.registry import query
from crawltracks.plans.sqlviews import HOST, english, sql
from crawltracks.plans.tracks import dense
from crawltracks.sources import fixtures as fx

_FILES = "(SELECT DISTINCT file_id FROM trk)"
_ALL = f"(SELECT count(*) + count(*) FILTER (file_id % 12 = 0) + count(*) FILTER (file_id % 15 = 5) FROM {_FILES})"
_COUNTS = {
    "unique_url": f"(SELECT {_ALL} - count(*) FROM {_FILES} WHERE file_id % 12 = 0 AND file_id IN (SELECT page_id FROM pages))",
    **{s: f"(SELECT count(*) FROM {_FILES})" for s in ("unique_content", "parsed")},
    **{s: f"(SELECT count(*) FROM {v})" for s, v in zip(pipeline.STAGES[3:], ("one", "banded", "dense", "sized", "good", "private", "supported"))},
}
_STAGE_SQL = ", ".join(f"({i}, '{s}', {_COUNTS[s]})" for i, s in enumerate(pipeline.STAGES, 1))
_FUNNEL = f"""SELECT stage, stage_no, n_in, n_out, CASE WHEN n_in > 0 THEN round(n_out / n_in, 6) END AS ratio FROM
(SELECT stage, stage_no, lag(n_out, 1, {_ALL}) OVER (ORDER BY stage_no) AS n_in, n_out FROM (VALUES {_STAGE_SQL}) v(stage_no, stage, n_out))"""


@query(sql("supported", _FUNNEL))
def s1_funnel(spark: SparkSession, sf: str) -> DataFrame:
    """The funnel of the whole pipeline, from XML text on."""
    return pipeline.funnel(pipeline.flags(pipeline.stand_in(spark, sf)))


_FINAL = f"""SELECT p.file_id, i.url, 'archive-' || i.archive AS warc_file, i."offset" AS warc_offset, i.length AS warc_len, c.country, p.lang AS desc_lang, length(masked) AS desc_chars, md5(masked) AS desc_digest,
md5({english("masked", "p.lang")}) AS en_digest, r.source AS elev_source, round(highest, 2) AS elev_highest, round(lowest, 2) AS elev_lowest, round(up, 2) AS uphill, round(down, 2) AS downhill,
round(len2d, 2) AS length_2d, round(len3d, 2) AS length_3d, apart <= 350 AS is_circular, line_points, line_digest
FROM {{}} p JOIN props r USING (file_id, track_no) JOIN ends e USING (file_id, track_no) JOIN lines USING (file_id, track_no) LEFT JOIN idx i ON i.page_id = p.file_id
LEFT JOIN cells c ON lat1 >= south AND lat1 < south + 2 AND lon1 >= west AND lon1 < west + 2"""
_FINAL_VIEWS = "props ends lines cells idx "


@F.arrow_udf(StringType())
def line_digest(lines: pa.Array) -> pa.Array:
    """Digest of the points of a published line, in micro-degrees and centimetres."""

    def of(line: bytes) -> str:
        whole = np.floor(read_line_z(line) * (1e6, 1e6, 100.0) + 0.5)
        return md5(";".join(f"{int(a)},{int(b)},{'none' if h != h else int(h)}" for a, b, h in whole).encode()).hexdigest()

    return pa.array([None if x is None else of(x) for x in lines.to_pylist()], pa.string())


def _rounded(df: DataFrame) -> DataFrame:
    """The published columns; texts and lines by their digests."""
    r = [F.round(c, 2).alias(c) for c in ("elev_highest", "elev_lowest", "uphill", "downhill", "length_2d", "length_3d")]
    line = [((F.octet_length("geometry") - 9) / 24).cast("long").alias("line_points"), line_digest("geometry").alias("line_digest")]
    texts = [F.length("desc").cast("long").alias("desc_chars"), F.md5("desc").alias("desc_digest"), F.md5("desc_en").alias("en_digest")]
    return df.select("file_id", "url", "warc_file", "warc_offset", "warc_len", "country", "desc_lang", *texts, "elev_source", *r, "is_circular", *line)


def _before_judges(spark: SparkSession, sf: str) -> DataFrame:
    inputs = pipeline.stand_in(spark, sf)
    return pipeline.assemble(pipeline.flags(inputs, skip=("quality", "privacy", "language")).where("ok_language"), inputs)


@query(sql(_FINAL_VIEWS + "read", _FINAL.format("read")))
def w8_properties(spark: SparkSession, sf: str) -> DataFrame:
    """All published properties of the tracks before the judges and the language barrier."""
    return _rounded(_before_judges(spark, sf))


@query(sql(_FINAL_VIEWS + "supported", _FINAL.format("supported")))
def w8_final(spark: SparkSession, sf: str) -> DataFrame:
    return _rounded(pipeline.run(pipeline.stand_in(spark, sf)).final)


_RELEASE = "(file_id + CASE WHEN file_id % 12 = 0 THEN 1 ELSE 0 END) % 6"
_STATS = f""", f AS ({_FINAL.format("read")}), e AS (SELECT {english("masked", "lang")} AS en FROM read), x(statistic, item, value) AS (
SELECT 'tracks', 'all', count(*) FROM f UNION ALL SELECT 'domains', 'all', count(DISTINCT {HOST}) FROM f
UNION ALL SELECT 'circular share', 'all', round(count(*) FILTER (is_circular) / count(*), 6) FROM f
UNION ALL SELECT 'km', unnest(['least', 'greatest', 'mean', 'median']), unnest([min(length_2d), max(length_2d), avg(length_2d), median(length_2d)]) / 1000 FROM f
UNION ALL SELECT 'characters', unnest(['least', 'greatest', 'mean', 'median']), unnest([min(desc_chars), max(desc_chars), avg(desc_chars), median(desc_chars)]) FROM f
UNION ALL SELECT 'characters in English', unnest(['least', 'greatest', 'mean', 'median']), unnest([min(length(en)), max(length(en)), avg(length(en)), median(length(en))]) FROM e
UNION ALL SELECT 'language', desc_lang, count(*) FROM f GROUP BY desc_lang UNION ALL SELECT 'country', coalesce(country, 'none'), count(*) FROM f GROUP BY country
UNION ALL SELECT 'heights', elev_source, count(*) FROM f GROUP BY elev_source
UNION ALL SELECT 'km bin', CAST(least(CAST(floor(length_2d / 500) AS BIGINT), 20) AS VARCHAR), count(*) FROM f GROUP BY 2
UNION ALL SELECT 'characters bin', CAST(desc_chars // 100 AS VARCHAR), count(*) FROM f GROUP BY 2
UNION ALL SELECT 'yield of a release', 'all', round(avg(n), 6) FROM (SELECT count(*) AS n FROM f WHERE url IS NOT NULL GROUP BY {_RELEASE})
UNION ALL SELECT 'releases for 10000', 'all', ceil(10000 / avg(n)) FROM (SELECT count(*) AS n FROM f WHERE url IS NOT NULL GROUP BY {_RELEASE}))
SELECT statistic, item, round(CAST(value AS DOUBLE), 4) AS value FROM x"""


def statistics(final: DataFrame, pointers: DataFrame) -> DataFrame:
    """All statistics of a published table as rows (statistic, item, value)."""
    rows = to_table(final.select("file_id", "url", "country", "desc_lang", "elev_source", "is_circular", F.length("desc").alias("chars"), F.length("desc_en").alias("en"), F.round("length_2d", 2).alias("m")))
    out = []

    def add(name: str, counted: DataFrame, item, value) -> None:
        out.append(counted.select(F.lit(name).alias("statistic"), item.cast("string").alias("item"), F.round(value.cast("double"), 4).alias("value")))

    add("tracks", rows.agg(F.count("*").alias("v")), F.lit("all"), F.col("v"))
    add("domains", profile.domain_count(rows, url_host(F.col("url"))), F.lit("all"), F.col("domains"))
    add("circular share", rows.agg(F.round(F.try_divide(F.count_if("is_circular"), F.count("*")), 6).alias("v")), F.lit("all"), F.col("v"))
    for name, x in (("km", F.col("m") / 1000), ("characters", F.col("chars")), ("characters in English", F.col("en"))):
        one = profile.length_stats(rows, x, 6)
        add(name, one.select(F.explode(F.create_map(*[y for k in ("least", "greatest", "mean", "median") for y in (F.lit(k), F.col(k))]))), F.col("key"), F.col("value"))
    for name, key in (("language", F.col("desc_lang")), ("country", F.coalesce("country", F.lit("none"))), ("heights", F.col("elev_source")),
                      ("km bin", F.least(F.floor(F.col("m") / 500), F.lit(20))), ("characters bin", F.floor(F.col("chars") / 100))):
        add(name, rows.groupBy(key.alias("k")).agg(F.count("*").alias("n")), F.col("k"), F.col("n"))
    per = rows.where("url IS NOT NULL").select("file_id").join(pointers.select("file_id", "release"), "file_id").groupBy("release").agg(F.count("*").alias("n"))
    need = profile.extrapolate(per, "n", 10_000)
    add("yield of a release", need, F.lit("all"), F.col("yield_per_release"))
    add("releases for 10000", need, F.lit("all"), F.col("releases_needed"))
    return reduce(DataFrame.unionByName, out)


@query(sql(_FINAL_VIEWS + "read", _STATS))
def w9_statistics(spark: SparkSession, sf: str) -> DataFrame:
    """Every statistic over the published table (before the judges, where the stand-ins leave enough rows to count)."""
    return statistics(_before_judges(spark, sf), pipeline.stand_in(spark, sf).pointers)


@query(sql(_FINAL_VIEWS + "supported", _STATS.replace("FROM read)", "FROM supported)").replace("FROM read p", "FROM supported p")))
def w9_final_statistics(spark: SparkSession, sf: str) -> DataFrame:
    inputs = pipeline.stand_in(spark, sf)
    return statistics(pipeline.run(inputs).final, inputs.pointers)


@query(sql("supported", f"SELECT files, final, round(final / files, 6) AS yield FROM (SELECT {_ALL} AS files, (SELECT count(*) FROM supported) AS final)"))
def s2_rates(spark: SparkSession, sf: str) -> DataFrame:
    f = pipeline.flags(pipeline.stand_in(spark, sf))
    return f.agg(F.count("*").alias("files"), F.count_if(F.col("ok_language")).alias("final"), F.round(F.count_if(F.col("ok_language")) / F.count("*"), 6).alias("yield"))


@query(sql("private", "SELECT lang, count(*) AS n FROM private GROUP BY lang"))
def s6_langs(spark: SparkSession, sf: str) -> DataFrame:
    f = pipeline.flags(pipeline.stand_in(spark, sf)).where("ok_privacy")
    return profile.top(f.withColumnRenamed("desc_lang", "lang"), "lang")


def _sized(spark: SparkSession, sf: str) -> DataFrame:
    from crawltracks.plans.texts import sized

    return sized(spark, sf)


@query(sql("sized", "SELECT lang, count(*) AS n, min(length(cleaned)) AS least, max(length(cleaned)) AS greatest, round(median(length(cleaned)), 2) AS median FROM sized GROUP BY lang"))
def s7_desc_stats(spark: SparkSession, sf: str) -> DataFrame:
    n = F.length("cleaned").cast("long")
    return _sized(spark, sf).groupBy("lang").agg(F.count("*").alias("n"), F.min(n).alias("least"), F.max(n).alias("greatest"), F.round(F.median(n), 2).alias("median"))


_LOCATED = "dense d JOIN ends e USING (file_id, track_no) LEFT JOIN cells ON lat1 >= south AND lat1 < south + 2 AND lon1 >= west AND lon1 < west + 2"


def located(spark: SparkSession, sf: str) -> DataFrame:
    from crawltracks.operators.country import assign_country

    return assign_country(dense(spark, sf), fx.country_cells(spark, sf))


@query(sql("dense ends cells", f"SELECT country, count(*) AS n FROM {_LOCATED} WHERE country IS NOT NULL GROUP BY country ORDER BY n DESC, country LIMIT 5"))
def s8_top_countries(spark: SparkSession, sf: str) -> DataFrame:
    return profile.top(located(spark, sf).where("country IS NOT NULL"), "country", 5)


@query(sql("dense", "SELECT count(*) AS n, round(min(len2d), 2) AS least, round(max(len2d), 2) AS greatest, round(avg(len2d), 2) AS mean, round(median(len2d), 2) AS median FROM dense"))
def s9_track_stats(spark: SparkSession, sf: str) -> DataFrame:
    return profile.length_stats(dense(spark, sf), F.col("len2d"))


_HIST = """SELECT bin, round({low} + (bin - 1) * ({high} - {low}) / {bins}, 6) AS start, count(x) AS n FROM (SELECT unnest(range(0, {bins} + 2)) AS bin)
LEFT JOIN (SELECT {x} AS x FROM {t}) v ON CASE WHEN x < {low} THEN 0 WHEN x >= {high} THEN {bins} + 1 ELSE CAST(floor((x - {low}) * {bins} / ({high} - {low})) AS BIGINT) + 1 END = bin GROUP BY bin"""


@query(sql("dense", _HIST.format(low="0.0", high="10.0", bins=20, x="len2d / 1000", t="dense")))
def s10_hist_km(spark: SparkSession, sf: str) -> DataFrame:
    return profile.histogram(dense(spark, sf), F.col("len2d") / 1000, 0, 10, 20)


@query(sql("cleaned", _HIST.format(low="0.0", high="2000.0", bins=20, x="length(cleaned)", t="cleaned")))
def s10_hist_chars(spark: SparkSession, sf: str) -> DataFrame:
    from crawltracks.functions import text as tx

    return profile.histogram(fx.descriptions(spark, sf), F.length(tx.clean(F.col("text"))), 0, 2000, 20)


@query(sql("dense idx", "SELECT round(avg(n), 6) AS yield_per_release, CAST(ceil(10000 / avg(n)) AS BIGINT) AS releases_needed FROM (SELECT release, count(*) AS n FROM dense JOIN idx ON page_id = file_id GROUP BY release)"))
def s11_extrapolate(spark: SparkSession, sf: str) -> DataFrame:
    release = fx.crawl_index(spark, sf).select(F.col("page_id").alias("file_id"), "release")
    per = dense(spark, sf).join(release, "file_id").groupBy("release").agg(F.count("*").alias("n"))
    return profile.extrapolate(per, "n", 10_000)


def _ablation(stage: str, views: str, sql_count: str) -> None:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        f = pipeline.flags(pipeline.stand_in(spark, sf), skip=(stage,))
        return f.agg(F.count_if(F.col("ok_language")).alias("kept"))

    query(sql(views, sql_count), f"abl_no_{stage}")(run)


_TAIL = """, s AS (SELECT d.file_id, c.lang, c.cleaned FROM {0} d JOIN spoken c ON c.doc_id = d.file_id),
g AS (SELECT s.* FROM s JOIN labels l ON l.doc_id = s.file_id WHERE {1})
SELECT coalesce(sum(n), 0)::BIGINT AS kept FROM (SELECT count(*) AS n FROM g WHERE lang <> 'un' OR {2} = 0 GROUP BY lang HAVING count(*) > {2})"""
_SIZE = "length(cleaned) BETWEEN 50 AND 2000"
_ablation("length", "trk spoken", _TAIL.format("(SELECT * FROM trk WHERE file_id IN (SELECT file_id FROM trk GROUP BY file_id HAVING count(*) = 1) AND n_points * 100 >= len2d)", f"{_SIZE} AND quality = 1 AND toxic = 0", 5))
_ablation("density", "banded spoken", _TAIL.format("banded", f"{_SIZE} AND quality = 1 AND toxic = 0", 5))
_ablation("description", "dense spoken", _TAIL.format("dense", "quality = 1 AND toxic = 0", 5))
_ablation("quality", "dense spoken", _TAIL.format("dense", f"{_SIZE} AND toxic = 0", 5))
_ablation("privacy", "dense spoken", _TAIL.format("dense", f"{_SIZE} AND quality = 1", 5))
_ablation("language", "dense spoken", _TAIL.format("dense", f"{_SIZE} AND quality = 1 AND toxic = 0", 0))


@query(sql("private", "SELECT t AS more_than, coalesce((SELECT sum(n) FROM (SELECT count(*) AS n FROM private GROUP BY lang) WHERE n > t), 0)::BIGINT AS kept FROM (SELECT unnest([0, 2, 5, 10]) AS t)"))
def abl_language_sweep(spark: SparkSession, sf: str) -> DataFrame:
    """Rows left at several thresholds of language support."""
    f = pipeline.flags(pipeline.stand_in(spark, sf)).where("ok_privacy").groupBy("desc_lang").agg(F.count("*").alias("n"))
    sums = f.agg(*[F.coalesce(F.sum(F.when(F.col("n") > t, F.col("n"))), F.lit(0)).alias(f"t{t}") for t in (0, 2, 5, 10)])
    return sums.select(F.explode(F.array(*[F.struct(F.lit(t).alias("more_than"), F.col(f"t{t}").alias("kept")) for t in (0, 2, 5, 10)])).alias("x")).select("x.*")


@query(sql("sized", "SELECT count(*) AS quality_last, (SELECT count(DISTINCT file_id) FROM trk JOIN documents ON doc_id = file_id) AS quality_first FROM sized"))
def abl_gate_order(spark: SparkSession, sf: str) -> DataFrame:
    """Judge calls when the quality gate comes after the native gates, and when it comes first."""
    late = _sized(spark, sf).agg(F.count("*").alias("quality_last"))
    early = fx.tracks(spark, sf).select("file_id").distinct().join(fx.table(spark, sf, "documents"), F.col("doc_id") == F.col("file_id")).agg(F.count("*").alias("quality_first"))
    return late.join(F.broadcast(early))  # one row each


@query(sql("dense ends", """SELECT d.file_id, k.poi_id, round(m, 2) AS metres FROM dense d JOIN ends e USING (file_id, track_no) JOIN
(SELECT s_suppkey AS poi_id, ((40 + 2 * (s_nationkey // 5)) * 1000000 + (s_suppkey * 7919) % 2000000) / 1e6 AS plat, ((2 * (s_nationkey % 5)) * 1000000 + (s_suppkey * 104729) % 2000000) / 1e6 AS plon FROM supplier) k ON true,
LATERAL (SELECT 2 * 6371000 * asin(sqrt(pow(sin(radians(plat - lat1) / 2), 2) + cos(radians(lat1)) * cos(radians(plat)) * pow(sin(radians(plon - lon1) / 2), 2))) AS m) WHERE m <= 100000"""))
def w11_poi_near(spark: SparkSession, sf: str) -> DataFrame:
    """Points of interest within 100 km of a track's start: cells of two degrees and their neighbours, then the distance."""
    from crawltracks.operators.relational import within

    p = geo.first_point(F.col("segments"))
    starts = dense(spark, sf).select("file_id", p["lat"].alias("lat"), p["lon"].alias("lon"))
    return within(starts, fx.poi(spark, sf), 100_000, 2.0).select("file_id", "poi_id", F.round("metres", 2).alias("metres"))


@query(sql(_FINAL_VIEWS + "read", f"SELECT file_id, md5({english('masked', 'lang')}) AS text_digest, line_digest FROM read JOIN lines USING (file_id, track_no) WHERE {english('masked', 'lang')} IS NOT NULL"))
def w12_training_pairs(spark: SparkSession, sf: str) -> DataFrame:
    """(English text, geometry) pairs as JSON lines, read back from them and digested."""
    pair = F.to_json(F.struct(F.col("file_id").alias("id"), F.col("desc_en").alias("text"), F.base64("geometry").alias("geometry")))
    lines = _before_judges(spark, sf).where("desc_en IS NOT NULL").select(pair.alias("line"))
    back = lines.select(F.from_json("line", "id long, text string, geometry string").alias("x")).select("x.*")
    return back.select(F.col("id").alias("file_id"), F.md5("text").alias("text_digest"), line_digest(F.unbase64("geometry")).alias("line_digest"))


@query(r"""SELECT lang, word, n FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY n DESC, word) AS rk FROM (SELECT lang, word, count(*) AS n
FROM (SELECT lang, unnest(regexp_split_to_array(lower(text), '[^\p{L}]+')) AS word FROM documents) WHERE length(word) > 3 GROUP BY lang, word)) WHERE rk <= 10""")
def w13_wording(spark: SparkSession, sf: str) -> DataFrame:
    """The ten most frequent longer words of each language (counts first, so the window sees words, not occurrences)."""
    from crawltracks.operators.language import tokens

    words = fx.descriptions(spark, sf).select("lang", F.explode(tokens(F.col("text"))).alias("word")).where("length(word) > 3")
    counts = words.groupBy("lang", "word").agg(F.count("*").alias("n"))
    rk = F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "word"))
    return counts.withColumn("rk", rk).where("rk <= 10").drop("rk")


@query(sql("steps", """, b AS (SELECT file_id, track_no, seg_no, ts, event_id, degrees(atan2(sin(radians(lon - plon)) * cos(radians(lat)), cos(radians(plat)) * sin(radians(lat)) - sin(radians(plat)) * cos(radians(lat)) * cos(radians(lon - plon)))) AS bearing FROM steps),
t AS (SELECT 180 - abs(abs(lag(bearing) OVER (PARTITION BY file_id, track_no, seg_no ORDER BY ts, event_id) - bearing) % 360 - 180) AS turn FROM b)
SELECT least(CAST(floor(turn / 30) AS BIGINT), 5) AS sector, count(*) AS n FROM t WHERE turn IS NOT NULL GROUP BY 1"""))
def w14_turns(spark: SparkSession, sf: str) -> DataFrame:
    """Turns at inner points, in sectors of 30 degrees."""
    turns = fx.tracks(spark, sf).select(F.explode(F.flatten(F.transform("segments", geo.turns_deg))).alias("turn"))
    return turns.groupBy(F.least(F.floor(F.col("turn") / 30), F.lit(5)).cast("long").alias("sector")).agg(F.count("*").alias("n"))


@query("""SELECT q, vec_id, rk FROM (SELECT a.vec_id AS q, b.vec_id AS vec_id, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) DESC, b.vec_id) AS rk
FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0) WHERE rk <= 5""")
def w15_similar(spark: SparkSession, sf: str) -> DataFrame:
    """The five nearest vectors of every fiftieth, against all."""
    from crawltracks.operators.relational import cosine_top

    e = fx.table(spark, sf, "embeddings")
    return cosine_top(e.where("vec_id % 50 = 0"), e, 5)


@query(sql("dense ends cells", f"SELECT region, country, count(*) AS n FROM {_LOCATED} GROUP BY ROLLUP (region, country)"))
def w16_regions(spark: SparkSession, sf: str) -> DataFrame:
    return located(spark, sf).rollup("region", "country").agg(F.count("*").alias("n"))


#: Words that stand for a kind of outing in the stand-in texts.
ACTIVITIES = {
    "ride": ["ing", "reed", "orth"],
    "run": ["ered", "edst"],
    "walk": ["thon", "thand", "erth"],
}


def _activity_sql() -> str:
    arms = " ".join(f"WHEN len(list_filter(w, lambda x: x IN ({', '.join(repr(v) for v in words)}))) > 0 THEN '{kind}'" for kind, words in ACTIVITIES.items())
    return rf"SELECT lang, activity, count(*) AS n FROM (SELECT lang, CASE {arms} ELSE 'other' END AS activity FROM (SELECT lang, regexp_split_to_array(lower(text), '[^\p{{L}}]+') AS w FROM documents)) GROUP BY ALL"


@query(_activity_sql())
def w17_activities(spark: SparkSession, sf: str) -> DataFrame:
    from crawltracks.operators.language import tokens

    w, out = F.col("w"), F.lit("other")
    for kind, words in reversed(ACTIVITIES.items()):
        out = F.when(F.arrays_overlap(w, F.array(*[F.lit(x) for x in words])), kind).otherwise(out)
    rows = fx.descriptions(spark, sf).select("lang", tokens(F.col("text")).alias("w"))
    return rows.groupBy("lang", out.alias("activity")).agg(F.count("*").alias("n"))
