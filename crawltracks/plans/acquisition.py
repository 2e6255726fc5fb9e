"""Registered queries of the acquisition methods: index, discovery, ranges, deduplication."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from crawltracks.config import DEFAULT as CFG
from crawltracks.functions.url import url_host
from crawltracks.materialise import new_path
from crawltracks.operators import dedup, fetch
from crawltracks.operators.discover import discover, discovery_agreement, is_ext, is_mime
from crawltracks.plans.registry import query
from crawltracks.plans.sqlviews import HOST, sql
from crawltracks.sources import fixtures as fx


@query(sql("idx", "SELECT release, part, count(*) AS n, CAST(sum(length) AS BIGINT) AS bytes FROM idx GROUP BY ALL"))
def a1_index_scan(spark: SparkSession, sf: str) -> DataFrame:
    return fx.crawl_index(spark, sf).groupBy("release", "part").agg(F.count("*").alias("n"), F.sum("length").alias("bytes"))


def _discover(mode: str):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        return discover(fx.crawl_index(spark, sf), CFG.mime_token, CFG.ext, mode).select("page_id", "release", "part", "url")

    return run


for _name, _mode, _where in (("a2_discover", "either", "is_mime OR is_ext"), ("a2a_discover_mime", "mime", "is_mime"), ("a2b_discover_ext", "ext", "is_ext"), ("a2c_discover_both", "both", "is_mime AND is_ext")):
    query(sql("idx", f"SELECT page_id, release, part, url FROM idx WHERE {_where}"), _name)(_discover(_mode))


@query(sql("idx", "SELECT is_mime, is_ext, count(*) AS n FROM idx GROUP BY ALL"))
def a2d_agreement(spark: SparkSession, sf: str) -> DataFrame:
    return discovery_agreement(fx.crawl_index(spark, sf), CFG.mime_token, CFG.ext)


@query(sql("idx", "SELECT regexp_extract(" + "url" + r", '^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*([^?#]*)', 1) AS path, count(*) AS n FROM idx WHERE is_ext GROUP BY ALL"))
def a2e_url_paths(spark: SparkSession, sf: str) -> DataFrame:
    from crawltracks.functions.url import url_path

    return discover(fx.crawl_index(spark, sf), CFG.mime_token, CFG.ext, "ext").groupBy(url_path(F.col("url")).alias("path")).agg(F.count("*").alias("n"))


@query(sql("idx", r"""SELECT ext, count(*) AS n FROM (SELECT lower(regexp_extract(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*([^?#]*)', 1), '\.([A-Za-z0-9]+)$', 1)) AS ext FROM idx)
WHERE ext IN ('html', 'php', 'htm', 'aspx') GROUP BY ALL"""))
def a2f_multi_ext(spark: SparkSession, sf: str) -> DataFrame:
    from crawltracks.functions.url import url_ext

    wanted = ["html", "php", "htm", "aspx"]
    return discover(fx.crawl_index(spark, sf), CFG.mime_token, wanted, "ext").groupBy(url_ext(F.col("url")).alias("ext")).agg(F.count("*").alias("n"))


@query(sql("idx", 'SELECT page_id, archive, "offset", length FROM idx WHERE is_mime OR is_ext'))
def a3_pointers(spark: SparkSession, sf: str) -> DataFrame:
    return discover(fx.crawl_index(spark, sf), CFG.mime_token, CFG.ext).select("page_id", "archive", "offset", "length")


def _stored_archives(spark: SparkSession, sf: str) -> fetch.FileRangeReader:
    """The stand-in archives as files in the shared folder."""
    root = new_path(spark, "archives")
    fetch.write_archives(fx.archives(spark, sf), root)
    return fetch.FileRangeReader(root)


def _fetched(spark: SparkSession, sf: str, mode: str, gap: int | None = None) -> DataFrame:
    """Records of the captures found, read by byte ranges out of archive files."""
    found = discover(fx.crawl_index(spark, sf), CFG.mime_token, CFG.ext, mode).select(F.col("page_id").cast("string").alias("url"), "archive", "offset", "length")
    rows = fetch.fetch_ranges(found, _stored_archives(spark, sf), int(spark.conf.get("spark.sql.shuffle.partitions")), gap=gap).where("fetch_status = 'ok'")
    return rows.select(F.col("url").cast("long").alias("page_id"), F.md5(F.encode("content", "UTF-8")).alias("digest"), F.octet_length("content").cast("long").alias("bytes"))


@query(sql("idx", "SELECT page_id, md5(html) AS digest, length AS bytes FROM idx WHERE is_ext"))
def a4_range_fetch(spark: SparkSession, sf: str) -> DataFrame:
    """One range request for each record."""
    return _fetched(spark, sf, "ext")


@query(sql("idx", "SELECT page_id, md5(html) AS digest, length AS bytes FROM idx WHERE is_mime OR is_ext"))
def a4a_coalesced_fetch(spark: SparkSession, sf: str) -> DataFrame:
    """Near records share a request and are cut out of its answer."""
    return _fetched(spark, sf, "either", CFG.coalesce_gap)


@query(sql("idx", "SELECT page_id, md5(html) AS digest, length AS bytes FROM idx WHERE is_mime OR is_ext"))
def n1_full_fetch(spark: SparkSession, sf: str) -> DataFrame:
    """The baseline: every touched archive is read whole."""
    found = fetch.cut_ranges(discover(fx.crawl_index(spark, sf), CFG.mime_token, CFG.ext), fx.archives(spark, sf))
    return found.select("page_id", F.md5("content").alias("digest"), F.octet_length("content").cast("long").alias("bytes"))


@query(sql("idx", """, hits AS (SELECT archive, "offset", length, max("offset" + length) OVER (PARTITION BY archive ORDER BY "offset" ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS reach FROM idx WHERE is_mime OR is_ext),
isl AS (SELECT *, sum(CASE WHEN reach IS NULL OR "offset" > reach + 4096 THEN 1 ELSE 0 END) OVER (PARTITION BY archive ORDER BY "offset") AS island FROM hits)
SELECT archive, CAST(min("offset") AS BIGINT) AS read_from, CAST(max("offset" + length) AS BIGINT) AS read_to, count(*) AS records, CAST(sum(length) AS BIGINT) AS wanted FROM isl GROUP BY archive, island"""))
def a4a_coalesced_ranges(spark: SparkSession, sf: str) -> DataFrame:
    merged = fetch.coalesce_ranges(discover(fx.crawl_index(spark, sf), CFG.mime_token, CFG.ext).select("archive", "offset", "length"), CFG.coalesce_gap)
    return merged.groupBy("archive", "island", "read_from", "read_to").agg(F.count("*").alias("records"), F.sum("length").alias("wanted")).drop("island")


@query(sql("idx", "SELECT count(*) AS identified, count(*) FILTER (page_id % 61 <> 7) AS fetched, round(count(*) FILTER (page_id % 61 <> 7) / count(*), 6) AS success_rate FROM idx"))
def a5_fetch_success(spark: SparkSession, sf: str) -> DataFrame:
    """All captures are fetched; the reader fails at some records, and all attempts at them fail."""
    index = fx.crawl_index(spark, sf)
    bad = index.where("page_id % 61 = 7").select(F.col("archive").cast("string"), "offset").collect()  # the stand-in failures
    reader = fetch.FlakyReader(_stored_archives(spark, sf), frozenset((r[0], r[1]) for r in bad))
    rows = fetch.fetch_ranges(index, reader, int(spark.conf.get("spark.sql.shuffle.partitions")), max_attempts=2, pause_s=0.0)
    return fetch.fetch_stats(rows, F.col("fetch_status") == "ok")


@query(sql("caps", """SELECT url, release, archive, "offset", length FROM (SELECT *, row_number() OVER (PARTITION BY url ORDER BY release DESC, archive, "offset") AS rn FROM caps) WHERE rn = 1"""))
def a6_dedup_url(spark: SparkSession, sf: str) -> DataFrame:
    return dedup.dedup_url(fx.captures(spark, sf))


@query(sql("caps", "SELECT count(*) AS urls, count(*) FILTER (n > 1) AS in_several, round(count(*) FILTER (n > 1) / count(*), 6) AS share FROM (SELECT url, count(DISTINCT release) AS n FROM caps GROUP BY url)"))
def a6a_url_overlap(spark: SparkSession, sf: str) -> DataFrame:
    return dedup.url_overlap(fx.captures(spark, sf))


@query("SELECT min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY sha256(text)")
def a7_dedup_content(spark: SparkSession, sf: str) -> DataFrame:
    return dedup.dedup_content(fx.table(spark, sf, "documents"), "doc_id", dedup.content_key(F.col("text")))


@query(r"SELECT min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY trim(regexp_replace(lower(text), '[ \n\r\t]+', ' ', 'g'), ' ')")
def a7a_dedup_normalised(spark: SparkSession, sf: str) -> DataFrame:
    return dedup.dedup_content(fx.table(spark, sf, "documents"), "doc_id", dedup.content_key(F.col("text"), "normalised"))


@query(sql("pts", """, body AS (SELECT file_id, string_agg(lat_u || ',' || lon_u, ';' ORDER BY track_no, seg_no, ts, event_id) AS line FROM pts GROUP BY file_id)
SELECT min(b.file_id) AS file_id, count(*) AS copies FROM body b LEFT JOIN documents d ON d.doc_id = b.file_id GROUP BY line, coalesce(text, '')"""))
def a7b_dedup_payload(spark: SparkSession, sf: str) -> DataFrame:
    """Equal geometry and description; times and everything else about a file do not count."""
    trk = fx.tracks(spark, sf).join(fx.table(spark, sf, "documents").select(F.col("doc_id").alias("file_id"), "text"), "file_id", "left")
    line = F.array_join(F.transform(F.flatten("segments"), lambda p: F.concat_ws(",", p["lat"].cast("string"), p["lon"].cast("string"))), ";")
    whole = trk.groupBy("file_id").agg(F.sort_array(F.collect_list(F.struct("track_no", line.alias("line")))).alias("lines"), F.first("text").alias("text"))
    key = F.sha2(F.concat(F.coalesce("text", F.lit("")), F.array_join(F.transform("lines", lambda x: x["line"]), "|")), 256)
    return dedup.dedup_content(whole, "file_id", key)


@query(sql("idx", "SELECT CAST(sum(CASE WHEN is_ext THEN length ELSE 0 END) AS BIGINT) AS range_bytes, CAST(sum(length) AS BIGINT) AS archive_bytes, round(sum(CASE WHEN is_ext THEN length ELSE 0 END) / sum(length), 6) AS share FROM idx"))
def a8_bytes_saved(spark: SparkSession, sf: str) -> DataFrame:
    return fetch.transfer_model(fx.crawl_index(spark, sf), is_ext(F.col("url"), CFG.ext))


@query(f"SELECT count(DISTINCT {HOST}) AS domains FROM pages")
def s5_domains(spark: SparkSession, sf: str) -> DataFrame:
    return fx.table(spark, sf, "pages").agg(F.count_distinct(url_host(F.col("url"))).alias("domains"))


@query(sql("caps", """SELECT DISTINCT url FROM caps WHERE release = 0 INTERSECT SELECT DISTINCT url FROM caps WHERE release = 1"""))
def q_release_intersect(spark: SparkSession, sf: str) -> DataFrame:
    c = fx.captures(spark, sf)
    return c.where("release = 0").select("url").intersect(c.where("release = 1").select("url"))


@query(sql("caps", """SELECT DISTINCT url FROM caps WHERE release = 1 EXCEPT SELECT DISTINCT url FROM caps WHERE release = 0"""))
def q_release_except(spark: SparkSession, sf: str) -> DataFrame:
    c = fx.captures(spark, sf)
    return c.where("release = 1").select("url").subtract(c.where("release = 0").select("url"))


@query(sql("caps", "SELECT DISTINCT url FROM caps c WHERE release = 5 AND NOT EXISTS (SELECT 1 FROM caps o WHERE o.url = c.url AND o.release < 5)"))
def q_new_urls(spark: SparkSession, sf: str) -> DataFrame:
    c = fx.captures(spark, sf)
    return c.where("release = 5").select("url").distinct().join(c.where("release < 5").select("url"), "url", "left_anti")


@query(sql("idx", "SELECT page_id, url, mime_detected FROM idx WHERE is_mime"))
def q_scan_parquet(spark: SparkSession, sf: str) -> DataFrame:
    return fx.crawl_index(spark, sf).where(is_mime(F.col("mime_detected"), CFG.mime_token)).select("page_id", "url", "mime_detected")
