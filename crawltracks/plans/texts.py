"""Registered queries of cleaning, judging, masking, language and translation."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from crawltracks.config import DEFAULT as CFG
from crawltracks.functions import text as tx
from crawltracks.operators import gates
from crawltracks.operators.judge import LabelJudge, RuleJudge, judge_gate, judge_quality, looks_private, reads_like_prose
from crawltracks.operators.language import UNKNOWN, detect_language, gate_known
from crawltracks.operators.translate import LexiconTranslator, defects, translate
from crawltracks.plans.registry import query
from crawltracks.plans.sqlviews import detected, english, q, sql
from crawltracks.plans.tracks import dense
from crawltracks.sources import fixtures as fx


_STRIP = f"regexp_replace(html, {q(tx.TAG)}, '', 'g')"
for _name, _value in tx.ENTITIES.items():
    _STRIP = f"replace({_STRIP}, {q(_name)}, {q(_value)})"
_NO_SCRIPT = f"regexp_replace(html, {q(tx.WITH_CONTENT)}, '', 'g')"


@query(f"SELECT page_id, md5(x) AS digest, length(x) AS chars FROM (SELECT page_id, {_STRIP} AS x FROM pages)")
def c2_strip_html(spark: SparkSession, sf: str) -> DataFrame:
    x = tx.strip_html(F.col("html"))
    return fx.table(spark, sf, "pages").select("page_id", x.alias("x")).select("page_id", F.md5("x").alias("digest"), F.length("x").cast("long").alias("chars"))


_MORE = f"replace(replace({_STRIP}, '&copy;', '©'), '&middot;', '·')"


@query(f"SELECT page_id, md5(x) AS digest, length(x) AS chars FROM (SELECT page_id, {_MORE} AS x FROM (SELECT page_id, {_NO_SCRIPT} AS html FROM pages))")
def c2a_html_parser(spark: SparkSession, sf: str) -> DataFrame:
    """Texts by a parser, after scripts are gone: it also knows the references that the pattern's list leaves as they are."""
    x = fx.table(spark, sf, "pages").select("page_id", tx.strip_html_parsed(tx.strip_scripts(F.col("html"))).alias("x"))
    return x.select("page_id", F.md5("x").alias("digest"), F.length("x").cast("long").alias("chars"))


@query(f"SELECT page_id, md5(x) AS digest, length(x) AS chars FROM (SELECT page_id, {_NO_SCRIPT} AS x FROM pages)")
def c2b_strip_scripts(spark: SparkSession, sf: str) -> DataFrame:
    x = tx.strip_scripts(F.col("html"))
    return fx.table(spark, sf, "pages").select("page_id", x.alias("x")).select("page_id", F.md5("x").alias("digest"), F.length("x").cast("long").alias("chars"))


_WS = r"regexp_replace(text, '[\n\r\t\x0B\f]+', ' ', 'g')"


@query(f"SELECT doc_id, md5({_WS}) AS digest FROM documents")
def c3_whitespace(spark: SparkSession, sf: str) -> DataFrame:
    return fx.descriptions(spark, sf).select("doc_id", F.md5(tx.flatten_ws(F.col("text"))).alias("digest"))


@query(r"SELECT doc_id, md5(regexp_replace(text, '[\n\r\t\x0B\f]', ' ', 'g')) AS digest FROM documents")
def c3a_whitespace_each(spark: SparkSession, sf: str) -> DataFrame:
    return fx.descriptions(spark, sf).select("doc_id", F.md5(tx.flatten_ws(F.col("text"), collapse=False)).alias("digest"))


_MARKED = "SELECT doc_id, CASE WHEN doc_id % 10 = 0 THEN '[app 1.2] ' || text || ' {route: test}' ELSE text END AS text FROM documents"
_DROP = r"regexp_replace(regexp_replace(text, '\[[^\[\]]*\]|\{[^{}]*\}', '', 'g'), '\[[^\[\]]*\]|\{[^{}]*\}', '', 'g')"


@query(f"SELECT doc_id, md5({_DROP}) AS digest FROM ({_MARKED})")
def c4_brackets(spark: SparkSession, sf: str) -> DataFrame:
    return fx.descriptions(spark, sf, markers=True).select("doc_id", F.md5(tx.drop_bracketed(F.col("text"))).alias("digest"))


_CLEAN = f"trim(regexp_replace({_DROP.replace('(text,', f'({_WS},')}, ' {{2,}}', ' ', 'g'), ' ')"


@query(f"SELECT doc_id, md5({_CLEAN}) AS digest FROM ({_MARKED})")
def c4a_clean_all(spark: SparkSession, sf: str) -> DataFrame:
    return fx.descriptions(spark, sf, markers=True).select("doc_id", F.md5(tx.clean(F.col("text"))).alias("digest"))


@query(sql("cleaned", "SELECT min(doc_id) AS doc_id FROM cleaned WHERE length(cleaned) BETWEEN 50 AND 2000 GROUP BY text"))
def c5_desc_len(spark: SparkSession, sf: str) -> DataFrame:
    rows = fx.descriptions(spark, sf).where(gates.ok_description(tx.clean(F.col("text"))))
    return rows.groupBy("text").agg(F.min("doc_id").alias("doc_id")).select("doc_id")


@query("SELECT round(quantile_cont(length(text), 0.99), 2) AS p99, round(quantile_cont(length(text), 0.5), 2) AS median FROM documents")
def c5a_length_p99(spark: SparkSession, sf: str) -> DataFrame:
    n = F.length("text")
    return fx.descriptions(spark, sf).agg(F.round(F.percentile(n, 0.99), 2).alias("p99"), F.round(F.percentile(n, 0.5), 2).alias("median"))


@query("SELECT d.doc_id FROM documents d JOIN labels l USING (doc_id) WHERE quality = 1")
def c6_quality_gate(spark: SparkSession, sf: str) -> DataFrame:
    judge = LabelJudge(fx.table(spark, sf, "labels"), "quality")
    return judge_gate(fx.descriptions(spark, sf), "text", judge, CFG.quality_in_doubt, True).select("doc_id")


_LETTERS = r"length(regexp_replace(text, '[^\p{L}]', '', 'g'))"
_PROSE = rf"(length(text) >= 80 AND {_LETTERS} / length(text) >= 0.7 AND NOT regexp_matches(text, '\||[#$%&*]{{3}}'))"


@query(f"SELECT doc_id, {_PROSE} AS verdict FROM documents")
def c6b_rule_judge(spark: SparkSession, sf: str) -> DataFrame:
    return RuleJudge(reads_like_prose).verdicts(fx.descriptions(spark, sf), "text", False).select("doc_id", "verdict")


@query(f"""SELECT *, round(tp / (tp + fp), 6) AS precision, round(tp / (tp + fn), 6) AS recall, round(2 * (tp / (tp + fp)) * (tp / (tp + fn)) / (tp / (tp + fp) + tp / (tp + fn)), 6) AS f1
FROM (SELECT count(*) FILTER (v AND t) AS tp, count(*) FILTER (v AND NOT t) AS fp, count(*) FILTER (NOT v AND t) AS fn, count(*) FILTER (NOT v AND NOT t) AS tn
FROM (SELECT {_PROSE} AS v, quality = 1 AS t FROM documents JOIN labels USING (doc_id)))""")
def c6c_judge_confusion(spark: SparkSession, sf: str) -> DataFrame:
    rows = fx.descriptions(spark, sf).join(fx.table(spark, sf, "labels"), "doc_id").withColumn("truth", F.col("quality") == 1)
    return judge_quality(RuleJudge(reads_like_prose).verdicts(rows, "text", False), "truth")


def _masked(mask, pattern: str):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        x = F.col("text")
        hits = F.regexp_count(x, F.lit(pattern)).cast("long")
        return fx.descriptions(spark, sf).select("doc_id", hits.alias("hits"), F.md5(mask(x)).alias("digest")).where("hits > 0")

    return run


def _mask_sql(pattern: str, token: str) -> str:
    found = f"len(regexp_extract_all(text, {q(pattern)}))"
    return f"SELECT doc_id, {found} AS hits, md5(regexp_replace(text, {q(pattern)}, '{token}', 'g')) AS digest FROM documents WHERE {found} > 0"


query(_mask_sql(tx.EMAIL_PATTERN, tx.EMAIL), "p1_mask_email")(_masked(tx.mask_email, tx.EMAIL_PATTERN))
query(_mask_sql(tx.PHONE_PATTERN, tx.TELEPHONE), "p3_mask_phone")(_masked(tx.mask_phone, tx.POSSIBLE_PATTERN))
query(_mask_sql(tx.STRICT_PHONE_PATTERN, tx.TELEPHONE), "p3a_mask_phone_strict")(_masked(lambda c: tx.mask_phone(c, "valid"), tx.STRICT_PHONE_PATTERN))


@query(f"SELECT doc_id, md5(regexp_replace(text || ' ' || url, {q(tx.URL_PATTERN)}, '{tx.URL}', 'g')) AS digest FROM documents JOIN pages ON page_id = doc_id")
def p2_mask_url(spark: SparkSession, sf: str) -> DataFrame:
    rows = fx.descriptions(spark, sf).join(fx.table(spark, sf, "pages").select(F.col("page_id").alias("doc_id"), "url"), "doc_id")
    return rows.select("doc_id", F.md5(tx.mask_url(F.concat_ws(" ", "text", "url"))).alias("digest"))


def _count(pattern: str, text: str = "text") -> str:
    return f"len(regexp_extract_all({text}, {q(pattern)}))"


_PHONED = f"regexp_replace(text, {q(tx.PHONE_PATTERN)}, '{tx.TELEPHONE}', 'g')"


@query(f"SELECT count(*) FILTER ({_count(tx.CARD_PATTERN)} <> {_count(tx.CARD_PATTERN, _PHONED)}) AS cards_hit, count(*) FILTER ({_count(tx.QUAD_PATTERN)} <> {_count(tx.QUAD_PATTERN, _PHONED)}) AS quads_hit FROM documents")
def p3b_phone_false_hits(spark: SparkSession, sf: str) -> DataFrame:
    """Cards and dotted quads that phone masking would touch: none."""
    x, y = F.col("text"), tx.mask_phone(F.col("text"))
    other = lambda p: F.count_if(F.regexp_count(x, F.lit(p)) != F.regexp_count(y, F.lit(p)))
    return fx.descriptions(spark, sf).agg(other(tx.CARD_PATTERN).alias("cards_hit"), other(tx.QUAD_PATTERN).alias("quads_hit"))


@query("SELECT unnest(['lat', 'lon', 'ele']) AS field")
def p4_no_time(spark: SparkSession, sf: str) -> DataFrame:
    """Fields that any point has after times are dropped, read from the data itself."""
    from crawltracks.functions.geo import drop_times

    points = fx.tracks(spark, sf).select(F.explode(F.flatten(drop_times(F.col("segments")))).alias("p"))
    return points.select(F.explode(F.json_object_keys(F.to_json("p", {"ignoreNullFields": "false"}))).alias("field")).distinct()


@query(sql("pts", "SELECT CASE WHEN n = 0 THEN 'none' WHEN n = a THEN 'all' ELSE 'some' END AS times, count(*) AS tracks FROM (SELECT count(CASE WHEN event_id % 3 > 0 OR file_id % 5 > 0 THEN ts END) FILTER (file_id % 7 > 0) AS n, count(*) AS a FROM pts GROUP BY file_id, track_no) GROUP BY 1"))
def p4a_time_coverage(spark: SparkSession, sf: str) -> DataFrame:
    """Tracks with none, some or all times; a seventh of the files loses all, a fifth some."""
    p = fx.points(spark, sf)
    t = F.when((F.col("file_id") % 7 > 0) & ((F.col("event_id") % 3 > 0) | (F.col("file_id") % 5 > 0)), F.col("ts"))
    per = p.groupBy("file_id", "track_no").agg(F.count(t).alias("n"), F.count("*").alias("a"))
    return per.groupBy(F.when(F.col("n") == 0, "none").when(F.col("n") == F.col("a"), "all").otherwise("some").alias("times")).agg(F.count("*").alias("tracks"))


@query("SELECT d.doc_id FROM documents d JOIN labels l USING (doc_id) WHERE toxic = 0")
def p5_privacy_gate(spark: SparkSession, sf: str) -> DataFrame:
    judge = LabelJudge(fx.table(spark, sf, "labels"), "toxic")
    return judge_gate(fx.descriptions(spark, sf), "text", judge, CFG.privacy_in_doubt, False).select("doc_id")


_PRIVATE = "(" + " OR ".join(f"regexp_matches(text, {q(p)})" for p in (tx.EMAIL_PATTERN, tx.PHONE_PATTERN, tx.URL_PATTERN, tx.CARD_PATTERN, tx.QUAD_PATTERN)) + ")"


@query(f"SELECT toxic = 1 AS judge_drops, {_PRIVATE} AS patterns_drop, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY ALL")
def n6_patterns_only(spark: SparkSession, sf: str) -> DataFrame:
    """The baseline without a privacy judge: what patterns alone find, against the judge's answers."""
    rows = fx.descriptions(spark, sf).withColumn("masked", tx.mask_all(F.col("text")))
    rows = RuleJudge(looks_private).verdicts(rows, "masked", True).withColumnRenamed("verdict", "patterns_drop")
    rows = rows.join(fx.table(spark, sf, "labels").select("doc_id", (F.col("toxic") == 1).alias("judge_drops")), "doc_id")
    return rows.groupBy("judge_drops", "patterns_drop").agg(F.count("*").alias("n"))


@query(f"SELECT doc_id FROM documents WHERE {_PRIVATE}")
def p5a_rule_privacy(spark: SparkSession, sf: str) -> DataFrame:
    """Documents that the rule judge removes after masking."""
    rows = fx.descriptions(spark, sf).withColumn("masked", tx.mask_all(F.col("text")))
    return judge_gate(rows, "masked", RuleJudge(looks_private), True, True).select("doc_id")


@query(f"SELECT CAST(sum({_count(tx.EMAIL_PATTERN)}) AS BIGINT) AS emails, CAST(sum({_count(tx.PHONE_PATTERN)}) AS BIGINT) AS phones, CAST(sum({_count(tx.CARD_PATTERN)}) AS BIGINT) AS cards, CAST(sum({_count(tx.QUAD_PATTERN)}) AS BIGINT) AS quads FROM documents")
def p5b_pii_report(spark: SparkSession, sf: str) -> DataFrame:
    n = lambda p: F.sum(F.regexp_count("text", F.lit(p))).cast("long")
    return fx.descriptions(spark, sf).agg(n(tx.EMAIL_PATTERN).alias("emails"), n(tx.POSSIBLE_PATTERN).alias("phones"), n(tx.CARD_PATTERN).alias("cards"), n(tx.QUAD_PATTERN).alias("quads"))


_DETECT = detected("(SELECT doc_id, text, lang FROM documents)")


@query(f"SELECT lang, found, count(*) AS n FROM ({_DETECT}) GROUP BY ALL")
def l1_detect(spark: SparkSession, sf: str) -> DataFrame:
    return detect_language(fx.descriptions(spark, sf), "text", "found").groupBy("lang", "found").agg(F.count("*").alias("n"))


@query(f"SELECT doc_id, found FROM ({_DETECT}) WHERE found <> '{UNKNOWN}'")
def l2_known(spark: SparkSession, sf: str) -> DataFrame:
    return gate_known(detect_language(fx.descriptions(spark, sf), "text", "found").select("doc_id", "found"), "found")


def sized(spark: SparkSession, sf: str) -> DataFrame:
    docs = fx.descriptions(spark, sf).select(F.col("doc_id").alias("file_id"), "lang", tx.clean(F.col("text")).alias("cleaned"))
    return dense(spark, sf).join(docs, "file_id").where(gates.ok_description(F.col("cleaned")))


_SUPPORT = sql("sized", "SELECT file_id, lang FROM sized WHERE lang IN (SELECT lang FROM sized GROUP BY lang HAVING count(*) > 5)")


@query(_SUPPORT)
def l3_lang_support(spark: SparkSession, sf: str) -> DataFrame:
    return gates.language_support(sized(spark, sf).select("file_id", "lang"))


@query(_SUPPORT)
def l3a_lang_support_window(spark: SparkSession, sf: str) -> DataFrame:
    return gates.language_support(sized(spark, sf).select("file_id", "lang"), plan="window")


_WORDS_SQL = english("text", "lang")


@query(f"SELECT doc_id, md5({_WORDS_SQL}) AS digest, CASE lang WHEN 'en' THEN 'original' ELSE 'translated' END AS translate_status FROM documents")
def l4_translate(spark: SparkSession, sf: str) -> DataFrame:
    return translate(fx.descriptions(spark, sf), LexiconTranslator(), "text", "lang").select("doc_id", F.md5("desc_en").alias("digest"), "translate_status")


@query(r"""SELECT preamble, layout, digits, "length", count(*) AS n FROM (SELECT regexp_matches(done, '(?i)^(the text is in|here is|here''s|sure|translation)') AS preamble,
length(text) - length(replace(text, chr(10), '')) <> length(done) - length(replace(done, chr(10), '')) AS layout, regexp_replace(text, '[^0-9]', '', 'g') <> regexp_replace(done, '[^0-9]', '', 'g') AS digits,
length(done) > 1.5 * length(text) OR length(done) < 0.5 * length(text) AS "length"
FROM (SELECT text, CASE doc_id % 3 WHEN 0 THEN 'Here is the English translation: ' || text WHEN 1 THEN replace(text, chr(10), ' ') ELSE text END AS done FROM documents)) GROUP BY ALL""")
def l4b_defects(spark: SparkSession, sf: str) -> DataFrame:
    m, x = F.col("doc_id") % 3, F.col("text")
    done = F.when(m == 0, F.concat(F.lit("Here is the English translation: "), x)).when(m == 1, F.replace(x, F.lit("\n"), F.lit(" "))).otherwise(x)
    flags = defects(x, F.col("done"))
    return fx.descriptions(spark, sf).withColumn("done", done).groupBy(*[c.alias(k) for k, c in flags.items()]).agg(F.count("*").alias("n"))
