"""Stand-in inputs as SQL views for the oracles (the same formulas as sources/fixtures.py)."""

from __future__ import annotations

from crawltracks.functions import text as tx
from crawltracks.operators.language import LETTERS, MIN_LETTERS, MIN_SHARE, STOP_WORDS, UNKNOWN
from crawltracks.operators.translate import LEXICON

PATH = r"regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*([^?#]*)', 1)"
EXT = rf"lower(regexp_extract({PATH}, '\.([A-Za-z0-9]+)$', 1))"
HOST = r"lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://([^/?#:]+)', 1))"



def q(pattern: str) -> str:
    """A pattern as an SQL literal."""
    return "'" + pattern.replace("'", "''") + "'"


def _score(lang: str, text: str) -> str:
    stops = ", ".join(q(w) for w in STOP_WORDS[lang])
    marks = f" + length(lower({text})) - length(translate(lower({text}), {q(LETTERS[lang])}, ''))" if LETTERS[lang] else ""
    return rf"len(list_filter(regexp_split_to_array(lower({text}), '[^\p{{L}}]+'), lambda w: w IN ({stops}))){marks}"


def detected(source: str, text: str = "text") -> str:
    """All columns of ``source`` and ``found``, the language of ``text``."""
    codes = sorted(STOP_WORDS)
    best = f"greatest({', '.join(f's_{x}' for x in codes)})"
    arms = " ".join(f"WHEN s_{x} = {best} THEN '{x}'" for x in codes)
    scores = ", ".join(f"{_score(x, text)} AS s_{x}" for x in codes)
    return rf"""SELECT * EXCLUDE (letters, {', '.join(f's_{x}' for x in codes)}), CASE WHEN letters < {MIN_LETTERS} OR letters < {MIN_SHARE} * length({text}) OR {best} = 0 THEN '{UNKNOWN}' {arms} END AS found
    FROM (SELECT *, length(regexp_replace({text}, '[^\p{{L}}]', '', 'g')) AS letters, {scores} FROM {source})"""


def english(text: str, lang: str) -> str:
    """The word-by-word translation of ``text``; NULL where the lexicon has no such language."""
    looked_up = lambda m: f"CASE w {' '.join(f'WHEN {q(a)} THEN {q(b)}' for a, b in m.items())} ELSE w END"
    arms = " ".join(f"WHEN '{x}' THEN array_to_string(list_transform(string_split({text}, ' '), lambda w: {looked_up(m)}), ' ')" for x, m in LEXICON.items())
    return f"CASE {lang} WHEN 'en' THEN {text} {arms} END"


_MASKED = f"regexp_replace(regexp_replace(regexp_replace(cleaned, {q(tx.URL_PATTERN)}, '{tx.URL}', 'g'), {q(tx.EMAIL_PATTERN)}, '{tx.EMAIL}', 'g'), {q(tx.PHONE_PATTERN)}, '{tx.TELEPHONE}', 'g')"

_VIEWS = {
    "idx": (
        "",
        f"""SELECT page_id, page_id % 6 AS release, page_id % 300 AS part, url, html,
        CASE WHEN page_id % 9 = 0 THEN 'Application/XHTML+xml' ELSE 'text/html' END AS mime_detected, page_id // 50 AS archive,
        CAST(coalesce(sum(octet_length(encode(html))) OVER (PARTITION BY page_id // 50 ORDER BY page_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS "offset",
        CAST(octet_length(encode(html)) AS BIGINT) AS length, page_id % 9 = 0 AS is_mime, {EXT} = 'html' AS is_ext FROM pages""",
    ),
    "caps": ("idx", "SELECT * FROM idx UNION ALL SELECT * REPLACE ((page_id + 1) % 6 AS release) FROM idx WHERE page_id % 12 = 0"),
    "pts": (
        "",
        """SELECT file_id, track_no, seg_no, ts, event_id, ele,
        CAST(41000000 + 2000000 * ((file_id % 27) // 5) + sum((k - 50) * m) OVER w AS BIGINT) AS lat_u,
        CAST(1000000 + 2000000 * ((file_id % 27) % 5) + sum(((37 * event_id) % 101 - 50) * m) OVER w AS BIGINT) AS lon_u
        FROM (SELECT user_id AS file_id, event_id, ts, CASE WHEN user_id % 10 = 9 AND event_id % 2 = 1 THEN 1 ELSE 0 END AS track_no,
          CAST(day(ts) // 11 AS INTEGER) AS seg_no, ([1, 5, 10, 15, 20, 40, 100, 700])[user_id % 8 + 1] AS m, CAST(json_extract(props, '$.k') AS BIGINT) AS k,
          CASE WHEN user_id % 2 = 1 OR (user_id % 6 = 0 AND event_type = 'error') THEN NULL ELSE value END AS ele FROM events)
        WINDOW w AS (PARTITION BY file_id, track_no ORDER BY ts, event_id)""",
    ),
    "steps": (
        "pts",
        """SELECT *, 2 * 6371000 * asin(sqrt((pow(sin(radians(lat - plat) / 2), 2) + cos(radians(plat)) * cos(radians(lat)) * pow(sin(radians(lon - plon) / 2), 2)))) AS step, ele - pele AS rise
        FROM (SELECT *, lat_u / 1e6 AS lat, lon_u / 1e6 AS lon, lag(lat_u) OVER w / 1e6 AS plat, lag(lon_u) OVER w / 1e6 AS plon, lag(ele) OVER w AS pele
              FROM pts WINDOW w AS (PARTITION BY file_id, track_no, seg_no ORDER BY ts, event_id))""",
    ),
    "ends": (
        "pts",
        """SELECT file_id, track_no, 2 * 6371000 * asin(sqrt((pow(sin(radians(lat2 - lat1) / 2), 2) + cos(radians(lat1)) * cos(radians(lat2)) * pow(sin(radians(lon2 - lon1) / 2), 2)))) AS apart, lat1, lon1
        FROM (SELECT file_id, track_no, arg_min(lat_u, (seg_no, ts, event_id)) / 1e6 AS lat1, arg_min(lon_u, (seg_no, ts, event_id)) / 1e6 AS lon1,
              arg_max(lat_u, (seg_no, ts, event_id)) / 1e6 AS lat2, arg_max(lon_u, (seg_no, ts, event_id)) / 1e6 AS lon2 FROM pts GROUP BY ALL)""",
    ),
    "trk": (
        "steps",
        """SELECT file_id, track_no, count(*) AS n_points, count(DISTINCT seg_no) AS n_segments, coalesce(sum(step), 0) AS len2d, coalesce(max(step), 0) AS max_step,
        coalesce(sum(sqrt(step * step + coalesce(rise, 0) * coalesce(rise, 0))), 0) AS len3d_raw, count(ele) AS n_ele FROM steps GROUP BY ALL""",
    ),
    "one": ("trk", "SELECT * FROM trk WHERE file_id IN (SELECT file_id FROM trk GROUP BY file_id HAVING count(*) = 1)"),
    "banded": ("one", "SELECT * FROM one WHERE len2d BETWEEN 500 AND 100000"),
    "dense": ("banded", "SELECT * FROM banded WHERE n_points * 100 >= len2d"),
    "cleaned": ("", r"""SELECT doc_id, lang, trim(regexp_replace(regexp_replace(text, '[\n\r\t\x0B\f]+', ' ', 'g'), ' {2,}', ' ', 'g'), ' ') AS cleaned, text FROM documents"""),
    "sized": ("dense cleaned", "SELECT d.*, c.lang, c.cleaned FROM dense d JOIN cleaned c ON c.doc_id = d.file_id WHERE length(c.cleaned) BETWEEN 50 AND 2000"),
    "good": ("sized", "SELECT s.*, l.toxic FROM sized s JOIN labels l ON l.doc_id = s.file_id WHERE l.quality = 1"),
    "spoken": ("cleaned", "SELECT * EXCLUDE (found, lang), found AS lang FROM (" + detected(f"(SELECT doc_id, lang, cleaned, {_MASKED} AS masked FROM cleaned)", "masked") + ")"),
    "read": ("sized spoken", "SELECT s.* EXCLUDE (lang), k.lang, k.masked FROM sized s JOIN spoken k ON k.doc_id = s.file_id"),
    "private": ("good spoken", "SELECT g.* EXCLUDE (lang), k.lang, k.masked FROM good g JOIN spoken k ON k.doc_id = g.file_id WHERE toxic = 0"),
    "supported": ("private", "SELECT * FROM private WHERE lang <> 'un' AND lang IN (SELECT lang FROM private GROUP BY lang HAVING count(*) > 5)"),
    "cells": (
        "",
        """SELECT trim(n_name) AS country, trim(r_name) AS region, 40 + 2 * (n_nationkey // 5) AS south, 2 * (n_nationkey % 5) AS west FROM nation JOIN region ON n_regionkey = r_regionkey""",
    ),
    "lit": (
        "pts",
        """SELECT p.*, e.embedding[(lat_u % 1000000) * 8 // 1000000 * 8 + (lon_u % 1000000) * 8 // 1000000 + 1]::DOUBLE * 1000 + 600 AS dem
        FROM pts p LEFT JOIN embeddings e ON e.vec_id = (lat_u // 1000000 - 40) * 10 + lon_u // 1000000""",
    ),
    "filled": (
        "lit",
        """SELECT * EXCLUDE (ele, dem, n_ele, n_all), CASE WHEN n_ele = n_all THEN ele ELSE dem END AS ele, CASE WHEN n_ele = n_all THEN 'GPS' ELSE 'DEM' END AS source, n_ele, n_all, dem
        FROM (SELECT *, count(ele) OVER (PARTITION BY file_id, track_no) AS n_ele, count(*) OVER (PARTITION BY file_id, track_no) AS n_all FROM lit)""",
    ),
    "lines": (
        "filled",
        """SELECT file_id, track_no, count(*) AS line_points, md5(string_agg(lat_u || ',' || lon_u || ',' || coalesce(CAST(CAST(floor(ele * 100 + 0.5) AS BIGINT) AS VARCHAR), 'none'), ';' ORDER BY seg_no, ts, event_id)) AS line_digest
        FROM filled GROUP BY ALL""",
    ),
    "climbs": (
        "filled",
        """SELECT *, ele - lag(ele) OVER w AS rise, 2 * 6371000 * asin(sqrt((pow(sin(radians(lat_u / 1e6 - lag(lat_u) OVER w / 1e6) / 2), 2)
          + cos(radians(lag(lat_u) OVER w / 1e6)) * cos(radians(lat_u / 1e6)) * pow(sin(radians(lon_u / 1e6 - lag(lon_u) OVER w / 1e6) / 2), 2)))) AS step
        FROM filled WINDOW w AS (PARTITION BY file_id, track_no, seg_no ORDER BY ts, event_id)""",
    ),
    "props": (
        "climbs",
        """SELECT file_id, track_no, min(source) AS source, max(ele) AS highest, min(ele) AS lowest, coalesce(sum(greatest(rise, 0)), 0) AS up, coalesce(sum(greatest(-rise, 0)), 0) AS down,
        coalesce(sum(sqrt(step * step + coalesce(rise, 0) * coalesce(rise, 0))), 0) AS len3d FROM climbs GROUP BY ALL""",
    ),
}


def sql(views: str, select: str) -> str:
    """``select`` after the named views and all they stand on."""
    needed: list[str] = []

    def add(name: str) -> None:
        for below in _VIEWS[name][0].split():
            add(below)
        if name not in needed:
            needed.append(name)

    for name in views.split():
        add(name)
    views_sql = ",\n".join(f"{n} AS ({_VIEWS[n][1]})" for n in needed)
    return f"WITH {views_sql}\n{select.strip()}"
