"""Queries of the whole pipeline against their SQL on tables where pages share URLs."""

from pathlib import Path

import duckdb
import pytest

from crawltracks.plans import all_oracles, all_queries
from test_oracles import TABLES, _plain

TABLES_FROM = Path("/root/testdata/sf0.01")

NAMES = [
    "abl_language_sweep",
    "abl_no_density",
    "abl_no_description",
    "abl_no_language",
    "abl_no_length",
    "abl_no_privacy",
    "abl_no_quality",
    "s1_funnel",
    "s2_rates",
    "s6_langs",
    "w12_training_pairs",
    "w8_final",
    "w8_properties",
]


@pytest.fixture(scope="module")
def shared_urls(tmp_path_factory):
    """The given tables, but six pages in a row, all of other releases, give the URL of the first."""
    folder = tmp_path_factory.mktemp("shared-urls")
    for t in TABLES:
        if t != "pages":
            (folder / f"{t}.parquet").symlink_to(TABLES_FROM / f"{t}.parquet")
    pages = f"read_parquet('{TABLES_FROM}/pages.parquet')"
    duckdb.execute(f"copy (select p.page_id, f.url, p.html from {pages} p join {pages} f on f.page_id = p.page_id - p.page_id % 6) to '{folder}/pages.parquet' (format parquet)")
    return folder


@pytest.mark.parametrize("name", NAMES)
def test_pages_that_share_a_url_are_all_kept(spark, shared_urls, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from read_parquet('{shared_urls}/{t}.parquet')")
    df = all_queries()[name](spark, str(shared_urls))
    columns = sorted(df.columns)
    got = sorted(repr(tuple(_plain(r[c]) for c in columns)) for r in df.collect())
    result = con.execute(all_oracles()[name])
    order = [d[0] for d in result.description]
    assert got == sorted(repr(tuple(_plain(row[order.index(c)]) for c in columns)) for row in result.fetchall())
