"""All registered queries of the engine itself against their SQL, on the smallest tables."""

import duckdb
import pytest

from crawltracks.plans import all_oracles, all_queries

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from read_parquet('{small}/{t}.parquet')")
    return con


def _plain(v):
    return None if v is None or v != v else f"{float(v):.9g}" if isinstance(v, float) or type(v).__name__ == "Decimal" else v


NAMES = sorted(all_oracles())


@pytest.mark.parametrize("name", NAMES)
def test_matches_sql(spark, small, duck, name):
    df = all_queries()[name](spark, small)
    columns = sorted(df.columns)
    got = sorted(repr(tuple(_plain(r[c]) for c in columns)) for r in df.collect())
    result = duck.execute(all_oracles()[name])
    order = [d[0] for d in result.description]
    assert sorted(order) == columns
    want = sorted(repr(tuple(_plain(row[order.index(c)]) for c in columns)) for row in result.fetchall())
    assert got == want


def test_queries_without_sql_run(spark, small):
    for name in sorted(set(all_queries()) - set(all_oracles())):
        assert all_queries()[name](spark, small).count() >= 0, name


def test_entry(spark):
    import __spark_entry__ as e

    rows = {r["stage"]: r["n_out"] for r in e.entry(spark).collect()}
    assert rows == {"unique_url": 16, "unique_content": 15, "parsed": 15, "single_track": 14, "length": 11, "density": 7, "description": 4, "quality": 1, "privacy": 1, "language": 0}
