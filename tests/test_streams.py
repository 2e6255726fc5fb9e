"""Streams give what the batch operators give."""

import pandas as pd
import pytest
from pyspark.sql import functions as F

from crawltracks.operators import gates
from crawltracks.operators.discover import discover
from crawltracks.sources import fixtures as fx
from crawltracks.streaming import jobs


@pytest.fixture
def stream(spark, tmp_path):
    def make(df, parts=3):
        path = str(tmp_path / "in")
        df.repartition(parts).write.parquet(path)
        return jobs.file_stream(spark, path, df.schema, 1)

    return make


def test_discovery(spark, small, tmp_path, stream):
    index = fx.crawl_index(spark, small)
    jobs.run_once(jobs.discover_stream(stream(index)), str(tmp_path / "out"), str(tmp_path / "cp"))
    assert spark.read.parquet(str(tmp_path / "out")).count() == discover(index, "xhtml", "html").count()


def test_dedup(spark, small, tmp_path, stream):
    docs = fx.table(spark, small, "documents").select("doc_id", "text")
    jobs.run_once(jobs.dedup_content_stream(stream(docs)), str(tmp_path / "out"), str(tmp_path / "cp"))
    assert spark.read.parquet(str(tmp_path / "out")).count() == docs.select("text").distinct().count() == 189


def test_language_gate(spark, tmp_path, stream):
    rows = spark.createDataFrame(pd.DataFrame({"doc_id": range(20), "lang": ["a"] * 9 + ["b"] * 6 + ["c"] * 5}))
    jobs.run_once(jobs.language_support_stream(stream(rows)), str(tmp_path / "out"), str(tmp_path / "cp"))
    got = sorted(r["doc_id"] for r in spark.read.parquet(str(tmp_path / "out")).collect())
    assert got == sorted(r["doc_id"] for r in gates.language_support(rows).collect())


def test_windows_and_sessions(spark, small, tmp_path, stream):
    events = fx.table(spark, small, "events")
    s = stream(events)
    jobs.run_once(jobs.counts_per_window(s, late="100 days"), "win", str(tmp_path / "cp"), "complete")
    assert spark.table("win").agg(F.sum("n")).first()[0] == events.count()
    jobs.run_once(jobs.sessions(s, late="100 days"), "sess", str(tmp_path / "cp2"), "complete")
    batch = events.groupBy("user_id", F.session_window("ts", "6 hours")).count().count()
    assert spark.table("sess").count() == batch
