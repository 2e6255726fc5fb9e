"""Streaming twins of the batch operators: new releases as a file stream, deduplication, windows, sessions.

``events.ts`` is read without a time zone; watermarks need an instant, so it is cast under the
session's time zone (UTC). Every function maps a streaming DataFrame to a streaming DataFrame.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from crawltracks.config import DEFAULT, PipelineConfig
from crawltracks.operators.discover import discover
from crawltracks.operators.judge import Judge


def file_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 64) -> DataFrame:
    """New Parquet files of a folder as they arrive; the schema is given, never inferred."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def discover_stream(index: DataFrame, cfg: PipelineConfig = DEFAULT) -> DataFrame:
    return discover(index, cfg.mime_token, cfg.ext)


def dedup_content_stream(rows: DataFrame, text: str = "text", event_time: str | None = None, keep_for: str = "30 days") -> DataFrame:
    """First row of each content; with an event time the state is dropped after ``keep_for``."""
    keyed = rows.withColumn("content_sha", F.sha2(F.col(text), 256))
    if event_time is None:
        return keyed.dropDuplicates(["content_sha"])
    return keyed.withWatermark(event_time, keep_for).dropDuplicatesWithinWatermark(["content_sha"])


def timed(events: DataFrame, late: str = "1 day") -> DataFrame:
    """Events with a watermark on ``at``."""
    return events.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", late)


def counts_per_window(events: DataFrame, size: str = "1 day", slide: str | None = None, late: str = "1 day") -> DataFrame:
    w = F.window("at", size, slide) if slide else F.window("at", size)
    return timed(events, late).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select("w.start", "event_type", "n")


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "1 day") -> DataFrame:
    """Points of a user between gaps: the segments of a recording."""
    w = F.session_window("at", gap)
    return timed(events, late).groupBy("user_id", w.alias("w")).agg(F.count("*").alias("n")).select("user_id", "w.start", "w.end", "n")


def language_support_stream(rows: DataFrame, more_than: int = DEFAULT.lang_more_than) -> DataFrame:
    """Rows (doc_id, lang) of a language are held until it has enough, then all come out: the batch gate is monotone.

    A language's state is its at most ``more_than`` waiting ids, so state is bounded by languages.
    """

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        opened, waiting = state.get if state.exists else (False, [])
        ids = [int(i) for b in batches for i in b["doc_id"]]
        held = list(waiting) + ids
        opened = opened or len(held) > more_than
        if opened:
            state.update((True, []))
            if held:
                yield pd.DataFrame({"doc_id": held, "lang": [key[0]] * len(held)})
        else:
            state.update((False, held))

    return rows.select("doc_id", "lang").groupBy("lang").applyInPandasWithState(step, "doc_id long, lang string", "opened boolean, waiting array<bigint>", "append", GroupStateTimeout.NoTimeout)


def judged_stream(rows: DataFrame, judge: Judge, text: str, default: bool) -> DataFrame:
    """A stream joined to static answers."""
    return judge.verdicts(rows, text, default)


def run_once(df: DataFrame, target: str, checkpoint: str, mode: str = "append") -> None:
    """Write everything that is there to ``target`` (Parquet, or a memory table by name) and stop."""
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    query = writer.format("parquet").start(target) if "/" in target else writer.format("memory").queryName(target).start()
    query.awaitTermination()


def keep_funnel(df: DataFrame, flags: list[str], target: str, checkpoint: str) -> None:
    """Per micro-batch counts of each flag, appended to ``target`` with the batch's number (safe to repeat)."""

    def write(batch: DataFrame, number: int) -> None:
        counts = batch.agg(F.count("*").alias("rows"), *[F.count_if(F.col(f)).alias(f) for f in flags]).withColumn("batch", F.lit(number))
        counts.write.mode("overwrite").parquet(f"{target}/batch={number}")

    df.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
