"""Byte-range fetch of records out of archives, its accounting and its baseline."""

from __future__ import annotations

import gzip
import time
import urllib.request
import uuid
import zlib
from collections.abc import Iterator
from typing import Protocol

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


class RangeReader(Protocol):
    def read(self, archive: str, offset: int, length: int) -> bytes: ...


class FileRangeReader:
    """Archives as files under a root (a path or URI of any file system that Arrow knows) that every executor reaches."""

    def __init__(self, root: str):
        self.root = root

    def read(self, archive: str, offset: int, length: int) -> bytes:
        files, at = pafs.FileSystem.from_uri(f"{self.root}/{archive}")
        with files.open_input_file(at) as f:
            return f.read_at(length, offset)


class FlakyReader:
    """A reader that fails at some records, for trying what follows; ``bad`` has (archive, offset) pairs."""

    def __init__(self, reader: RangeReader, bad: frozenset[tuple[str, int]]):
        self.reader, self.bad = reader, bad

    def read(self, archive: str, offset: int, length: int) -> bytes:
        if (archive, offset) in self.bad:
            raise OSError("not served")
        return self.reader.read(archive, offset, length)


def write_archives(archives: DataFrame, root: str) -> None:
    """One file for each row (archive, body) under ``root``; a file appears whole or not at all."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, top = pafs.FileSystem.from_uri(root)
        files.create_dir(top)
        for batch in batches:
            for r in batch.to_pylist():
                part = f"{top}/{r['archive']}.{uuid.uuid4().hex}"
                with files.open_output_stream(part) as f:
                    f.write(r["body"])
                files.move(part, f"{top}/{r['archive']}")
            yield batch.select(["archive"])

    archives.select(F.col("archive").cast("string").alias("archive"), "body").mapInArrow(write, "archive string").count()


class HttpRangeReader:
    """Archives behind a web server that serves byte ranges."""

    def __init__(self, base_url: str, timeout_s: float = 60.0):
        self.base_url, self.timeout_s = base_url.rstrip("/"), timeout_s

    def read(self, archive: str, offset: int, length: int) -> bytes:
        if length == 0:
            return b""
        request = urllib.request.Request(f"{self.base_url}/{archive}", headers={"Range": range_header(offset, length)})
        with urllib.request.urlopen(request, timeout=self.timeout_s) as answer:
            if answer.status != 206:
                raise OSError(f"range not served: status {answer.status}")
            return answer.read()


def range_header(offset: int, length: int) -> str:
    """The inclusive range of ``length`` bytes from ``offset``."""
    if offset < 0 or length < 1:
        raise ValueError("a range has at least one byte")
    return f"bytes={offset}-{offset + length - 1}"


def decode_record(data: bytes) -> str | None:
    """Text of a stored record: unpacked where it is compressed; None where it is no UTF-8."""
    try:
        if data[:2] == b"\x1f\x8b":
            data = gzip.decompress(data)
        elif data[:1] == b"\x78":
            data = zlib.decompress(data)
        return data.decode("utf-8")
    except (OSError, EOFError, zlib.error, UnicodeDecodeError):
        return None


def coalesce_ranges(pointers: DataFrame, gap: int) -> DataFrame:
    """Merge ranges of an archive that lie at most ``gap`` bytes apart: adds island, read_from and read_to."""
    w = Window.partitionBy("archive").orderBy("offset", "length")
    reach = F.max(F.col("offset") + F.col("length")).over(w.rowsBetween(Window.unboundedPreceding, -1))
    new = F.coalesce((F.col("offset") > reach + gap).cast("int"), F.lit(1))
    marked = pointers.withColumn("new", new).withColumn("island", F.sum("new").over(w)).drop("new")
    whole = Window.partitionBy("archive", "island")
    return marked.withColumn("read_from", F.min("offset").over(whole)).withColumn("read_to", F.max(F.col("offset") + F.col("length")).over(whole))


def fetch_ranges(pointers: DataFrame, reader: RangeReader, partitions: int, max_attempts: int = 3, pause_s: float = 0.5, gap: int | None = None) -> DataFrame:
    """Content of each pointer row (url, archive, offset, length) with fetch_status and attempts.

    Rows are dealt by archive and read in order of offset; with ``gap``, near ranges are one
    request. A record that fails is kept with its status, so a later run can retry it.
    """
    rows = pointers.select("url", F.col("archive").cast("string").alias("archive"), "offset", "length")
    rows = coalesce_ranges(rows, -1 if gap is None else gap)
    if gap is None:  # every record is a request of its own
        rows = rows.withColumn("read_from", F.col("offset")).withColumn("read_to", F.col("offset") + F.col("length"))
    rows = rows.select("url", "archive", "offset", "length", "read_from", "read_to")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple | None = None
        for batch in batches:
            out = []
            for r in batch.to_pylist():
                key, attempts, error = (r["archive"], r["read_from"], r["read_to"]), 0, None
                if held is None or held[0] != key:
                    held = None
                    while attempts < max_attempts and held is None:
                        attempts += 1
                        try:
                            data = reader.read(r["archive"], r["read_from"], r["read_to"] - r["read_from"])
                            if len(data) != r["read_to"] - r["read_from"]:
                                raise OSError("short answer")
                            held = (key, data)
                        except OSError as e:
                            error = str(e)
                            if attempts < max_attempts:
                                time.sleep(pause_s * 2 ** (attempts - 1))
                content = None
                if held is not None:
                    at = r["offset"] - r["read_from"]
                    content = decode_record(held[1][at : at + r["length"]])
                status = "ok" if content is not None else "failed" if held is None else "undecodable"
                out.append({k: r[k] for k in ("url", "archive", "offset", "length")} | {"content": content, "fetch_status": status, "attempts": attempts, "error": error})
            yield pa.RecordBatch.from_pylist(out, _FETCHED)

    return rows.repartition(partitions, "archive").sortWithinPartitions("archive", "offset").mapInArrow(run, FETCHED)


FETCHED = "url string, archive string, offset long, length long, content string, fetch_status string, attempts int, error string"
_FETCHED = pa.schema(
    [("url", pa.string()), ("archive", pa.string()), ("offset", pa.int64()), ("length", pa.int64()), ("content", pa.string()), ("fetch_status", pa.string()), ("attempts", pa.int32()), ("error", pa.string())]
)


def cut_ranges(pointers: DataFrame, archives: DataFrame) -> DataFrame:
    """The baseline: read every touched archive whole, then cut the records out of it."""
    return pointers.join(archives, "archive").withColumn("content", F.decode(F.substring(F.col("body"), (F.col("offset") + 1).cast("int"), F.col("length").cast("int")), "UTF-8")).drop("body")


def fetch_stats(fetched: DataFrame, ok: Column) -> DataFrame:
    return fetched.agg(F.count("*").alias("identified"), F.count_if(ok).alias("fetched"), F.round(F.count_if(ok) / F.count("*"), 6).alias("success_rate"))


def transfer_model(index: DataFrame, picked: Column) -> DataFrame:
    """Bytes of the picked records against those of all records."""
    part = F.sum(F.when(picked, F.col("length")).otherwise(0)).cast("long")
    whole = F.sum("length").cast("long")
    return index.agg(part.alias("range_bytes"), whole.alias("archive_bytes"), F.round(part / whole, 6).alias("share"))
