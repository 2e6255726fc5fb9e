"""What the operators share: input reading, Arrow slicing and tables cut from their lineage."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Texts are handled in slices of about so many bytes, which bounds a worker's memory.
SLICE_BYTES = 4 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``. Where it is unset a local run gets a folder of its own; a cluster has to name one."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if not held.isDefined() and not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        named = held.get() if held.isDefined() else tempfile.mkdtemp(prefix="crawltracks-")
        spark.conf.set("spark.checkpoint.dir", named)
    return named


def stored(df: DataFrame, name: str = "cut", root: str | None = None) -> str:
    """Write ``df`` as a table under ``root`` (the shared folder, if not given); returns its path."""
    path = f"{(root or shared_dir(df.sparkSession)).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return path


def cut(df: DataFrame, name: str = "cut") -> DataFrame:
    """Write ``df`` as a table in the shared folder and read it again: a lineage cut that outlives executors."""
    return df.sparkSession.read.schema(df.schema).parquet(stored(df, name))


def drop_stored(spark: SparkSession, *paths: str) -> None:
    """Delete tables made by :func:`stored`, once nothing reads them any more."""
    for path in paths:
        at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def drop_cut(df: DataFrame) -> None:
    """As :func:`drop_stored`, for the table that :func:`cut` read."""
    drop_stored(df.sparkSession, *{f.rpartition("/")[0] for f in df.inputFiles()})


def buckets(spark: SparkSession, times: int = 1) -> int:
    """Number of hash buckets; follows the session's shuffle partitions, which are sized to the data."""
    return max(8, times * int(spark.conf.get("spark.sql.shuffle.partitions")))


def slices(batches: Iterator[pa.RecordBatch], column: str = "text", limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Arrow batches cut so that the texts of each hold about ``limit`` bytes (a longer text stands alone)."""
    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
        part = np.cumsum(sizes, dtype=np.int64) // limit
        edges = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), batch.num_rows]
        for a, b in zip(edges, edges[1:]):
            yield batch.slice(a, b - a)


#: Stands for a missing id where ids are ordered or joined; results have null again.
NO_ID = -(1 << 63)


def texts_of(docs: DataFrame, no_id: int | None = None) -> DataFrame:
    """Just the id (null: ``no_id``) and the text (null: empty), whatever other columns there are."""
    return docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(no_id).cast("long")).alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))


def with_null_ids(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.when(F.col(c) != NO_ID, F.col(c)) for c in columns})
