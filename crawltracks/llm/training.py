"""What the two text models share: bounded labelled samples, an optimiser and batch scoring."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crawltracks.llm.common import slices, texts_of


def held_out() -> F.Column:
    """True for the fifth of all ids whose labels are never learnt from."""
    return F.crc32(F.encode(F.col("doc_id").cast("string"), "UTF-8")) % 5 == 0


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, per_class: int, max_bytes: int) -> tuple[list[str], np.ndarray]:
    """At most ``per_class`` texts of each label, those of least hashed id; held-out ids are left out.

    Texts are kept whole up to ``max_bytes`` of all of them; the sample is for learning only.
    """
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y")).where("y in (0, 1)")
    known = known.groupBy("doc_id").agg(F.max("y").alias("y")).where(~held_out())
    order = F.xxhash64(F.col("doc_id"), F.lit(17))
    ids = [known.where(F.col("y") == y).orderBy(order, "doc_id").limit(per_class) for y in (0, 1)]
    rows = texts_of(docs).join(F.broadcast(ids[0].unionByName(ids[1])), "doc_id").orderBy(F.xxhash64(F.col("doc_id"), F.lit(17)), "doc_id").limit(2 * per_class)
    texts, y, held = [], [], 0
    for r in rows.toLocalIterator():
        held += len(r["text"])
        if held > max_bytes and texts:
            break
        texts.append(r["text"])
        y.append(r["y"])
    return texts, np.asarray(y, np.float32)


class Adam:
    """Adaptive moments over a dictionary of arrays."""

    def __init__(self, params: dict[str, np.ndarray], rate: float):
        self.params, self.rate, self.t = params, rate, 0
        self.m = {k: np.zeros_like(v) for k, v in params.items()}
        self.v = {k: np.zeros_like(v) for k, v in params.items()}

    def step(self, grads: dict[str, np.ndarray]) -> None:
        self.t += 1
        for k, g in grads.items():
            self.m[k] += 0.1 * (g - self.m[k])
            self.v[k] += 0.001 * (g * g - self.v[k])
            m, v = self.m[k] / (1 - 0.9**self.t), self.v[k] / (1 - 0.999**self.t)
            self.params[k] -= self.rate * m / (np.sqrt(v) + 1e-8)


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def score_documents(docs: DataFrame, score: Callable[[pa.Array], np.ndarray], slice_bytes: int = 1 << 20) -> DataFrame:
    """doc_id and the score of every whole text; ``score`` maps a column of texts to probabilities."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, limit=slice_bytes):
            got = np.asarray(score(batch.column("text")), np.float64)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(got, pa.float64())], ["doc_id", "score"])

    return texts_of(docs).mapInArrow(run, "doc_id long, score double")


def keep_documents(docs: DataFrame, score: Callable[[pa.Array], np.ndarray], below: float, slice_bytes: int = 1 << 20) -> DataFrame:
    """``docs``, all columns, without the rows whose whole text scores ``below`` or more."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, limit=slice_bytes):
            yield batch.filter(pa.array(np.asarray(score(batch.column("text"))) < below))

    return docs.mapInArrow(run, docs.schema)
