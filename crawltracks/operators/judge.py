"""Yes/no gates over texts: label, rule and model judges with a defined answer in doubt."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Protocol

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crawltracks.functions.text import CARD_PATTERN, EMAIL, QUAD_PATTERN, TELEPHONE, URL, parse_verdict

#: Our own wording: criterion, the two allowed answers, the answer in doubt, the fenced text.
QUALITY_QUESTION = "Is the fenced text a useful account of a walk, ride, run or route that tells a reader what to expect? Answer True or False only; answer False when it is hard to say.\n<<<\n{text}\n>>>"
PRIVACY_QUESTION = "Does the fenced text name or locate a private person, for instance by name, address or contact? Answer True or False only; answer True when it is hard to say.\n<<<\n{text}\n>>>"


class Judge(Protocol):
    def verdicts(self, rows: DataFrame, text_col: str, default: bool) -> DataFrame:
        """``rows`` with a boolean column ``verdict`` that is never NULL."""
        ...


class LabelJudge:
    """Known answers by id; no answer is doubt."""

    def __init__(self, labels: DataFrame, label: str, id_col: str = "doc_id"):
        self.labels, self.label, self.id_col = labels, label, id_col

    def verdicts(self, rows: DataFrame, text_col: str, default: bool) -> DataFrame:
        known = self.labels.groupBy(F.col(self.id_col).alias("_id")).agg(F.max(self.label).alias("_label"))
        joined = rows.join(known, rows[self.id_col] == F.col("_id"), "left")
        return joined.withColumn("verdict", F.coalesce(F.col("_label") == 1, F.lit(default))).drop("_id", "_label")


class RuleJudge:
    """A native predicate; NULL is doubt."""

    def __init__(self, rule: Callable[[Column], Column]):
        self.rule = rule

    def verdicts(self, rows: DataFrame, text_col: str, default: bool) -> DataFrame:
        return rows.withColumn("verdict", F.coalesce(self.rule(F.col(text_col)), F.lit(default)))


class ModelJudge:
    """A model behind ``make``: called once a worker, it gives a function from prompts to replies.

    Each distinct text is asked once; ``cache`` (key, raw) holds replies of earlier runs.
    """

    def __init__(self, make: Callable[[], Callable[[list[str]], list[str]]], question: str, cache: DataFrame | None = None):
        self.make, self.question, self.cache = make, question, cache

    def replies(self, texts: DataFrame) -> DataFrame:
        make, question = self.make, self.question

        def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            model = make()
            for batch in batches:
                raw = model([question.format(text=t or "") for t in batch.column("text").to_pylist()])
                yield pa.RecordBatch.from_arrays([batch.column("key"), pa.array(raw, pa.string())], ["key", "raw"])

        return texts.mapInArrow(ask, "key string, raw string")

    def verdicts(self, rows: DataFrame, text_col: str, default: bool) -> DataFrame:
        keyed = rows.withColumn("_key", F.sha2(F.coalesce(F.col(text_col), F.lit("")), 256))
        wanted = keyed.groupBy(F.col("_key").alias("key")).agg(F.first(text_col).alias("text"))
        known = self.cache
        missing = wanted if known is None else wanted.join(known, "key", "left_anti")
        raw = self.replies(missing) if known is None else self.replies(missing).unionByName(known.select("key", "raw"))
        joined = keyed.join(raw, F.col("_key") == F.col("key"), "left")
        return joined.withColumn("verdict", parse_verdict(F.coalesce("raw", F.lit("")), default)).drop("_key", "key", "raw")


def judge_gate(rows: DataFrame, text_col: str, judge: Judge, default: bool, keep: bool) -> DataFrame:
    """Rows whose verdict is ``keep``."""
    return judge.verdicts(rows, text_col, default).where(F.col("verdict") == keep).drop("verdict")


def letter_share(text: Column) -> Column:
    return F.length(F.regexp_replace(text, r"[^\p{L}]", "")) / F.nullif(F.length(text), F.lit(0))


def reads_like_prose(text: Column) -> Column:
    """Long enough, mostly letters, no tables and no runs of marks."""
    return (F.length(text) >= 80) & (letter_share(text) >= 0.7) & ~F.rlike(text, F.lit(r"\||[#$%&*]{3}"))


def looks_private(text: Column) -> Column:
    """A mask token, a card number or a dotted quad stands in the text."""
    return text.contains(EMAIL) | text.contains(TELEPHONE) | text.contains(URL) | F.rlike(text, F.lit(CARD_PATTERN)) | F.rlike(text, F.lit(QUAD_PATTERN))


def judge_quality(verdicts: DataFrame, truth: str) -> DataFrame:
    """Counts of verdict against truth (a boolean column), with precision, recall and F1."""
    v, t = F.col("verdict"), F.col(truth)
    c = verdicts.agg(F.count_if(v & t).alias("tp"), F.count_if(v & ~t).alias("fp"), F.count_if(~v & t).alias("fn"), F.count_if(~v & ~t).alias("tn"))
    p, r = F.col("tp") / F.nullif(F.col("tp") + F.col("fp"), F.lit(0)), F.col("tp") / F.nullif(F.col("tp") + F.col("fn"), F.lit(0))
    return c.select("*", F.round(p, 6).alias("precision"), F.round(r, 6).alias("recall"), F.round(2 * p * r / (p + r), 6).alias("f1"))
