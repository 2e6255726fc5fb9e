"""From raw documents to packed training sequences, by the training-data operators.

Each stage works on all that its predecessor kept, is written as Parquet and read again:
toxic documents go; one document of each class of near-duplicates stays; repeated word
windows are cut out of the texts; documents that hold benchmark passages go; the rest is
tokenised and packed. SQL cannot express the first stage, so there is no oracle.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from crawltracks.llm.common import cut, table
from crawltracks.llm.decontamination import drop_contaminated
from crawltracks.llm.jaccard import one_of_each_class
from crawltracks.llm.packing import pack
from crawltracks.llm.queries import public_tokenizer
from crawltracks.llm.substrings import shorten
from crawltracks.llm.toxicity import fit_toxicity
from crawltracks.llm.training import keep_documents

TOXIC_FROM = 0.5


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = fit_toxicity(docs, table(spark, sf_dir, "labels"))
    return keep_documents(docs, model, TOXIC_FROM)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return one_of_each_class(docs)


def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The texts are those left (words joined by one space)."""
    return shorten(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return drop_contaminated(docs, table(spark, sf_dir, "benchmark")).select(docs.columns)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack(docs, public_tokenizer())


STAGES = [
    ("toxicity", toxicity),
    ("jaccard", near_duplicates),
    ("substring", substring_dedup),
    ("decontamination", decontamination),
    ("packing", packing),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The packed pieces of the whole documents table."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
