"""Translation to English, and the detectors of what chat models do wrong with it."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: A word-by-word stand-in where no model is at hand.
LEXICON = {
    "de": {"der": "the", "die": "the", "das": "the", "und": "and", "mit": "with", "von": "of", "nicht": "not", "ist": "is"},
    "es": {"el": "the", "los": "the", "las": "the", "y": "and", "para": "for", "una": "a", "del": "of"},
    "fr": {"le": "the", "les": "the", "et": "and", "pour": "for", "une": "a", "du": "of", "est": "is"},
}


def _looked_up(words: Column) -> Callable[[Column], Column]:
    return lambda w: F.coalesce(F.try_element_at(words, w), w)


class LexiconTranslator:
    """Word-by-word and native; languages outside the lexicon have no translation."""

    def __init__(self, lexicon: dict[str, dict[str, str]] = LEXICON):
        self.lexicon = lexicon

    def translate(self, rows: DataFrame, text: str, lang: str) -> DataFrame:
        words = {code: F.create_map(*[F.lit(x) for kv in m.items() for x in kv]) for code, m in self.lexicon.items()}
        out: Column = F.lit(None).cast("string")
        for code, m in words.items():
            done = F.array_join(F.transform(F.split(F.col(text), " "), _looked_up(m)), " ")
            out = F.when(F.col(lang) == code, done).otherwise(out)
        return rows.withColumn("desc_en", out)


class ModelTranslator:
    """A model behind ``make``: once a worker, it gives a function from (texts, languages) to English texts."""

    def __init__(self, make: Callable[[], Callable[[list[str], list[str]], list[str | None]]]):
        self.make = make

    def translate(self, rows: DataFrame, text: str, lang: str) -> DataFrame:
        make, schema = self.make, f"{', '.join(f'`{f.name}` {f.dataType.simpleString()}' for f in rows.schema)}, desc_en string"

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            model = make()
            for batch in batches:
                done = model(batch.column(text).to_pylist(), batch.column(lang).to_pylist())
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(done, pa.string())], [*batch.schema.names, "desc_en"])

        return rows.mapInArrow(run, schema)


def translate(rows: DataFrame, translator, text: str = "desc", lang: str = "desc_lang") -> DataFrame:
    """Adds desc_en and translate_status; English rows never reach the translator."""
    english = rows.where(F.col(lang) == "en").withColumn("desc_en", F.col(text)).withColumn("translate_status", F.lit("original"))
    foreign = translator.translate(rows.where(~F.col(lang).eqNullSafe("en")), text, lang)
    return english.unionByName(foreign.withColumn("translate_status", F.when(F.col("desc_en").isNull(), "no_model").otherwise("translated")))


def defects(source: Column, done: Column) -> dict[str, Column]:
    """What a chat model may have added or changed."""
    lines = lambda c: F.length(c) - F.length(F.replace(c, F.lit("\n"), F.lit("")))
    digits = lambda c: F.regexp_replace(c, "[^0-9]", "")
    return {
        "preamble": F.rlike(done, F.lit(r"(?i)^(the text is in|here is|here's|sure|translation)")),
        "layout": lines(source) != lines(done),
        "digits": digits(source) != digits(done),
        "length": (F.length(done) > 1.5 * F.length(source)) | (F.length(done) < 0.5 * F.length(source)),
    }
