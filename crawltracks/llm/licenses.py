"""Operator 4: licence scan by diagonal voting, with built-in functions only.

Rolling word grams of all texts (of two words; of four for templates of more than ``LONG`` words) that
are a gram of some template are joined to the templates' grams, so by their words; a hit votes for the diagonal
(position in text minus position in template). Neighbouring diagonals, at most ``DRIFT`` apart, are merged to
bands, as a word more or less moves the rest of a match by one. A band is verified as a span: it has to hold a
``share`` of the template's own positions, each counted once, on not many more words than the template has.
A diagonal with all positions of a base phrase is an exact place of it.

Cases: a null text has no words; every row has a row in the result, and rows that repeat an id are
scanned apart (those with the same text once); rows without an id are as others; spans that tie are listed each; an
empty table gives an empty table; other columns are not looked at. Very long texts are one array of words in one row.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Base phrases and their labels.
BASE = {
    "cc by": "cc-by",
    "general public license": "gpl",
    "all rights reserved": "reserved",
}
#: Templates of our own: statements that name a licence.
TEMPLATES = {
    "licensed under the gnu general public license version 3": "gpl-3",
    "released under the mit license": "mit",
    "licensed under the apache license version 2 0": "apache-2",
    "licensed under cc by nc 4 0": "cc-by-nc-4",
    "licensed under cc by sa 4 0": "cc-by-sa-4",
    "redistribution and use in source and binary forms with or without modification are permitted": "bsd",
    "dedicated to the public domain": "public-domain",
    "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files": "mit",
    "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software": "mit",
    "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis": "apache-2",
    "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation": "gpl",
    "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer": "bsd",
    "this is free and unencumbered software released into the public domain": "public-domain",
    "this work is licensed under a creative commons attribution": "cc-by",
}
SHARE = 0.75
DRIFT = 1
#: Templates of more words have grams of four words, shorter ones of two.
LONG = 12
#: A span has at most so many times the words of its template.
STRETCH = 1.25
SEPARATOR = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def grams_of(base: dict[str, str], templates: dict[str, str]) -> list[tuple]:
    """(template, label, is_base, at, k, words, grams, most) of every gram of every template; ``most`` words a span has at most."""
    out = []
    for kind, group in ((True, base), (False, templates)):
        for text, label in group.items():
            w = text.split()
            k = 4 if len(w) > LONG else 2
            out += [(text, label, kind, i, k, w[i : i + k], len(w) - k + 1, math.ceil(STRETCH * len(w))) for i in range(len(w) - k + 1)]
    return out


def words(text: Column) -> Column:
    """Words of a text: runs of letters, digits and anything beyond ASCII, in lower case.

    lower() also folds capitals beyond ASCII; no such word can equal a word of a template.
    """
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), SEPARATOR), lambda w: w != "")


def _positions(k: int, grams: list[list[str]]) -> Column:
    """Where ``k`` words of ``w`` in a row are one of ``grams``."""
    whole, heads = sorted({" ".join(g) for g in grams}), sorted({g[0] for g in grams})
    starts = F.when(F.size("w") >= k, F.sequence(F.lit(0), F.size("w") - k)).otherwise(F.array().cast("array<int>"))
    return F.filter(starts, lambda i: F.get("w", i).isin(heads) & F.concat_ws(" ", *[F.get("w", i + j) for j in range(k)]).isin(whole))


def _gram_at(hit, k: int):
    return lambda i: hit(i, F.slice("w", i + 1, F.lit(k)))


def scan_licenses(docs: DataFrame, base: dict[str, str] | None = None, templates: dict[str, str] | None = None, share: float = SHARE) -> DataFrame:
    """One row per document: number of words, places of base phrases, labels, spans (label:first-last word) and score."""
    spark = docs.sparkSession
    grams = grams_of(BASE if base is None else base, TEMPLATES if templates is None else templates)
    known = spark.createDataFrame(grams, "template string, label string, is_base boolean, at int, k int, gram array<string>, grams int, most int")
    sizes = sorted({g[4] for g in grams})

    text = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    split = text.select("doc_id", F.xxhash64("text").alias("version"), words(F.col("text")).alias("w")).withColumn("n_words", F.size("w").cast("long"))
    # one hit that stands for the row itself, then the few positions whose words some template has
    hit = lambda pos, gram: F.struct(pos.cast("long").alias("pos"), gram.alias("gram"))
    every = [F.array(hit(F.lit(-1), F.lit(None).cast("array<string>")))]
    for k in sizes:
        every.append(F.transform(_positions(k, [g[5] for g in grams if g[4] == k]), _gram_at(hit, k)))
    placed = split.select("doc_id", "version", "n_words", F.explode(F.concat(*every)).alias("hit")).select("doc_id", "version", "n_words", "hit.pos", "hit.gram")
    hits = placed.join(F.broadcast(known), "gram", "left").where("pos < 0 or label is not null")
    row = ["doc_id", "version", "n_words"]
    copies = F.count(F.when(F.col("pos") < 0, 1)).over(Window.partitionBy("doc_id", "version"))
    hits = hits.withColumn("copies", copies).withColumn("diagonal", F.col("pos") - F.col("at"))
    votes = hits.groupBy(*row, "copies", "template", "label", "is_base", "grams", "k", "most", "diagonal").agg(F.collect_set("at").alias("ats"), F.min("pos").alias("low"), F.max("pos").alias("high"))
    along = Window.partitionBy("doc_id", "version", "template", "is_base").orderBy("diagonal")
    new = F.coalesce((F.col("diagonal") - F.lag("diagonal").over(along) > DRIFT).cast("int"), F.lit(1))
    merged = votes.withColumn("new", new).withColumn("band", F.sum("new").over(along))
    full = F.col("is_base") & (F.size("ats") == F.col("grams"))
    bands = merged.groupBy(*row, "copies", "template", "label", "is_base", "grams", "k", "most", "band").agg(
        F.size(F.array_distinct(F.flatten(F.collect_list("ats")))).alias("votes"),  # at most the template's positions, a band's diagonals times
        F.count_if(full).alias("places"),
        F.min(F.when(full, F.col("diagonal"))).alias("first"),
        F.max(F.when(full, F.col("diagonal"))).alias("last"),
        F.min("low").alias("low"),
        (F.max("high") + F.col("k") - 1).alias("high"),
    )
    part = F.col("votes") / F.col("grams")
    is_base = F.col("is_base") & (F.col("places") > 0)
    own = ~F.col("is_base") & (part >= share) & (F.col("high") - F.col("low") < F.col("most"))
    joined = lambda keep, what: F.array_join(F.array_sort(F.collect_set(F.when(keep, what))), ",")
    span = F.concat("label", F.lit(":"), F.col("low").cast("string"), F.lit("-"), F.col("high").cast("string"))
    scanned = bands.groupBy(*row, "copies").agg(
        F.sum(F.coalesce("places", F.lit(0))).cast("long").alias("n_base"),
        F.min("first").alias("first_word"),
        F.max("last").alias("last_word"),
        joined(is_base, F.col("label")).alias("base_labels"),
        joined(is_base | own, F.col("label")).alias("labels"),
        joined(own, span).alias("spans"),
        F.coalesce(F.max(F.when(is_base, F.lit(1.0)).when(~F.col("is_base"), part)), F.lit(0.0)).alias("score"),
    )
    return scanned.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).drop("version", "copies", "copy")
