"""Operator 5: bottom-k sketches of word shingles, with built-in functions only.

A sketch is the sorted array of the k least 64-bit hashes of a text's five-word shingles.
Sketches merge (the k least of both), and estimate resemblance, containment and the number of
distinct shingles. Equal texts have equal sketches.

Cases: a null or empty text has an empty sketch; a text of one to four words has its whole
word sequence as one shingle; two empty sketches are alike (1), an empty and another are not
(0); rows that repeat an id follow one another in the order of their texts; rows without an id
come first, as if theirs were the least; other columns are
not looked at; an empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from crawltracks.llm.common import NO_ID, buckets, texts_of, with_null_ids

K = 128
SHINGLE = 5
_EMPTY = "array<bigint>"


def with_sketch(df: DataFrame, text: str, name: str, k: int = K, size: int = SHINGLE) -> DataFrame:
    """Add the sketch of column ``text`` as column ``name``."""
    w, h = f"{name}_words", f"{name}_hashes"
    n = F.size(w)
    df = df.withColumn(w, F.filter(F.split(text, r"[\x20\x09-\x0D]+"), lambda x: x != ""))
    shingles = F.transform(F.sequence(F.lit(0), n - size), lambda i: F.xxhash64(*[F.get(w, i + j) for j in range(size)]))
    hashes = F.when(n >= size, shingles).when(n > 0, F.array(F.xxhash64(F.array_join(w, " ")))).otherwise(F.array().cast(_EMPTY))
    df = df.withColumn(h, hashes)
    return df.withColumn(name, F.slice(F.sort_array(F.array_distinct(h)), 1, k)).drop(w, h)


def merge(a: Column, b: Column, k: int = K) -> Column:
    """The sketch of both parts together."""
    return F.slice(F.sort_array(F.array_union(a, b)), 1, k)


def merge_all(sketch: str, k: int = K) -> Column:
    """Aggregate: the sketch of all rows of a group; partial sets stay within distinct hashes of sketches."""
    return F.slice(F.sort_array(F.array_distinct(F.flatten(F.collect_set(sketch)))), 1, k)


def resemblance(a: Column, b: Column, k: int = K) -> Column:
    """Estimated Jaccard similarity of the shingle sets behind two sketches."""
    both = merge(a, b, k)
    shared = F.size(F.array_intersect(F.array_intersect(a, b), both))
    return F.when(F.size(both) == 0, F.lit(1.0)).otherwise(shared / F.size(both))


def distinct_shingles(a: Column, k: int = K) -> Column:
    """Estimated number of distinct shingles: exact below k, else from the k-th least hash."""
    reach = (F.element_at(a, -1).cast("double") + F.lit(float(1 << 63))) / F.lit(float(1 << 64))
    return F.when(F.size(a) < k, F.size(a).cast("double")).otherwise((k - 1) / reach)


def containment(a: Column, b: Column, k: int = K) -> Column:
    """Estimated part of a's shingles that b has too."""
    j = resemblance(a, b, k)
    shared = j / (1 + j) * (distinct_shingles(a, k) + distinct_shingles(b, k))
    return F.when(F.size(a) == 0, F.lit(1.0)).otherwise(F.least(shared / distinct_shingles(a, k), F.lit(1.0)))


def as_string(a: Column) -> Column:
    """All 64 bits of every hash, as 16 hexadecimal digits each, in the order of the sketch."""
    return F.array_join(F.transform(a, lambda x: F.lpad(F.hex(x), 16, "0")), "")


def from_string(text: Column) -> Column:
    """The sketch that :func:`as_string` wrote."""
    halves = lambda at, n: F.conv(F.substring(text, at, F.lit(n)), 16, 10).cast("long")
    places = F.when(F.length(text) > 0, F.sequence(F.lit(1), F.length(text), F.lit(16))).otherwise(F.array().cast("array<int>"))
    return F.transform(places, lambda at: F.shiftleft(halves(at, 8), 32).bitwiseOR(halves(at + 8, 8)))


def in_sequence(docs: DataFrame) -> DataFrame:
    """Deal documents to buckets of ascending ids; the head of each bucket goes to the one before it too.

    Adds bucket, place (order in the bucket) and extra (true for a head that is only looked at;
    the head of the first bucket closes the last). Buckets are even parts of 64 id quantiles, so
    uneven ids do not fill one bucket; the tables sent to all rows have one row a bucket.
    """
    spark = docs.sparkSession
    rows = texts_of(docs, NO_ID)
    marks = 64
    split = max(1, -(-buckets(spark, 4) // marks))
    bounds = rows.agg(F.min("doc_id"), F.percentile_approx("doc_id", [i / marks for i in range(1, marks)], 10000), F.max("doc_id")).first()
    edges = sorted({bounds[0] or 0, *(bounds[1] or []), min((bounds[2] or 0) + 1, (1 << 63) - 1)})
    known = F.array(*[F.lit(e).cast("long") for e in edges])
    band = F.greatest(F.size(F.filter(known, lambda e: e <= F.col("doc_id"))), F.lit(1))
    low, high = F.element_at(known, F.col("band")), F.element_at(known, F.least(F.col("band") + 1, F.lit(len(edges))))
    part = ((F.col("doc_id").cast("double") - low.cast("double")) / F.greatest(high.cast("double") - low.cast("double"), F.lit(1.0)) * split).cast("long")
    ids = lambda df: df.withColumn("band", band).withColumn("bucket", F.col("band") * split + F.least(part, F.lit(split - 1))).drop("band")
    heads = ids(rows.select("doc_id")).groupBy("bucket").agg(F.min("doc_id").alias("head"))
    order = Window.orderBy("bucket")
    heads = heads.withColumn("before", F.lag("bucket").over(order))
    last = F.max("bucket").over(order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    heads = heads.select("bucket", "head", F.col("before").isNull().alias("wraps"), F.coalesce("before", last).alias("before"))
    dealt = ids(rows).join(F.broadcast(heads), "bucket", "left")
    own = F.struct(F.col("bucket"), F.col("doc_id").alias("place"), F.lit(False).alias("extra"))
    other = F.struct(F.col("before").alias("bucket"), F.when(F.col("wraps"), F.lit((1 << 63) - 1)).otherwise(F.col("doc_id")).alias("place"), F.lit(True).alias("extra"))
    to = F.explode(F.when(F.col("doc_id") == F.col("head"), F.array(own, other)).otherwise(F.array(own))).alias("to")
    return dealt.select("doc_id", "text", to).select("doc_id", "text", "to.*")


def compare_with_next(docs: DataFrame, k: int = K) -> DataFrame:
    """Sketches of every text and of its edited text (second half from the next document), and their likeness."""
    along = Window.partitionBy("bucket").orderBy("place", "extra", "text")
    rows = in_sequence(docs).withColumn("next", F.lead("text").over(along))
    rows = with_sketch(rows, "text", "sketch", k).withColumn("next_sketch", F.lead("sketch").over(along)).where("not extra")
    chars = F.length("text")
    half = F.floor(chars / 2).cast("int")
    edited = F.concat(F.substring(F.col("text"), F.lit(1), chars - half), F.substring(F.col("next"), F.lit(1), half))
    rows = rows.select("doc_id", chars.cast("long").alias("n_chars"), edited.alias("edited"), "sketch", "next_sketch")
    rows = with_sketch(rows, "edited", "edited_sketch", k)
    compared = rows.select(
        "doc_id", "n_chars", "edited", "sketch", "edited_sketch",
        resemblance(F.col("sketch"), F.col("edited_sketch"), k).alias("near_edited"),
        resemblance(F.col("sketch"), F.col("next_sketch"), k).alias("near_next"),
    )
    return with_null_ids(compared, "doc_id")
