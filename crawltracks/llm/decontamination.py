"""Operator 6: benchmark passages found by spaced seeds.

A seed is a fixed mask over four or five consecutive words that looks at four, so passages with
substituted words still share seeds. Both sides become tables of seeds, one row for each text and
seed with all places of it, and are joined by Spark; documents first drop the seeds that a bitmap
of fixed size, made of all the benchmark's, rules out. A joined row votes for the diagonals (document place minus
item place) of its places, by a correlation where they are many, so a word that fills a text costs
no more than the text. Diagonals with enough votes are verified along their overlap.
An item is found whole where four fifths of its words match in the overlap of item and document,
wherever the others stand. Of a longer item a part is found as well: matching words count 1,
others -4, and the best run must have ``min_words`` matching words. Both have at most one other
word in five, so some five words in a row hold at most one: no such passage is without a seed,
and none of ten words or more without two.

Cases: null and empty texts and items match nothing; items of less than five words match only
by all of their words; equal items are reported each; repeated documents and those without an id are
reported each; an empty table on either side gives an empty table; other columns are not
looked at. Words are runs of letters and digits, without regard to ASCII case, and equal by a 64-bit hash.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crawltracks.llm.common import cut, slices, texts_of
from crawltracks.llm.words import mix, window_starts, words_of

#: The positions each mask looks at; any of five words may be another.
MASKS = (
    (0, 1, 2, 3),
    (0, 1, 2, 4),
    (0, 1, 3, 4),
    (0, 2, 3, 4),
)
LEAST = 4
CHUNK = 1 << 21
#: Bits of the filter that documents are held against.
BITS = 26
FOUND = "doc_id long, item_id long, start long, end long, item_start long, matched long, identity double"
_KEYED = "kind int, row long, id long, seed long, places binary, words binary"
_ID, _SEED = 0, 1


def seeds(hashes: np.ndarray, mask: tuple[int, ...]) -> np.ndarray:
    """Hash of the mask and the looked-at words at every position where the mask fits."""
    n = len(hashes) - mask[-1]
    if n <= 0:
        return np.zeros(0, np.uint64)
    total = np.full(n, sum(1 << i for i in mask), np.uint64)
    for i in mask:
        total = mix(total * np.uint64(0xD6E8FEB86659FD93) + hashes[i : i + n])
    return total


def _short_masks() -> list[tuple[int, ...]]:
    return [tuple(range(n)) for n in range(1, LEAST)]


def _places(seed: np.ndarray, text: np.ndarray, place: np.ndarray) -> Iterator[tuple[int, int, np.ndarray]]:
    """(text, seed, its places in order) of each text and seed."""
    if len(seed):
        order = np.lexsort((place, seed, text))
        seed, text, place = seed[order], text[order], place[order]
        edges = np.flatnonzero((seed[1:] != seed[:-1]) | (text[1:] != text[:-1])) + 1
        for at, held in zip([0, *edges.tolist()], np.split(place, edges)):
            yield int(text[at]), int(seed[at]), held


def _keyed(items: bool, bitmap: np.ndarray | None = None):
    """Rows of a table of texts: words of each text that has seeds, and places of each of its seeds.

    Of items with less than four words the whole item is a seed; a document has seeds of all kinds.
    """

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = TaskContext.get().partitionId() << 40
        for batch in slices(batches):
            words = words_of(batch.column("text"), letters=True)
            doc_of, counts, found = words.document_of(), words.counts, []
            for mask in (*MASKS, *_short_masks()):
                starts = window_starts(words.first, mask[-1] + 1)
                if items and len(mask) < LEAST:
                    starts = starts[counts[doc_of[starts]] == len(mask)]
                if len(starts):
                    seed = seeds(words.hashes, mask)[starts]
                    if bitmap is not None:
                        bit = seed >> np.uint64(64 - BITS)
                        near = (bitmap[bit >> np.uint64(3)] >> (bit & np.uint64(7)).astype(np.uint8)) & 1 > 0
                        seed, starts = seed[near], starts[near]
                    found.append((seed, doc_of[starts], starts - words.first[doc_of[starts]]))
            rows, ids, texts = [], batch.column("doc_id").to_pylist(), set()
            if found:
                for text, seed, places in _places(*(np.concatenate(x) for x in zip(*found))):
                    rows.append((_SEED, number + text, None, seed - (1 << 63), places.astype(np.int32).tobytes(), None))
                    texts.add(text)
            rows += [(_ID, number + t, ids[t], None, None, words.hashes[words.first[t] : words.first[t + 1]].tobytes()) for t in sorted(texts)]
            number += batch.num_rows
            cols = list(zip(*rows)) or [()] * 6
            kinds = [pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], [c.split()[0] for c in _KEYED.split(", ")])

    return keyed


def _bitmap(known: DataFrame) -> np.ndarray:
    """One bit for the upper ``BITS`` bits of every seed; of fixed size, whatever the benchmark's."""
    bit = F.shiftrightunsigned(F.col("seed").bitwiseXOR(F.lit(-(1 << 63))), 64 - BITS)
    parts = known.where(f"kind = {_SEED}").select(bit.alias("b")).groupBy(F.expr("bitmap_bucket_number(b + 1)").alias("bucket")).agg(F.expr("bitmap_construct_agg(bitmap_bit_position(b + 1))").alias("bits"))
    out = np.zeros(1 << (BITS - 3), np.uint8)
    for r in parts.toLocalIterator():
        at = (r["bucket"] - 1) * len(r["bits"])
        out[at : at + len(r["bits"])] = np.frombuffer(r["bits"], np.uint8)
    return out


def _votes(places: np.ndarray, item: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Diagonals of all pairs of places, and how many pairs lie on each."""
    if len(places) * len(item) <= CHUNK:
        return np.unique((places[:, None] - item[None, :]).ravel(), return_counts=True)
    low, high = int(places[0]), int(item[-1])
    a, b = np.zeros(int(places[-1]) - low + 1), np.zeros(high - int(item[0]) + 1)
    a[places - low] = 1
    b[high - item] = 1
    size = len(a) + len(b) - 1
    both = np.fft.irfft(np.fft.rfft(a, size) * np.fft.rfft(b, size), size)
    at = np.flatnonzero(both > 0.5)
    return at + low - high, np.rint(both[at]).astype(np.int64)


def _diagonals(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out = []
        for places, item in zip(batch.column("places").to_pylist(), batch.column("item_places").to_pylist()):
            out.append(np.concatenate(_votes(np.frombuffer(places, np.int32).astype(np.int64), np.frombuffer(item, np.int32).astype(np.int64))).astype(np.int32).tobytes())
        yield pa.RecordBatch.from_arrays([batch.column("row"), batch.column("item"), pa.array(out, pa.binary())], ["row", "item", "votes"])


def _promising(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Diagonals of each document and item that have as many votes as a found passage has at least."""
    for batch in batches:
        out = []
        for votes, size in zip(batch.column("votes").to_pylist(), batch.column("size").to_pylist()):
            held = [np.frombuffer(v, np.int32).reshape(2, -1) for v in votes]
            diagonal, at = np.unique(np.concatenate([h[0] for h in held]), return_inverse=True)
            enough = np.bincount(at, np.concatenate([h[1] for h in held])) >= (2 if size >= 10 else 1)
            out.append(diagonal[enough].tobytes() if enough.any() else None)
        yield pa.RecordBatch.from_arrays([batch.column("row"), batch.column("item"), pa.array(out, pa.binary())], ["row", "item", "diagonals"])


def _chunks(sizes: np.ndarray) -> Iterator[slice]:
    """Slices of rows whose sizes sum to about ``CHUNK`` (a larger row stands alone)."""
    edges = [0, *(np.flatnonzero(np.diff(np.cumsum(sizes) // CHUNK)) + 1).tolist(), len(sizes)]
    return (slice(x, y) for x, y in zip(edges, edges[1:]) if y > x)


def _best_run(same: np.ndarray) -> tuple[int, int, int]:
    """Start, end and matches of the run with the greatest sum of 1 a match and -4 a mismatch."""
    total = np.concatenate([[0], np.cumsum(np.where(same, 1, -4))])
    low = np.minimum.accumulate(total)
    end = int(np.argmax(total - low))
    start = int(np.flatnonzero(total[: end + 1] == low[end])[-1])
    return start, end, int(same[start:end].sum())


def _verified(min_words: int):
    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for r in batch.to_pylist():
                doc, item, origin = np.frombuffer(r["words"], np.uint64), np.frombuffer(r["item_words"], np.uint64), np.frombuffer(r["diagonals"], np.int32).astype(np.int64)
                wanted = -(-len(item) * 4 // 5)
                least = min(min_words, wanted)
                a, b = np.maximum(origin, 0), np.minimum(origin + len(item), len(doc))
                for part in _chunks(b - a):
                    n = (b - a)[part]
                    step = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                    same = doc[np.repeat(a[part], n) + step] == item[np.repeat((a - origin)[part], n) + step]
                    ends = np.cumsum(n)
                    matching = np.add.reduceat(same.astype(np.int64), ends - n)
                    for k in np.flatnonzero(matching >= least).tolist():
                        here, at, first = same[ends[k] - n[k] : ends[k]], int(a[part][k]), int(origin[part][k])
                        start, end, matched = 0, int(n[k]), int(matching[k])
                        if matched < wanted:  # not the whole item
                            start, end, matched = _best_run(here)
                        if matched >= least:
                            out.append((r["id"], r["item_id"], at + start, at + end, at + start - first, matched, matched / (end - start)))
            cols = list(zip(*out)) or [()] * 7
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols[:6]] + [pa.array(cols[6], pa.float64())], [c.split()[0] for c in FOUND.split(", ")])

    return verify


def find_passages(docs: DataFrame, benchmark: DataFrame, min_words: int = 13) -> DataFrame:
    """Spans (in words) of ``docs`` that repeat a part of a ``benchmark`` item (item_id, text)."""
    items = benchmark.select(F.col("item_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    known = cut(items.mapInArrow(_keyed(True), _KEYED), "item-seeds")
    bitmap = _bitmap(known)
    near = cut(texts_of(docs).mapInArrow(_keyed(False, bitmap), _KEYED), "seeds")
    item_seeds = known.where(f"kind = {_SEED}").select("seed", F.col("row").alias("item"), F.col("places").alias("item_places"))
    item_words = known.where(f"kind = {_ID}").select(F.col("row").alias("item"), F.col("id").alias("item_id"), F.col("words").alias("item_words"))
    sizes = item_words.select("item", (F.octet_length("item_words") / 8).cast("int").alias("size"))
    hits = near.where(f"kind = {_SEED}").select("seed", "row", "places").join(item_seeds, "seed")
    votes = hits.select("row", "item", "places", "item_places").mapInArrow(_diagonals, "row long, item long, votes binary")
    voted = votes.groupBy("row", "item").agg(F.collect_list("votes").alias("votes")).join(sizes, "item")  # one blob for a seed of the item
    promising = voted.select("row", "item", "votes", "size").mapInArrow(_promising, "row long, item long, diagonals binary").where("diagonals is not null")
    doc_words = near.where(f"kind = {_ID}").select("row", "id", "words")
    both = promising.join(item_words, "item").join(doc_words, "row")
    return both.select("id", "words", "item_id", "item_words", "diagonals").mapInArrow(_verified(min_words), FOUND)


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, min_words: int = 13) -> DataFrame:
    """``docs``, all columns, without the rows whose text holds a passage of the benchmark.

    Rows are told by a 64-bit hash of id and text, so a clean row that repeats the id of another stays.
    """
    key = "_text_digest"
    digest = F.md5(F.encode(F.coalesce(F.col("text"), F.lit("")), "UTF-8"))
    numbered = docs.select(F.xxhash64("doc_id", digest).alias("doc_id"), "text")
    found = find_passages(numbered, benchmark, min_words).select(F.col("doc_id").alias(key)).distinct()
    return docs.withColumn(key, F.xxhash64("doc_id", digest)).join(found, key, "left_anti").select(*docs.columns)
