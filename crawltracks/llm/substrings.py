"""Operator 3: removal of repeated word windows with a log-structured fingerprint index.

A window is ``WINDOW`` consecutive words of one document. Each window is stood for by one
fingerprint, the least of the hashes of its ``GRAM``-word runs, so equal windows have equal
fingerprints and a document has about one distinct fingerprint for eight windows. The index
is a list of immutable runs; a run holds, for each part of the fingerprint space, the sorted
fingerprints of one batch of documents and the slices (groups of documents) they come from.

``append`` sorts a batch into a run and merge-joins it with the runs before it: fingerprints
seen twice are *hits*, told to all slices that hold them. When there are ``max_runs`` runs they are
merged into one first, dealt to more parts if they have grown. ``remove_repeats`` then looks
only at windows whose fingerprint is a hit and verifies them by a 128-bit cryptographic digest
of their words; the first start of each word sequence stays, and the words under all others go.
A fingerprint or window that a third of all documents hold is sent once for a slice, never once
for a document.

An index given to several calls makes them incremental: what an earlier call has seen is first,
whatever its ids. For that the index keeps the texts of its documents by slice, and reads those
slices again that share a fingerprint with the new documents. ``save`` and ``open`` carry an
index from one session to the next by a manifest in its folder.

Cases: a null or empty text has no words; a text of fewer words than a window loses none;
rows that repeat an id are one after the other in the order of a hash of id and text; rows without
an id come first (the least long stands for a missing id); an empty table gives an
empty table; other columns are not looked at, and handed on by :func:`shorten`.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from hashlib import blake2b

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructType

from crawltracks.llm.common import NO_ID, buckets, drop_stored, shared_dir, slices, stored, with_null_ids
from crawltracks.llm.words import plain_words, window_starts, windows, words_of

WINDOW = 20
GRAM = 6
SLICE_TEXT = 32 << 20
PART_PRINTS = 4 << 20
_RUN = "kind int, part int, slice long, n long, fps binary, slices binary"
_TEXTS = "slice long, doc_id long, h long, text string"
_BLOBS = ("high", "low", "ids", "docs", "starts", "lengths")
_MOVED = "part int, slice long, kind int, " + ", ".join(f"{c} binary" for c in _BLOBS)
_MANIFEST = "version int, window int, gram int, parts int, max_runs int, next_slice long, runs array<string>, texts array<string>"
NEW, PASSED, PAST = 0, 1, 2


def _sliding(op: np.ufunc, x: np.ndarray, width: int) -> np.ndarray:
    """op over each ``width`` neighbours of x, by doubling."""
    done = 1
    while done * 2 <= width:
        x = op(x[:-done], x[done:])
        done *= 2
    return op(x[: len(x) - (width - done)], x[width - done :]) if done < width else x


def window_prints(hashes: np.ndarray, first: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts of all windows, the fingerprint of each, and all selected grams' hashes (one for each place)."""
    starts = window_starts(first, window)
    if not len(starts):
        return starts, np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    grams = windows(hashes, gram)
    width = window - gram + 1
    least = _sliding(np.minimum, grams, width)
    prints = least[starts]
    held = np.zeros(len(least) + 2 * (width - 1), np.uint64)
    held[starts + width - 1] = prints
    chosen = _sliding(np.maximum, held, width)[: len(grams)] == grams
    return starts, prints, grams[chosen]


def digests(words, starts: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Two halves of the digest of the words (with one space between) of each window."""
    flat, begins, ends = plain_words(words)
    flat = flat.tobytes()
    found = b"".join([blake2b(flat[a:b], digest_size=16).digest() for a, b in zip(begins[starts].tolist(), ends[starts + window - 1].tolist())])
    both = np.frombuffer(found, np.uint64).reshape(-1, 2)
    return both[:, 0], both[:, 1]


def _as_runs(docs: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted (document, start) pairs as runs of consecutive starts."""
    if not len(docs):
        return docs, starts, starts
    head = np.flatnonzero(np.concatenate([[True], (docs[1:] != docs[:-1]) | (starts[1:] != starts[:-1] + 1)]))
    return docs[head], starts[head], np.diff(np.append(head, len(docs)))


def _blob(x: np.ndarray, kind: type) -> bytes:
    return np.ascontiguousarray(x, dtype=kind).tobytes()


def _joined(column: pa.ChunkedArray, kind: type) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), kind)


def _split(values: np.ndarray, by: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """(value of ``by``, indices) of each of its values, in order of the indices."""
    if len(values):
        order = np.argsort(by, kind="stable")
        for at in np.split(order, np.flatnonzero(np.diff(by[order])) + 1):
            yield int(by[at[0]]), values[at]


class FingerprintIndex:
    """Runs of window fingerprints in the shared folder (or in ``folder``), and the texts behind them."""

    def __init__(self, spark: SparkSession, window: int = WINDOW, gram: int = GRAM, parts: int | None = None, max_runs: int = 4, folder: str | None = None):
        self.spark, self.window, self.gram, self.max_runs = spark, window, gram, max_runs
        self.folder = folder or shared_dir(spark)
        self.parts = parts or buckets(spark)
        self.runs: list[str] = []
        self.texts: list[str] = []
        self.replaced: list[str] = []
        self.next_slice = self.version = 0

    @classmethod
    def open(cls, spark: SparkSession, folder: str) -> "FingerprintIndex":
        """The index that was saved last in ``folder``."""
        last = spark.read.schema(_MANIFEST).json(f"{folder.rstrip('/')}/manifest").orderBy(F.desc("version")).first()
        if last is None:
            raise ValueError(f"no index in {folder}")
        index = cls(spark, last["window"], last["gram"], last["parts"], last["max_runs"], folder)
        index.runs, index.texts, index.next_slice, index.version = list(last["runs"]), list(last["texts"]), last["next_slice"], last["version"]
        return index

    def save(self) -> None:
        """Write a manifest: what it names is never changed, so an index is whole or as it was before."""
        self.version += 1
        row = (self.version, self.window, self.gram, self.parts, self.max_runs, self.next_slice, self.runs, self.texts)
        self.spark.createDataFrame([row], _MANIFEST).write.mode("append").json(f"{self.folder.rstrip('/')}/manifest")

    def vacuum(self) -> None:
        """Delete the runs that compaction has replaced, once no result made before is still to be read."""
        drop_stored(self.spark, *self.replaced)
        self.replaced = []

    def history(self) -> DataFrame | None:
        """Texts of earlier calls: slice, doc_id, h, text."""
        return self.spark.read.schema(_TEXTS).parquet(*self.texts) if self.texts else None

    def remember(self, texts: DataFrame) -> None:
        self.texts.append(stored(texts.select("slice", "doc_id", "h", "text"), "texts", self.folder))

    def take_slices(self, n: int) -> int:
        """The first of ``n`` slice numbers that no other call has."""
        self.next_slice += n
        return self.next_slice - n

    def _entries(self) -> DataFrame:
        if not self.runs:
            return self.spark.createDataFrame([], "part int, n long, fps binary, slices binary")
        return self.spark.read.schema(_RUN).parquet(*self.runs).where("kind = 0").select("part", "n", "fps", "slices")

    def append(self, docs: DataFrame) -> DataFrame:
        """Add a batch (text, slice); returns its hits: (slice, fps) of this and of earlier batches."""
        if len(self.runs) >= self.max_runs:
            self.compact()
        window, gram, parts = self.window, self.gram, self.parts

        def prints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in slices(batches):
                words = words_of(batch.column("text"))
                of = batch.column("slice").to_numpy()
                ids, out = np.unique(of), []
                places = words.first
                for s in ids:  # the slice's documents, kept apart from one another
                    rows = np.flatnonzero(of == s)
                    lengths = np.diff(places)[rows]
                    at = np.concatenate([[0], np.cumsum(lengths)])
                    hashes = np.concatenate([words.hashes[places[r] : places[r + 1]] for r in rows])
                    out.append(_blob(window_prints(hashes, at, window, gram)[2], np.uint64))
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(out, pa.binary())], ["slice", "fps"])

        def by_part(group: pa.Table) -> pa.Table:
            found, times = np.unique(_joined(group["fps"], np.uint64), return_counts=True)
            rows = [(p, _blob(found[at], np.uint64), _blob(times[at] > 1, np.uint8)) for p, at in _split(np.arange(len(found)), (found % np.uint64(parts)).astype(np.int32))]
            names, fps, twice = zip(*rows) if rows else ((), (), ())
            slice_of = [group["slice"][0].as_py()] * len(rows)
            return pa.table({"part": pa.array(names, pa.int32()), "slice": pa.array(slice_of, pa.int64()), "fps": pa.array(fps, pa.binary()), "slices": pa.array(twice, pa.binary())})

        def merge(new: pa.Table, old: pa.Table) -> pa.Table:
            fps = _joined(new["fps"], np.uint64)
            of = np.repeat(new["slice"].to_numpy(), [len(x) // 8 for x in new["fps"].to_pylist()])
            twice = _joined(new["slices"], np.uint8).astype(bool)
            order = np.argsort(fps, kind="stable")
            fps, of, twice = fps[order], of[order], twice[order]
            past, past_of = _joined(old["fps"], np.uint64), _joined(old["slices"], np.int64)
            known = np.sort(past)
            at = np.searchsorted(known, fps)
            seen = (known[np.minimum(at, len(known) - 1)] == fps) if len(known) else np.zeros(len(fps), bool)
            same = np.zeros(len(fps), bool)
            same[1:] = fps[1:] == fps[:-1]
            same[:-1] |= same[1:]
            hit = np.unique(fps[same | twice | seen])
            rows = [(0, None, len(fps), _blob(fps, np.uint64), _blob(of, np.int64))]
            for values, owners in ((fps, of), (past, past_of)):
                if len(hit) and len(values):
                    told = hit[np.minimum(np.searchsorted(hit, values), len(hit) - 1)] == values
                    rows += [(1, s, len(x), _blob(x, np.uint64), b"") for s, x in _split(values[told], owners[told])]
            part = (new if new.num_rows else old)["part"][0].as_py()
            kinds, names, counts, blobs, owners = zip(*rows)
            return pa.table(
                {"kind": pa.array(kinds, pa.int32()), "part": pa.array([part] * len(rows), pa.int32()), "slice": pa.array(names, pa.int64()), "n": pa.array(counts, pa.int64()), "fps": pa.array(blobs, pa.binary()), "slices": pa.array(owners, pa.binary())}
            )

        found = docs.select("slice", "text").mapInArrow(prints, "slice long, fps binary")
        new = found.groupBy("slice").applyInArrow(by_part, "part int, slice long, fps binary, slices binary")
        old = self._entries().select("part", "fps", "slices")
        made = stored(new.groupBy("part").cogroup(old.groupBy("part")).applyInArrow(merge, _RUN), "run", self.folder)
        self.runs.append(made)
        return self.spark.read.schema(_RUN).parquet(made).where("kind = 1").select("slice", "fps")

    def compact(self) -> None:
        """Merge all runs into one, of so many parts that each has ``PART_PRINTS`` fingerprints at most on average."""
        entries = self._entries()
        total = entries.agg(F.sum("n")).first()[0] or 0
        self.parts = parts = max(self.parts, -(-total // PART_PRINTS))

        def dealt(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for fps, of in zip(batch.column("fps").to_pylist(), batch.column("slices").to_pylist()):
                    fps, of = np.frombuffer(fps, np.uint64), np.frombuffer(of, np.int64)
                    rows = [(p, _blob(fps[at], np.uint64), _blob(of[at], np.int64)) for p, at in _split(np.arange(len(fps)), (fps % np.uint64(parts)).astype(np.int32))]
                    names, prints, owners = zip(*rows) if rows else ((), (), ())
                    yield pa.RecordBatch.from_arrays([pa.array(names, pa.int32()), pa.array(prints, pa.binary()), pa.array(owners, pa.binary())], ["part", "fps", "slices"])

        def merged(group: pa.Table) -> pa.Table:
            fps, of = _joined(group["fps"], np.uint64), _joined(group["slices"], np.int64)
            order = np.argsort(fps, kind="stable")
            one = (0, group["part"][0].as_py(), None, len(fps), _blob(fps[order], np.uint64), _blob(of[order], np.int64))
            kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.binary()]
            return pa.table({c.split()[0]: pa.array([v], k) for c, v, k in zip(_RUN.split(", "), one, kinds)})

        moved = entries.select("fps", "slices").mapInArrow(dealt, "part int, fps binary, slices binary")
        one = stored(moved.groupBy("part").applyInArrow(merged, _RUN), "run", self.folder)
        self.replaced += self.runs
        self.runs = [one]


def _in_order(group: pa.Table) -> pa.Table:
    return group.sort_by([("doc_id", "ascending"), ("h", "ascending")])


def _found(rows: list[tuple]) -> pa.Table:
    cols = list(zip(*rows)) or [()] * (3 + len(_BLOBS))
    return pa.table({"part": pa.array(cols[0], pa.int32()), "slice": pa.array(cols[1], pa.int64()), "kind": pa.array(cols[2], pa.int32())} | {c: pa.array(v, pa.binary()) for c, v in zip(_BLOBS, cols[3:])})


def _candidates(kind: int, window: int, gram: int, parts: int):
    """Windows of a slice whose fingerprint is a hit: the first of each sequence, and (of new slices) the starts of all others."""

    def candidates(group: pa.Table, told: pa.Table) -> pa.Table:
        if not group.num_rows or not told.num_rows:
            return _found([])
        name = group["slice"][0].as_py()
        hit = np.unique(_joined(told["fps"], np.uint64))
        group = _in_order(group.select(["slice", "doc_id", "h", "text"]))
        ids, done, got = group["doc_id"].to_numpy(), 0, []
        for piece in slices(iter(group.select(["text"]).combine_chunks().to_batches())):
            words = words_of(piece.column("text"))
            starts, prints, _ = window_prints(words.hashes, words.first, window, gram)
            starts = starts[hit[np.minimum(np.searchsorted(hit, prints), len(hit) - 1)] == prints]
            doc = words.document_of()[starts]
            got.append((*digests(words, starts, window), (doc + done).astype(np.int32), (starts - words.first[doc]).astype(np.int32)))
            done += piece.num_rows
        high, low, doc, start = (np.concatenate(x) for x in zip(*got))
        order = np.lexsort((low, high))  # stable: places of a sequence stay in order
        high, low, doc, start = high[order], low[order], doc[order], start[order]
        again = np.zeros(len(high), bool)
        again[1:] = (high[1:] == high[:-1]) & (low[1:] == low[:-1])
        rows = []
        if kind == NEW:
            by = np.lexsort((start[again], doc[again]))
            runs = _as_runs(doc[again][by], start[again][by])
            rows.append((name % parts, name, PASSED, b"", b"", b"", *(_blob(x, np.int32) for x in runs)))
        high, low, doc, start = high[~again], low[~again], doc[~again], start[~again]
        for p, at in _split(np.arange(len(high)), (high % np.uint64(parts)).astype(np.int32)):
            rows.append((p, name, kind, _blob(high[at], np.uint64), _blob(low[at], np.uint64), _blob(ids[doc[at]], np.int64), _blob(doc[at], np.int32), _blob(start[at], np.int32), b""))
        return _found(rows)

    return candidates


def _losers(group: pa.Table) -> pa.Table:
    """Of the windows of one part, all but the first of each sequence, told to their slices; those of the past are first."""
    kinds = group["kind"].to_numpy()
    passed = group.filter(pc.equal(group["kind"], PASSED))
    rows = list(zip(passed["slice"].to_pylist(), *(passed[c].to_pylist() for c in ("docs", "starts", "lengths"))))
    group = group.filter(pc.not_equal(group["kind"], PASSED))
    if group.num_rows:
        high, low, ids = _joined(group["high"], np.uint64), _joined(group["low"], np.uint64), _joined(group["ids"], np.int64)
        doc, start = _joined(group["docs"], np.int32), _joined(group["starts"], np.int32)
        sizes = [len(x) // 8 for x in group["high"].to_pylist()]
        of, new = np.repeat(group["slice"].to_numpy(), sizes), np.repeat(kinds[kinds != PASSED] == NEW, sizes)
        order = np.argsort(high, kind="stable")
        same = np.zeros(len(order), bool)
        same[1:] = high[order][1:] == high[order][:-1]
        same[:-1] |= same[1:]
        order = order[same]  # what stands alone is first
        order = order[np.lexsort((start[order], doc[order], of[order], ids[order], new[order], low[order], high[order]))]
        again = np.zeros(len(order), bool)
        again[1:] = (high[order][1:] == high[order][:-1]) & (low[order][1:] == low[order][:-1])
        at = order[again]
        at = at[new[at]]
        at = at[np.lexsort((start[at], doc[at], of[at]))]
        rows += [(s, *(_blob(y, np.int32) for y in _as_runs(doc[x], start[x]))) for s, x in _split(at, of[at])]
    cols = list(zip(*rows)) or [()] * 4
    return pa.table({"slice": pa.array(cols[0], pa.int64())} | {c: pa.array(v, pa.binary()) for c, v in zip(("docs", "starts", "lengths"), cols[1:])})


def _removed(window: int, extra: bool):
    names = ["doc_id", "row"] if extra else ["doc_id"]

    def removed(group: pa.Table, told: pa.Table) -> pa.Table:
        group = _in_order(group)
        doc, start, length = (_joined(told[c], np.int32).astype(np.int64) for c in ("docs", "starts", "lengths"))
        order = np.argsort(doc, kind="stable")
        doc, start, length = doc[order], start[order], length[order]
        edges = np.searchsorted(doc, np.arange(group.num_rows + 1))
        n_words, n_removed, left = [], [], []
        for i, text in enumerate(group["text"].to_pylist()):
            words = text.encode().split()
            n_words.append(len(words))
            a, b = edges[i], edges[i + 1]
            gone = 0
            if a < b:
                step = np.zeros(len(words) + 1, np.int32)
                np.add.at(step, start[a:b], 1)
                np.add.at(step, start[a:b] + length[a:b] - 1 + window, -1)
                mask = np.cumsum(step[:-1]) > 0
                gone = int(mask.sum())
                words = [words[k] for k in np.flatnonzero(~mask)]
            n_removed.append(gone)
            left.append(b" ".join(words).decode())
        kept = {c: group[c].combine_chunks() for c in names}
        return pa.table(kept | {"n_words": pa.array(n_words, pa.int64()), "n_removed": pa.array(n_removed, pa.int64()), "text": pa.array(left, pa.string())})

    return removed


def _batched(docs: DataFrame, batches: int, index: FingerprintIndex, extra: Column | None) -> tuple[DataFrame, list[Column]]:
    """Documents with their slice, and for each batch (a range of ids) which rows are in it."""
    doc_id, text = F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)), F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select(doc_id.alias("doc_id"), text.alias("text"), F.xxhash64(doc_id, text).alias("h"), *([extra.alias("row")] if extra is not None else []))
    marks = [i / batches for i in range(1, batches)] or [1.0]
    found = rows.agg(F.percentile_approx("doc_id", marks, 1000), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    marks = sorted(set(found[0] or []))[: batches - 1]
    n = max(buckets(rows.sparkSession), -(-found[1] // (batches * SLICE_TEXT)))
    number: Column = sum(((F.col("doc_id") > m).cast("long") for m in marks), F.lit(0).cast("long"))
    inner = F.shiftrightunsigned(F.shiftrightunsigned("h", 32) * n, 32)  # slices in the order of the hash
    first = index.take_slices(n * (len(marks) + 1))
    rows = rows.withColumn("slice", F.lit(first) + number * n + inner)
    return rows, [F.col("slice").between(first + n * b, first + n * (b + 1) - 1) for b in range(len(marks) + 1)]


def remove_repeats(docs: DataFrame, batches: int = 3, window: int = WINDOW, gram: int = GRAM, index: FingerprintIndex | None = None, extra: Column | None = None) -> DataFrame:
    """``docs`` (doc_id, text) without the words under windows that start earlier elsewhere.

    The documents enter the index in ``batches`` batches of ascending ids; an ``index`` that is given
    has all that earlier calls saw before them, and remembers these. Returns doc_id, n_words, n_removed and
    the text left (words joined by one space); with ``extra`` also ``row``, its value of each row.
    """
    spark = docs.sparkSession
    lasting = index is not None
    index = index or FingerprintIndex(spark, window, gram, max_runs=2)
    window, gram = index.window, index.gram
    past = index.history()
    rows, inside = _batched(docs, batches, index, extra)
    if lasting:
        index.remember(rows)
    told = reduce(DataFrame.unionByName, [index.append(rows.where(part)) for part in inside])
    parts = index.parts
    dealt = rows.repartition(buckets(spark), "slice")
    found = dealt.groupBy("slice").cogroup(told.groupBy("slice")).applyInArrow(_candidates(NEW, window, gram, parts), _MOVED)
    if past is not None:
        shared = past.join(told.select("slice").distinct(), "slice", "left_semi").select("slice", "doc_id", "h", "text")
        found = found.unionByName(shared.groupBy("slice").cogroup(told.groupBy("slice")).applyInArrow(_candidates(PAST, window, gram, parts), _MOVED))
    lost = found.groupBy("part").applyInArrow(_losers, "slice long, docs binary, starts binary, lengths binary")
    made = StructType().add("doc_id", LongType())
    if extra is not None:
        made.add("row", rows.schema["row"].dataType)  # as it is: also where null cannot be
    made.add("n_words", LongType()).add("n_removed", LongType()).add("text", StringType())
    left = dealt.groupBy("slice").cogroup(lost.groupBy("slice")).applyInArrow(_removed(window, extra is not None), made)
    return with_null_ids(left, "doc_id")


def shorten(docs: DataFrame, **how) -> DataFrame:
    """``docs``, all rows and columns, with the text that :func:`remove_repeats` leaves and, where there is one, its ``n_chars``."""
    others = [c for c in docs.columns if c not in ("text", "n_chars")]
    left = remove_repeats(docs, extra=F.struct(*others), **how)
    kept = {c: F.col(f"row.`{c}`") for c in others} | {"text": F.col("text"), "n_chars": F.length("text").cast("long")}
    return left.select(*[kept[c].alias(c) for c in docs.columns])
