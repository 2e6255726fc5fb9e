"""Operator 8: exact-verified Jaccard join of word shingle sets by chosen paths.

Texts become sets of five-word shingles, and each set a signature of ``COORDS`` min-hashes (each a
token sampled from the set), so that two sets agree in a coordinate with the probability of their similarity.
A run is a forest of paths. At each node its path chooses coordinates, 1/threshold of them on average, and
a set goes on under the value it has in each: sets with the same values meet. A pair at the threshold
so has one common child on average at every node, and its chance to stay together falls slowly with depth. Small buckets are
searched by brute force on signatures. In a large one all sets are compared with a leader, the first of one
of four orders; those all but equal to it are left with it, the others are split again. What is
large at the last depth is searched block by block, so that all its pairs meet. Runs are
repeated until a pair at the threshold is missed with a probability of at most 1 - recall.

What meets and is alike by signature is joined to candidate classes. Within these every pair
is compared exactly, block by block, so links are counted over true sets and a class is a
component of true links. Signatures have ``COORDS`` coordinates so that sets which merely share a long passage
(half their shingles, say) are not alike by signature, and candidate classes do not grow with them.
Equal texts (by a 128-bit digest) are one set from the start and count as many.

Cases: null and empty texts have no shingles and are linked to nothing, not even one another; a
text of one to four words has its whole word sequence as one shingle; equal texts are linked;
texts, not ids, are compared, so rows that repeat an id or have none keep all their links; a class is
named by its least id, and has none only if no row of it has one; an empty table gives an empty
table; other columns are not looked at.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crawltracks.llm.common import buckets, cut, drop_cut, slices
from crawltracks.llm.words import mix, window_starts, windows, words_of

SHINGLE = 5
COORDS = 128
#: Sets of a bucket that is searched by brute force: all pairs of so many signatures cost less than one more split.
SMALL = 2000
DEPTH = 6
CELL = 512
BLOCK, BLOCK_BYTES = 512, 16 << 20
#: Share of coordinates from which a set is taken for its leader's all but equal.
TIGHT = 0.95
#: Stands for a missing id and comes after all others.
LAST_ID = (1 << 63) - 1
_SALTS = mix(np.arange(1, COORDS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)


def shingle_sets(texts: pa.Array, size: int = SHINGLE) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of every text."""
    words = words_of(texts)
    hashes, starts = windows(words.hashes, size), window_starts(words.first, size)
    edges = np.searchsorted(starts, words.first)
    found, counts = hashes[starts], words.counts
    out = []
    for i, n in enumerate(counts):
        if n >= size:
            out.append(np.unique(found[edges[i] : edges[i + 1]]))
        elif n:
            out.append(mix(windows(words.hashes[words.first[i] : words.first[i] + n], int(n)) + np.uint64(n)))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def signature(shingles: np.ndarray) -> np.ndarray:
    """Least salted hash for every coordinate, as 32 bits; shingle hashes are well mixed, so a product is enough."""
    best = np.full(COORDS, np.iinfo(np.uint64).max, np.uint64)
    for i in range(0, len(shingles), 2048):
        best = np.minimum(best, (shingles[i : i + 2048, None] * _SALTS[None, :]).min(axis=0))
    return (best >> np.uint64(32)).astype(np.uint32)


def _chosen(threshold: float) -> tuple[int, float]:
    """Coordinates that every node takes, and the chance of one more: 1 / threshold on average."""
    sure = math.floor(1 / threshold)
    return sure, 1 / threshold - sure


def least_alike(threshold: float) -> int:
    """Coordinates in which two sets at the threshold agree at least: four deviations below the mean."""
    return math.floor(COORDS * threshold - 4 * math.sqrt(COORDS * threshold * (1 - threshold)))


def miss(share: np.ndarray, threshold: float, depth: int = DEPTH) -> np.ndarray:
    """Chance that a pair that agrees in ``share`` of the coordinates has no common bucket at ``depth`` in a run."""
    sure, more = _chosen(threshold)
    lost = np.zeros_like(share)
    for _ in range(depth):
        one = 1 - share + share * lost
        lost = one**sure * (1 - more + more * one)
    return lost


def runs_needed(threshold: float, recall: float) -> int:
    """Runs until a pair at the threshold is missed, even if all its buckets are large, with 1 - recall at most.

    All runs draw from the same ``COORDS`` coordinates, so the chance to meet is that of the number
    in which the pair agrees; pairs that agree in too few are not alike by signature at all.
    """
    agree = np.arange(COORDS + 1)
    chance = np.asarray([math.comb(COORDS, int(m)) * threshold**m * (1 - threshold) ** (COORDS - m) for m in agree])
    lost = np.where(agree >= least_alike(threshold), miss(agree / COORDS, threshold), 1.0)
    if float(chance[lost == 1].sum()) >= 1 - recall:
        raise ValueError(f"{COORDS} coordinates cannot give a recall of {recall}")
    runs = 1
    while float((chance * lost**runs).sum()) > 1 - recall:
        runs += 1
    return runs


def _forest(n: int, left: np.ndarray, right: np.ndarray) -> list[tuple[int, int]]:
    """Spanning (least member, member) pairs of the components of a graph on 0..n-1."""
    label = np.arange(n)
    while len(left):
        low = np.minimum(label[left], label[right])
        new = label.copy()
        np.minimum.at(new, left, low)
        np.minimum.at(new, right, low)
        new = new[new]
        if (new == label).all():
            break
        label = new
    return [(int(label[i]), i) for i in range(n) if label[i] != i]


def _alike_pairs(sign: np.ndarray, group: np.ndarray, node: np.ndarray, least: int, step: int = 1 << 16) -> np.ndarray:
    """Spanning pairs of nodes whose rows are of the same (sorted) group and agree in at least ``least`` coordinates."""
    found, held = np.zeros((0, 2), np.int64), []
    n = int(node.max(initial=-1)) + 1

    def spanning() -> np.ndarray:
        both = np.concatenate([found, *held])
        return np.asarray(_forest(n, both[:, 0], both[:, 1]), np.int64).reshape(-1, 2)

    i, k = np.arange(len(group) - 1), 1
    while len(i):
        i = i[i + k < len(group)]
        i = i[group[i] == group[i + k]]
        for at in range(0, len(i), step):
            a = i[at : at + step]
            a = a[(sign[a] == sign[a + k]).sum(axis=1, dtype=np.int16) >= least]
            held.append(np.stack([node[a], node[a + k]], axis=1))
        if sum(map(len, held)) > 1 << 20:
            found, held = spanning(), []
        k += 1
    return spanning()


def components(edges: DataFrame) -> DataFrame:
    """(id, label): label is the least id of the component; ``edges`` are pairs a, b."""
    edges = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    before = None
    while True:  # every node is tied to the least neighbour, then the least neighbour's neighbours
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).withColumn("m", F.least("a", "m"))
        large = both.join(least, "a").where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = large.unionByName(least.where("a > m").select("a", F.col("m").alias("b"))).where("a <> b").distinct()
        down = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(down, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(down.select("a", F.col("m").alias("b")))
        new = cut(small.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
        now = new.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        drop_cut(edges)
        edges = new
        if now == before:
            break
        before = now
    return edges.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("label"))


def _signs(batch: pa.RecordBatch) -> np.ndarray:
    return np.frombuffer(b"".join(batch.column("sign").to_pylist()), np.uint8).reshape(-1, COORDS)


def _children(path: np.ndarray, value_of, threshold: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Rows that go on and their new paths, for every coordinate that the nodes choose; ``value_of`` has a row's value in a coordinate."""
    sure, more = _chosen(threshold)
    for s in range(sure + 1):
        drawn = mix(path + np.uint64(0x632BE59BD9B4E019) * np.uint64(s + 1))
        rows = np.arange(len(path)) if s < sure else np.flatnonzero(mix(drawn + np.uint64(1)).astype(np.float64) < more * 2.0**64)
        c = (drawn[rows] % np.uint64(COORDS)).astype(np.int64)
        yield rows, mix(path[rows] ^ mix((value_of(rows, c).astype(np.uint64) << np.uint64(8)) + np.uint64(s + 1)))


_ROW = "rep long, path long, sign binary"
_SPLIT = "a long, b long, path long, sign binary"


def candidate_classes(sets: DataFrame, threshold: float, recall: float) -> DataFrame:
    """(id, label) of every set of ``sets`` (rep, sign of 32 bits a coordinate) that is alike another by signature."""
    spark = sets.sparkSession
    dealt, least, tight = buckets(spark), least_alike(threshold), math.ceil(TIGHT * COORDS)
    roots = mix(np.arange(1, runs_needed(threshold, recall) + 1, dtype=np.uint64))

    def paths(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Every run's first split, by all 32 bits; later ones see eight."""
        for batch in batches:
            whole = np.frombuffer(b"".join(batch.column("sign").to_pylist()), np.uint32).reshape(-1, COORDS)
            rep = batch.column("rep").to_numpy()
            short = pa.array([x.tobytes() for x in whole.astype(np.uint8)], pa.binary())
            for root in roots:
                for rows, path in _children(np.full(len(whole), root), lambda r, c: whole[r, c], threshold):
                    yield pa.RecordBatch.from_arrays([pa.array(rep[rows]), pa.array(path.view(np.int64)), short.take(pa.array(rows))], ["rep", "path", "sign"])

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Compare with the bucket's leader; what is not all but equal to it goes on."""
        for batch in batches:
            sign, lead = _signs(batch), np.frombuffer(b"".join(batch.column("lead_sign").to_pylist()), np.uint8).reshape(-1, COORDS)
            rep, leader, path = (batch.column(c).to_numpy() for c in ("rep", "leader", "path"))
            agree = (sign == lead).sum(axis=1)
            tied = np.flatnonzero((agree >= least) & (rep != leader))
            none = pa.nulls(len(tied))
            yield pa.RecordBatch.from_arrays([pa.array(rep[tied]), pa.array(leader[tied]), none.cast(pa.int64()), none.cast(pa.binary())], ["a", "b", "path", "sign"])
            on = np.flatnonzero((agree < tight) & (rep != leader))
            for rows, new in _children(path[on].view(np.uint64), lambda r, c: sign[on[r], c], threshold):
                at = pa.array(on[rows])
                yield pa.RecordBatch.from_arrays([batch.column("rep").take(at), pa.nulls(len(rows), pa.int64()), pa.array(new.view(np.int64)), batch.column("sign").take(at)], ["a", "b", "path", "sign"])

    def brute(group: pa.Table) -> pa.Table:
        """Spanning pairs of what is alike in the buckets of a bundle."""
        group = group.sort_by([("path", "ascending"), ("chunk", "ascending")])
        path, chunk = group["path"].to_numpy(), group["chunk"].to_numpy()
        number = np.concatenate([[0], np.cumsum((path[1:] != path[:-1]) | (chunk[1:] != chunk[:-1]))])
        rep, at = np.unique(group["rep"].to_numpy(), return_inverse=True)
        found = _alike_pairs(np.frombuffer(b"".join(group["sign"].to_pylist()), np.uint8).reshape(-1, COORDS), number, at, least)
        return pa.table({"a": pa.array(rep[found[:, 0]]), "b": pa.array(rep[found[:, 1]])})

    rows, pairs = sets.mapInArrow(paths, _ROW), []
    for depth in range(DEPTH):
        sizes = rows.groupBy("path").agg(F.count("*").alias("n")).where("n > 1")
        held = cut(rows.join(sizes, "path"), "paths")
        small, large = held.where(F.col("n") <= SMALL).withColumn("chunk", F.lit(0).cast("long")), held.where(F.col("n") > SMALL)
        last = depth == DEPTH - 1
        if last:  # every two blocks of a bucket meet in a cell
            blocked = large.withColumn("blocks", F.ceil(F.col("n") / CELL)).withColumn("block", F.pmod(F.xxhash64("rep", "path"), F.col("blocks")))
            others = F.filter(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1), lambda x: (x != F.col("block")) | (F.col("blocks") == 1))
            met = blocked.withColumn("other", F.explode(others))
            cells = met.withColumn("chunk", F.least("block", "other") * F.col("blocks") + F.greatest("block", "other"))
            small = small.unionByName(cells.drop("blocks", "block", "other"))
        bundle = F.pmod(F.xxhash64("path", "chunk"), F.lit(4 * dealt)).alias("bundle")
        pairs.append(small.select("rep", "path", "sign", "chunk", bundle).groupBy("bundle").applyInArrow(brute, "a long, b long"))
        if last or large.isEmpty():
            break
        # one of four orders of all sets, so buckets of a group of copies mostly have the same few leaders
        leader = F.min(F.struct(F.xxhash64(F.pmod("path", F.lit(4)), "rep").alias("h"), "rep", "sign")).alias("x")
        leaders = large.groupBy("path").agg(leader).select("path", F.col("x.rep").alias("leader"), F.col("x.sign").alias("lead_sign"))
        after = cut(large.select("rep", "path", "sign").join(leaders, "path").mapInArrow(split, _SPLIT), "split")
        pairs.append(after.where("sign is null").select("a", "b"))
        rows = after.where("sign is not null").select(F.col("a").alias("rep"), "path", "sign")
    candidates = pairs[0]
    for more in pairs[1:]:
        candidates = candidates.unionByName(more)
    rough = components(candidates)
    return rough.unionByName(rough.select(F.col("label").alias("id"), "label").distinct())


def _key() -> Column:
    return F.md5(F.encode(F.coalesce(F.col("text"), F.lit("")), "UTF-8"))


def _id() -> Column:
    return F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST_ID))


def _sets(docs: DataFrame, size: int) -> DataFrame:
    """One row per distinct text: key, rep (a number of its own), first_id, copies, size and signature (null if blank)."""

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            sets = shingle_sets(batch.column("text"), size)
            signs = pa.array([signature(s).tobytes() if len(s) else None for s in sets], pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("key"), pa.array([len(s) for s in sets], pa.int64()), signs], ["doc_id", "key", "size", "sign"])

    keyed = docs.select(_id().alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"), _key().alias("key"))
    signed = keyed.mapInArrow(sign, "doc_id long, key string, size long, sign binary")
    one = signed.groupBy("key").agg(F.min("doc_id").alias("first_id"), F.count("*").alias("copies"), F.min("size").alias("size"), F.min("sign").alias("sign"))
    return cut(one.withColumn("rep", F.monotonically_increasing_id()), "sets")  # written, so a number stays


def text_classes(docs: DataFrame, threshold: float, recall: float, size: int = SHINGLE) -> DataFrame:
    """One row per distinct text: key, first_id, copies, blank, class_id and lead_key (id and key of the class's first text) and n_links."""
    sets = _sets(docs, size)
    rough = candidate_classes(sets.where("sign is not null").select("rep", "sign"), threshold, recall)
    links = _links(docs, sets.drop("sign"), rough, threshold, size)
    counts = links.groupBy("rep").agg(F.sum("links").alias("links"))
    labels = components(links.select(F.col("rep").alias("a"), F.col("root").alias("b")))
    named = sets.drop("sign").join(counts, "rep", "left").join(labels, F.col("rep") == labels.id, "left").withColumn("label", F.coalesce("label", "rep"))
    linked = named.where("links is not null")  # the others are classes of one text
    first = linked.groupBy("label").agg(F.min(F.struct("first_id", "key")).alias("lead"))
    named = named.join(first, "label", "left")
    return named.select(
        "key", "first_id", "copies", F.col("size").eqNullSafe(F.lit(0)).alias("blank"), F.coalesce("lead.first_id", "first_id").alias("class_id"), F.coalesce("lead.key", "key").alias("lead_key"),
        F.when(F.col("size") > 0, F.coalesce("links", F.lit(0)) + F.col("copies") - 1).otherwise(0).cast("long").alias("n_links"),
    )


def _links(docs: DataFrame, sets: DataFrame, rough: DataFrame, threshold: float, size: int) -> DataFrame:
    """(rep, links, root): exact links of each text inside each cell of its candidate class, and a linked text."""
    dealt = buckets(docs.sparkSession)
    members = rough.join(sets, rough.id == sets.rep).select("rep", "label", "copies", "key", "first_id", "size")
    blocks = F.greatest(F.ceil(F.count("*") / BLOCK), F.ceil(F.sum("size") * 8 / BLOCK_BYTES)).cast("int").alias("blocks")
    members = members.join(members.groupBy("label").agg(blocks), "label").withColumn("block", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int")).drop("size")
    texts = docs.select(_id().alias("first_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"), _key().alias("key"))
    mine = texts.join(members, ["key", "first_id"]).dropDuplicates(["rep"]).select("rep", "text", "label", "copies", "block", "blocks")

    def shingled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            found = [s.tobytes() for s in shingle_sets(batch.column("text"), size)]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("rep", "label", "copies", "block", "blocks")), pa.array(found, pa.binary())], ["rep", "label", "copies", "block", "blocks", "shingles"])

    rows = mine.mapInArrow(shingled, "rep long, label long, copies long, block int, blocks int, shingles binary")
    # a block meets every other block of its class in a cell of its own
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")
    cells = rows.select("rep", "label", "copies", "block", "shingles", other)
    cells = cells.select("rep", "label", "copies", "shingles", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block")
    cells = cells.withColumn("bundle", F.pmod(F.xxhash64("label", "i", "j"), F.lit(4 * dealt)))

    def compare(rows: pd.DataFrame) -> pd.DataFrame:
        """Links of each text inside each cell, and spanning pairs of them."""
        out = []
        for (_, i, j), cell in rows.groupby(["label", "i", "j"]):
            if len(cell) < 2:
                continue
            cell = cell.sort_values(["block", "rep"])
            found = [np.frombuffer(x, np.uint64) for x in cell.shingles]
            size_of = np.asarray([len(x) for x in found])
            _, column = np.unique(np.concatenate(found), return_inverse=True)
            row = np.repeat(np.arange(len(found)), size_of)
            order = np.argsort(column, kind="stable")
            row, column = row[order], column[order]
            shared = np.zeros((len(found), len(found)), np.float32)
            width = max(1, (16 << 20) // (4 * len(found)))
            for a in range(0, int(column[-1]) + 1, width):
                x, y = np.searchsorted(column, [a, a + width])
                dense = np.zeros((len(found), min(width, int(column[-1]) + 1 - a)), np.float32)
                dense[row[x:y], column[x:y] - a] = 1
                shared += dense @ dense.T
            union = size_of[:, None] + size_of[None, :] - shared
            near = shared >= threshold * union - 1e-6
            np.fill_diagonal(near, False)
            block = cell.block.to_numpy()
            if i != j:
                near &= block[:, None] != block[None, :]
            ids, times = cell.rep.to_numpy(), cell.copies.to_numpy()
            links = near @ times
            left, right = np.nonzero(np.triu(near))
            root = np.arange(len(ids))
            for x, y in _forest(len(ids), left, right):
                root[y] = x
            out += [(int(d), int(n), int(ids[r])) for d, n, r in zip(ids, links, root) if n]
        return pd.DataFrame(out, columns=["rep", "links", "root"], dtype="int64")

    return cut(cells.groupBy("bundle").applyInPandas(compare, "rep long, links long, root long"), "links")


def near_classes(docs: DataFrame, threshold: float = 0.8, recall: float = 0.999, size: int = SHINGLE) -> DataFrame:
    """doc_id, class_id (least doc_id of the class) and n_links of every document.

    n_links is the number of other documents whose similarity is at least ``threshold``.
    """
    known = text_classes(docs, threshold, recall, size).select("key", "blank", "class_id", "n_links")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), _key().alias("key")).join(known, "key")
    class_id = F.when(F.col("blank"), F.col("doc_id")).otherwise(F.nullif("class_id", F.lit(LAST_ID)))
    return rows.select("doc_id", class_id.alias("class_id"), "n_links")


def one_of_each_class(docs: DataFrame, threshold: float = 0.8, recall: float = 0.999) -> DataFrame:
    """``docs``, all columns, with one row of every class (of those of least id the first text by digest) and all blank rows."""
    key, at = "_class_text_key", "_class_first_id"
    known = text_classes(docs, threshold, recall)
    lead = known.where("blank or key = lead_key").select(F.col("key").alias(key), F.col("first_id").alias(at), "blank")
    rows = docs.withColumns({key: _key(), at: _id()})
    blank = F.trim(F.translate(F.coalesce(F.col("text"), F.lit("")), "\t\n\u000b\f\r", "     ")) == ""
    full = rows.where(~blank).join(lead.where("not blank").drop("blank"), [key, at], "left_semi")
    again = docs.select(_key().alias(key), _id().alias(at)).groupBy(key, at).agg(F.count("*").alias("n")).where("n > 1").drop("n")
    alone = full.join(again, [key, at], "left_anti")
    repeated = full.join(again, [key, at], "left_semi").dropDuplicates([key, at])
    return rows.where(blank).unionByName(alone).unionByName(repeated).select(*docs.columns)
