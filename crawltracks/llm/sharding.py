"""Operator 1: shards from a k-d tree over text metadata.

A node is split at the weighted median (weight: bytes) of its widest dimension, in the
proportion of the leaves below, until there are as many leaves as the target bytes ask for.
Medians are found by refining histograms: executors count bytes by bin and keep of each node
the one bin that the median lies in, so the driver gets one row a node and round. The tree is a
few numbers a node; a row finds its node by walking it, so rows are written once, with their keys.

Every dimension is a 62-bit key: the measure in the upper bits, a hash of the text below it.
Equal texts have equal keys in all dimensions, so a group of copies stays in one shard as
long as it is small against a shard; a larger group is split by a hash of the document id
and, within equal ids, of the row.

Cases: a null text has the size of its row overhead; repeated rows, extreme ids and rows without an
id are placed one by one, those without an id as if they had one of their own; an empty table gives
an empty table; other columns are not looked at; with fewer documents than shards some shards stay empty.
"""

from __future__ import annotations

import json
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from crawltracks.llm.common import buckets, cut

ROW_OVERHEAD = 16


def default_dimensions(text: Column, size: Column) -> dict[str, Column]:
    """Measures in 0..1: length of the text, bytes per character, words per byte."""
    chars = F.length(text)
    return {
        "bytes": F.least(F.log2(size.cast("double")) / 40, F.lit(1.0)),
        "width": F.when(chars > 0, (F.octet_length(text) / chars - 1) / 3).otherwise(0.0),
        "spaces": F.when(chars > 0, (chars - F.length(F.replace(text, F.lit(" "), F.lit("")))) / chars).otherwise(0.0),
    }


def _numbers(values: list, kind: str) -> str:
    """SQL of an array of constants: one small expression until the optimizer folds it."""
    return f"from_json('{json.dumps(values)}', 'array<{kind}>')"


def _key(measure: Column, text_hash: Column) -> Column:
    """30 bits of the measure over 32 bits of the text's hash."""
    level = F.least(F.floor(measure * (1 << 30)), F.lit((1 << 30) - 1)).cast("long")
    return F.shiftleft(level, 32).bitwiseOR(text_hash.bitwiseAND(F.lit(0xFFFFFFFF)))


@dataclass
class _Node:
    first: int  # shard
    leaves: int
    weight: int = 0
    dim: int = -1  # -1: not split
    at: int = 0  # keys below go left
    tie_at: int = 0  # and of key ``at`` those whose tie is below
    children: tuple[int, int] = (0, 0)


@dataclass
class _Tree:
    nodes: list[_Node] = field(default_factory=list)
    depth: int = 0

    def node_of(self) -> str:
        """SQL of the node that a row (keys, tie) has come to, by a walk from the root."""
        if not self.depth:
            return "0"
        dim, left, right = (_numbers([f(n) for n in self.nodes], "int") for f in (lambda n: n.dim, lambda n: n.children[0], lambda n: n.children[1]))
        at, tie_at = (_numbers([f(n) for n in self.nodes], "bigint") for f in (lambda n: n.at, lambda n: n.tie_at))
        low = f"(get(keys, {dim}[k]) < {at}[k] or get(keys, {dim}[k]) = {at}[k] and tie < {tie_at}[k])"
        return f"aggregate(sequence(1, {self.depth}), 0, (k, _) -> CASE WHEN {dim}[k] < 0 THEN k WHEN {low} THEN {left}[k] ELSE {right}[k] END)"


def assign_shards(docs: DataFrame, shards: int = 40, target_bytes: int | None = None, bins: int = 4096, slack: float = 0.002) -> DataFrame:
    """doc_id, size, text_crc32, shard and slot of every document.

    ``target_bytes``, when given, sets the number of leaves in place of ``shards``. ``slack`` is
    the part of a shard's bytes by which a cut may miss its place to keep a group whole.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    size = (F.octet_length(text) + ROW_OVERHEAD).cast("long")
    dims = default_dimensions(F.col("text"), F.col("size"))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"), size.alias("size"))
    keys = F.array(*[_key(m, F.xxhash64("text")) for m in dims.values()]).alias("keys")
    # 43 bits of the id's hash over 18 of the row's number
    row = F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(1 << 18))
    tie = F.shiftleft(F.shiftrightunsigned(F.xxhash64("doc_id"), 21), 18).bitwiseOR(row).alias("tie")
    rows = cut(rows.select("doc_id", "size", F.crc32(F.encode("text", "UTF-8")).alias("text_crc32"), keys, tie), "shard-keys")
    whole = rows.agg(F.sum("size")).first()[0] or 0
    if target_bytes:
        shards = max(1, -(-whole // target_bytes))
    tolerance = slack * whole / shards

    tree = _Tree([_Node(0, shards, whole)])
    while any(n.leaves > 1 and n.dim < 0 for n in tree.nodes):
        held = rows.selectExpr("size", "keys", "tie", f"{tree.node_of()} AS node")
        todo = [k for k, n in enumerate(tree.nodes) if n.leaves > 1 and n.dim < 0]
        inside = _numbers([n.leaves > 1 and n.dim < 0 for n in tree.nodes], "boolean") + "[node]"
        ends = [F.expr(f"{f}(keys[{i}]) AS {f}_{i}") for i in range(len(dims)) for f in ("min", "max")]
        spans = {r["node"]: r for r in held.where(inside).groupBy("node").agg(*ends).collect()}
        cuts = {}
        for k in todo:
            n = tree.nodes[k]
            if k in spans:
                widest = max(range(len(dims)), key=lambda i: spans[k][f"max_{i}"] - spans[k][f"min_{i}"])
                cuts[k] = _Cut(widest, spans[k][f"min_{widest}"], spans[k][f"max_{widest}"] + 1, n.weight * (n.leaves // 2) / n.leaves)
            else:  # no rows
                n.leaves = 1
        _refine(held, len(tree.nodes), cuts, bins, tolerance)
        for k, c in cuts.items():
            n = tree.nodes[k]
            half = n.leaves // 2
            n.dim, n.at, n.tie_at, n.children = c.dim, c.at, c.tie_at, (len(tree.nodes), len(tree.nodes) + 1)
            tree.nodes += [_Node(n.first, half, c.below), _Node(n.first + half, n.leaves - half, n.weight - c.below)]
        tree.depth += bool(cuts)
    shard = _numbers([n.first for n in tree.nodes], "int")
    return _slots(rows.selectExpr("doc_id", "size", "text_crc32", f"{shard}[{tree.node_of()}] AS shard"))


class _Cut:
    """Where a node is cut: keys below ``at``, and of key ``at`` the ties below ``tie_at``."""

    def __init__(self, dim: int, low: int, high: int, target: float):
        self.dim, self.low, self.high, self.target = dim, low, high, target
        self.before = 0  # bytes below ``low``
        self.at, self.tie_at = 0, 0
        self.group: int | None = None  # the key that is split by ties
        self.below = 0

    def width(self, bins: int) -> int:
        return max(1, -(-(self.high - self.low) // bins))


def _refine(held: DataFrame, n_nodes: int, cuts: dict[int, _Cut], bins: int, tolerance: float) -> None:
    """Narrow every cut of a level together. Executors keep the bin that a cut lies in, so a round sends one row a node."""
    todo = dict(cuts)
    while todo:
        known = {k: (c.dim, c.group is not None, c.group or 0, c.low, c.high, c.width(bins), float(c.target - c.before)) for k, c in todo.items()}
        none = (-1, False, 0, 0, 0, 1, 0.0)
        kinds = ("int", "boolean", "bigint", "bigint", "bigint", "bigint", "double")
        lists = [_numbers([known.get(k, none)[i] for k in range(n_nodes)], kind) + "[node]" for i, kind in enumerate(kinds)]
        dim, by_tie, group, low, high, width, wanted = lists
        rows = held.where(f"{dim} >= 0").selectExpr("node", "size", "tie", f"get(keys, {dim}) AS key", f"{by_tie} AS by_tie", f"{group} AS part", f"{low} AS low", f"{high} AS high", f"{width} AS width", f"{wanted} AS wanted")
        rows = rows.selectExpr("node", "size", "low", "high", "width", "wanted", "CASE WHEN NOT by_tie THEN key WHEN key = part THEN tie END AS v").where("v >= low AND v < high")
        aggregates = [F.expr(x) for x in ("sum(size) AS bytes", "count(*) AS n", "min(v) AS least", "max(v) AS most")]
        counts = rows.groupBy("node", "wanted", F.expr("(v - low) div width AS bin")).agg(*aggregates)
        along = "(PARTITION BY node ORDER BY bin)"  # at most ``bins`` rows a node
        run = counts.selectExpr("*", f"sum(bytes) OVER {along} AS run", f"lead(bin) OVER {along} IS NULL AS last")
        hit = "run >= wanted AND run - bytes < wanted OR last"
        by = {}
        for r in run.where(hit).select("node", "bin", "bytes", "run", "n", "least", "most").orderBy("node", "bin").collect():
            by.setdefault(r["node"], r)
        for k, c in list(todo.items()):
            r = by.get(k)
            if r is None:  # nothing in the range: the cut is at its start
                start, stop, size, run_to, one = c.low, c.low, 0, c.before, True
            else:
                start, stop, size, run_to, one = r["least"], r["most"] + 1, r["bytes"], c.before + r["run"] - r["bytes"], r["n"] == 1
            if one or size <= tolerance or stop == start + 1 and (c.group is not None or size <= 8 * tolerance):
                near_start = c.target - run_to <= run_to + size - c.target
                at, c.below = (start, run_to) if near_start else (stop, run_to + size)
                if c.group is None:
                    c.at, c.tie_at = at, 0
                else:
                    c.at, c.tie_at = c.group, at
                del todo[k]
            elif stop == start + 1:  # one group of copies, too large to stay whole
                c.group, c.before, c.low, c.high = start, run_to, 0, 1 << 61
            else:
                c.low, c.high, c.before = start, stop, run_to


def _slots(rows: DataFrame) -> DataFrame:
    """Number the rows of each shard from 0: ranks inside small buckets of a shard, plus the bucket's first slot."""
    spark = rows.sparkSession
    n = buckets(spark, 8)
    rows = rows.withColumn("bucket", F.pmod(F.xxhash64("doc_id"), F.lit(n)).cast("int"))
    first = rows.groupBy("shard", "bucket").agg(F.count("*").alias("n"))
    first = first.select("shard", "bucket", (F.sum("n").over(Window.partitionBy("shard").orderBy("bucket")) - F.col("n")).alias("first"))
    ranked = rows.withColumn("rank", F.row_number().over(Window.partitionBy("shard", "bucket").orderBy("doc_id", "size", "text_crc32")) - 1)
    return ranked.join(first, ["shard", "bucket"]).select("doc_id", "size", "text_crc32", F.col("shard").cast("int").alias("shard"), (F.col("first") + F.col("rank")).cast("long").alias("slot"))
