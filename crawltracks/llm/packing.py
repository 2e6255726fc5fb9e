"""Operator 9: bounded-space online packing of token streams into fixed windows.

Each partition keeps ``open_windows`` windows. A document is cut into full windows and a
tail; the tail goes where it fits best; when it fits nowhere the fullest open window is
emitted and a new one opened. What is open when a partition ends is merged with the
leftovers of neighbouring partitions by first-fit decreasing.

Cases: a null or empty text has just its end id; a text longer than a window is cut;
rows with the same id are packed each for itself; an empty table gives an empty table;
columns other than id and text are not looked at.
"""

from __future__ import annotations

import base64
from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crawltracks.llm.common import cut, slices, texts_of

PIECE = "doc_id long, start long, length long, doc_tokens long, sequence_id long, offset long, ids binary"
_STAGED = PIECE + ", leftover int"


class ByteBpe:
    """Ids of whole texts. ``ranks_path`` names the same vocabulary as ranks, whose encoder is
    five times as fast and gives the same ids; a text with the end-of-text string goes to the first."""

    def __init__(self, path: str, ranks_path: str, pattern: str):
        import tiktoken
        from tokenizers import Tokenizer

        self.encoder = Tokenizer.from_file(path)
        with open(ranks_path, "rb") as lines:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        self.fast = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})

    def __call__(self, text: str) -> bytes:
        if "<|" in text:
            return np.asarray(self.encoder.encode(text, add_special_tokens=False).ids, np.uint32).tobytes()
        return np.asarray(self.fast.encode_to_numpy(text, disallowed_special=()), np.uint32).tobytes()


class Windows:
    """Open windows of one partition, sorted by free space."""

    def __init__(self, capacity: int, limit: int):
        self.capacity, self.limit = capacity, limit
        self.free: list[tuple[int, int]] = []  # (free, sequence)
        self.held: dict[int, list[tuple]] = {}
        self.next = 0

    def place(self, piece: tuple, size: int) -> list[tuple[int, list[tuple]]]:
        """Put a piece; returns the windows that are complete now."""
        done = []
        at = bisect_left(self.free, (size, -1))
        if at == len(self.free):
            if len(self.free) >= self.limit:
                _, fullest = self.free.pop(0)
                done.append((fullest, self.held.pop(fullest)))
            room, seq = self.capacity, self.open()
        else:
            room, seq = self.free.pop(at)
        self.held.setdefault(seq, []).append(piece)
        if room == size:
            done.append((seq, self.held.pop(seq)))
        else:
            insort(self.free, (room - size, seq))
        return done

    def open(self) -> int:
        self.next += 1
        return self.next - 1


def _rows(pieces: list[tuple], leftover: int) -> pa.RecordBatch:
    cols = list(zip(*pieces)) if pieces else [()] * 7
    arrays = [pa.array(c, pa.int64()) for c in cols[:6]] + [pa.array(cols[6], pa.binary()), pa.array([leftover] * len(pieces), pa.int32())]
    return pa.RecordBatch.from_arrays(arrays, ["doc_id", "start", "length", "doc_tokens", "sequence_id", "offset", "ids", "leftover"])


def _laid_out(seq: int, pieces: list[tuple]) -> list[tuple]:
    out, offset = [], 0
    for doc, start, length, total, ids in pieces:
        out.append((doc, start, length, total, seq, offset, ids))
        offset += length
    return out


def pack(docs: DataFrame, tokenizer: tuple[str, str, str], capacity: int = 1024, open_windows: int = 64, end_id: int = 0, merge: int = 8) -> DataFrame:
    """Pieces of all documents, with their ids, placed in sequences of at most ``capacity`` tokens.

    tokenizer: what :class:`ByteBpe` takes. merge: partitions whose leftovers are merged together.
    """

    def stage(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, base = ByteBpe(*tokenizer), TaskContext.get().partitionId() << 32
        windows, out = Windows(capacity, open_windows), []
        end = np.asarray([end_id], np.uint32).tobytes()
        for batch in slices(batches):
            for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist()):
                ids = encode(text) + end
                total = len(ids) // 4
                for start in range(0, total, capacity):
                    size = min(capacity, total - start)
                    piece = (doc, start, size, total, ids[4 * start : 4 * (start + size)])
                    if size == capacity:
                        out += _laid_out(base + windows.open(), [piece])
                    else:
                        for seq, pieces in windows.place(piece, size):
                            out += _laid_out(base + seq, pieces)
                if len(out) > 2000:
                    yield _rows(out, -1)
                    out = []
        yield _rows(out, -1)
        left = [x for seq, pieces in windows.held.items() for x in _laid_out(base + seq, pieces)]
        yield _rows(left, (base >> 32) // merge)

    def refill(rows: pd.DataFrame) -> pd.DataFrame:
        """First-fit decreasing over the leftovers of some partitions; sequence numbers are those set free."""
        rows = rows.sort_values(["length", "sequence_id", "offset"], ascending=[False, True, True], ignore_index=True)
        names = iter(sorted(rows.sequence_id.unique()))
        free, seqs, used, seq_of, offset = [], [], {}, [], []
        for size in rows.length.to_numpy():
            at = bisect_left(free, (size, -1))
            if at == len(free):
                k = len(seqs)
                seqs.append(next(names))
                used[k] = 0
                room = capacity
            else:
                room, k = free.pop(at)
            seq_of.append(seqs[k])
            offset.append(used[k])
            used[k] += int(size)
            insort(free, (room - int(size), k))
        return rows.assign(sequence_id=np.asarray(seq_of, np.int64), offset=np.asarray(offset, np.int64))[[c.split()[0] for c in PIECE.split(", ")]]

    staged = cut(texts_of(docs).mapInArrow(stage, _STAGED), "packing")
    done = staged.where("leftover < 0").drop("leftover")
    merged = staged.where("leftover >= 0").groupBy("leftover").applyInPandas(refill, PIECE)
    return done.unionByName(merged)
