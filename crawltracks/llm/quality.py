"""Operator 7: a byte-level convolutional network for text quality, in numpy.

A text is a sequence of bytes. Byte embeddings pass through filters of ``WIDTH`` bytes laid
at every ``STRIDE`` bytes (they overlap) over chunks of ``CHUNK`` bytes that overlap by half;
each filter's greatest and mean value over a chunk go through a small hidden layer to a chunk
score; chunk scores are combined by their maximum and mean into one probability.

Cases: null and empty texts are one chunk of padding and get the score of that; without
labels of both kinds every score is the share of label 1 (0.5 without labels); rows that
repeat are scored each; an empty table gives an empty table; other columns are not looked at.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from crawltracks.llm.training import Adam, labelled_sample, score_documents, sigmoid
from crawltracks.llm.words import text_buffer

EMBED, WIDTH, STRIDE, FILTERS, HIDDEN = 6, 12, 4, 24, 16
CHUNK, STEP = 512, 256
POSITIONS = (CHUNK - WIDTH) // STRIDE + 1


def chunks_of(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All chunks of a column (rows of CHUNK bytes, 0 beyond a text's end) and the document of each."""
    data, offsets = text_buffer(texts)
    sizes = np.diff(offsets)
    count = np.maximum(1, -(-np.maximum(sizes - (CHUNK - STEP), 0) // STEP))
    of = np.repeat(np.arange(len(sizes)), count)
    number = np.arange(len(of)) - np.repeat(np.cumsum(count) - count, count)
    at = offsets[of] + number * STEP
    end = offsets[of + 1]
    padded = np.concatenate([data, np.zeros(CHUNK, np.uint8)])
    view = np.lib.stride_tricks.sliding_window_view(padded, CHUNK)
    rows = view[np.minimum(at, len(data))]
    room = end - at
    short = np.flatnonzero(room < CHUNK)
    rows[short] = np.where(np.arange(CHUNK) < room[short, None], rows[short], 0)
    return rows, of


class ByteConvNet:
    def __init__(self, seed: int = 7):
        r = np.random.default_rng(seed)
        f = np.float32
        self.p = {
            "embed": r.normal(0, 0.5, (256, EMBED)).astype(f),
            "filters": r.normal(0, 1 / np.sqrt(WIDTH * EMBED), (WIDTH * EMBED, FILTERS)).astype(f),
            "bias": np.zeros(FILTERS, f),
            "hidden": r.normal(0, 1 / np.sqrt(2 * FILTERS), (2 * FILTERS, HIDDEN)).astype(f),
            "hidden_bias": np.zeros(HIDDEN, f),
            "out": r.normal(0, 1 / np.sqrt(HIDDEN), HIDDEN).astype(f),
            "out_bias": np.zeros(1, f),
            "combine": np.asarray([0.5, 0.5, 0.0], f),
        }
        self.constant: float | None = None

    def _patches(self, rows: np.ndarray) -> np.ndarray:
        e = self.p["embed"][rows].reshape(len(rows), CHUNK * EMBED)
        view = np.lib.stride_tricks.sliding_window_view(e, WIDTH * EMBED, axis=1)[:, :: STRIDE * EMBED]
        return np.ascontiguousarray(view).reshape(-1, WIDTH * EMBED)

    def _chunk(self, rows: np.ndarray):
        p = self.p
        x = self._patches(rows)
        a = np.maximum(x @ p["filters"] + p["bias"], 0).reshape(len(rows), POSITIONS, FILTERS)
        pooled = np.concatenate([a.max(axis=1), a.mean(axis=1)], axis=1)
        h = np.maximum(pooled @ p["hidden"] + p["hidden_bias"], 0)
        return x, a, pooled, h, h @ p["out"] + p["out_bias"][0]

    def logits(self, rows: np.ndarray, block: int = 256) -> np.ndarray:
        return np.concatenate([self._chunk(rows[i : i + block])[4] for i in range(0, len(rows), block)]) if len(rows) else np.zeros(0, np.float32)

    def _combined(self, z: np.ndarray, of: np.ndarray, n: int):
        first = np.searchsorted(of, np.arange(n))
        top = np.maximum.reduceat(z, first)
        mean = np.add.reduceat(z, first) / np.diff(np.append(first, len(z)))
        c = self.p["combine"]
        return top, mean, c[0] * top + c[1] * mean + c[2]

    def __call__(self, texts: pa.Array) -> np.ndarray:
        if not len(texts):
            return np.zeros(0)
        if self.constant is not None:
            return np.full(len(texts), self.constant)
        rows, of = chunks_of(texts)
        return sigmoid(self._combined(self.logits(rows), of, len(texts))[2])

    def fit(self, texts: list[str], y: np.ndarray, epochs: int = 6, batch: int = 48, rate: float = 0.004, seed: int = 3) -> "ByteConvNet":
        if not len(y) or y.min() == y.max():
            self.constant = float(y.mean()) if len(y) else 0.5
            return self
        rows, of = chunks_of(pa.array(texts, pa.string()))
        first = np.searchsorted(of, np.arange(len(texts) + 1))
        weight = np.where(y == 1, 0.5 / max((y == 1).sum(), 1), 0.5 / max((y == 0).sum(), 1)) * len(y)
        optimiser, r = Adam(self.p, rate), np.random.default_rng(seed)
        for epoch in range(epochs):
            optimiser.rate = rate * (1 - epoch / epochs) + 1e-4
            order = r.permutation(len(texts))
            for i in range(0, len(order), batch):
                docs = order[i : i + batch]
                pick = [r.choice(np.arange(first[d], first[d + 1]), min(6, first[d + 1] - first[d]), replace=False) for d in docs]
                optimiser.step(self._gradients(rows[np.concatenate(pick)], np.repeat(np.arange(len(docs)), [len(x) for x in pick]), y[docs], weight[docs]))
        return self

    def _gradients(self, rows: np.ndarray, of: np.ndarray, y: np.ndarray, weight: np.ndarray) -> dict[str, np.ndarray]:
        p, n = self.p, len(y)
        x, a, pooled, h, z = self._chunk(rows)
        top, mean, out = self._combined(z, of, n)
        d = ((sigmoid(out) - y) * weight / n).astype(np.float32)
        count = np.bincount(of, minlength=n)
        is_top = z == top[of]
        ties = np.bincount(of, is_top, minlength=n)
        dz = (d[of] * (p["combine"][0] * is_top / ties[of] + p["combine"][1] / count[of])).astype(np.float32)
        g = {"combine": np.asarray([(d * top).sum(), (d * mean).sum(), d.sum()], np.float32), "out": h.T @ dz, "out_bias": dz.sum(keepdims=True)}
        dh = np.outer(dz, p["out"]) * (h > 0)
        g["hidden"], g["hidden_bias"] = pooled.T @ dh, dh.sum(axis=0)
        dp = dh @ p["hidden"].T
        da = np.repeat(dp[:, None, FILTERS:] / POSITIONS, POSITIONS, axis=1)
        best = a.argmax(axis=1)
        np.put_along_axis(da, best[:, None, :], np.take_along_axis(da, best[:, None, :], 1) + dp[:, None, :FILTERS], 1)
        da = (da * (a > 0)).reshape(-1, FILTERS)
        g["filters"], g["bias"] = x.T @ da, da.sum(axis=0)
        dx = (da @ p["filters"].T).reshape(len(rows), POSITIONS, WIDTH, EMBED)
        de = np.zeros((len(rows), CHUNK, EMBED), np.float32)
        for k in range(WIDTH):
            de[:, k : k + STRIDE * POSITIONS : STRIDE] += dx[:, :, k]
        g["embed"] = np.stack([np.bincount(rows.ravel(), de[..., j].ravel(), minlength=256) for j in range(EMBED)], axis=1).astype(np.float32)
        return g


def fit_quality(docs: DataFrame, labels: DataFrame, per_class: int = 1200, max_bytes: int = 12 << 20) -> ByteConvNet:
    """Learn ``labels.quality`` on the driver from a sample of at most 2 x ``per_class`` documents."""
    return ByteConvNet().fit(*labelled_sample(docs, labels, "quality", per_class, max_bytes))


def score_quality(docs: DataFrame, model: ByteConvNet) -> DataFrame:
    """doc_id and the probability of label 1 of every whole text."""
    return score_documents(docs, model)
