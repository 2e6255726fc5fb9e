"""Operator 10: a bidirectional gated recurrent network with attention pooling, in numpy.

A word enters as an embedding of its own (words seen in several training texts) beside the
sum of its character grams' embeddings (over the root of their number). Windows of ``LENGTH`` words that overlap by
``LENGTH - STEP`` cover the whole text; both directions of a gated recurrent unit run over a
window, attention pools their states, and the text's score is that of its worst window.

Cases: null and empty texts are one window of padding and get the score of that; without
labels of both kinds every score is the share of label 1 (0.5 without labels); rows that
repeat are scored each; an empty table gives an empty table; other columns are not looked at.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from crawltracks.llm.training import Adam, labelled_sample, score_documents, sigmoid
from crawltracks.llm.words import Words, words_of

LENGTH, STEP = 24, 16
WORD, CHAR, GRAMS, STATE, ATTEND = 8, 12, 1 << 15, 12, 8


@dataclass
class _Inputs:
    """Distinct words of a column: row in the word table, character grams; and windows as rows of distinct words."""

    word: np.ndarray
    gram: np.ndarray
    gram_first: np.ndarray
    window: np.ndarray  # windows x LENGTH, the number of distinct words standing for padding
    of: np.ndarray  # document of each window


def _grams(words: Words, pick: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashed grams of three and five bytes around every byte of the picked words, and where each word's begin."""
    sizes = words.ends[pick] - words.starts[pick]
    first = np.concatenate([[0], np.cumsum(sizes)])
    word = np.repeat(np.arange(len(pick)), sizes)
    real = np.arange(first[-1]) + 2 + 4 * word  # two borders on either side of a word
    flat = np.ones(first[-1] + 4 * len(pick) + 4, np.int64)
    flat[real] = words.data[words.starts[pick][word] - first[word] + np.arange(first[-1])]
    three = flat[real - 1] * 7919 + flat[real] * 104729 + flat[real + 1] * 1299709
    five = three * 31 + flat[real - 2] * 15485863 + flat[real + 2] * 32452843 + 1
    return np.stack([three % GRAMS, five % GRAMS], axis=1).ravel(), 2 * first


class ToxicityNet:
    def __init__(self, seed: int = 11):
        r, f = np.random.default_rng(seed), np.float32
        width = WORD + CHAR
        self.seed = seed
        self.known = np.zeros(0, np.uint64)
        self.p = {"word": np.zeros((1, WORD), f), "char": r.normal(0, 0.1, (GRAMS, CHAR)).astype(f)}
        for d in ("f", "b"):
            self.p[f"in_{d}"] = r.normal(0, 1 / np.sqrt(width), (width, 3 * STATE)).astype(f)
            self.p[f"in_bias_{d}"] = np.zeros(3 * STATE, f)
            self.p[f"rec_{d}"] = r.normal(0, 1 / np.sqrt(STATE), (STATE, 3 * STATE)).astype(f)
        self.p["attend"] = r.normal(0, 0.4, (2 * STATE, ATTEND)).astype(f)
        self.p["attend_to"] = r.normal(0, 0.4, ATTEND).astype(f)
        self.p["out"] = r.normal(0, 0.4, 2 * STATE).astype(f)
        self.p["out_bias"] = np.full(1, -1.0, f)
        self.constant: float | None = None

    def inputs(self, texts: pa.Array) -> _Inputs:
        words = words_of(texts, letters=True)
        distinct, pick, inverse = np.unique(words.hashes, return_index=True, return_inverse=True)
        at = np.searchsorted(self.known, distinct)
        row = np.zeros(len(distinct), np.int64)
        if len(self.known):
            near = np.minimum(at, len(self.known) - 1)
            row = np.where(self.known[near] == distinct, near + 1, 0)
        gram, first = _grams(words, pick) if len(pick) else (np.zeros(0, np.int64), np.zeros(1, np.int64))
        sizes = words.counts
        count = np.maximum(1, -(-np.maximum(sizes - (LENGTH - STEP), 0) // STEP))
        of = np.repeat(np.arange(len(sizes)), count)
        number = np.arange(len(of)) - np.repeat(np.cumsum(count) - count, count)
        start = words.first[of] + number * STEP
        index = start[:, None] + np.arange(LENGTH)
        padded = np.append(inverse.astype(np.int64), len(distinct))
        inside = index < words.first[of + 1][:, None]
        window = np.where(inside, padded[np.minimum(index, len(inverse))], len(distinct))
        return _Inputs(row, gram, first, window, of)

    def _vectors(self, x: _Inputs) -> np.ndarray:
        """Input of every distinct word; the last row is padding."""
        out = np.zeros((len(x.word) + 1, WORD + CHAR), np.float32)
        if len(x.word):
            out[:-1, :WORD] = self.p["word"][x.word]
            for i in range(0, len(x.word), 4096):
                a, b = x.gram_first[i], x.gram_first[min(i + 4096, len(x.word))]
                part = x.gram_first[i : min(i + 4096, len(x.word))] - a
                out[i : i + len(part), WORD:] = np.add.reduceat(self.p["char"][x.gram[a:b]], part, axis=0)
            out[:-1, WORD:] /= np.sqrt(np.diff(x.gram_first))[:, None]
        return out

    def _run(self, projected: np.ndarray, d: str, window: np.ndarray, inside: np.ndarray, keep: bool):
        """States of one direction at all places; with ``keep`` what the way back needs."""
        rec, n = self.p[f"rec_{d}"], len(window)
        h = np.zeros((n, STATE), np.float32)
        states, kept = np.empty((n, LENGTH, STATE), np.float32), []
        for t in range(LENGTH) if d == "f" else range(LENGTH - 1, -1, -1):
            a, u = projected[window[:, t]], h @ rec
            gates = 1 / (1 + np.exp(-(a[:, : 2 * STATE] + u[:, : 2 * STATE])))
            z, r = gates[:, :STATE], gates[:, STATE:]
            c = np.tanh(a[:, 2 * STATE :] + r * u[:, 2 * STATE :])
            if keep:
                kept.append((t, h, z, r, c, u[:, 2 * STATE :]))
            h = h + z * (c - h) * inside[:, t, None]
            states[:, t] = h
        return states, kept

    def _forward(self, vectors: np.ndarray, window: np.ndarray, keep: bool = False, projected: dict | None = None):
        p = self.p
        inside = (window < len(vectors) - 1).astype(np.float32)
        projected = projected or {d: vectors @ p[f"in_{d}"] + p[f"in_bias_{d}"] for d in "fb"}
        forth, kept_f = self._run(projected["f"], "f", window, inside, keep)
        back, kept_b = self._run(projected["b"], "b", window, inside, keep)
        states = np.concatenate([forth, back], axis=2)
        q = np.tanh(states @ p["attend"])
        e = np.exp(np.clip(q @ p["attend_to"], -20, 20)) * inside
        share = e / np.maximum(e.sum(axis=1, keepdims=True), 1e-9)
        pooled = (share[:, :, None] * states).sum(axis=1)
        z = pooled @ p["out"] + p["out_bias"][0]
        return z, (inside, kept_f, kept_b, states, q, share, pooled)

    def logits(self, x: _Inputs, block: int = 2048) -> np.ndarray:
        vectors = self._vectors(x)
        projected = {d: vectors @ self.p[f"in_{d}"] + self.p[f"in_bias_{d}"] for d in "fb"}
        return np.concatenate([self._forward(vectors, x.window[i : i + block], projected=projected)[0] for i in range(0, len(x.window), block)])

    def __call__(self, texts: pa.Array) -> np.ndarray:
        if not len(texts):
            return np.zeros(0)
        if self.constant is not None:
            return np.full(len(texts), self.constant)
        x = self.inputs(texts)
        return sigmoid(np.maximum.reduceat(self.logits(x), np.searchsorted(x.of, np.arange(len(texts)))))

    def _gradients(self, x: _Inputs, vectors: np.ndarray, window: np.ndarray, y: np.ndarray, weight: np.ndarray) -> dict[str, np.ndarray]:
        p = self.p
        z, (inside, kept_f, kept_b, states, q, share, pooled) = self._forward(vectors, window, keep=True)
        d = ((sigmoid(z) - y) * weight / len(y)).astype(np.float32)
        g = {"out": pooled.T @ d, "out_bias": d.sum(keepdims=True)}
        dpooled = np.outer(d, p["out"])
        dshare = (states * dpooled[:, None, :]).sum(axis=2)
        ds = share * (dshare - (share * dshare).sum(axis=1, keepdims=True))
        dq = ds[:, :, None] * p["attend_to"] * (1 - q * q)
        g["attend_to"] = (q * ds[:, :, None]).sum(axis=(0, 1))
        g["attend"] = states.reshape(-1, 2 * STATE).T @ dq.reshape(-1, ATTEND)
        dstates = share[:, :, None] * dpooled[:, None, :] + dq @ p["attend"].T
        dx = np.zeros((len(window), LENGTH, WORD + CHAR), np.float32)
        for name, kept, part in (("f", kept_f, dstates[:, :, :STATE]), ("b", kept_b, dstates[:, :, STATE:])):
            dh, rec = np.zeros((len(window), STATE), np.float32), p[f"rec_{name}"]
            g[f"rec_{name}"], da_all = np.zeros_like(rec), np.zeros((len(window), LENGTH, 3 * STATE), np.float32)
            for t, h, zt, r, c, u in reversed(kept):
                dh = dh + part[:, t]
                m = inside[:, t, None]
                dc = dh * m * zt * (1 - c * c)
                dz, dr = dh * m * (c - h) * zt * (1 - zt), dc * u * r * (1 - r)
                du = np.concatenate([dz, dr, dc * r], axis=1)
                da_all[:, t] = np.concatenate([dz, dr, dc], axis=1)
                g[f"rec_{name}"] += h.T @ du
                dh = dh * (1 - m * zt) + du @ rec.T
            flat = da_all.reshape(-1, 3 * STATE)
            g[f"in_{name}"], g[f"in_bias_{name}"] = vectors[window.ravel()].T @ flat, flat.sum(axis=0)
            dx += da_all @ p[f"in_{name}"].T
        used, inverse = np.unique(window.ravel(), return_inverse=True)
        dv = np.zeros((len(used), WORD + CHAR), np.float32)
        np.add.at(dv, inverse.ravel(), dx.reshape(-1, WORD + CHAR))
        dv, used = dv[used < len(x.word)], used[used < len(x.word)]
        g["word"], g["char"] = np.zeros_like(p["word"]), np.zeros_like(p["char"])
        np.add.at(g["word"], x.word[used], dv[:, :WORD])
        g["word"][0] = 0  # words not known
        for u, v in zip(used, dv[:, WORD:]):
            a, b = x.gram_first[u], x.gram_first[u + 1]
            np.add.at(g["char"], x.gram[a:b], v / np.sqrt(b - a))
        return g

    def fit(self, texts: list[str], y: np.ndarray, epochs: int = 6, batch: int = 48, rate: float = 0.02, least: int = 3) -> "ToxicityNet":
        """Each text learns through its worst window; ``least``: texts that a known word stands in."""
        if not len(y) or y.min() == y.max():
            self.constant = float(y.mean()) if len(y) else 0.5
            return self
        r = np.random.default_rng(self.seed)
        column = pa.array(texts, pa.string())
        seen = []
        for text in texts:  # one text at a time keeps the driver small
            seen.append(np.unique(words_of(pa.array([text], pa.string()), letters=True).hashes))
        hashes, times = np.unique(np.concatenate(seen), return_counts=True)
        self.known = hashes[times >= least]
        self.p["word"] = r.normal(0, 0.1, (len(self.known) + 1, WORD)).astype(np.float32)
        self.p["word"][0] = 0
        weight = np.where(y == 1, 0.5 / max((y == 1).sum(), 1), 0.5 / max((y == 0).sum(), 1)) * len(y)
        optimiser = Adam(self.p, rate)
        for epoch in range(epochs):
            optimiser.rate = rate * (1 - epoch / epochs) + 1e-3
            order = r.permutation(len(texts))
            for i in range(0, len(order), batch):
                docs = order[i : i + batch]
                x = self.inputs(column.take(pa.array(docs)))
                z = self.logits(x)
                first = np.searchsorted(x.of, np.arange(len(docs)))
                worst = [a + int(np.argmax(z[a:b])) for a, b in zip(first, np.append(first[1:], len(z)))]
                optimiser.step(self._gradients(x, self._vectors(x), x.window[worst], y[docs], weight[docs]))
        return self


def fit_toxicity(docs: DataFrame, labels: DataFrame, per_class: int = 1200, max_bytes: int = 8 << 20) -> ToxicityNet:
    """Learn ``labels.toxic`` on the driver from a sample of at most 2 x ``per_class`` documents."""
    return ToxicityNet().fit(*labelled_sample(docs, labels, "toxic", per_class, max_bytes))


def score_toxicity(docs: DataFrame, model: ToxicityNet) -> DataFrame:
    """doc_id and the probability of label 1 of every whole text."""
    return score_documents(docs, model)
