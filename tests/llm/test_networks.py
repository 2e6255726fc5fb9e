"""The two networks against plain forward passes and finite differences."""

import numpy as np
import pyarrow as pa
import pytest

from crawltracks.llm import quality, toxicity
from crawltracks.llm.training import sigmoid

TEXTS = ["a vile thing it is", "", "good words " * 40, "one", "tail " * 30 + "vile", "x" * 700]


def loss(z, y, weight):
    p = sigmoid(z.astype(np.float64))
    return float(-(weight * (y * np.log(p) + (1 - y) * np.log(1 - p))).sum() / len(y))


def directional(net, grads, value, rtol=0.04, eps=2e-3):
    """Every parameter's gradient along a random direction."""
    r = np.random.default_rng(5)
    for name, g in grads.items():
        old = net.p[name]
        v = r.normal(0, 1, old.shape).astype(old.dtype) * (np.asarray(g) != 0)
        if not v.any():
            continue
        ends = []
        for sign in (1, -1):
            net.p[name] = old + old.dtype.type(sign * eps) * v
            ends.append(value())
        net.p[name] = old
        assert (ends[0] - ends[1]) / (2 * eps) == pytest.approx(float((g * v).sum()), rel=rtol, abs=3e-4), name


def test_toxicity_gradients():
    net = toxicity.ToxicityNet()
    net.fit(["vile a b", "a b c", "vile c", "b c"] * 3, np.asarray([1, 0, 1, 0] * 3, np.float32), epochs=1, least=1)
    x = net.inputs(pa.array(TEXTS, pa.string()))
    y, weight = (np.arange(len(x.window)) % 2).astype(np.float32), np.linspace(0.5, 1.5, len(x.window)).astype(np.float32)
    grads = net._gradients(x, net._vectors(x), x.window, y, weight)
    directional(net, grads, lambda: loss(net._forward(net._vectors(x), x.window)[0], y, weight))


def test_quality_gradients():
    net = quality.ByteConvNet()
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    rows, of = quality.chunks_of(pa.array(TEXTS, pa.string()))
    y, weight = (np.arange(len(TEXTS)) % 2).astype(np.float32), np.linspace(0.5, 1.5, len(TEXTS)).astype(np.float32)
    value = lambda: loss(net._combined(net._chunk(rows)[4], of, len(TEXTS))[2], y, weight)
    directional(net, net._gradients(rows, of, y, weight), value, rtol=0.01, eps=1e-7)  # small steps, as greatest values have kinks


def test_toxicity_scores_are_those_of_a_plain_pass():
    net = toxicity.ToxicityNet()
    net.fit(["vile a b", "a b c", "vile c", "b c"] * 3, np.asarray([1, 0, 1, 0] * 3, np.float32), epochs=2, least=1)
    p, s = net.p, toxicity.STATE

    def gru(vectors, d):
        h, out = np.zeros(s), []
        for v in vectors:
            a, u = v @ p[f"in_{d}"] + p[f"in_bias_{d}"], h @ p[f"rec_{d}"]
            z, r = sigmoid(a[:s] + u[:s]), sigmoid(a[s : 2 * s] + u[s : 2 * s])
            h = h + z * (np.tanh(a[2 * s :] + r * u[2 * s :]) - h)
            out.append(h)
        return out

    for text in TEXTS:
        x = net.inputs(pa.array([text], pa.string()))
        vectors, n = net._vectors(x), len(text.split())
        starts = [k for k in range(0, max(n, 1), toxicity.STEP) if k == 0 or k + toxicity.LENGTH - toxicity.STEP < n]
        assert len(starts) == len(x.window)
        best = -np.inf
        for w, start in enumerate(starts):
            inside = [vectors[k] for k in x.window[w] if k < len(vectors) - 1]
            assert len(inside) == min(n - start, toxicity.LENGTH)
            states = [np.concatenate(pair) for pair in zip(gru(inside, "f"), gru(inside[::-1], "b")[::-1])]
            weights = np.exp([np.tanh(t @ p["attend"]) @ p["attend_to"] for t in states])
            pooled = sum((a * t for a, t in zip(weights / weights.sum(), states)), np.zeros(2 * s)) if states else np.zeros(2 * s)
            best = max(best, pooled @ p["out"] + p["out_bias"][0])
        assert net(pa.array([text]))[0] == pytest.approx(sigmoid(best), abs=1e-4)


def test_quality_scores_are_those_of_a_plain_pass():
    net = quality.ByteConvNet()
    p = net.p
    for text in (*TEXTS, "é" * 600):
        data = text.encode()
        starts = [k for k in range(0, max(len(data), 1), quality.STEP) if k == 0 or k + quality.CHUNK - quality.STEP < len(data)]
        z = []
        for start in starts:
            chunk = data[start : start + quality.CHUNK].ljust(quality.CHUNK, b"\0")
            spans = [chunk[i : i + quality.WIDTH] for i in range(0, quality.CHUNK - quality.WIDTH + 1, quality.STRIDE)]
            a = np.asarray([np.maximum(np.concatenate([p["embed"][c] for c in span]) @ p["filters"] + p["bias"], 0) for span in spans])
            h = np.maximum(np.concatenate([a.max(axis=0), a.mean(axis=0)]) @ p["hidden"] + p["hidden_bias"], 0)
            z.append(h @ p["out"] + p["out_bias"][0])
        want = sigmoid(p["combine"][0] * max(z) + p["combine"][1] * np.mean(z) + p["combine"][2])
        assert net(pa.array([text]))[0] == pytest.approx(want, abs=1e-4)
