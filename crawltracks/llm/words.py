"""Vectorised words, windows and hashes over Arrow string columns.

All functions work on one Arrow batch at a time: a column of texts is seen as one byte
buffer with document offsets, so no Python object is made for a word. Nulls count as
empty texts. A word is a maximal run of bytes other than space and 0x09-0x0D, which are
the same in every UTF-8 text.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa

def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit multiply-xorshift generator; a bijection of 64-bit integers."""
    x = x ^ (x >> np.uint64(30))
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_LEFT, _LONG = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)
_MASKS = np.asarray([(1 << 8 * k) - 1 for k in range(9)], np.uint64)


def _word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A hash of each byte span: blocks of eight bytes, each mixed with its place in the word, summed and mixed again."""
    sizes = ends - starts
    blocks = (sizes + 7) >> 3
    first = np.cumsum(blocks) - blocks
    of = np.repeat(np.arange(len(starts)), blocks)
    number = np.arange(len(of)) - first[of]
    at = starts[of] + 8 * number
    padded = np.concatenate([data, np.zeros(8, np.uint8)])
    block = np.ndarray(len(data) + 1, "<u8", buffer=padded, strides=(1,))[at]
    block &= _MASKS[np.minimum(ends[of] - at, 8)]
    salts = mix(np.arange(1, int(blocks.max(initial=0)) + 1, dtype=np.uint64) * _LONG)
    return mix(np.add.reduceat(mix(block ^ salts[number]), first) + sizes.astype(np.uint64) * _LEFT)


_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_LETTER = np.zeros(256, bool)
_LETTER[48:58] = _LETTER[97:123] = _LETTER[128:] = True


@dataclass
class Words:
    """Words of a batch: byte spans into ``data``, document of each, first word of each document."""

    data: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    first: np.ndarray  # word index where a document begins; one entry more than documents
    hashes: np.ndarray

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def document_of(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), self.counts)


def text_buffer(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all texts and len(texts)+1 offsets; a null is empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if texts.null_count:
        texts = texts.fill_null("")
    if not pa.types.is_large_string(texts.type):
        texts = texts.cast(pa.large_string())
    _, off, data = texts.buffers()
    offsets = np.frombuffer(off, np.int64)[texts.offset : texts.offset + len(texts) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    raw = raw[offsets[0] : offsets[-1]] if len(offsets) else raw[:0]
    return raw, offsets - offsets[0]


def words_of(texts: pa.Array, hashed: bool = True, letters: bool = False) -> Words:
    """Words of a string column, with a 64-bit hash of each.

    letters: words are runs of ASCII letters (lower-cased), digits and other than ASCII instead.
    """
    data, offsets = text_buffer(texts)
    n = len(data)
    if letters:
        data = _LOWER[data]
        word = _LETTER[data]
    else:
        word = (data != 32) & ((data < 9) | (data > 13))
    begins = word.copy()
    begins[1:] &= ~word[:-1]
    ends = word.copy()
    ends[:-1] &= ~word[1:]
    inner = offsets[(offsets > 0) & (offsets < n)]
    begins[inner] = word[inner]
    ends[inner - 1] = word[inner - 1]
    starts = np.flatnonzero(begins)
    stops = np.flatnonzero(ends) + 1
    first = np.searchsorted(starts, offsets)
    hashes = np.zeros(0, np.uint64)
    if hashed and len(starts):
        hashes = _word_hashes(data, starts, stops)
    return Words(data, starts, stops, first, hashes)


def windows(hashes: np.ndarray, size: int) -> np.ndarray:
    """Hash of each run of ``size`` consecutive word hashes, mixed at every doubling; document borders are not looked at."""
    n = len(hashes) - size + 1
    if n < 1:
        return np.zeros(0, np.uint64)
    level, width, out, done = hashes, 1, None, 0
    while True:
        if size & width:
            out = level[:n] if out is None else mix(level[done : done + n] * _LONG + out)
            done += width
        if 2 * width > size:
            return out
        level, width = mix(level[:-width] * _LEFT + level[width:]), 2 * width


def window_starts(first: np.ndarray, size: int) -> np.ndarray:
    """Word indices at which a window of ``size`` words lies inside one document."""
    n = int(first[-1])
    if n < size:
        return np.zeros(0, np.int64)
    ok = np.ones(n - size + 1, bool)
    for back in range(1, size):  # starts in the last size-1 words of a document run over its end
        at = first[1:] - back
        at = at[(at >= first[:-1]) & (at < len(ok))]
        ok[at] = False
    return np.flatnonzero(ok)


def plain_words(words: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bytes of all words with one space after each, and where each word begins and ends there."""
    sizes = words.ends - words.starts
    begins = np.cumsum(sizes + 1) - (sizes + 1)
    of = np.repeat(np.arange(len(sizes)), sizes)
    step = np.arange(len(of)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    out = np.full(int((sizes + 1).sum()), 32, np.uint8)
    out[begins[of] + step] = words.data[words.starts[of] + step]
    return out, begins, begins + sizes
