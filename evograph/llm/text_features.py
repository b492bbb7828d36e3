"""Vectorised text features: hashed character trigrams and simple counts."""

from __future__ import annotations

import numpy as np

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_LOWER[[9, 10, 11, 12, 13]] = 32
_DIGIT = np.zeros(256, dtype=bool)
_DIGIT[48:58] = True
_UPPER = np.zeros(256, dtype=bool)
_UPPER[65:91] = True
_SYMBOL = np.zeros(256, dtype=bool)
_SYMBOL[[33, 35, 36, 37, 38, 42, 43, 60, 61, 62, 64, 91, 92, 93, 94, 95, 96, 123, 124, 125, 126]] = True


def doc_of_bytes(offsets: np.ndarray) -> np.ndarray:
    """The text each byte of a group belongs to; the joining newline counts to the text before it."""
    return np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))


def trigrams(data: bytes, offsets: np.ndarray, dims: int) -> np.ndarray:
    """Rows of square-rooted, length-one counts of hashed byte trigrams, one row per text."""
    n = len(offsets) - 1
    raw = _LOWER[np.frombuffer(data + b"\n", dtype=np.uint8)].astype(np.uint32)
    out = np.zeros((n, dims), dtype=np.float32)
    if len(raw) >= 3:
        code = raw[:-2] | raw[1:-1] << np.uint32(8) | raw[2:] << np.uint32(16)
        code = (code * np.uint32(2654435761)) >> np.uint32(32 - int(dims).bit_length() + 1)
        doc = doc_of_bytes(offsets)[: len(code)]
        inside = np.arange(len(code)) + 2 <= offsets[doc + 1] - 1  # the newline after a text may end a trigram
        for a in range(0, n, 64):  # bounded memory: 64 rows at once
            lo, hi = np.searchsorted(doc, [a, min(n, a + 64)])
            m = min(n, a + 64) - a
            k = (doc[lo:hi][inside[lo:hi]] - a) * dims + code[lo:hi][inside[lo:hi]]
            out[a : a + m] = np.sqrt(np.bincount(k, minlength=m * dims)).reshape(m, dims)
    norm = np.sqrt((out**2).sum(axis=1, keepdims=True))
    return out / np.maximum(norm, 1e-12)


def per_text(flag: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Number of set flags of every text."""
    total = np.concatenate(([0], np.cumsum(flag)))
    return (total[np.minimum(offsets[1:], len(flag))] - total[np.minimum(offsets[:-1], len(flag))]).astype(np.float64)


def layout(data: bytes, offsets: np.ndarray) -> np.ndarray:
    """Per text: log size, log lines, log line length, shares of capitals, symbols and digits."""
    raw = np.frombuffer(data, dtype=np.uint8)
    size = np.maximum(np.diff(offsets) - 1, 0).astype(np.float64)
    lines = per_text(raw == 10, offsets) + 1
    lines[:-1] -= 1  # the joining newline
    safe = np.maximum(size, 1)
    return np.stack([np.log1p(size), np.log1p(np.maximum(lines, 0)), np.log1p(size / np.maximum(lines, 1)), per_text(_UPPER[raw], offsets) / safe, per_text(_SYMBOL[raw], offsets) / safe, per_text(_DIGIT[raw], offsets) / safe], axis=1)


def repetition(h: np.ndarray, word_offsets: np.ndarray) -> np.ndarray:
    """Per text: share of distinct words, of words equal to the word before, log number of words."""
    n = len(word_offsets) - 1
    count = np.diff(word_offsets).astype(np.float64)
    doc = np.repeat(np.arange(n), np.diff(word_offsets))
    if len(h):
        order = np.lexsort((h, doc))
        hs, ds = h[order], doc[order]
        first = np.append(True, (hs[1:] != hs[:-1]) | (ds[1:] != ds[:-1]))
        distinct = np.bincount(ds[first], minlength=n)
        same = np.append(False, (h[1:] == h[:-1]) & (doc[1:] == doc[:-1]))
        again = np.bincount(doc[same], minlength=n)
    else:
        distinct = again = np.zeros(n)
    safe = np.maximum(count, 1)
    return np.stack([distinct / safe, again / safe, np.log1p(count)], axis=1)
