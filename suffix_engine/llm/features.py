"""Features of whole texts for the classifiers: shares of pairs of character classes, figures of words and lines, hashed words."""

from __future__ import annotations

from collections import Counter

import numpy as np

from suffix_engine.llm.blocks import range_hashes
from suffix_engine.llm.windows import word_ranges

#: Classes of bytes: lower, upper, digit, blank, line end, other control, beyond ASCII, and each mark of its own.
_MARKS = b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
CLASSES = 7 + len(_MARKS)
_CLASS = np.full(256, 5, np.uint16)
_CLASS[97:123], _CLASS[65:91], _CLASS[48:58], _CLASS[32], _CLASS[10], _CLASS[128:] = 0, 1, 2, 3, 4, 6
for _i, _c in enumerate(_MARKS):
    _CLASS[_c] = 7 + _i
FIGURES = 8


def shape_features(b: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """One row for each text of a buffer: root shares of class pairs, and figures; all zero for an empty text."""
    out = np.zeros((len(bounds) - 1, CLASSES * CLASSES + FIGURES), np.float32)
    for i in range(len(out)):
        t = b[bounds[i] : bounds[i + 1]]
        if not len(t):
            continue
        c = _CLASS[t]
        pairs = np.bincount(c[:-1] * np.uint16(CLASSES) + c[1:], minlength=CLASSES * CLASSES)
        out[i, : CLASSES * CLASSES] = np.sqrt(pairs / len(t))
        raw = t.tobytes()
        words = raw.split()
        if not words:
            continue
        counts = Counter(words)
        lines = raw.split(b"\n")
        length = np.fromiter(map(len, words), np.int64, len(words))
        out[i, CLASSES * CLASSES :] = (
            np.log1p(len(words)) / 10,
            length.mean() / 10,
            length.std() / 10,
            len(counts) / len(words),
            max(counts.values()) / len(words),
            len(set(lines)) / len(lines),
            min(len(t) / len(lines) / 500, 2),
            1.0,
        )
    return out


def word_slots(b: np.ndarray, bounds: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Which hashed lower-cased words each text has, as (text, slot) without repeats, and the number of words of each text."""
    low = b.copy()
    low[(low >= 65) & (low <= 90)] += 32
    solid = low.copy()
    solid[_CLASS[low] >= 7] = 32  # marks part words
    begin, end, first = word_ranges(solid, bounds)
    slot = (range_hashes(low, begin, end) % np.uint64(buckets)).astype(np.int64)
    counts = np.diff(first)
    both = np.unique(np.repeat(np.arange(len(bounds) - 1), counts) * buckets + slot)
    return both // buckets, both % buckets, counts


def class_shares(b: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """One row for each text: root shares of the classes of its bytes."""
    n = len(bounds) - 1
    length = np.diff(bounds)
    doc = np.repeat(np.arange(n), length)
    counts = np.bincount(doc * CLASSES + _CLASS[b], minlength=n * CLASSES).reshape(n, CLASSES)
    return np.sqrt(counts / np.maximum(length, 1)[:, None]).astype(np.float32)
