"""Word shingles of many texts at once, as 64-bit hashes."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from .common import U64, Spans, as_bytes, mix64

WORDS = 5
#: White space of the word rule, as UTF-8 bytes.
SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_STEP = U64(0xD6E8FEB86659FD93)


def shingle_sets(texts: pa.Array, k: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct hashes of every text's shingles, one after another, and the n+1 offsets.

    Words are what white space (space, tab to carriage return) leaves, A-Z lower-cased; a text of
    fewer than k words has its whole sequence as one shingle, a text without words none."""
    raw, off = as_bytes(texts)
    n_docs = len(off) - 1
    # a space after each text, so that no word crosses
    at = np.arange(len(raw)) + np.repeat(np.arange(n_docs), np.diff(off))
    buf = np.full(len(raw) + n_docs + 1, 0x20, np.uint8)
    buf[at + 1] = LOWER[raw]
    ink = ~SPACE[buf]
    edge = np.diff(ink.astype(np.int8))
    start, end = np.flatnonzero(edge == 1) + 1, np.flatnonzero(edge == -1) + 1
    word = Spans(buf).of(start, end)
    doc = np.searchsorted(off[1:] + np.arange(1, n_docs + 1), start, side="right")
    count = np.bincount(doc, minlength=n_docs)
    first = np.cumsum(count) - count
    with np.errstate(over="ignore"):
        return _sets(word, count, first, k)


def _sets(word: np.ndarray, count: np.ndarray, first: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    n_docs = len(count)
    if len(word) >= k:
        roll = np.zeros(len(word) - k + 1, U64)
        for j in range(k):
            roll = roll * _STEP + word[j : len(word) - k + 1 + j]
        roll = mix64(roll)
    else:
        roll = np.zeros(0, U64)
    sets = []
    for i in np.arange(n_docs):
        c, f = int(count[i]), int(first[i])
        if c >= k:
            s = np.sort(roll[f : f + c - k + 1])
            if len(s) > 1:
                s = s[np.append(True, s[1:] != s[:-1])]
        elif c:
            h = U64(c)
            for x in word[f : f + c]:
                h = h * _STEP + x
            s = mix64(np.array([h], U64))
        else:
            s = np.zeros(0, U64)
        sets.append(s)
    size = np.fromiter(map(len, sets), np.int64, n_docs)
    return (np.concatenate(sets) if sets else np.zeros(0, U64)), np.concatenate([[0], np.cumsum(size)])
