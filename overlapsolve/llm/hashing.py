"""Hashed words and word pairs of many texts at once."""

from __future__ import annotations

import numpy as np

_SPACE = np.zeros(256, bool)
_SPACE[list(b" \t\n\x0b\f\r")] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_POWERS = np.array([pow(1_000_003, k, 1 << 64) for k in range(64)], np.uint64)
_MIX = np.uint64(0x9E3779B97F4A7C15)


def word_hashes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(text index, 64-bit hash) of each white-space word, A-Z in lower case; beyond its 64th byte a word's place is not told apart."""
    if not texts:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    data = np.frombuffer(b"\n".join(texts) + b"\n", np.uint8)
    first = np.cumsum([0] + [len(t) + 1 for t in texts])[:-1]
    space = _SPACE[data]
    start = np.flatnonzero(~space & np.concatenate([[True], space[:-1]]))
    if not len(start):
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    end = np.flatnonzero(space & np.concatenate([[False], ~space[:-1]]))
    place = np.arange(len(data)) - np.repeat(np.concatenate([[0], start[1:]]), np.diff(np.concatenate([[0], start[1:], [len(data)]])))
    with np.errstate(over="ignore"):
        terms = (_LOWER[data].astype(np.uint64) + np.uint64(1)) * _POWERS[np.clip(place, 0, 63)]
        terms[space] = 0
        h = np.add.reduceat(terms, start) * _MIX
        h = (h ^ (h >> np.uint64(29)) ^ (end - start).astype(np.uint64)) * _MIX
    return np.searchsorted(first, start, side="right") - 1, h


def ngram_buckets(texts: list[bytes], bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(text index, bucket) of each word and each pair of neighbouring words."""
    doc, h = word_hashes(texts)
    with np.errstate(over="ignore"):
        pair = (h[:-1] * np.uint64(0xC2B2AE3D27D4EB4F) + h[1:]) * _MIX
    same = doc[1:] == doc[:-1]
    keys = np.concatenate([h, pair[same]]) >> np.uint64(64 - bits)
    return np.concatenate([doc, doc[1:][same]]), keys.astype(np.int64)
