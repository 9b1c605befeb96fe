"""Spark's xxhash64 of a long, in numpy, so that positions are the same as Columns and in Python workers."""

from __future__ import annotations

import numpy as np

#: Fixed primes of the published xxHash64 algorithm.
P1, P2, P3 = np.uint64(0x9E3779B185EBCA87), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9)
P4, P5 = np.uint64(0x85EBCA77C2B2AE63), np.uint64(0x27D4EB2F165667C5)


def _rotl(x: np.ndarray, n: int) -> np.ndarray:
    return (x << np.uint64(n)) | (x >> np.uint64(64 - n))


def _hash_long(x: np.ndarray, seed: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        h = seed + P5 + np.uint64(8)
        h = h ^ (_rotl(x * P2, 31) * P1)
        h = _rotl(h, 27) * P1 + P4
        h = (h ^ (h >> np.uint64(33))) * P2
        h = (h ^ (h >> np.uint64(29))) * P3
        return h ^ (h >> np.uint64(32))


def prepared(h: np.ndarray) -> np.ndarray:
    """First half of ``xxhash64(h, ...)``, as uint64, to be shared by hashes of the same longs; idempotent."""
    h = np.asarray(h)
    if h.dtype == np.uint64:
        return h
    h = h.astype(np.int64).astype(np.uint64)
    return _hash_long(h, np.full(h.shape, 42, np.uint64))


def xxhash64(first, second) -> np.ndarray:
    """``xxhash64(first, second)`` of two longs, as uint64 (the seed of Spark's function is 42); ``first`` may be prepared."""
    first = prepared(first)
    return _hash_long(np.asarray(second, np.int64).astype(np.uint64), first)


def reduce_to(h: np.ndarray, n) -> np.ndarray:
    """Upper 31 bits of a hash onto [0, n), n below 2**31."""
    return (((h >> np.uint64(33)) * np.asarray(n).astype(np.uint64)) >> np.uint64(31)).astype(np.int64)
