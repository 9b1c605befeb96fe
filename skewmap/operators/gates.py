"""Approximate-membership gates: Bloom, XOR and binary fuse filters, one per shard of the key space.

A gate of a shard is a row (family, parameter, seed, number of cells, cells). Cells of XOR and fuse gates are
fingerprints of ``r`` bits, packed; Bloom cells are bits. Building and probing are the same functions in
numpy for whole shards; ``might_contain`` is the probe of a Bloom gate as a Column. A family that was registered
with its own functions is built and probed by them; any other name is refused.
"""

from __future__ import annotations

import struct

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions import gatecost
from . import hashing
from .peeling import assign, peel

TRIES = 200


def pack_bits(values: np.ndarray, bits: int) -> bytes:
    """Unsigned values of ``bits`` bits each, end to end."""
    planes = (values[:, None] >> np.arange(bits)) & 1
    return np.packbits(planes.astype(np.uint8).ravel(), bitorder="little").tobytes()


def unpack_bits(data: bytes, bits: int, n: int) -> np.ndarray:
    planes = np.unpackbits(np.frombuffer(data, np.uint8), count=n * bits, bitorder="little").reshape(n, bits)
    return (planes.astype(np.int64) << np.arange(bits)).sum(1)


def _xor_positions(h: np.ndarray, seed: int, cells: int) -> np.ndarray:
    third = cells // 3
    return np.stack([hashing.reduce_to(hashing.xxhash64(h, seed * 8 + i), third) + i * third for i in range(3)], 1)


def _fuse_positions(h: np.ndarray, seed: int, cells: int, arity: int, length: int) -> np.ndarray:
    start = hashing.reduce_to(hashing.xxhash64(h, seed * 8), cells - (arity - 1) * length) // length * length
    inner = [hashing.reduce_to(hashing.xxhash64(h, seed * 8 + 1 + i), length) for i in range(arity)]
    return np.stack([start + i * length + x for i, x in enumerate(inner)], 1)


def _fingerprints(h: np.ndarray, seed: int, bits: int) -> np.ndarray:
    return (hashing.xxhash64(h, seed * 8 + 7) & np.uint64((1 << bits) - 1)).astype(np.int64)


def _bloom_bits(h: np.ndarray, seed: int, cells: int, hashes: int) -> np.ndarray:
    return np.stack([hashing.reduce_to(hashing.xxhash64(h, seed * 64 + i), cells) for i in range(hashes)], 1)


ARITY = {"xor": 0, "fuse3": 3, "fuse4": 4}


def _bloom_shape(family: str, param: float) -> tuple[int, float] | None:
    """Number of hashes and bits a key of a Bloom family; the idealised one has the whole number of hashes next to its best."""
    if family == "ideal_bloom":
        return max(1, round(param)), 1.44 * param
    if family.startswith("bloom") and family[5:].isdigit():
        return int(family[5:]), param
    return None


def _own(family: str | gatecost.GateFamily) -> gatecost.GateFamily | None:
    """The registered family that has functions of its own, if the name is of one."""
    found = family if isinstance(family, gatecost.GateFamily) else gatecost.FAMILIES.get(family)
    return found if found is not None and found.build is not None and found.probe is not None else None


def named(family: str):
    """What to hand to workers for a family: its name, or the registered family itself, which they may not know."""
    if family in ARITY or _bloom_shape(family, 1):
        return family
    if (own := _own(family)) is None:
        raise ValueError(f"gate family {family!r} has no functions to build and probe it")
    return own


def peeled(family: str, h: np.ndarray, seed: int = 0) -> tuple[int, int, int, list, np.ndarray]:
    """Seed, cells, segment length, layers and positions of an XOR or fuse gate over distinct prepared hashes."""
    for s in range(seed, seed + TRIES):
        grown = 1 + 0.01 * (s - seed)
        if family == "xor":
            length, cells = 0, gatecost.xor_cells(len(h), grown)
            at = _xor_positions(h, s, cells)
        else:
            arity = ARITY[family]
            length, segments = gatecost.fuse_shape(int(len(h) * grown), arity)
            cells = (segments + arity - 1) * length
            at = _fuse_positions(h, s, cells, arity, length)
        layers, left = peel(at, cells)
        if not len(left):
            return s, cells, length, layers, at
    raise RuntimeError(f"no {family} gate for {len(h)} keys after {TRIES} seeds")


def nested(family: str, h: np.ndarray, others: np.ndarray, bits: int = 8) -> tuple[int, np.ndarray]:
    """Cells of an XOR or fuse gate, and by how much the fingerprints of other keys miss.

    Fingerprints of fewer bits are the low bits of those of more, and so are the cells: a key passes the gate
    of r bits if the low r bits of its miss are zero. One peeling so tells the leaks of all settings.
    """
    h, others = hashing.prepared(np.unique(h)), hashing.prepared(others)
    if not len(h):
        return 0, np.full(len(others), -1)
    seed, cells, length, layers, at = peeled(family, h)
    values = np.zeros(cells, np.int64)
    assign(layers, at, _fingerprints(h, seed, bits), values)
    at = _xor_positions(others, seed, cells) if family == "xor" else _fuse_positions(others, seed, cells, ARITY[family], length)
    return cells, np.bitwise_xor.reduce(values[at], axis=1) ^ _fingerprints(others, seed, bits)


def bloom_hashes(family: str, h: np.ndarray) -> list[np.ndarray] | None:
    """What decides the bits of keys in Bloom gates of any size with seed 0; None for other families."""
    shape = _bloom_shape(family, 1)
    return [hashing.xxhash64(h, i) for i in range(shape[0])] if shape and family != "ideal_bloom" else None


def bloom_leaks(family: str, param: float, hashed: list[np.ndarray], inside: np.ndarray, outside: np.ndarray) -> tuple[np.ndarray, int]:
    """Which of ``outside`` pass the Bloom gate that ``build`` makes for ``inside``, rows of keys of different hashes, and its bytes."""
    cells = gatecost.bloom_cells(_bloom_shape(family, param)[1], len(inside))
    bits = np.zeros(cells, bool)
    for x in hashed:
        bits[hashing.reduce_to(x[inside], cells)] = True
    for x in hashed:
        outside = outside[bits[hashing.reduce_to(x[outside], cells)]]
    return outside, 12 + -(-cells // 8)


def build(family, param: float, h: np.ndarray, seed: int = 0) -> bytes:
    """Gate over distinct key hashes: a header (seed, cells, segment length) and the cells."""
    if (own := _own(family)) is not None:
        return own.build(param, np.unique(h), seed) if len(h) else b""
    shape = _bloom_shape(family, param)
    if shape is None and family not in ARITY:
        raise ValueError(f"unknown gate family {family!r}")
    if shape is None and int(param) < 1:
        raise ValueError(f"a {family} gate has at least one bit a cell, not {param}")
    h = hashing.prepared(np.unique(h))
    if not len(h):
        return b""
    if shape is not None:
        cells = gatecost.bloom_cells(shape[1], len(h))
        bits = np.zeros(cells, np.uint8)
        bits[_bloom_bits(h, seed, cells, shape[0]).ravel()] = 1
        return struct.pack("<III", seed, cells, 0) + np.packbits(bits, bitorder="little").tobytes()
    r = int(param)
    s, cells, length, layers, at = peeled(family, h, seed)
    values = np.zeros(cells, np.int64)
    assign(layers, at, _fingerprints(h, s, r), values)
    return struct.pack("<III", s, cells, length) + pack_bits(values, r)


def probe(family, param: float, gate: bytes, h: np.ndarray) -> np.ndarray:
    """Whether each key hash may be in the gate; never False for a key it was built from."""
    if not gate:
        return np.zeros(len(h), bool)
    if (own := _own(family)) is not None:
        return np.asarray(own.probe(param, gate, h), bool)
    seed, cells, length = struct.unpack_from("<III", gate)
    h = hashing.prepared(h)
    if (shape := _bloom_shape(family, param)) is not None:
        bits = np.unpackbits(np.frombuffer(gate, np.uint8, offset=12), bitorder="little", count=cells)
        return bits[_bloom_bits(h, seed, cells, shape[0])].all(1)
    if family not in ARITY:
        raise ValueError(f"unknown gate family {family!r}")
    r = int(param)
    values = unpack_bits(gate[12:], r, cells)
    at = _xor_positions(h, seed, cells) if family == "xor" else _fuse_positions(h, seed, cells, ARITY[family], length)
    return np.bitwise_xor.reduce(values[at], axis=1) == _fingerprints(h, seed, r)


def might_contain(words: Column, cells: Column, key_hash: Column, hashes: int, seed: int = 0) -> Column:
    """Probe of a Bloom gate as a Column, for a join with its words (array of longs): no Python at run time."""
    out = F.lit(True)
    for i in range(hashes):
        h = F.shiftrightunsigned(F.xxhash64(key_hash, F.lit(seed * 64 + i).cast("long")), 33)
        at = F.shiftrightunsigned(h * cells, 31)
        word = F.get(words, F.shiftright(at, 6).cast("int"))
        out = out & (F.getbit(word, (at % 64).cast("int")) == 1)
    return out
