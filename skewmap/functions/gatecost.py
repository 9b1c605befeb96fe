"""Cost curves of approximate-membership gates: bits per inserted key at a false-positive rate.

Constants are the published ones: 1.44 log2(1/e) for an idealised Bloom filter, 1.23 slots a key for XOR
filters, 1.125 and 1.075 for binary fuse filters of arity 3 and 4. These are what gates cost at large; a gate over a
shard's few thousand keys takes more, which ``stored`` tells exactly, as building uses the same shapes. Planners of
indexes to be built plan with ``stored`` costs, so that a positive bound is one on what is built.

Any other family can be registered with its curves and with functions to build and probe it.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Setting:
    """A gate setting: family name, parameter (fingerprint bits, or bits per element), its rate and cost."""

    family: str
    param: float
    eps: float
    bits: float


@dataclass(frozen=True)
class GateFamily:
    """A family: ``params`` it can be set to, and curves ``eps(param)`` and ``bits(eps)``."""

    name: str
    params: tuple[float, ...]
    eps: Callable[[float], float]
    bits: Callable[[float], float]
    bits_column: Callable[[Column], Column] = field(repr=False, default=None)
    log_cost: float | None = None  # C where bits = C log2(1/eps)
    #: Stored bits of a gate with a parameter over so many keys, header included; None: as the curve says.
    stored: Callable[[float, int], float] | None = field(repr=False, default=None)
    #: Of registered families: ``build(param, hashes, seed) -> bytes`` and ``probe(param, gate, hashes) -> bool array``.
    build: Callable | None = field(repr=False, default=None)
    probe: Callable | None = field(repr=False, default=None)

    def settings(self, keys: float | None = None) -> list[Setting]:
        """Settings with their costs: at large, or as stored by a gate over ``keys`` keys."""
        if keys is None or self.stored is None:
            return [Setting(self.name, p, self.eps(p), self.bits(self.eps(p))) for p in self.params]
        n = max(1, round(keys))
        return [Setting(self.name, p, self.eps(p), self.stored(p, n) / n) for p in self.params]


#: Header of a gate: seed, number of cells, segment length.
HEADER_BITS = 96


def xor_cells(n: int, grown: float = 1.0) -> int:
    """Cells of an XOR filter over n keys, in three equal parts."""
    return 3 * math.ceil((1.23 * n + 32) * grown / 3)


def fuse_shape(n: int, arity: int) -> tuple[int, int]:
    """Segment length and number of start segments by the published size rules of binary fuse filters."""
    n = max(n, 2)
    if arity == 3:
        length = 1 << int(math.floor(math.log(n) / math.log(3.33) + 2.25))
        factor = max(1.125, 0.875 + 0.25 * math.log(1e6) / math.log(n))
    else:
        length = 1 << int(math.floor(math.log(n) / math.log(2.91) - 0.5))
        factor = max(1.075, 0.77 + 0.305 * math.log(6e5) / math.log(n))
    length = max(4, min(length, 1 << 18))
    segments = max(1, -(-round(n * factor) // length) - (arity - 1))
    return length, segments


def fuse_cells(n: int, arity: int) -> int:
    length, segments = fuse_shape(n, arity)
    return (segments + arity - 1) * length


def bloom_cells(bits: float, n: int) -> int:
    return max(8, math.ceil(bits * n))


def _bytes(bits: float) -> int:
    return 8 * math.ceil(bits / 8)


def _logarithmic(name: str, cost: float, cells: Callable[[float, int], float]) -> GateFamily:
    """A family whose parameter is log2(1/eps); ``cells(param, n)``: bits of its cells."""
    return GateFamily(
        name, tuple(range(1, 9)), lambda r: 2.0**-r, lambda e: cost * math.log2(1 / e), lambda e: F.lit(cost) * F.log2(F.lit(1.0) / e), cost, lambda r, n: _bytes(cells(r, n)) + HEADER_BITS,
    )


def bloom(hashes: int, params: tuple[float, ...] = tuple(range(1, 17))) -> GateFamily:
    """Bloom filter with a fixed number of hash functions, set by its bits per element."""
    return GateFamily(
        f"bloom{hashes}", params, lambda b: (1 - math.exp(-hashes / b)) ** hashes, lambda e: -hashes / math.log(1 - e ** (1 / hashes)),
        lambda e: F.lit(-float(hashes)) / F.ln(F.lit(1.0) - F.pow(e, F.lit(1 / hashes))), stored=lambda b, n: _bytes(bloom_cells(b, n)) + HEADER_BITS,
    )


XOR = _logarithmic("xor", 1.23, lambda r, n: xor_cells(n) * r)
FUSE3 = _logarithmic("fuse3", 1.125, lambda r, n: fuse_cells(n, 3) * r)
FUSE4 = _logarithmic("fuse4", 1.075, lambda r, n: fuse_cells(n, 4) * r)
IDEAL_BLOOM = _logarithmic("ideal_bloom", 1.44, lambda r, n: bloom_cells(1.44 * r, n))
FAMILIES: dict[str, GateFamily] = {f.name: f for f in (XOR, FUSE3, FUSE4, IDEAL_BLOOM, bloom(1), bloom(3))}


def register_gate_family(family: GateFamily) -> GateFamily:
    """Make a family known by its name to planners and queries."""
    FAMILIES[family.name] = family
    return family


def settings(names, keys: float | None = None) -> list[Setting]:
    return [s for n in names for s in FAMILIES[n].settings(keys)]
