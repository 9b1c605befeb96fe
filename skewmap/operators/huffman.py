"""Optimal prefix codes from frequencies of frequencies, and canonical codebooks.

Huffman's algorithm runs over (weight, multiplicity) runs: equal weights are paired in bulk, so its cost follows
the number of different frequencies, not of values. Values are ranked by falling frequency (ties by value); as
optimal lengths rise with rank, a table of how many codes each length has describes the whole code, and
``rank`` alone gives a value's length and canonical codeword.
"""

from __future__ import annotations

import heapq
from collections import Counter
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import stats


def length_counts(runs: list[tuple[int, int]]) -> dict[int, int]:
    """{code length: number of codes} of an optimal code for (frequency, multiplicity) runs; one symbol has length 0."""
    runs = [(int(f), int(m)) for f, m in runs if m]
    if not runs:
        return {}
    # Nodes are kept as runs of equal trees; a tree is a dict of leaf counts by depth below its root.
    heap: list[tuple[int, int, int, tuple]] = []
    order = 0
    for f, m in sorted(runs):
        heapq.heappush(heap, (f, order, m, ((0, 1),)))
        order += 1
    while True:
        f, _, m, shape = heapq.heappop(heap)
        if m == 1 and not heap:
            return dict(shape)
        if m >= 2:
            pairs, odd = divmod(m, 2)
            heapq.heappush(heap, (2 * f, order, pairs, _under(shape, shape)))
            order += 1
            if odd:
                heapq.heappush(heap, (f, order - m, 1, shape))
            continue
        g, _, k, other = heapq.heappop(heap)
        heapq.heappush(heap, (f + g, order, 1, _under(shape, other)))
        order += 1
        if k > 1:
            heapq.heappush(heap, (g, order - k, k - 1, other))


def _under(a: tuple, b: tuple) -> tuple:
    """Leaf depths of a tree that joins two."""
    total: Counter = Counter()
    for shape in (a, b):
        for depth, n in shape:
            total[depth + 1] += n
    return tuple(sorted(total.items()))


@dataclass(frozen=True)
class Code:
    """A canonical code as numbers of codes by length; ranks count from 0 in order of falling frequency."""

    lengths: tuple[int, ...]
    counts: tuple[int, ...]

    @classmethod
    def of(cls, runs: list[tuple[int, int]]) -> Code:
        found = sorted(length_counts(runs).items())
        return cls(tuple(n for n, _ in found), tuple(c for _, c in found))

    @property
    def longest(self) -> int:
        return max(self.lengths, default=0)

    def table(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """By length from 0: number of codes, rank of the first code, and the first codeword."""
        n = np.zeros(self.longest + 1, np.int64)
        for a, c in zip(self.lengths, self.counts):
            n[a] = c
        first_rank = np.concatenate([[0], np.cumsum(n)[:-1]])
        first_code, code = np.zeros(self.longest + 1, np.int64), 0
        for a in range(1, self.longest + 1):
            code = (code + int(n[a - 1])) << 1 if a > 1 else 0
            first_code[a] = code
        return n, first_rank, first_code

    def encode(self, ranks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Code lengths and codewords of ranks."""
        n, first_rank, first_code = self.table()
        size = np.searchsorted(first_rank + n, ranks, "right")
        return size, first_code[size] + ranks - first_rank[size]

    def total_bits(self, runs: list[tuple[int, int]]) -> int:
        """Bits of all codewords for the (frequency, multiplicity) runs that the code was made for."""
        out, left = 0, [list(x) for x in zip(self.lengths, self.counts)]
        i = 0
        for f, m in sorted(runs, reverse=True):
            while m:
                k = min(m, left[i][1])
                out += f * k * left[i][0]
                m -= k
                left[i][1] -= k
                i += not left[i][1]
        return out

    def length_of(self, rank: Column) -> Column:
        n, first_rank, _ = self.table()
        out = F.lit(None).cast("int")
        for a in reversed(range(len(n))):
            if n[a]:
                out = F.when(rank < int(first_rank[a] + n[a]), F.lit(a)).otherwise(out)
        return out

    def code_of(self, rank: Column) -> Column:
        n, first_rank, first_code = self.table()
        out = F.lit(None).cast("long")
        for a in reversed(range(len(n))):
            if n[a]:
                out = F.when(rank < int(first_rank[a] + n[a]), rank - int(first_rank[a]) + int(first_code[a])).otherwise(out)
        return out


def collect_runs(freqs: DataFrame) -> list[tuple[int, int]]:
    """(freq, multiplicity) rows on the driver: about sqrt(2 N) at most."""
    return [(r["freq"], r["multiplicity"]) for r in freqs.collect()]


SMALL = 100_000


def ranked_values(histogram: DataFrame, distinct: int, name: str = "ranked") -> DataFrame:
    """(value, freq, rank): ranks from 0 by falling frequency, ties by value, nulls last.

    Up to ``SMALL`` values one window does it. Beyond, values are range-partitioned in that order, ranked within
    their partitions, and moved up by the sizes of the partitions before.
    """
    order = [F.desc("freq"), F.asc_nulls_last("value")]
    if distinct <= SMALL:
        return histogram.withColumn("rank", (F.row_number().over(Window.orderBy(*order)) - 1).cast("long"))
    return stats.ranked(histogram, order, name).select("value", "freq", "rank")


def canonical_codebook(histogram: DataFrame, distinct: int, code: Code) -> DataFrame:
    """(value, freq, rank, code_len, code)."""
    ranked = ranked_values(histogram, distinct)
    return ranked.withColumns({"code_len": code.length_of(F.col("rank")), "code": code.code_of(F.col("rank"))})


def entropy_sandwich(codebook: DataFrame) -> DataFrame:
    """One row: entropy, mean code length, and whether the mean lies between the entropy and one bit more."""
    total = codebook.agg(F.sum("freq").alias("total"))
    p = F.col("freq") / F.col("total")
    row = codebook.crossJoin(F.broadcast(total)).agg(F.sum(-p * F.log2(p)).alias("entropy"), F.sum(p * F.col("code_len")).alias("mean_length"))
    return row.withColumn("holds", (F.col("entropy") <= F.col("mean_length") + 1e-9) & (F.col("mean_length") <= F.col("entropy") + 1 + 1e-9))
