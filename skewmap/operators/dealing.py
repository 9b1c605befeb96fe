"""Work by shard: each shard's rows in one task, in as many tasks as there are shards or partitions.

A shard is a few bytes a key and much work. Adaptive execution goes by bytes and would put all shards of a small
relation in one task; an exchange with a number of partitions of its own is left as it is.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import partitions


#: Shards of a task at most.
TASK_SHARDS = 16


def dealt(rows: DataFrame, shards: int, shard: str = "shard") -> DataFrame:
    """Rows in tasks by shard."""
    n = max(1, min(shards, max(partitions(rows.sparkSession), shards // TASK_SHARDS)))
    return rows.repartitionById(n, F.pmod(shard, F.lit(n)).cast("int"))


def _cuts(*columns: np.ndarray) -> list[tuple[int, int]]:
    """Stretches of rows that are equal in all columns."""
    edge = np.zeros(max(0, len(columns[0]) - 1), bool)
    for c in columns:
        edge |= c[1:] != c[:-1]
    cuts = [0, *(np.flatnonzero(edge) + 1).tolist(), len(columns[0])]
    return [(lo, hi) for lo, hi in zip(cuts, cuts[1:]) if lo < hi]


def by_shard(rows: DataFrame, shards: int, run: Callable[[pa.Table], pa.Table], schema: str) -> DataFrame:
    """What ``run`` makes of all rows of each ``shard``. A task holds the rows of one shard at a time."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, held = None, []
        for batch in batches:
            shard = batch.column("shard").to_numpy()
            for lo, hi in _cuts(shard):
                if held and shard[lo] != at:
                    yield from run(pa.Table.from_batches(held)).combine_chunks().to_batches()
                    held = []
                at = shard[lo]
                held.append(batch.slice(lo, hi - lo))
        if held:
            yield from run(pa.Table.from_batches(held)).combine_chunks().to_batches()

    return dealt(rows, shards).sortWithinPartitions("shard").mapInArrow(each, schema)


def met(keys: DataFrame, h: Column, given: DataFrame, shards: int, read: Callable[[list, np.ndarray, pa.RecordBatch], list[np.ndarray]], found: tuple[str, ...], features: Column | None = None, ready: Callable[[list], list] = list) -> DataFrame:
    """``keys`` with the whole numbers ``found`` that ``read`` gets for a shard's keys from the shard's row of ``given``.

    ``read`` takes what ``ready`` makes, once, of the row's values without ``shard``, and hashes and rows of keys, with
    ``features`` as ``__x``. A task reads a shard's row and then streams the shard's keys past it; keys of a shard
    without a row get 0.
    """
    columns, parts = list(keys.columns), [f for f in given.schema.fields if f.name != "shard"]
    wide = keys.select("*", *([features.alias("__x")] if features is not None else []))
    none = lambda f, name: F.lit(None).cast(f.dataType).alias(name)
    asked = wide.select(F.pmod(h, F.lit(shards)).alias("__shard"), F.lit(1).alias("__kind"), h.alias("__h"), *(none(f, f"__g_{f.name}") for f in parts), *wide.columns)
    rows = given.select(F.col("shard").alias("__shard"), F.lit(0).alias("__kind"), F.lit(0).cast("long").alias("__h"), *(F.col(f.name).alias(f"__g_{f.name}") for f in parts), *(none(f, f.name) for f in wide.schema.fields))
    fields = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in keys.schema.fields), *(f"{x} long" for x in found)])

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, row = None, []
        for batch in batches:
            shard, kind, h = (batch.column(i).to_numpy() for i in range(3))
            out = np.zeros((len(found), batch.num_rows), np.int64)
            own = batch.select(list(range(3 + len(parts), batch.num_columns)))
            for lo, hi in _cuts(shard, kind):
                if kind[lo] == 0:
                    at, row = shard[lo], ready([batch.column(3 + i)[lo].as_py() for i in range(len(parts))])
                elif shard[lo] == at:
                    out[:, lo:hi] = read(row, h[lo:hi], own.slice(lo, hi - lo))
            done = pa.RecordBatch.from_arrays([*own.columns[: len(columns)], *(pa.array(x) for x in out)], [*columns, *found])
            yield done.filter(pa.array(kind == 1))

    return dealt(rows.union(asked), shards, "__shard").sortWithinPartitions("__shard", "__kind").mapInArrow(stream, fields)
