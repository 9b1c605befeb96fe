"""The planner for SQL users: temporary functions, table functions, and a data source over a saved index."""

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.bounds import DELTA3, lower_bound
from ..functions.gatecost import FAMILIES


@F.udtf(returnType="family string, param double, eps double, bits double")
class GateSettings:
    """``gate_settings(family)``: the settings of a gate family."""

    def eval(self, family: str):
        for s in FAMILIES[family].settings():
            yield s.family, float(s.param), s.eps, s.bits


@F.udtf(returnType="use_gate boolean, param double, eps double, bound double")
class PlanSkewmap:
    """``plan_skewmap(alpha, n, num_keys, family)``: the gap planner's decision as a row, for ``LATERAL`` joins."""

    def eval(self, alpha: float, n: int, num_keys: int, family: str):
        best = max(FAMILIES[family].settings(), key=lambda s: (lower_bound(alpha, s.eps, s.bits, n / num_keys), -s.bits))
        bound = lower_bound(alpha, best.eps, best.bits, n / num_keys)
        yield bound > 0, float(best.param), best.eps, bound


@F.udtf(returnType="kmer string")
class Kmers:
    """``kmers(text, k)``: the k-character substrings of a text."""

    def eval(self, text: str, k: int):
        for i in range(len(text or "") - k + 1):
            yield (text[i : i + k],)


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL, under names that begin with ``sm_`` where they are scalar."""
    spark.udtf.register("gate_settings", GateSettings)
    spark.udtf.register("plan_skewmap", PlanSkewmap)
    spark.udtf.register("kmers", Kmers)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sm_lower_bound(a DOUBLE, e DOUBLE, b DOUBLE, r DOUBLE) RETURNS DOUBLE RETURN a * {DELTA3} * (1 - e) - (1 - a) * b - r")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sm_upper_bound(a DOUBLE, e DOUBLE, b DOUBLE, r DOUBLE) RETURNS DOUBLE RETURN {DELTA3} * (2 - a * e / 2) + r - b * (1 - a)")
    spark.udf.register("empirical_entropy", empirical_entropy)
    spark.udf.register("huffman_bits", huffman_bits)
    spark.dataSource.register(SkewmapSource)


def register_lookup(spark: SparkSession, name: str, index) -> None:
    """Make ``name(key columns)`` a SQL function that looks keys up in an index, for points as for columns.

    The index and its codebook are sent to every executor, so they are checked against the size that a stream's index
    may have. Values come as strings; keys whose hashes collide are refused at registration.
    """
    import numpy as np

    from ..operators import gates, huffman
    from ..operators.index import ranks_in_shard
    from ..session import shared
    from ..streaming.drift import STREAM_BYTES

    m = index.manifest
    size = (index.shards.agg(F.sum(F.octet_length("cells") + F.octet_length("gate"))).first()[0] or 0) + index.book_bytes
    if size > STREAM_BYTES or m.exceptions:
        raise ValueError(f"an index of {size} bytes and {m.exceptions} colliding keys cannot be a function; use its lookup")
    shards = {r["shard"]: (bytes(r["gate"] or b""), bytes(r["cells"] or b"")) for r in index.shards.select("shard", "gate", "cells").collect()}
    book = [r["v"] for r in index.codebook.orderBy("rank").select(F.col("value").cast("string").alias("v")).collect()]
    handle = shared(spark, (shards, np.array(book, object)))
    code, family = huffman.Code(*m.code), gates.named(m.plan.family) if m.plan.use_gate else None

    @F.arrow_udf("string")
    def value(h: pa.Array) -> pa.Array:
        held, values = handle.value
        h = h.to_numpy(zero_copy_only=False)
        rank, own = np.zeros(len(h), np.int64), h % m.shards
        for s in np.unique(own):
            at = np.flatnonzero(own == s)
            rank[at] = ranks_in_shard(m, family, code, *held.get(int(s), (b"", b"")), h[at])
        return pa.array(values[np.minimum(rank, len(values) - 1)], pa.string())

    spark.udf.register(f"{name}_by_hash", value)
    mask = " | ".join(f"if({k} IS NULL, {1 << (i % 30)}, 0)" for i, k in enumerate(m.keys))
    parameters = ", ".join(f"{k} {index.key_types[k]}" for k in m.keys)
    if any(t in ("double", "float") or t.startswith(("array", "struct")) for t in index.key_types.values()):
        raise TypeError("keys of floating or nested types are looked up with the index itself")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({parameters}) RETURNS STRING RETURN {name}_by_hash(xxhash64({m.seed}, {mask}, {', '.join(m.keys)}))")


def _frequencies(v) -> list[int]:
    return [int(x) for x in v if x is not None and x == x]


@F.pandas_udf(T.DoubleType())
def empirical_entropy(freq: pd.Series) -> float:
    """Entropy in bits of a group's frequencies."""
    import math

    f = _frequencies(freq)
    n = sum(f)
    return float(-sum(x / n * math.log2(x / n) for x in f if x)) if n else 0.0


@F.pandas_udf(T.LongType())
def huffman_bits(freq: pd.Series) -> int:
    """Bits of an optimal prefix code over a group's frequencies."""
    from collections import Counter

    from ..operators.huffman import Code

    runs = list(Counter(_frequencies(freq)).items())
    return Code.of(runs).total_bits(runs) if runs else 0


class SkewmapSource(DataSource):
    """``spark.read.format("skewmap").load(path)``: shard statistics of a saved index (its keys cannot be listed)."""

    @classmethod
    def name(cls) -> str:
        return "skewmap"

    def schema(self) -> str:
        return "shard long, keys long, gate_bytes long, map_bytes long"

    def reader(self, schema) -> DataSourceReader:
        return ShardReader(self.options["path"])


class ShardReader(DataSourceReader):
    def __init__(self, path: str) -> None:
        self.path = path.rstrip("/")

    def partitions(self) -> list[InputPartition]:
        import pyarrow.dataset as ds

        return [InputPartition(f) for f in ds.dataset(f"{self.path}/shards".removeprefix("file://"), format="parquet").files]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        import pyarrow.compute as pc
        import pyarrow.parquet as pq

        t = pq.read_table(partition.value)
        size = lambda c: pc.cast(pc.fill_null(pc.binary_length(t.column(c)), 0), pa.int64())
        yield from pa.table({"shard": t.column("shard"), "keys": t.column("keys"), "gate_bytes": size("gate"), "map_bytes": size("cells")}).to_batches()
