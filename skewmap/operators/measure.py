"""Measures: size, latency, build time, false-positive rate, exactness, and comparisons of methods."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import gates, huffman
from .index import Index, Plan, model_bits, ranks_in_shard


def timed(build: Callable):
    """What ``build`` returns, and its seconds; builders write their tables, so the work is done."""
    began = time.perf_counter()
    out = build()
    return out, time.perf_counter() - began


def total_bpk(index) -> float:
    """Stored bits over keys, all parts."""
    found = [r["bpk"] for r in index.measured_bits().collect() if r["bpk"] is not None]
    return sum(found) if found else None


def model_bits_frame(spark, runs: list[tuple[int, int]], plan: Plan, delta: float = 1.089) -> DataFrame:
    """(part, bits, bpk) of the cost model for a plan."""
    n = sum(f * m for f, m in runs)
    terms = model_bits(runs, plan.eps if plan.use_gate else None, plan.bits, delta)
    rows = [(k, float(v), v / max(1, n)) for k, v in terms.items() if k != "longest"]
    return spark.createDataFrame(rows, "part string, bits double, bpk double")


def savings(ungated, gated) -> float:
    """Bits per key that the gate saves, measured."""
    return total_bpk(ungated) - total_bpk(gated)


def mismatches(index, df: DataFrame, keys: tuple[str, ...], value: str) -> DataFrame:
    """Stored pairs that the index answers otherwise; empty for an exact index. Rows are compared as multisets."""
    base = df.select(*keys, value)
    answered = index.lookup(base.select(*keys)).select(*keys, value)
    kind = base.schema[value].dataType
    if isinstance(kind, (T.MapType,)):
        answered, base = (x.withColumn(value, F.to_json(value)) for x in (answered, base))
    return base.exceptAll(answered)


def observed_fpr(index: Index) -> float:
    """Dominant keys that passed the gate, over all dominant keys."""
    m = index.manifest
    return m.leaked / m.dominant_count if m.dominant_count and m.plan.use_gate else 0.0


def lookup_latency(index, keys: DataFrame, repeats: int = 3, inside: bool = True) -> DataFrame:
    """One row: job, scan and net nanoseconds a key (median of warm runs), and with ``inside`` the time inside shards.

    The sink is ``noop``, so nothing is written; net is the lookup job less a job that only scans the keys.
    """
    n = keys.count()

    def run(df: DataFrame) -> float:
        took = []
        for _ in range(repeats):
            began = time.perf_counter()
            df.write.format("noop").mode("overwrite").save()
            took.append(time.perf_counter() - began)
        return float(np.median(took))

    scan, job = run(keys), run(index.lookup(keys))
    inner = _inside(index, keys) if inside and isinstance(index, Index) else None
    scale = 1e9 / max(1, n)
    return keys.sparkSession.createDataFrame([(job * scale, scan * scale, max(0.0, job - scan) * scale, inner)], "job_ns double, scan_ns double, net_ns double, in_shard_ns double")


def _inside(index: Index, keys: DataFrame) -> float:
    """Nanoseconds a key of probing and decoding alone, timed in the workers."""
    from ..sources.keyvalue import key_hash

    m = index.manifest
    code, family = huffman.Code(*m.code), gates.named(m.plan.family) if m.plan.use_gate else None
    tagged = keys.select(key_hash(keys, m.keys, m.seed).alias("h")).withColumn("s", F.pmod("h", F.lit(m.shards)))

    def run(k: pa.Table, s: pa.Table) -> pa.Table:
        h = k.column("h").to_numpy()
        began = time.perf_counter_ns()
        if s.num_rows and len(h):
            ranks_in_shard(m, family, code, s.column("gate")[0].as_py() or b"", s.column("cells")[0].as_py() or b"", h)
        return pa.table({"ns": pa.array([time.perf_counter_ns() - began]), "n": pa.array([len(h)])})

    out = tagged.groupBy("s").cogroup(index.shards.groupBy("shard")).applyInArrow(run, "ns long, n long").agg(F.sum("ns"), F.sum("n")).first()
    return out[0] / max(1, out[1])


def pareto_front(results: DataFrame, size: str = "bpk", speed: str = "ns", by: tuple[str, ...] = ("workload",)) -> DataFrame:
    """Rows of ``results`` with no other of their workload that is at least as small and as fast, and better in one."""
    a, b = results.alias("a"), results.alias("b")
    same = F.lit(True)
    for c in by:
        same = same & F.col(f"a.{c}").eqNullSafe(F.col(f"b.{c}"))
    better = (F.col(f"b.{size}") <= F.col(f"a.{size}")) & (F.col(f"b.{speed}") <= F.col(f"a.{speed}")) & ((F.col(f"b.{size}") < F.col(f"a.{size}")) | (F.col(f"b.{speed}") < F.col(f"a.{speed}")))
    return a.join(b, same & better, "left_anti")


def ratio_table(results: DataFrame, base: str, measures: tuple[str, ...] = ("bpk", "ns", "build_s")) -> DataFrame:
    """Each method's measures over those of ``base``, by workload."""
    ref = results.where(F.col("method") == base).select("workload", *(F.col(m).alias(f"__{m}") for m in measures))
    return results.join(F.broadcast(ref), "workload").select("workload", "method", *(F.try_divide(m, F.col(f"__{m}")).alias(f"{m}_ratio") for m in measures))
