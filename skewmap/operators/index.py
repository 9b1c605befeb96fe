"""Skew-aware static key -> value indexes: coded maps, gates, and gated maps, as tables of shards.

Keys are hashed to 64 bits and dealt to shards; one exchange by shard brings a shard's keys to its gate
and its linear system, for building as for looking up. A shard is cut into buckets of about
``BUCKET_BITS`` equations, each a GF(2) system; a shard's systems are solved side by side by lazy elimination. Bit j of
a key's codeword is the XOR of cells h0 + j, h1 + j, h2 + j (and h3 + j) of its bucket.

Keys whose 64-bit hashes coincide cannot both be in a system; all but the first go to ``exceptions``, a table
with the original keys that lookups ask first.
"""

from __future__ import annotations

import functools
import json
import math
import struct
from dataclasses import asdict, dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.gatecost import FAMILIES
from ..session import partitions, stored
from ..sources.keyvalue import KeyValueSpec, key_hash
from . import gates, hashing, huffman, stats
from .dealing import by_shard, dealt
from .peeling import solve

#: Equations of a bucket, keys of a shard, buckets that are solved side by side, header bytes of a bucket.
BUCKET_BITS, SHARD_KEYS, SIDE_BY_SIDE, HEADER = 2000, 100_000, 400, 4
#: Keys of a shard of an index with few shards; codebooks up to so many bytes are sent to every task.
SPLIT_KEYS, BROADCAST_BYTES = 25_000, 16 << 20
#: By number of hashes: cells per equation, spare cells, and words of cells that may be set aside; small buckets need
#: a little over the asymptotic overhead.
SPACE = {3: (1.089, 24, 4), 4: (1.024, 16, 6)}


# ---------------------------------------------------------------- linear systems of a shard


def positions(h: np.ndarray, seed: np.ndarray, cells: np.ndarray, hashes: int) -> np.ndarray:
    """Distinct first cells of each key: offsets are drawn from what is left of the ring."""
    out = [hashing.reduce_to(hashing.xxhash64(h, seed * 8), cells)]
    taken = np.zeros((len(h), 0), np.int64)
    for i in range(1, hashes):
        d = hashing.reduce_to(hashing.xxhash64(h, seed * 8 + i), cells - i) + 1
        for j in range(taken.shape[1]):
            d += d >= taken[:, j]
        taken = np.sort(np.concatenate([taken, d[:, None]], 1), axis=1)
        out.append((out[0] + d) % cells)
    return np.stack(out, 1)


def bucket_of(h: np.ndarray, buckets: int) -> np.ndarray:
    return hashing.reduce_to(hashing.xxhash64(h, -1), buckets)


def solve_shard(h: np.ndarray, sizes: np.ndarray, codes: np.ndarray, hashes: int) -> bytes:
    """Cells of a shard whose keys have codewords of given sizes: header, bucket table, packed cells.

    All buckets are solved side by side; those whose system is singular take the next seed, and a little more space.
    """
    h = hashing.prepared(h)
    buckets = max(1, round(int(sizes.sum()) / BUCKET_BITS))
    own = bucket_of(h, buckets)
    eqs = np.bincount(own, sizes, buckets).astype(np.int64)
    most = np.zeros(buckets, np.int64)
    np.maximum.at(most, own, sizes)
    factor, spare, words = SPACE[hashes]
    seeds, counts = np.zeros(buckets, np.int64), np.zeros(buckets, np.int64)
    parts: list[np.ndarray] = [np.zeros(0, np.uint8)] * buckets
    todo = np.flatnonzero(eqs > 0)
    for seed in range(0x10000):
        if not len(todo):
            break
        failed = [todo[:0]]
        seeds[todo] = seed
        counts[todo] = np.maximum(most[todo] + hashes, np.ceil(factor * eqs[todo] * (1 + 0.01 * (seed // 8))).astype(np.int64) + spare)
        for lo in range(0, len(todo), SIDE_BY_SIDE):
            some = todo[lo : lo + SIDE_BY_SIDE]
            place = np.full(buckets, -1)
            place[some] = np.arange(len(some))
            rows = np.flatnonzero(place[own] >= 0)
            size, start = counts[some], np.cumsum(counts[some]) - counts[some]
            n, which = sizes[rows], place[own[rows]]
            key = np.repeat(np.arange(len(rows)), n)
            bit = np.arange(len(key)) - np.repeat(np.cumsum(n) - n, n)
            want = (codes[rows][key] >> (n[key] - 1 - bit)) & 1
            at = positions(h[rows], np.full(len(rows), seed), size[which], hashes)
            at = (at[key] + bit[:, None]) % size[which[key], None] + start[which[key], None]
            values, solved = solve(at, want, which[key], np.repeat(np.arange(len(some)), size), len(some), words)
            for i in np.flatnonzero(solved).tolist():
                parts[some[i]] = values[start[i] : start[i] + size[i]]
            failed.append(some[~solved])
        todo = np.concatenate(failed)
    else:
        raise RuntimeError("no seed solves a bucket")
    if counts.max(initial=0) > 0xFFFF:
        raise RuntimeError("a bucket has more cells than its header can tell")
    head = struct.pack("<I", buckets) + seeds.astype("<u2").tobytes() + counts.astype("<u2").tobytes()
    return head + np.packbits(np.concatenate(parts), bitorder="little").tobytes()


def bucket_hash(h: np.ndarray) -> np.ndarray:
    """What decides a key's bucket, whatever the number of buckets."""
    return hashing.xxhash64(hashing.prepared(h), -1)


def mixed_bytes(mixed: np.ndarray, sizes: np.ndarray, hashes: int) -> int:
    """``shard_bytes`` of keys by their ``bucket_hash``."""
    buckets = max(1, round(int(sizes.sum()) / BUCKET_BITS))
    own = hashing.reduce_to(mixed, buckets)
    eqs, most = np.bincount(own, sizes, buckets).astype(np.int64), np.zeros(buckets, np.int64)
    np.maximum.at(most, own, sizes)
    factor, spare, _ = SPACE[hashes]
    cells = np.where(eqs > 0, np.maximum(most + hashes, np.ceil(factor * eqs).astype(np.int64) + spare), 0)
    return 4 + HEADER * buckets + -(-int(cells.sum()) // 8)


def shard_bytes(h: np.ndarray, sizes: np.ndarray, hashes: int) -> int:
    """Length of what ``solve_shard`` gives, without solving: the first seeds do not change the number of cells."""
    return mixed_bytes(bucket_hash(h), sizes, hashes)


def read_shard(data: bytes, h: np.ndarray, code: huffman.Code, hashes: int) -> np.ndarray:
    """Ranks that a shard's cells give for key hashes; any rank for keys that were never in it."""
    if code.longest == 0:
        return np.zeros(len(h), np.int64)
    (buckets,) = struct.unpack_from("<I", data)
    seeds = np.frombuffer(data, "<u2", buckets, 4).astype(np.int64)
    counts = np.frombuffer(data, "<u2", buckets, 4 + 2 * buckets).astype(np.int64)
    bits = np.unpackbits(np.frombuffer(data, np.uint8, offset=4 + HEADER * buckets), bitorder="little")
    base = np.cumsum(counts) - counts
    h = hashing.prepared(h)
    own = bucket_of(h, buckets)
    n, first_rank, first_code = code.table()
    out = np.zeros(len(h), np.int64)
    live = np.flatnonzero(counts[own] > hashes)
    own = own[live]
    size, start = counts[own], base[own]
    at = positions(h[live], seeds[own], size, hashes)
    word = np.zeros(len(live), np.int64)
    open_ = np.arange(len(live))
    for length in range(1, code.longest + 1):
        cell = (at[open_] + (length - 1)) % size[open_, None] + start[open_, None]
        word[open_] = (word[open_] << 1) | np.bitwise_xor.reduce(bits[cell], axis=1)
        k = word[open_] - first_code[length]
        hit = (k >= 0) & (k < n[length])
        out[live[open_[hit]]] = first_rank[length] + k[hit]
        open_ = open_[~hit]
        if not len(open_):
            break
    return out


# ---------------------------------------------------------------- the index


@dataclass(frozen=True)
class Plan:
    """A planner's decision: whether to gate, with which family and parameter, and the bound that said so."""

    use_gate: bool
    family: str | None = None
    param: float | None = None
    eps: float = 1.0
    bits: float = 0.0
    bound: float = 0.0
    planner: str = "gap"


@dataclass(frozen=True)
class Manifest:
    """All that a reader needs besides the shards."""

    keys: tuple[str, ...]
    value: str
    seed: int
    shards: int
    hashes: int
    num_keys: int
    distinct_values: int
    dominant_count: int
    leaked: int
    base_code: tuple[tuple[int, ...], tuple[int, ...]]
    code: tuple[tuple[int, ...], tuple[int, ...]]
    dominant_place: int
    plan: Plan = field(default_factory=lambda: Plan(False))
    exceptions: int = 0


@dataclass
class Index:
    """A built index. ``shards``: (shard, gate, cells, keys); ``codebook``: (value, freq, rank)."""

    manifest: Manifest
    shards: DataFrame
    codebook: DataFrame
    exceptions: DataFrame
    key_types: dict[str, str]

    @property
    def plan(self) -> Plan:
        return self.manifest.plan

    @functools.cached_property
    def book_bytes(self) -> int:
        """Bytes of the codebook's values and ranks."""
        kind = self.codebook.schema["value"].dataType
        size = F.octet_length("value") if isinstance(kind, (T.StringType, T.BinaryType)) else F.octet_length(F.col("value").cast("string"))
        return self.codebook.agg(F.coalesce(F.sum(F.coalesce(size, F.lit(0)) + 24), F.lit(0))).first()[0]

    def lookup(self, keys: DataFrame, absent: str = "arbitrary") -> DataFrame:
        """``keys`` with a column of values. Keys that are not in the index get any value.

        One exchange of the keys by shard serves gate and map; the codebook is joined by rank. A task reads a shard's
        row and then streams the keys of that shard past it, so repeated keys, however many, are never gathered.
        """
        if absent != "arbitrary":
            raise ValueError("this index stores no key fingerprints; absent keys get any value")
        m = self.manifest
        extra = [c for c in keys.columns]
        h = key_hash(keys, m.keys, m.seed)
        asked = keys.select(F.pmod(h, F.lit(m.shards)).alias("__shard"), F.lit(1).alias("__kind"), h.alias("__h"), F.lit(None).cast("binary").alias("__gate"), F.lit(None).cast("binary").alias("__cells"), *extra)
        given = self.shards.select(F.col("shard").alias("__shard"), F.lit(0).alias("__kind"), F.lit(0).cast("long").alias("__h"), F.col("gate").alias("__gate"), F.col("cells").alias("__cells"), *(F.lit(None).cast(f.dataType).alias(f.name) for f in keys.schema.fields))
        n = max(1, min(m.shards, partitions(keys.sparkSession)))
        met = given.union(asked).repartitionById(n, F.pmod("__shard", F.lit(n)).cast("int")).sortWithinPartitions("__shard", "__kind")
        fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in keys.schema.fields)
        found = met.mapInArrow(_lookup(m, extra), f"{fields + ', ' if fields else ''}__rank long")
        book = self.codebook.select(F.col("rank").alias("__rank"), F.col("value").alias(m.value))
        book = F.broadcast(book) if self.book_bytes <= BROADCAST_BYTES else book
        out = found.join(book, "__rank", "left").select(*extra, m.value)
        if not m.exceptions:
            return out
        odd = self.exceptions.select(*(F.col(k).alias(f"__e_{k}") for k in m.keys), F.col(m.value).alias("__e_value"), F.lit(True).alias("__e"))
        cond = F.lit(True)
        for k in m.keys:
            cond = cond & F.col(k).eqNullSafe(F.col(f"__e_{k}"))
        odd = F.broadcast(odd) if m.exceptions <= huffman.SMALL else odd
        return out.join(odd, cond, "left").select(*extra, F.when(F.col("__e"), F.col("__e_value")).otherwise(F.col(m.value)).alias(m.value))

    def filter_equals(self, keys: DataFrame, value) -> DataFrame:
        """Keys whose value is ``value``; for a value other than the dominant one, the gate turns most keys away."""
        return self.lookup(keys).where(F.col(self.manifest.value).eqNullSafe(F.lit(value)))

    def measured_bits(self) -> DataFrame:
        """(part, bits, bpk): stored bits of gate, map and codebook over all keys; headers are listed apart."""
        m = self.manifest
        sums = self.shards.agg(
            F.coalesce(F.sum(F.greatest(F.octet_length("gate") - 12, F.lit(0))), F.lit(0)).alias("gate"), F.coalesce(F.sum(F.octet_length("cells") - F.col("head")), F.lit(0)).alias("map"),
            F.coalesce(F.sum(F.col("head") + F.least(F.octet_length("gate"), F.lit(12))), F.lit(0)).alias("headers"),
        ).first()
        width = length_bits(huffman.Code(*m.code))
        values = self.codebook.agg(F.coalesce(F.sum(F.octet_length(F.col("value").cast("string"))), F.lit(0))).first()[0] * 8
        parts = [("gate", sums["gate"] * 8), ("map", sums["map"] * 8), ("headers", sums["headers"] * 8), ("code_lengths", m.distinct_values * width), ("values", values)]
        n = max(1, m.num_keys)
        return self.shards.sparkSession.createDataFrame([(p, int(b), b / n) for p, b in parts], "part string, bits long, bpk double")

    def save(self, path: str) -> None:
        """Tables under ``path``; the manifest is written last, so a folder with one is complete."""
        self.shards.repartition("shard").sortWithinPartitions("shard").write.parquet(f"{path}/shards")
        self.codebook.write.parquet(f"{path}/codebook")
        self.exceptions.write.parquet(f"{path}/exceptions")
        text = json.dumps({"manifest": asdict(self.manifest), "key_types": self.key_types})
        self.shards.sparkSession.createDataFrame([(text,)], "value string").coalesce(1).write.text(f"{path}/manifest")


def load_index(spark: SparkSession, path: str) -> Index:
    stored_ = json.loads(spark.read.text(f"{path}/manifest").first()[0])
    m = stored_["manifest"]
    pair = lambda x: (tuple(x[0]), tuple(x[1]))
    manifest = Manifest(**{**m, "keys": tuple(m["keys"]), "base_code": pair(m["base_code"]), "code": pair(m["code"]), "plan": Plan(**m["plan"])})
    return Index(manifest, spark.read.parquet(f"{path}/shards"), spark.read.parquet(f"{path}/codebook"), spark.read.parquet(f"{path}/exceptions"), stored_["key_types"])


def length_bits(code: huffman.Code) -> int:
    """Bits of a codeword's length in the codebook."""
    return math.ceil(math.log2(code.longest)) if code.longest > 1 else 0


def dominant_place(runs: list[tuple[int, int]], leaked: int) -> int:
    """The dominant value's place among the others by their frequencies in a gated map."""
    top = max((f for f, _ in runs), default=0)
    return sum(m for f, m in runs if f > leaked) - (1 if top > leaked else 0)


def _moved(rank: np.ndarray, place: int) -> np.ndarray:
    """Ranks after the dominant value, once first, has moved to ``place``."""
    return np.where(rank == 0, place, np.where(rank <= place, rank - 1, rank))


def _back(rank: np.ndarray, place: int) -> np.ndarray:
    return np.where(rank == place, 0, np.where(rank < place, rank + 1, rank))


def _column(table: pa.Table, name: str) -> np.ndarray:
    return table.column(name).to_numpy()


def ranks_in_shard(m: Manifest, family, code: huffman.Code, gate: bytes, cells: bytes, h: np.ndarray) -> np.ndarray:
    """Ranks of values that a shard gives for key hashes."""
    rank, passed = np.zeros(len(h), np.int64), np.arange(len(h))
    given, h = h, hashing.prepared(h)
    if m.plan.use_gate:
        passed = np.flatnonzero(gates.probe(family, m.plan.param, gate, h if isinstance(family, str) else given))
    if len(passed) and cells:
        rank[passed] = _back(read_shard(cells, h[passed], code, m.hashes), m.dominant_place)
    return rank


def _lookup(m: Manifest, extra: list[str]):
    """For ``mapInArrow`` over (shard, kind, hash, gate, cells, keys), sorted by shard, its own row before its keys."""
    code, family = huffman.Code(*m.code), gates.named(m.plan.family) if m.plan.use_gate else None

    def run(batches):
        at, gate, cells = None, b"", b""
        for batch in batches:
            shard, kind, h = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(3))
            rank = np.zeros(batch.num_rows, np.int64)
            cuts = np.flatnonzero((shard[1:] != shard[:-1]) | (kind[1:] != kind[:-1])) + 1
            for lo, hi in zip([0, *cuts], [*cuts, len(shard)]):
                if lo == hi:
                    continue
                if kind[lo] == 0:
                    at, gate, cells = shard[lo], batch.column(3)[lo].as_py() or b"", batch.column(4)[lo].as_py() or b""
                elif shard[lo] == at:
                    rank[lo:hi] = ranks_in_shard(m, family, code, gate, cells, h[lo:hi])
            keys = pa.array(kind == 1)
            out = pa.RecordBatch.from_arrays([*(batch.column(5 + i) for i in range(len(extra))), pa.array(rank)], [*extra, "__rank"])
            yield out.filter(keys)

    return run


def _gate_shard(plan: Plan):
    """For ``by_shard``: a shard's gate, colliding hashes, and the keys that its map is to hold, by rising hash: minority keys and leaked ones."""
    family = gates.named(plan.family) if plan.use_gate else None

    def run(keys: pa.Table) -> pa.Table:
        h, rank = _column(keys, "h"), _column(keys, "rank")
        order = np.lexsort((rank, h))
        h, rank = h[order], rank[order]
        twice = np.concatenate([[False], h[1:] == h[:-1]])
        other = np.unique(h[twice])
        h, rank = h[~twice], rank[~twice]
        gate, stay = b"", np.ones(len(h), bool)
        if plan.use_gate:
            gate = gates.build(family, plan.param, h[rank != 0])
            stay = rank != 0
            stay[~stay] = gates.probe(family, plan.param, gate, h[~stay])
        return pa.table({
            "shard": pa.array([keys.column("shard")[0].as_py()], pa.int64()), "gate": pa.array([gate], pa.binary()), "h": pa.array([h[stay].tobytes()], pa.binary()), "rank": pa.array([rank[stay].tobytes()], pa.binary()),
            "n_leaked": pa.array([int((rank[stay] == 0).sum())], pa.int64()), "collided": pa.array([other.tolist()], pa.list_(pa.int64())), "keys": pa.array([len(h)], pa.int64()),
        })

    return run


def _map_shard(code: huffman.Code, hashes: int, place: int):
    """For ``mapInArrow`` over what ``_gate_shard`` gives: the linear system of each shard over its map's keys."""

    def run(batches):
        for batch in batches:
            for row in (r for i in range(batch.num_rows) for r in batch.slice(i, 1).to_pylist()):
                h, rank = (np.frombuffer(row[c], np.int64) for c in ("h", "rank"))
                cells, head = b"", 0
                if code.longest and len(h):
                    sizes, words = code.encode(_moved(rank, place))
                    cells = solve_shard(h, sizes, words, hashes)
                    head = 4 + HEADER * struct.unpack_from("<I", cells)[0]
                yield pa.RecordBatch.from_arrays([pa.array([row["shard"]], pa.int64()), pa.array([row["gate"]], pa.binary()), pa.array([cells], pa.binary()), pa.array([head], pa.int32()), pa.array([row["keys"]], pa.int64())], ["shard", "gate", "cells", "head", "keys"])

    return run


def shard_count(n: int, shard_keys: int = SHARD_KEYS) -> int:
    """Shards of an index over n keys: of about ``shard_keys``, but some for a few cores from 50,000 keys on."""
    shards = max(1, -(-n // shard_keys))
    return max(shards, min(8, n // SPLIT_KEYS)) if n >= 2 * SPLIT_KEYS else shards


def build(df: DataFrame, spec: KeyValueSpec, plan: Plan, hashes: int = 3, seed: int = 0, shard_keys: int = SHARD_KEYS) -> Index:
    """Index of ``df`` under a plan. Exchanges: histogram by value, and keys by shard for gate and map."""
    pairs = df if isinstance(df, Relation) else relation(df, spec, seed)
    return build_relation(pairs, plan, hashes, shard_keys)


@dataclass
class Relation:
    """A checked relation, stored once: rows (keys, value, __h), and its histogram with what planners ask of it."""

    pairs: DataFrame
    spec: KeyValueSpec
    seed: int
    histogram: DataFrame
    runs: list[tuple[int, int]]
    key_types: dict[str, str]

    @functools.cached_property
    def profile(self) -> stats.Profile:
        return stats.Profile(sum(f * m for f, m in self.runs), sum(m for _, m in self.runs), max((f for f, _ in self.runs), default=0))

    @property
    def entropy(self) -> float:
        n = max(1, self.profile.num_keys)
        return -sum(m * (f / n) * math.log2(f / n) for f, m in self.runs)


def relation(df: DataFrame, spec: KeyValueSpec, seed: int = 0) -> Relation:
    """Store a relation with its key hashes and find its histogram; refused if keys repeat and the policy says so."""
    pairs = spec.rows(df)
    hashed = stored(pairs.select(*spec.keys, spec.value, key_hash(pairs, spec.keys, seed).alias("__h")), "pairs")
    if spec.on_duplicate == "error":
        spec.refuse_repeats(hashed, "__h")
    histogram = stored(stats.value_histogram(hashed, spec.value), "histogram")
    runs = huffman.collect_runs(stats.freq_of_freq(histogram))
    return Relation(hashed, spec, seed, histogram, runs, {k: df.schema[k].dataType.simpleString() for k in spec.keys})


def build_relation(made: Relation, plan: Plan, hashes: int = 3, shard_keys: int = SHARD_KEYS) -> Index:
    """Index of a stored relation."""
    pairs, spec, seed, histogram, runs, profile = made.pairs, made.spec, made.seed, made.histogram, made.runs, made.profile
    distinct, n = profile.distinct_values, profile.num_keys
    book = stored(huffman.ranked_values(histogram, distinct), "codebook")
    base_code = huffman.Code.of(runs)
    shards = shard_count(n, shard_keys)
    if distinct <= 1:
        plan = replace(plan, use_gate=False)
    if plan.use_gate:
        gates.named(plan.family)
    ranks = book.select(F.col("value").alias("__v"), "rank")
    ranks = F.broadcast(ranks) if distinct <= huffman.SMALL else ranks
    keyed = pairs.select(F.col("__h").alias("h"), F.col(spec.value).alias("__value"))
    keyed = keyed.join(ranks, F.col("__value").eqNullSafe(F.col("__v"))).select(F.pmod("h", F.lit(shards)).alias("shard"), "h", "rank")
    gated = stored(by_shard(keyed, shards, _gate_shard(plan), "shard long, gate binary, h binary, rank binary, n_leaked long, collided array<long>, keys long"), "gates")
    totals = gated.agg(F.coalesce(F.sum("n_leaked"), F.lit(0)).alias("leaked"), F.coalesce(F.sum(F.size("collided")), F.lit(0)).alias("collided")).first()
    top = profile.dominant_count
    leaked = totals["leaked"] if plan.use_gate else top
    left = gated_runs(runs, leaked) if plan.use_gate and runs else list(runs)
    code = huffman.Code.of(left)
    place = dominant_place(runs, leaked) if plan.use_gate else 0
    packed = dealt(gated.select("shard", "gate", "h", "rank", "keys"), shards)
    shard_rows = stored(packed.mapInArrow(_map_shard(code, hashes, place), "shard long, gate binary, cells binary, head int, keys long"), "shards")
    odd = pairs.select(*spec.keys, spec.value)
    if totals["collided"]:
        hit = gated.select(F.explode("collided").alias("__h"))
        odd = stored(pairs.join(hit, "__h", "left_semi").select(*spec.keys, spec.value), "exceptions")
    else:
        odd = pairs.sparkSession.createDataFrame([], odd.schema)
    pair = lambda c: (c.lengths, c.counts)
    manifest = Manifest(tuple(spec.keys), spec.value, seed, shards, hashes, n, distinct, top, leaked, pair(base_code), pair(code), place, plan, totals["collided"])
    return Index(manifest, shard_rows, book, odd, made.key_types)


def gated_runs(runs: list[tuple[int, int]], leaked: int) -> list[tuple[int, int]]:
    """Frequencies in a gated map: the dominant value's is that of its leaked keys."""
    top = max(f for f, _ in runs)
    left = [(f, m - (f == top)) for f, m in runs]
    return [(f, m) for f, m in left if m] + [(max(leaked, 0), 1)]


def model_bits(runs: list[tuple[int, int]], eps: float | None = None, bits: float = 0.0, delta: float = 1.089) -> dict[str, float]:
    """Model cost terms in bits: map alone (``eps`` None), or gated with leaked keys at their expectation."""
    n, distinct = sum(f * m for f, m in runs), sum(m for _, m in runs)
    top = max((f for f, _ in runs), default=0)
    used, gate = list(runs), 0.0
    if eps is not None:
        used = [(f, m - (f == top)) for f, m in runs]
        used = [(f, m) for f, m in used if m] + [(max(1, round(eps * top)), 1)]
        gate = bits * (n - top)
    code = huffman.Code.of(used)
    width = math.ceil(math.log2(code.longest)) if code.longest > 1 else 0
    return {"map": delta * code.total_bits(used), "gate": gate, "code_lengths": float(distinct * width), "longest": float(code.longest)}


__all__ = ["FAMILIES", "Index", "Manifest", "Plan", "build", "load_index", "model_bits"]
