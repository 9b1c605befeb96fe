"""Sweeps that validate the planner: bounds against model savings over shares, distributions and settings."""

from __future__ import annotations

import math
import struct
from collections import Counter
from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.bounds import DELTA3, FORMS, lower_bound, upper_bound
from ..functions.gatecost import FAMILIES, HEADER_BITS
from ..operators import gates, huffman, index
from ..operators.index import model_bits
from ..sources.tables import UNIFORM_VALUES, ZIPF_EXPONENT, ZIPF_SUPPORT

ALPHAS = tuple(round(0.5 + 0.01 * i, 2) for i in range(50))
DISTRIBUTIONS = ("unique", "zipf", "uniform100")
GATES = ("xor", "fuse3", "bloom1", "bloom3")


def expected_runs(num_keys: int, alpha: float, dist: str) -> list[tuple[int, int]]:
    """(frequency, multiplicity) of a synthetic relation, with each minority frequency at its expectation."""
    top = round(alpha * num_keys)
    rest = num_keys - top
    if dist == "unique":
        freqs = {1: rest}
    elif dist == "uniform100":
        low, more = divmod(rest, UNIFORM_VALUES)
        freqs = {low + 1: more}
        freqs[low] = freqs.get(low, 0) + UNIFORM_VALUES - more
    else:
        weight = [r**-ZIPF_EXPONENT for r in range(1, ZIPF_SUPPORT + 1)]
        total, freqs, left = sum(weight), {}, rest
        for w in weight:
            f = min(left, max(1, round(rest * w / total)))
            left -= f
            freqs[f] = freqs.get(f, 0) + 1
            if not left:
                break
    freqs = {f: m for f, m in freqs.items() if f and m}
    freqs[top] = freqs.get(top, 0) + 1
    return sorted(freqs.items())


def sweep(spark: SparkSession, num_keys: int = 100_000, alphas: Iterable[float] = ALPHAS, dists: Iterable[str] = DISTRIBUTIONS, families: Iterable[str] = GATES, delta: float = DELTA3) -> DataFrame:
    """A row per share, distribution and setting: bounds and model saving.

    The cells are independent and run as tasks: ``mapInPandas`` evaluates the cost model of one share and
    distribution for all settings.
    """
    grid = spark.createDataFrame([(float(a), d, expected_runs(num_keys, a, d)) for a in alphas for d in dists], f"alpha double, dist string, {RUNS}")
    return sweep_of(grid, families, delta)


RUNS = "runs array<struct<freq: long, multiplicity: long>>"


def runs_by_share(keys: DataFrame, key: str, alphas: Iterable[float] = ALPHAS) -> DataFrame:
    """(alpha, dist, runs): frequencies in the relations of ``tables.synthetic`` over ``keys``, as they are.

    A key is in the minority of all shares whose dominant keys end before its place, so values are counted once by how many
    shares those are.
    """
    from ..sources import tables

    spark, ranks = keys.sparkSession, tables.synthetic_ranks(keys, key)
    alphas = sorted(set(map(float, alphas)))
    shares = spark.createDataFrame(list(enumerate(alphas)), "i long, alpha double").crossJoin(keys.agg(F.count(F.lit(1)).alias("n")))
    shares = shares.withColumn("cut", tables.dominant_cut(F.col("n"), F.col("alpha"))).collect()
    past = sum(((F.col("r") > s["cut"]).cast("int") for s in shares), F.lit(0)).alias("past")
    zipf = ranks.join(F.broadcast(tables.zipf_table(spark)), (F.col("u") >= F.col("lo")) & (F.col("u") < F.col("hi")))
    counted = zipf.select(F.lit("zipf").alias("dist"), "value", past).unionByName(ranks.select(F.lit("uniform100").alias("dist"), (F.col("r") % UNIFORM_VALUES).alias("value"), past))
    counted = counted.where("past > 0").groupBy("dist", "value", "past").agg(F.count(F.lit(1)).alias("n"))
    at = spark.createDataFrame([(i, float(s["alpha"])) for i, s in enumerate(shares)], "i long, alpha double")
    values = counted.join(F.broadcast(at), F.col("i") < F.col("past")).groupBy("dist", "alpha", "value").agg(F.sum("n").alias("freq")).select("dist", "alpha", "freq")
    rest = [(d, float(s["alpha"]), s["cut"]) for s in shares for d in DISTRIBUTIONS]  # the dominant value
    runs = values.unionByName(spark.createDataFrame(rest, "dist string, alpha double, freq long")).where("freq > 0").groupBy("dist", "alpha", "freq").agg(F.count(F.lit(1)).alias("multiplicity"))
    unique = [("unique", float(s["alpha"]), 1, s["n"] - s["cut"]) for s in shares]
    runs = runs.unionByName(spark.createDataFrame(unique, "dist string, alpha double, freq long, multiplicity long"))
    runs = runs.groupBy("dist", "alpha", "freq").agg(F.sum("multiplicity").alias("multiplicity")).where("multiplicity > 0")
    return runs.groupBy("alpha", "dist").agg(F.array_sort(F.collect_list(F.struct("freq", "multiplicity"))).alias("runs"))


def collected(cells: DataFrame) -> dict[tuple[float, str], list[tuple[int, int]]]:
    """``runs_by_share`` on the driver: as many numbers as the distributions have values, at most, by share."""
    return {(r["alpha"], r["dist"]): [tuple(x) for x in r["runs"]] for r in cells.collect()}


def sweep_of(cells: DataFrame, families: Iterable[str] = GATES, delta: float = DELTA3) -> DataFrame:
    """``sweep`` of relations with the frequencies of ``runs_by_share``."""
    families = tuple(families)
    grid = cells.select("alpha", "dist", "runs").repartition(16)

    def evaluate(frames):
        import pandas as pd

        for frame in frames:
            rows = []
            for a, d, held in zip(frame["alpha"], frame["dist"], frame["runs"]):
                runs = [(int(x["freq"]), int(x["multiplicity"])) for x in held]
                n = sum(f * m for f, m in runs)
                top, distinct = max(f for f, _ in runs), sum(m for _, m in runs)
                alpha, ratio = top / n, distinct / n
                alone = model_bits(runs, delta=delta)
                for name in families:
                    for s in FAMILIES[name].settings():
                        gated = model_bits(runs, s.eps, s.bits, delta)
                        saving = (alone["map"] + alone["code_lengths"] - gated["map"] - gated["gate"] - gated["code_lengths"]) / n
                        rows.append((a, d, name, float(s.param), s.eps, s.bits, alpha, ratio, lower_bound(alpha, s.eps, s.bits, ratio, delta), *(upper_bound(alpha, s.eps, s.bits, ratio, delta, f) for f in FORMS), saving))
            yield pd.DataFrame(rows, columns=["alpha", "dist", "family", "param", "eps", "bits", "share", "ratio", "lower", *(f"upper_{f}" for f in FORMS), "saving"])

    ups = ", ".join(f"upper_{f} double" for f in FORMS)
    return grid.mapInPandas(evaluate, f"alpha double, dist string, family string, param double, eps double, bits double, share double, ratio double, lower double, {ups}, saving double")


def _hashed(families: tuple[str, ...], h) -> dict:
    """Hashes of a shard's keys that Bloom gates of all shares use, by family."""
    import numpy as np

    different = len(np.unique(h)) == len(h)
    return {f: x for f in families if different and (x := gates.bloom_hashes(f, h))}


def _leaks(families: tuple[str, ...], h, hashed: dict, inside, outside):
    """For gates over a shard's keys ``h[inside]``: by family and parameter, which of ``outside`` pass and the gate's bits.

    Gates do not look at values: their leaks and sizes serve all distributions.
    """
    out = {}
    for name in families:
        params = FAMILIES[name].params
        if not len(inside):
            out |= {(name, float(p)): (outside[:0], 0) for p in params}
        elif name in gates.ARITY:
            cells, miss = gates.nested(name, h[inside], h[outside], int(max(params)))
            out |= {(name, float(p)): (outside[(miss & ((1 << p) - 1)) == 0], -(-cells * p // 8) * 8 + HEADER_BITS) for p in params}
        elif name in hashed:
            for p in params:
                let, size = gates.bloom_leaks(name, p, hashed[name], inside, outside)
                out[name, float(p)] = let, size * 8
        else:
            for p in params:
                gate = gates.build(name, p, h[inside])
                out[name, float(p)] = outside[gates.probe(name, p, gate, h[outside])], len(gate) * 8
    return out


#: Keys of one packed row of the mixed order, and keys that a range of the order of keys should have.
PIECE, RANGE = 1_000_000, 1_000_000
_PACKED = "id long, n long, keys binary, r binary"


def _packed(values, rising: bool = False) -> bytes:
    """Whole numbers, compressed in the narrowest type that holds what they are above their least or, if they rise, above the one before."""
    import numpy as np
    import pyarrow as pa

    values = np.ascontiguousarray(values, np.int64)
    least = int(values[0] if rising else values.min())
    above = (np.diff(values, prepend=values[:1]) if rising else values - least).view(np.uint64)
    width = next(w for w in (1, 2, 4, 8) if w == 8 or int(above.max()) < 1 << 8 * w)
    return struct.pack("<qqb?", least, len(values), width, rising) + pa.Codec("zstd", 1).compress(above.astype(f"<u{width}").tobytes(), asbytes=True)


def _unpacked(raw: bytes):
    import numpy as np
    import pyarrow as pa

    least, n, width, rising = struct.unpack_from("<qqb?", raw)
    above = np.frombuffer(pa.Codec("zstd", 1).decompress(raw[18:], n * width), f"<u{width}").astype(np.int64)
    return (np.cumsum(above) if rising else above) + least


def _rows(batches):
    """The packed rows of batches, as dicts."""
    return (row for batch in batches for row in batch.to_pylist())


def _batch(rows: list[tuple], schema):
    import pyarrow as pa

    return pa.RecordBatch.from_arrays([pa.array(c, kind) for c, kind in zip(zip(*rows), schema.values())], names=list(schema))


def _pieces(ids, key, r):
    """A batch with a packed row for each id: its keys in their order, and their ranks."""
    import numpy as np
    import pyarrow as pa

    order = np.lexsort((key, ids))
    ids, key, r = ids[order], key[order], r[order]
    cuts = [0, *(np.flatnonzero(ids[1:] != ids[:-1]) + 1).tolist(), len(ids)]
    rows = [(int(ids[a]), b - a, _packed(key[a:b], True), _packed(r[a:b])) for a, b in zip(cuts[:-1], cuts[1:])]
    return _batch(rows, {"id": pa.int64(), "n": pa.int64(), "keys": pa.binary(), "r": pa.binary()})


def _gathered(pieces: DataFrame, parts: int, name: str) -> DataFrame:
    """Stored: one packed row for each id, of all its pieces."""
    from ..session import stored

    def run(batches):
        import numpy as np

        at, held = None, []

        def joined():
            key, r = (np.concatenate(x) for x in zip(*held))
            return _pieces(np.full(len(key), at, np.int64), key, r)

        for row in _rows(batches):
            if held and row["id"] != at:
                yield joined()
                held = []
            at = row["id"]
            held.append((_unpacked(row["keys"]), _unpacked(row["r"])))
        if held:
            yield joined()

    return stored(pieces.repartition(parts, "id").sortWithinPartitions("id").mapInArrow(run, _PACKED), name)


def _mixed_order(keys: DataFrame, key: str) -> DataFrame:
    """Stored, in packed rows: the keys of each range of the mixed order of ``tables.synthetic_ranks``, and a row's place in its range."""
    from ..session import partitions, stored

    kept = keys.select(F.col(key).cast("long").alias("key"))
    mixed = (F.col("key") * F.lit(2654435761)) % F.lit(4294967296)

    def run(batches):
        import numpy as np
        import pyarrow as pa
        from pyspark import TaskContext

        part, at, held = TaskContext.get().partitionId(), 0, []

        def row():
            key = np.concatenate(held)
            return _batch([(part, at, len(key), _packed(key))], {"part": pa.int32(), "at": pa.int64(), "n": pa.int64(), "keys": pa.binary()})

        for batch in batches:
            if batch.num_rows:
                held.append(batch.column(0).to_numpy())
            if sum(map(len, held)) >= PIECE:
                yield row()
                at, held = at + sum(map(len, held)), []
        if held:
            yield row()

    placed = kept.repartitionByRange(partitions(keys.sparkSession), mixed, F.col("key")).sortWithinPartitions(mixed, "key")
    return stored(placed.mapInArrow(run, "part int, at long, n long, keys binary"), "synthetic")


def _shards(order: DataFrame, starts: dict[int, int], shards: int, before: int) -> DataFrame:
    """Stored: a packed row for each shard of the index, with its keys and their ranks."""
    from ..session import partitions

    def run(batches):
        import numpy as np

        for row in _rows(batches):
            key = _unpacked(row["keys"])
            r = np.arange(1, len(key) + 1) + (starts[row["part"]] + row["at"])
            yield _pieces(_key_hash(key, before) % shards, key, r)

    return _gathered(order.mapInArrow(run, _PACKED), min(shards, 4 * partitions(order.sparkSession)), "shards")


def _key_hash(key, before: int):
    """``key_hash`` of keys that are longs; ``before`` is the hash of what goes in before them."""
    import numpy as np

    from ..operators import hashing

    return hashing._hash_long(key.astype(np.uint64), np.full(len(key), before, np.int64).astype(np.uint64)).astype(np.int64)


def _shard(table, before: int):
    """Of a shard's packed row: hashes, keys, ranks and draws, as ``tables.synthetic_ranks`` has them."""
    import numpy as np

    key, r = (_unpacked(table.column(c)[0].as_py()) for c in ("keys", "r"))
    return _key_hash(key, before), key, r, np.fmod(key * 40503 + 12345, 1000003) / 1000003.0


def _values(dist: str, r, u, zipf: list[float]):
    """Values that minority keys have by ``zipf`` or ``uniform100``."""
    import numpy as np

    return r % UNIFORM_VALUES + 1 if dist == "uniform100" else np.searchsorted(zipf, u, "right") + 1


def _count_shard(cuts: list[tuple[float, int]], dists: tuple[str, ...], families: tuple[str, ...], zipf: list[float], before: int):
    """For ``applyInArrow`` over a shard's packed keys: leaked keys and gate bits of all shares, and keys by value and number of shares that have them in the minority."""
    ends = sorted(c for _, c in cuts)

    def run(table):
        import numpy as np
        import pyarrow as pa

        h, _, r, u = _shard(table, before)
        out, hashed = [], _hashed(families, h)
        for a, cut in cuts:
            found = _leaks(families, h, hashed, np.flatnonzero(r > cut), np.flatnonzero(r <= cut))
            out += [(name, p, a, len(let), bits) for (name, p), (let, bits) in found.items()]
        past = np.searchsorted(ends, r, "left")
        for d in dists:
            if d != "unique":
                kinds, n = np.unique(np.stack([_values(d, r, u, zipf), past]), axis=1, return_counts=True)
                out += [(d, float(v), float(p), int(c), 0) for (v, p), c in zip(kinds.T.tolist(), n)]
        return pa.Table.from_arrays([pa.array(c) for c in zip(*out)], names=["what", "param", "at", "n", "bits"])

    return run


def _thresholds(table: list[int], place: int | None, many: int) -> tuple[int, list[int]]:
    """Of values of equal frequency in their order: the first one's code length, and the places from which it grows by one.

    ``table`` has the ranks at which lengths end. ``place`` is the dominant value's rank, 0 if None: it is not one of the ``many``.
    """
    at = [b - 1 if place is None else b if b < place else max(place, b - 1) for b in table]
    return sum(t <= 0 for t in at), [t for t in at if 0 < t < many]


def _codes(cell) -> tuple:
    """Of one share and distribution: code length by value (``unique``: of the dominant one, the first one, and growth) and code lengths' bits, by setting."""
    import numpy as np

    alpha, dist, freq, leaked = cell
    if dist == "unique":
        cut, many = freq
        runs = sorted((Counter({cut: 1} if cut else {}) + Counter({1: many})).items())
    else:
        runs = sorted(Counter(f for f in freq if f).items())
        order = np.lexsort((np.arange(len(freq)), -np.array(freq)))
        rank = np.empty(len(freq), np.int64)
        rank[order] = np.arange(len(freq))
    distinct, out = sum(m for _, m in runs), {}
    for setting in [None, *leaked]:
        code = huffman.Code.of(runs if setting is None else index.gated_runs(runs, leaked[setting]))
        n, first, _ = code.table()
        ends = first + n
        place = None if setting is None else index.dominant_place(runs, leaked[setting])
        if dist == "unique":
            least, grows = _thresholds(ends.tolist(), place, many)
            sizes = int(np.searchsorted(ends, place or 0, "right")), least, grows
        else:
            sizes = np.searchsorted(ends, rank if setting is None else index._moved(rank, place), "right")
        out[setting] = sizes, distinct * index.length_bits(code), code.longest
    return alpha, dist, runs, out


def _size_shard(cuts: list[tuple[float, int]], dists: tuple[str, ...], families: tuple[str, ...], zipf: list[float], before: int, hashes: int, codes):
    """For ``applyInArrow`` over a shard's packed keys: bits of its maps, of all shares, distributions and settings."""

    def run(table):
        import numpy as np
        import pyarrow as pa

        known = codes.value
        h, key, r, u = _shard(table, before)
        mixed, hashed = index.bucket_hash(h), _hashed(families, h)
        given = {d: _values(d, r, u, zipf) for d in dists if d != "unique"}
        out = []
        for a, cut in cuts:
            least, most = np.flatnonzero(r > cut), np.flatnonzero(r <= cut)
            let = {None: most} | {s: x for s, (x, _) in _leaks(families, h, hashed, least, most).items()}
            for d in dists:
                for setting, (sizes, _, longest) in known[a, d].items():
                    if not longest:
                        continue
                    more = let[setting]
                    if d == "unique":
                        top, first, grows = sizes
                        size = np.concatenate([first + np.searchsorted(grows, key[least], "right"), np.full(len(more), top)])
                    else:
                        size = np.concatenate([sizes[given[d][least]], np.full(len(more), sizes[0])])
                    if len(size):
                        name, p = setting or ("", 0.0)
                        out.append((d, name, p, a, 8 * index.mixed_bytes(mixed[np.concatenate([least, more])], size, hashes)))
        out = out or [("", "", 0.0, 0.0, 0)]
        return pa.Table.from_arrays([pa.array(c) for c in zip(*out)], names=["dist", "family", "param", "alpha", "bits"])

    return run


def _keys_at(dealt: DataFrame, many: int, n: int, cuts: list[tuple[float, int]], places: dict[float, set[int]]) -> dict[tuple[float, int], int]:
    """By share and place: the key that has the place, from 0, among the share's minority keys in their order.

    Keys go to ranges, whose ends some keys of up to 64 of the ``many`` shards give; the counts of ranges, a row each, tell
    where a place is.
    """
    from ..session import discard, partitions

    spark = dealt.sparkSession
    parts = max(partitions(spark), -(-n // RANGE))

    def some(batches):
        import numpy as np
        import pyarrow as pa

        for row in _rows(batches):
            key = _unpacked(row["keys"])
            yield pa.RecordBatch.from_arrays([pa.array(key[:: max(1, len(key) // 200)].astype(np.int64))], names=["key"])

    known = sorted(x["key"] for x in dealt.where(F.col("id") % max(1, many // 64) == 0).mapInArrow(some, "key long").collect())
    ends = sorted({known[len(known) * i // parts] for i in range(1, parts)}) if known else []

    def deal(batches):
        import numpy as np

        for row in _rows(batches):
            key = _unpacked(row["keys"])
            yield _pieces(np.searchsorted(ends, key, "right").astype(np.int64), key, _unpacked(row["r"]))

    placed = _gathered(dealt.mapInArrow(deal, _PACKED), parts, "bykey")

    def count(batches):
        import pyarrow as pa

        for row in _rows(batches):
            r = _unpacked(row["r"])
            yield _batch([(row["id"], [int((r > cut).sum()) for _, cut in cuts])], {"id": pa.int64(), "past": pa.list_(pa.int64())})

    counts = sorted((x["id"], x["past"]) for x in placed.mapInArrow(count, "id long, past array<long>").collect())
    wanted: dict[int, list[tuple[int, int, int]]] = {}
    for i, (a, _) in enumerate(cuts):
        before = 0
        for part, past in counts:
            wanted.setdefault(part, []).extend((i, t, t - before) for t in places[a] if before <= t < before + past[i])
            before += past[i]

    def run(batches):
        import pyarrow as pa

        for row in _rows(batches):
            out, asked = [], {}
            for i, t, own in wanted.get(row["id"], []):
                asked.setdefault(i, []).append((t, own))
            if asked:
                key, r = _unpacked(row["keys"]), _unpacked(row["r"])
                for i, some in asked.items():
                    there = key[r > cuts[i][1]]
                    out += [(i, t, int(there[own])) for t, own in some]
                yield _batch(out, {"i": pa.int32(), "t": pa.int64(), "key": pa.int64()})

    found = placed.mapInArrow(run, "i int, t long, key long").collect()
    discard(placed)
    return {(cuts[x["i"]][0], x["t"]): x["key"] for x in found}


def measured_sweep(keys: DataFrame, key: str, alphas: Iterable[float] = ALPHAS, dists: Iterable[str] = DISTRIBUTIONS, families: Iterable[str] = GATES, delta: float = DELTA3, hashes: int = 3, shard_keys: int | None = None) -> DataFrame:
    """``sweep`` measured: a row per share, distribution and setting, with the bits that the built index takes less.

    The relations are those of ``tables.synthetic`` over ``keys``, which are distinct. Gates are built and probed with every
    dominant key, codes are made for the keys that really leak, and maps are sized bucket by bucket with headers and code
    lengths; only the maps' cells are not solved for, as their number does not depend on it. A task has the keys of
    one shard of the index and measures it for all shares, so a key goes through an exchange once for the gates and once
    for the maps, however many shares there are. Keys and ranks travel and are stored packed, some five bytes a key. Between the two, frequencies and leaks of all shards make the codes; values
    of one key each have their code length by their place, for which the few keys where it grows are looked up.
    ``bits`` is a gate's stored cost, and ``lower`` the bound with it; ``lower_at_large`` has the family's published cost.
    """
    from ..session import discard, partitions, shared
    from ..sources.keyvalue import key_hash

    spark, alphas, dists, families = keys.sparkSession, tuple(map(float, alphas)), tuple(dists), tuple(families)
    order, n, starts = _mixed_order(keys, key), 0, {}
    for x in order.groupBy("part").agg(F.sum("n").alias("n")).orderBy("part").collect():
        starts[x["part"]] = n
        n += x["n"]
    ups = ", ".join(f"upper_{f} double" for f in FORMS)
    schema = f"alpha double, dist string, family string, param double, eps double, bits double, share double, ratio double, lower double, lower_at_large double, {ups}, saving double, leaked long"
    if not n:
        return spark.createDataFrame([], schema)
    shards = index.shard_count(n, shard_keys or index.SHARD_KEYS)
    cuts = [(a, math.floor(n * round(a * 100) / 100 + 0.5)) for a in alphas]
    weight = [k**-ZIPF_EXPONENT for k in range(1, ZIPF_SUPPORT)]
    total, acc, edges = sum(weight) + ZIPF_SUPPORT**-ZIPF_EXPONENT, 0.0, []
    for w in weight:
        acc += w / total
        edges.append(acc)
    before = spark.range(1).select(key_hash(keys, ()).alias("h")).first()["h"]
    packed = _shards(order, starts, shards, before)
    discard(order)
    dealt = packed.repartition(min(shards, 4 * partitions(spark)), "id").groupBy("id")
    counted = dealt.applyInArrow(_count_shard(cuts, dists, families, edges, before), "what string, param double, at double, n long, bits long")
    leaked: dict[float, dict] = {a: {} for a in alphas}
    gate: dict[tuple, int] = {}
    ends = sorted(c for _, c in cuts)
    freq = {(a, d): [0] * (1 + (UNIFORM_VALUES if d == "uniform100" else ZIPF_SUPPORT)) for a in alphas for d in dists if d != "unique"}
    for x in counted.groupBy("what", "param", "at").agg(F.sum("n").alias("n"), F.sum("bits").alias("bits")).collect():
        if x["what"] in families:
            leaked[x["at"]][x["what"], x["param"]] = x["n"]
            gate[x["at"], x["what"], x["param"]] = x["bits"]
        else:
            for a, cut in cuts:
                inside = ends.index(cut) < x["at"]  # the key's place is past the share's dominant ones
                freq[a, x["what"]][int(x["param"]) if inside else 0] += x["n"]
    cells = [(a, d, (cut, n - cut) if d == "unique" else freq[a, d], leaked[a]) for a, cut in cuts for d in dists]
    coded = spark.sparkContext.parallelize(cells, len(cells)).map(_codes).collect()
    places = {a: {t for b, d, _, out in coded if b == a and d == "unique" for (_, _, grows), _, _ in out.values() for t in grows} for a in alphas}
    at = _keys_at(packed, shards, n, cuts, places) if any(places.values()) else {}
    known = {}
    for a, d, _, out in coded:
        if d == "unique":
            out = {s: ((top, first, sorted(at[a, t] for t in grows)), bits, longest) for s, ((top, first, grows), bits, longest) in out.items()}
        known[a, d] = out
    sized = dealt.applyInArrow(_size_shard(cuts, dists, families, edges, before, hashes, shared(spark, known)), "dist string, family string, param double, alpha double, bits long")
    maps = {(x["alpha"], x["dist"], x["family"], x["param"]): x["bits"] for x in sized.groupBy("dist", "family", "param", "alpha").agg(F.sum("bits").alias("bits")).collect()}
    discard(packed)
    rows = []
    for (a, d, runs, _), (_, cut) in zip(coded, [c for c in cuts for _ in dists]):
        top, distinct = max(f for f, _ in runs), sum(m for _, m in runs)
        alpha, ratio, codes = top / n, distinct / n, known[a, d]
        alone = codes[None][1] + maps.get((a, d, "", 0.0), 0)
        for name in families:
            large = {s.param: s.bits for s in FAMILIES[name].settings()}
            for s in FAMILIES[name].settings((n - cut) / shards):
                p = float(s.param)
                size = gate[a, name, p] + codes[name, p][1] + maps.get((a, d, name, p), 0)
                lower = [lower_bound(alpha, s.eps, b, ratio, delta) for b in (s.bits, large[s.param])]
                rows.append((a, d, name, p, s.eps, s.bits, alpha, ratio, *lower, *(upper_bound(alpha, s.eps, s.bits, ratio, delta, f) for f in FORMS), (alone - size) / n, leaked[a][name, p]))
    return spark.createDataFrame(rows, schema)


def epsilon_points(keys: DataFrame, key: str, alphas: Iterable[float] = (0.7, 0.9), dists: Iterable[str] = DISTRIBUTIONS, families: Iterable[str] = GATES, points: int = 60) -> DataFrame:
    """The rate sweep of every distribution and family: (alpha, dist, family, kind, eps, lower, upper, saving).

    ``kind``: ``continuous`` rows have the bounds over a range of rates and the cost model's saving, ``measured`` rows the
    settings there are with their stored saving, and ``optimum`` the rate of the greatest lower bound.
    """
    from .planner import continuous_setting

    spark, alphas, dists = keys.sparkSession, tuple(alphas), tuple(dists)
    cells = measured_sweep(keys, key, alphas, dists, families)
    upper = F.col("upper_binary_entropy").alias("upper")
    out = cells.select("alpha", "dist", "family", F.lit("measured").alias("kind"), "eps", "lower", upper, "saving")
    n = keys.count()
    for d in dists:
        curve = epsilon_sweep(spark, n, alphas, points, families, d)
        out = out.unionByName(curve.select("alpha", F.lit(d).alias("dist"), "family", F.lit("continuous").alias("kind"), "eps", "lower", "upper", "saving"))
    best = []
    for a in alphas:
        for d in dists:
            runs = expected_runs(n, a, d)
            ratio = sum(m for _, m in runs) / n
            for name in families:
                s = continuous_setting(FAMILIES[name], a)
                best.append((float(a), d, name, "optimum", s.eps, lower_bound(a, s.eps, s.bits, ratio), upper_bound(a, s.eps, s.bits, ratio, form="binary_entropy"), None))
    return out.unionByName(spark.createDataFrame(best, "alpha double, dist string, family string, kind string, eps double, lower double, upper double, saving double"))


def agreement(cells: DataFrame) -> DataFrame:
    """(dist, family, shares, agree, most_steps, most_regret): the planner's setting beside the best one, where it gates."""
    return parameter_regret(cells).groupBy("dist", "family").agg(F.count(F.lit(1)).alias("shares"), F.count_if(F.col("steps") == 0).alias("agree"), F.max("steps").alias("most_steps"), F.max("regret").alias("most_regret"))


PANEL = ("alpha", "dist", "family")


def panels(cells: DataFrame) -> DataFrame:
    """A row per share, distribution and family: the planner's setting, the best one, and their savings."""
    w = Window.partitionBy(*PANEL)
    step = cells.withColumn("step", F.row_number().over(w.orderBy("param")))
    chosen = F.max_by(F.struct("param", "step", "saving", "lower", "upper_binary_entropy", "upper_simplified"), F.struct("lower", -F.col("bits")))
    best = F.max_by(F.struct("param", "step", "saving", "lower", "upper_binary_entropy", "upper_simplified"), F.struct("saving", -F.col("bits")))
    return step.groupBy(*PANEL).agg(chosen.alias("chosen"), best.alias("best"))


def tightness(cells: DataFrame) -> DataFrame:
    """How far the bounds are from the saving at the planner's and at the best setting, and whether they contain it."""
    p = panels(cells)
    return p.select(
        *PANEL, F.col("best.saving").alias("saving"), (F.col("best.saving") - F.col("chosen.lower")).alias("lower_slack"),
        (F.col("chosen.upper_binary_entropy") - F.col("chosen.saving")).alias("upper_slack_chosen"), (F.col("best.upper_binary_entropy") - F.col("best.saving")).alias("upper_slack_best"),
        ((F.col("chosen.lower") <= F.col("chosen.saving") + 1e-9) & (F.col("chosen.saving") <= F.col("chosen.upper_binary_entropy") + 1e-9) & (F.col("best.saving") <= F.col("best.upper_binary_entropy") + 1e-9)).alias("contained"),
    )


def containment(cells: DataFrame) -> DataFrame:
    """Cells outside their bounds, by form of the upper bound; all zero."""
    out = [F.count_if(F.col("lower") > F.col("saving") + 1e-9).alias("below_lower")]
    out += [F.count_if(F.col(f"upper_{f}") < F.col("saving") - 1e-9).alias(f"above_{f}") for f in FORMS]
    return cells.groupBy("dist", "family").agg(F.count(F.lit(1)).alias("cells"), *out)


def decision_confusion(cells: DataFrame) -> DataFrame:
    """Gates advised that save nothing (must be none), and gates forgone that would have saved."""
    p = panels(cells)
    gate, useful = F.col("chosen.lower") > 0, F.col("best.saving") > 0
    return p.groupBy("dist", "family").agg(
        F.count_if(gate & (F.col("chosen.saving") > 0)).alias("gated_saving"), F.count_if(gate & (F.col("chosen.saving") <= 0)).alias("gated_harm"),
        F.count_if(~gate & useful).alias("forgone"), F.count_if(~gate & ~useful).alias("rightly_plain"),
        F.min(F.when(~gate & useful, F.col("alpha"))).alias("forgone_from"), F.max(F.when(~gate & useful, F.col("alpha"))).alias("forgone_to"), F.max(F.when(~gate & useful, F.col("best.saving"))).alias("forgone_most"),
    )


def parameter_regret(cells: DataFrame) -> DataFrame:
    """Best saving less the planner's, and how many settings apart they are, where the planner gates."""
    p = panels(cells).where("chosen.lower > 0")
    return p.select(*PANEL, (F.col("best.saving") - F.col("chosen.saving")).alias("regret"), F.abs(F.col("best.step") - F.col("chosen.step")).alias("steps"))


def crossing(cells: DataFrame) -> DataFrame:
    """First share whose best lower bound is positive."""
    return panels(cells).groupBy("dist", "family").agg(F.min(F.when(F.col("chosen.lower") > 0, F.col("alpha"))).alias("crossing"))


def heuristic_harm(spark: SparkSession, num_keys: int = 100_000, alphas: Iterable[float] = ALPHAS, dists: Iterable[str] = DISTRIBUTIONS, family: str = "ideal_bloom", given: dict | None = None) -> DataFrame:
    """(alpha, dist, eps, saving) of the entropy-fit heuristic's gates; negative savings are harm.

    ``given`` has frequencies by share and distribution; without it they are at their expectation.
    """
    from .planner import entropy_fit_plan
    from ..operators.stats import Profile

    rows = []
    for a in alphas:
        for d in dists:
            runs = given[a, d] if given else expected_runs(num_keys, a, d)
            n, top, distinct = sum(f * m for f, m in runs), max(f for f, _ in runs), sum(m for _, m in runs)
            h = -sum(m * (f / n) * math.log2(f / n) for f, m in runs)
            plan = entropy_fit_plan(Profile(n, distinct, top), h, family)
            if plan.use_gate:
                alone, gated = model_bits(runs), model_bits(runs, plan.eps, plan.bits)
                rows.append((float(a), d, plan.eps, (alone["map"] + alone["code_lengths"] - gated["map"] - gated["gate"] - gated["code_lengths"]) / n))
    return spark.createDataFrame(rows, "alpha double, dist string, eps double, saving double")


def epsilon_sweep(spark: SparkSession, num_keys: int = 100_000, alphas: Iterable[float] = (0.7, 0.9), points: int = 60, families: Iterable[str] = GATES, dist: str = "zipf", given: dict | None = None) -> DataFrame:
    """(alpha, family, eps, lower, upper, saving) over a continuous range of rates; ``given`` as in ``heuristic_harm``."""
    rows = []
    for a in alphas:
        runs = given[a, dist] if given else expected_runs(num_keys, a, dist)
        n, top, distinct = sum(f * m for f, m in runs), max(f for f, _ in runs), sum(m for _, m in runs)
        alone = model_bits(runs)
        for name in families:
            for i in range(1, points):
                e = 2 ** (-8 * i / points)
                b = FAMILIES[name].bits(e)
                gated = model_bits(runs, e, b)
                saving = (alone["map"] + alone["code_lengths"] - gated["map"] - gated["gate"] - gated["code_lengths"]) / n
                rows.append((float(a), name, e, lower_bound(top / n, e, b, distinct / n), upper_bound(top / n, e, b, distinct / n, form="binary_entropy"), saving))
    return spark.createDataFrame(rows, "alpha double, family string, eps double, lower double, upper double, saving double")
