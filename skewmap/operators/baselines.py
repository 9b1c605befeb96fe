"""Baselines: plain hash map, perfect-hash table, and model-coded map on ribbon retrieval."""

from __future__ import annotations

import functools
import math
import pickle
import struct
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import partitions, stored
from ..sources.keyvalue import KeyValueSpec, key_hash
from . import gates, hashing, huffman, stats
from .dealing import by_shard, met
from .peeling import peel

SHARD_KEYS = 50_000
#: Bytes up to which a plain table is sent to every executor; beyond, it is joined by an exchange.
BROADCAST_BYTES = 64 << 20


# ---------------------------------------------------------------- plain hash map


@dataclass
class HashTable:
    """All pairs, uncompressed: a hash join, broadcast while the table is small."""

    pairs: DataFrame
    spec: KeyValueSpec

    @classmethod
    def build(cls, df: DataFrame, spec: KeyValueSpec) -> HashTable:
        return cls(stored(spec.pairs(df), "pairs"), spec)

    @functools.cached_property
    def bytes(self) -> int:
        return (self.measured_bits().first()["bits"] or 0) // 8

    def lookup(self, keys: DataFrame) -> DataFrame:
        side = self.pairs.select(*(F.col(k).alias(f"__t_{k}") for k in self.spec.keys), F.col(self.spec.value))
        side = F.broadcast(side) if self.bytes <= BROADCAST_BYTES else side.hint("shuffle_hash")
        cond = F.lit(True)
        for k in self.spec.keys:
            cond = cond & F.col(k).eqNullSafe(F.col(f"__t_{k}"))
        return keys.join(side, cond, "left").select(*keys.columns, self.spec.value)

    def measured_bits(self) -> DataFrame:
        """Bits of keys and values as a row format holds them, with eight bytes of hash table slot at a load of 0.5."""
        size = lambda c: F.coalesce(F.octet_length(F.col(c).cast("string")), F.lit(0)) if dict(self.pairs.dtypes)[c] in ("string", "binary") else F.lit(8)
        row = sum((size(c) for c in self.pairs.columns[1:]), size(self.pairs.columns[0])) + 16
        return self.pairs.agg(F.lit("pairs").alias("part"), (F.sum(row) * 8).alias("bits"), (F.sum(row) * 8 / F.count(F.lit(1))).alias("bpk"))


# ---------------------------------------------------------------- perfect hashing


def _vertices(h: np.ndarray, seed: int, third: int) -> np.ndarray:
    return np.stack([hashing.reduce_to(hashing.xxhash64(h, seed * 8 + i), third) + i * third for i in range(3)], 1)


def perfect_hash(h: np.ndarray) -> tuple[int, int, np.ndarray]:
    """Seed, third, and a selector 0-2 for every vertex (3: owned by no key) of a hash without collisions on ``h``."""
    h = hashing.prepared(h)
    for seed in range(200):
        third = max(2, math.ceil(1.23 * len(h) / 3) + 1 + seed // 20)
        at = _vertices(h, seed, third)
        layers, left = peel(at, 3 * third)
        if len(left):
            continue
        pick = np.full(3 * third, 3, np.int64)
        for rows, own in reversed(layers):
            slot = (at[rows] == own[:, None]).argmax(1)
            others = np.where(np.arange(3)[None, :] == slot[:, None], 0, pick[at[rows]] % 3).sum(1)
            pick[own] = (slot - others) % 3
        return seed, third, pick
    raise RuntimeError("no seed peels the keys")


def perfect_ids(seed: int, third: int, pick: np.ndarray, h: np.ndarray) -> np.ndarray:
    """Dense ids from 0 of the keys the hash was made for."""
    at = _vertices(h, seed, third)
    slot = (pick[at] % 3).sum(1) % 3
    owner = at[np.arange(len(h)), slot]
    rank = np.cumsum(pick < 3) - 1
    return np.maximum(rank[owner], 0)


@dataclass
class PerfectHashTable:
    """Key -> dense id, and an array of packed value ranks by id; ids of shards follow one another."""

    shards: DataFrame
    dictionary: DataFrame
    spec: KeyValueSpec
    count: int
    width: int
    distinct: int

    @classmethod
    def build(cls, df: DataFrame, spec: KeyValueSpec) -> PerfectHashTable:
        pairs = spec.pairs(df)
        hist = stored(stats.value_histogram(pairs, spec.value), "histogram")
        distinct = hist.count()
        book = stored(huffman.ranked_values(hist, distinct).select("value", "rank"), "dictionary")
        width = math.ceil(math.log2(distinct)) if distinct > 1 else 0
        n = hist.agg(F.coalesce(F.sum("freq"), F.lit(0))).first()[0]
        shards = max(1, -(-n // SHARD_KEYS))
        side = F.broadcast(book) if distinct <= huffman.SMALL else book
        keyed = pairs.select(key_hash(pairs, spec.keys).alias("h"), F.col(spec.value).alias("__v")).join(side, F.col("__v").eqNullSafe(F.col("value"))).select(F.pmod("h", F.lit(shards)).alias("shard"), "h", "rank")

        def make(t: pa.Table) -> pa.Table:
            h, rank = t.column("h").to_numpy(), t.column("rank").to_numpy()
            if len(np.unique(h)) < len(h):
                raise ValueError("two keys of a shard share a 64-bit hash; build with another seed")
            seed, third, pick = perfect_hash(h)
            values = np.zeros(len(h), np.int64)
            values[perfect_ids(seed, third, pick, h)] = rank
            return pa.table({"shard": t.column("shard")[:1], "head": [struct.pack("<II", seed, third)], "pick": [gates.pack_bits(pick, 2)], "values": [gates.pack_bits(values, width) if width else b""], "n": pa.array([len(h)], pa.int64())})

        made = stored(by_shard(keyed, shards, make, "shard long, head binary, pick binary, values binary, n long"), "perfect")
        from pyspark.sql.window import Window

        starts = made.select("shard", F.coalesce(F.sum("n").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("start"))
        return cls(made.join(starts, "shard"), book, spec, n, width, distinct)

    def _probe(self, keys: DataFrame) -> DataFrame:
        shards = max(1, -(-self.count // SHARD_KEYS))
        width = self.width

        def read(row: list, h: np.ndarray, _: pa.RecordBatch) -> list[np.ndarray]:
            seed, third, pick, values, n, start = row
            local = np.minimum(perfect_ids(seed, third, pick, h), n - 1)
            return [local + start, values[local]]

        def ready(row: list) -> list:
            head, pick, values, n, start = row
            seed, third = struct.unpack("<II", head)
            return [seed, third, gates.unpack_bits(pick, 2, 3 * third), gates.unpack_bits(values, width, n) if width else np.zeros(n, np.int64), n, start]

        given = self.shards.select("shard", "head", "pick", "values", "n", "start")
        return met(keys, key_hash(keys, self.spec.keys), given, shards, read, ("__id", "__rank"), ready=ready)

    def lookup(self, keys: DataFrame) -> DataFrame:
        book = self.dictionary.select(F.col("rank").alias("__rank"), F.col("value").alias(self.spec.value))
        book = F.broadcast(book) if self.distinct <= huffman.SMALL else book
        return self._probe(keys).join(book, "__rank", "left").select(*keys.columns, self.spec.value)

    def ids(self, keys: DataFrame) -> DataFrame:
        """``keys`` with their dense ids."""
        return self._probe(keys).select(*keys.columns, F.col("__id").alias("id"))

    def measured_bits(self) -> DataFrame:
        row = self.shards.agg((F.sum(F.octet_length("pick")) * 8).alias("hash"), (F.sum(F.octet_length("values")) * 8).alias("values"), (F.sum(F.octet_length("head")) * 8).alias("headers")).first()
        words = self.dictionary.agg(F.coalesce(F.sum(F.octet_length(F.col("value").cast("string"))), F.lit(0)) * 8).first()[0]
        parts = [("hash", row["hash"]), ("values", row["values"]), ("headers", row["headers"]), ("dictionary", words)]
        return self.shards.sparkSession.createDataFrame([(p, int(b or 0), (b or 0) / max(1, self.count)) for p, b in parts], "part string, bits long, bpk double")


# ---------------------------------------------------------------- ribbon retrieval

RIBBON = 64


def ribbon_build(h: np.ndarray, bits: np.ndarray, salt: int = 0) -> bytes:
    """One bit for each key hash by a banded GF(2) system: a start column and 64 coefficients a key."""
    if not len(h):
        return b""
    for seed in range(200):
        columns = math.ceil(len(h) * (1.08 + 0.01 * (seed // 4))) + RIBBON
        start, coeff = _ribbon(h, seed + salt, columns)
        order = np.argsort(start, kind="stable")
        rows, want = [0] * columns, bytearray(columns)
        done = True
        for s, c, b in zip(start[order].tolist(), coeff[order].tolist(), bits[order].tolist()):
            while c:
                shift = (c & -c).bit_length() - 1
                s, c = s + shift, c >> shift
                if not rows[s]:
                    rows[s], want[s] = c, b
                    break
                c ^= rows[s]
                b ^= want[s]
            else:
                if b:
                    done = False
                    break
        if not done:
            continue
        x = bytearray(columns)
        window = 0  # solution bits of the 64 columns from i on
        for i in range(columns - 1, -1, -1):
            window = (window << 1) & 0xFFFFFFFFFFFFFFFF
            if rows[i]:
                x[i] = want[i] ^ ((rows[i] & window).bit_count() & 1)
            window |= x[i]
        return struct.pack("<II", seed + salt, columns) + np.packbits(np.frombuffer(x, np.uint8), bitorder="little").tobytes()
    raise RuntimeError("no seed solves the band")


def _ribbon(h: np.ndarray, seed: int, columns: int) -> tuple[np.ndarray, np.ndarray]:
    return hashing.reduce_to(hashing.xxhash64(h, seed * 4 + 1), columns - RIBBON + 1), hashing.xxhash64(h, seed * 4 + 2) | np.uint64(1)


def ribbon_get(data: bytes, h: np.ndarray) -> np.ndarray:
    if not data:
        return np.zeros(len(h), np.uint8)
    seed, columns = struct.unpack_from("<II", data)
    words = np.frombuffer(data[8:] + bytes(16 - (len(data) - 8) % 8), "<u8")  # and a word to spare
    start, coeff = _ribbon(h, seed, columns)
    word, shift = start >> 6, (start & 63).astype(np.uint64)
    band = (words[word] >> shift) | ((words[word + 1] << np.uint64(1)) << (np.uint64(63) - shift))
    return np.bitwise_count(band & coeff) & 1


# ---------------------------------------------------------------- model-coded map

#: Hidden layers of the models that are tried; an empty tuple is the linear one.
ARCHES = ((), (50,), (100,), (50, 50))
#: Symbols a model predicts; rarer values share one escape symbol, after which their rank follows in plain bits.
MODEL_SYMBOLS = 256
#: Scores are in 64ths of a power of two; probabilities are whole numbers below 2**30 over their sum.
_UNIT, _ONE = 64, 30
_POWERS = np.array([round(2 ** (_ONE - f / _UNIT)) for f in range(_UNIT)], np.int64)
#: Fingerprint bits that are tried for the filter before the codes.
FILTER_BITS = tuple(range(7))
#: Tasks that sizes are tried in.
TRIED = 32


def ordinal_features(col: Column, k: int) -> Column:
    """Place of each of the k letters a, c, g, t, over 3."""
    return F.transform(F.sequence(F.lit(1), F.lit(k)), lambda i: (F.instr(F.lit("acgt"), F.substr(col, i, F.lit(1))) - 1) / 3.0)


def _hash_bits(h: np.ndarray, width: int) -> np.ndarray:
    return ((h[:, None] >> np.arange(width)) & 1).astype(np.float32)


def _matrix(rows: pa.Table | pa.RecordBatch, h: str, x: str | None, width: int) -> np.ndarray:
    """Features of each row: its list column ``x`` of ``width`` numbers, or without one the lowest bits of its hash ``h``."""
    if x is None:
        return _hash_bits(rows.column(h).to_numpy(), width)
    column = rows.column(x)
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float32).reshape(len(column), width)


@dataclass(frozen=True)
class Network:
    """A trained model as float16 layers (weights, offsets). Evaluation is in float32, one addition after the other, so
    every machine gets the same bits."""

    layers: tuple[tuple[np.ndarray, np.ndarray], ...]

    def scores(self, x: np.ndarray) -> np.ndarray:
        """Logarithms of the symbols' odds, in 64ths of a power of two."""
        a = x.astype(np.float32)
        for i, (w, b) in enumerate(self.layers):
            out = np.repeat(b.astype(np.float32)[None, :], len(a), 0)
            for j in np.flatnonzero(w.any(1)):
                out += a[:, j : j + 1] * w[j].astype(np.float32)[None, :]
            a = np.maximum(out, np.float32(0)) if i + 1 < len(self.layers) else out
        return np.rint(np.clip(a, -600, 600) * np.float32(_UNIT / math.log(2))).astype(np.int64)

    @property
    def steady(self) -> bool:
        """Whether scores are the same for all features: a layer has no weights but zeros."""
        return any(not w.any() for w, _ in self.layers)

    @property
    def bits(self) -> int:
        """Stored bits: offsets, a mark for every row of weights, and the rows that are not zero."""
        return sum(16 * b.size + w.shape[0] + 16 * int(w.any(1).sum()) * w.shape[1] for w, b in self.layers)


def train(x: np.ndarray, y: np.ndarray, hidden: tuple[int, ...], classes: int, rounds: int = 40, patience: int = 3, seed: int = 1) -> Network:
    """Fit features to labels by Adam on cross entropy, stopping when the loss on a held-out tenth has not fallen for ``patience`` rounds.

    The last layer begins as the labels' frequencies whatever the features, and the best state seen is kept: a model
    that learns nothing stays at that and has no weights to store.
    """
    rng = np.random.default_rng(seed)
    sizes = [x.shape[1], *hidden, classes]
    prior = np.log((np.bincount(y, minlength=classes) + 0.1) / (len(y) + 0.1 * classes))
    layers = [[rng.normal(0, math.sqrt(2 / a), (a, b)) if i + 2 < len(sizes) else np.zeros((a, b)), np.zeros(b)] for i, (a, b) in enumerate(zip(sizes[:-1], sizes[1:]))]
    layers[-1][1] = prior.copy()
    held = rng.random(len(y)) < 0.1
    fit = np.flatnonzero(~held)

    def forward(part: np.ndarray) -> list[np.ndarray]:
        out = [part]
        for i, (w, b) in enumerate(layers):
            z = out[-1] @ w + b
            out.append(np.maximum(z, 0) if i + 1 < len(layers) else z)
        return out

    def loss(part: np.ndarray, label: np.ndarray) -> float:
        z = forward(part)[-1]
        top = z.max(1)
        return float((np.log(np.exp(z - top[:, None]).sum(1)) + top - z[np.arange(len(label)), label]).mean())

    def kept() -> Network:
        return Network(tuple((w.astype(np.float16), b.astype(np.float16)) for w, b in layers))

    if not held.any() or not len(fit):
        return kept()
    best, least, waited = kept(), loss(x[held], y[held]) - 1e-4, 0
    moments = [[np.zeros_like(p), np.zeros_like(p)] for layer in layers for p in layer]
    step = 0
    for _ in range(rounds):
        rng.shuffle(fit)
        for lo in range(0, len(fit), 256):
            rows = fit[lo : lo + 256]
            out = forward(x[rows])
            z = np.exp(out[-1] - out[-1].max(1, keepdims=True))
            g = z / z.sum(1, keepdims=True)
            g[np.arange(len(rows)), y[rows]] -= 1
            g /= len(rows)
            grads = []
            for i in reversed(range(len(layers))):
                grads[:0] = [out[i].T @ g, g.sum(0)]
                if i:
                    g = (g @ layers[i][0].T) * (out[i] > 0)
            step += 1
            for (m, v), grad, (i, j) in zip(moments, grads, [(i, j) for i in range(len(layers)) for j in range(2)]):
                m += 0.1 * (grad - m)
                v += 0.001 * (grad * grad - v)
                layers[i][j] = layers[i][j] - 3e-3 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
        now = loss(x[held], y[held])
        if now < least:
            best, least, waited = kept(), now, 0
        else:
            waited += 1
            if waited >= patience:
                break
    return best


def _odds(scores: np.ndarray) -> np.ndarray:
    """Whole-numbered odds of the symbols of each key, by integers alone."""
    below = scores.max(1, keepdims=True) - scores
    return np.maximum(_POWERS[below & (_UNIT - 1)] >> np.minimum(below >> 6, _ONE), 1)


def _key_odds(network: Network, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different odds, and which of them each key has. All keys have the same if the model gives the same for all features."""
    if network.steady:
        return _odds(network.scores(x[:1])), np.zeros(len(x), np.int64)
    return _odds(network.scores(x)), np.arange(len(x))


def _guesses(odds: np.ndarray, extra: int) -> np.ndarray:
    """Each key's likeliest symbol, but never the escape, after which more bits must follow."""
    return (odds[:, :-1] if extra else odds).argmax(1)


def _order(values: np.ndarray) -> np.ndarray:
    """Stable ``argsort`` of each row of whole numbers below 2**48: sorted with their places in the low bits."""
    bits = max(1, (values.shape[1] - 1).bit_length())
    tagged = values << bits
    tagged |= np.arange(values.shape[1])
    tagged.sort(axis=1)
    tagged &= (1 << bits) - 1
    return tagged


def key_codes(odds: np.ndarray, guess: np.ndarray, bits: int) -> np.ndarray:
    """Codeword lengths of every symbol for each key that passed a filter of ``bits`` bits.

    Only one in 2**bits keys whose first guess is right passes, so the guess's odds fall by as much. Lengths are the
    least with 2**-length at most the probability; what the code then has to spare shortens the codewords that
    rounding made longest.
    """
    w = odds.copy()
    rows = np.arange(len(w))
    w[rows, guess] = np.maximum(w[rows, guess] >> bits, 1)
    total = w.sum(1, keepdims=True)
    length = np.frexp(total)[1].astype(np.int64) - np.frexp(w)[1]  # both are below 2**53: as many bits as they have
    scaled = w << length
    more = scaled < total
    length += more
    scaled <<= more
    cost = np.int64(1) << (48 - length)
    spare = (np.int64(1) << 48) - cost.sum(1, keepdims=True)
    order = _order(-scaled)
    ahead = np.take_along_axis(cost, order, 1).cumsum(1) <= spare
    row, place = np.nonzero(ahead)
    length[row, order[row, place]] -= 1
    return np.maximum(length, 1, out=length)


def _codeword(length: np.ndarray, like: np.ndarray, symbol: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Size and canonical codeword (shorter ones first, then by symbol) of one symbol of each key, whose lengths are the row ``like``."""
    kinds, each = np.unique(like * length.shape[1] + symbol, return_inverse=True)
    like, symbol = np.divmod(kinds, length.shape[1])
    own, length = length[like, symbol][:, None], length[like]
    before = (length < own) | ((length == own) & (np.arange(length.shape[1])[None, :] < symbol[:, None]))
    return own[:, 0][each], np.where(before, np.int64(1) << np.maximum(own - length, 0), 0).sum(1)[each]


CHUNK_KEYS = 20_000


@dataclass
class ModelCodedMap:
    """A model predicts every key's distribution over the values; the true value is stored by the key's own prefix code.

    Two ribbon structures hold a shard. A filter has the keys whose first guess is wrong, so most right guesses
    need nothing more; its number of bits is the one of least size in all. For the keys that pass, the
    other gives the bits of the codeword, one equation for a key and bit. The model is the architecture whose map is
    smallest, weights included, by the code lengths of a bounded sample of keys.
    """

    shards: DataFrame
    dictionary: DataFrame
    spec: KeyValueSpec
    network: Network
    hidden: tuple[int, ...]
    classes: int
    distinct: int
    count: int
    shard_count: int
    width: int
    features: Column | None
    filter_bits: int
    extra: int
    longest: int

    @classmethod
    def build(cls, df: DataFrame, spec: KeyValueSpec, arches=((),), features: Column | None = None, width: int = 32, sample: int = 20_000) -> ModelCodedMap:
        spark = df.sparkSession
        pairs = stored(spec.pairs(df.select(*spec.keys, spec.value)), "pairs")
        hist = stored(stats.value_histogram(pairs, spec.value), "histogram")
        distinct, n = hist.count(), pairs.count()
        book = stored(huffman.ranked_values(hist, distinct).select("value", "rank"), "dictionary")
        classes = max(2, min(distinct, MODEL_SYMBOLS) + (distinct > MODEL_SYMBOLS))
        extra = max(0, math.ceil(math.log2(distinct - classes + 1))) if distinct > classes else 0
        shards = max(1, -(-n // SHARD_KEYS))
        h = key_hash(pairs, spec.keys)
        x = "features" if features is not None else None  # bits of the hash need not travel
        own = [features.alias(x)] if x else []
        side = F.broadcast(book) if distinct <= huffman.SMALL else book
        keyed = pairs.select(h.alias("h"), *own, F.col(spec.value).alias("__v")).join(side, F.col("__v").eqNullSafe(F.col("value"))).select(F.pmod("h", F.lit(shards)).alias("shard"), "h", "rank", *([x] if x else []))
        keyed = stored(keyed, "keys")
        # Training and the choice of architecture see a bounded sample, the keys of smallest hash; the map holds all keys.
        # Architectures are trained side by side.
        few = stored(keyed.drop("shard").orderBy(F.xxhash64("h")).limit(sample), "sample")
        part = few.select(*([x] if x else []), F.least("rank", F.lit(classes - 1)).alias("label"), "h", F.explode(F.array(*(F.lit(i) for i in range(len(arches))))).alias("shard"))

        def fit(t: pa.Table) -> pa.Table:
            t = t.sort_by("h")
            net = train(_matrix(t, "h", x, width).astype(np.float64), t.column("label").to_numpy(), arches[t.column("shard")[0].as_py()], classes)
            return pa.table({"arch": t.column("shard")[:1], "net": pa.array([pickle.dumps(net)], pa.binary())})

        nets = {r["arch"]: pickle.loads(r["net"]) for r in by_shard(part, len(arches), fit, "arch int, net binary").collect()}
        blank = Network(((np.zeros((width, classes), np.float16), np.zeros(classes, np.float16)),))
        nets = {i: nets.get(i, blank) for i in range(len(arches))}

        def sizes(batches):
            """Bits of codes, filters and so on of each architecture and filter size, added up over a task's keys."""
            total = np.zeros((len(arches), len(FILTER_BITS)))
            keys = 0
            for batch in batches:
                feats, rank = _matrix(batch, "h", x, width), batch.column("rank").to_numpy()
                label = np.minimum(rank, classes - 1)
                keys += len(label)
                for i in range(len(arches)):
                    odds, like = _key_odds(nets[i], feats)
                    guess = _guesses(odds, extra)
                    wrong = guess[like] != label
                    for j, r in enumerate(FILTER_BITS):
                        size = key_codes(odds, guess, r)[like, label] + extra * (label == classes - 1)
                        total[i, j] += size[wrong].sum() + size[~wrong].sum() / 2**r + wrong.sum() * r
            i, j = (z.ravel() for z in np.indices(total.shape))
            yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(j), pa.array(total.ravel()), pa.array(np.full(total.size, keys))], ["arch", "bits", "size", "keys"])

        # Sums of whole numbers over powers of two are the same in any order of the tasks.
        tried = few.repartition(min(TRIED, partitions(spark))).mapInArrow(sizes, "arch long, bits long, size double, keys long").groupBy("arch", "bits").agg(F.sum("size").alias("size"), F.sum("keys").alias("keys")).collect()
        best = min(tried, key=lambda t: (t["size"] * 1.09 * n / max(1, t["keys"]) + nets[t["arch"]].bits, t["arch"], t["bits"]), default=None)
        arch, r = (best["arch"], FILTER_BITS[best["bits"]]) if best else (0, 0)
        network = nets[arch]

        def make(t: pa.Table) -> pa.Table:
            h, rank = t.column("h").to_numpy(), t.column("rank").to_numpy()
            feats = _matrix(t, "h", x, width)
            label = np.minimum(rank, classes - 1)
            guess = np.concatenate([_guesses(odds, extra)[like] for i in range(0, len(h), CHUNK_KEYS) for odds, like in [_key_odds(network, feats[i : i + CHUNK_KEYS])]])
            wrong = guess != label
            gate = ribbon_filter(h[wrong], r)
            passed = np.flatnonzero(wrong | ribbon_passes(gate, h, r))
            eqs, bits, longest = [np.zeros(0, np.int64)], [np.zeros(0, np.uint8)], 0
            for i in range(0, len(passed), CHUNK_KEYS):
                some = passed[i : i + CHUNK_KEYS]
                odds, like = _key_odds(network, feats[some])
                size, word = _codeword(key_codes(odds, _guesses(odds, extra), r), like, label[some])
                rare = (label[some] == classes - 1) & (extra > 0)
                word = np.where(rare, (word << extra) | (rank[some] - classes + 1), word)
                size = size + extra * rare
                longest = max(longest, int(size.max(initial=0)))
                key = np.repeat(np.arange(len(some)), size)
                bit = np.arange(len(key)) - np.repeat(np.cumsum(size) - size, size)
                eqs.append(_bit_hash(h[some][key], bit))
                bits.append(((word[key] >> (size[key] - 1 - bit)) & 1).astype(np.uint8))
            return pa.table({"shard": t.column("shard")[:1], "gate": pa.array([gate], pa.list_(pa.binary())), "codes": pa.array([ribbon_build(np.concatenate(eqs), np.concatenate(bits), 1000)], pa.binary()), "longest": pa.array([longest], pa.int32())})

        made = stored(by_shard(keyed, shards, make, "shard long, gate array<binary>, codes binary, longest int"), "model")
        longest = made.agg(F.coalesce(F.max("longest"), F.lit(0))).first()[0]
        return cls(made, book, spec, network, arches[arch], classes, distinct, n, shards, width, features, r, extra, longest)

    def lookup(self, keys: DataFrame) -> DataFrame:
        columns, network, classes, width, extra, distinct, r, longest = list(keys.columns), self.network, self.classes, self.width, self.extra, self.distinct, self.filter_bits, self.longest
        x = "__x" if self.features is not None else None

        def ranks(h: np.ndarray, feats: np.ndarray, gate: list[bytes], codes: bytes) -> np.ndarray:
            odds, like = _key_odds(network, feats)
            guess = _guesses(odds, extra)
            rank = guess.astype(np.int64)[like]
            passed = np.flatnonzero(ribbon_passes(gate, h, r))
            if not len(passed):
                return rank
            kinds, like = np.unique(like[passed], return_inverse=True)
            h, length = h[passed], key_codes(odds[kinds], guess[kinds], r)
            order = _order(length)
            sizes = np.take_along_axis(length, order, 1)
            spans = np.int64(1) << (48 - sizes)
            begins = spans.cumsum(1) - spans  # a codeword is the interval of all numbers that begin with it
            at, place = np.zeros(len(h), np.int64), np.zeros(len(h), np.int64)
            open_ = np.arange(len(h))
            # Keys of one row of codes only, whose codewords' begins rise: a place is found by bisection.
            placed = (lambda n: np.searchsorted(begins[0], at[n], "right") - 1) if len(begins) == 1 else (lambda n: (begins[like[n]] <= at[n, None]).sum(1) - 1)
            for bit in range(longest):
                at[open_] |= ribbon_get(codes, _bit_hash(h[open_], np.full(len(open_), bit))).astype(np.int64) << (47 - bit)
                place[open_] = placed(open_)
                open_ = open_[sizes[like[open_], place[open_]] > bit + 1]
                if not len(open_):
                    break
            symbol, size = order[like, place], sizes[like, place]
            if extra:
                rare = np.flatnonzero(symbol == classes - 1)
                more = np.zeros(len(rare), np.int64)
                for bit in range(extra):
                    more = (more << 1) | ribbon_get(codes, _bit_hash(h[rare], size[rare] + bit)).astype(np.int64)
                symbol[rare] += more
            rank[passed] = np.minimum(symbol, distinct - 1)
            return rank

        def read(row: list, h: np.ndarray, keys: pa.RecordBatch) -> list[np.ndarray]:
            rank, feats = np.zeros(len(h), np.int64), _hash_bits(h, width) if x is None else _matrix(keys, "", x, width)
            for i in range(0, len(h), CHUNK_KEYS):
                rank[i : i + CHUNK_KEYS] = ranks(h[i : i + CHUNK_KEYS], feats[i : i + CHUNK_KEYS], *row)
            return [rank]

        # One binary column: with a list column beside every key, Spark takes twenty times as long to hand keys over.
        gate = F.aggregate("gate", F.lit(b""), lambda a, b: F.concat(a, b)).alias("gate")
        found = met(keys, key_hash(keys, self.spec.keys), self.shards.select("shard", gate, "codes"), self.shard_count, read, ("__rank",), self.features, lambda row: [ribbons_apart(row[0], r), row[1]])
        book = self.dictionary.select(F.col("rank").alias("__rank"), F.col("value").alias(self.spec.value))
        book = F.broadcast(book) if self.distinct <= huffman.SMALL else book
        return found.join(book, "__rank", "left").select(*columns, self.spec.value)

    def measured_bits(self) -> DataFrame:
        gate = F.coalesce(F.sum(F.aggregate("gate", F.lit(0), lambda a, p: a + F.octet_length(p))), F.lit(0)) * 8
        row = self.shards.agg(gate.alias("gate"), (F.coalesce(F.sum(F.octet_length("codes")), F.lit(0)) * 8).alias("codes")).first()
        words = self.dictionary.agg(F.coalesce(F.sum(F.octet_length(F.col("value").cast("string"))), F.lit(0)) * 8).first()[0]
        parts = [("filter", row["gate"]), ("ribbons", row["codes"]), ("weights", self.network.bits), ("dictionary", words)]
        return self.shards.sparkSession.createDataFrame([(p, int(b), b / max(1, self.count)) for p, b in parts], "part string, bits long, bpk double")


def _bit_hash(h: np.ndarray, bit: np.ndarray) -> np.ndarray:
    return hashing.xxhash64(h, bit).view(np.int64)


def ribbon_filter(h: np.ndarray, bits: int) -> list[bytes]:
    """A filter of ``bits`` fingerprint bits, each a ribbon structure that gives it back for the keys that are in."""
    prints = hashing.xxhash64(h, 77)
    return [ribbon_build(h, ((prints >> np.uint64(j)) & np.uint64(1)).astype(np.uint8), 300 * j) for j in range(bits)]


def ribbons_apart(data: bytes, n: int) -> list[bytes]:
    """The n ribbon structures that stand end to end; all are empty or none."""
    out = []
    while data:
        size = 8 + -(-struct.unpack_from("<II", data)[1] // 8)
        out.append(data[:size])
        data = data[size:]
    return out or [b""] * n


def ribbon_passes(gate: list[bytes], h: np.ndarray, bits: int) -> np.ndarray:
    """Whether keys may be in the filter. A filter of no bits lets all pass; one of no keys none."""
    prints = hashing.xxhash64(h, 77)
    out = np.ones(len(h), bool)
    for j in range(bits):
        if not gate[j]:
            return np.zeros(len(h), bool)
        some = np.flatnonzero(out)
        out[some] = ribbon_get(gate[j], h[some]) == ((prints[some] >> np.uint64(j)) & np.uint64(1)).astype(np.uint8)
    return out


def best_model(df: DataFrame, spec: KeyValueSpec, arches=ARCHES, **options) -> ModelCodedMap:
    """The map of the architecture that makes it smallest in all, model included."""
    return ModelCodedMap.build(df, spec, tuple(arches), **options)
