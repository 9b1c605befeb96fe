"""Counts of all substrings of k characters, dealt by minimizers.

A text is cut into runs of neighbouring k-mers that have the same bucket: that of the least hash among a k-mer's
shorter substrings. A run of r k-mers travels as r + k - 1 characters instead of r * k, and equal k-mers
always meet in one bucket. There k-mers are packed into words of 64 bits and sorted by a hash with their place; neighbours
are compared by their words, so counts are exact whatever the hashes do.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import partitions

#: Bytes of text that are cut at once, characters of runs that are gathered at once, k-mers that a bucket should have, and
#: that are sorted at once; rows of a result batch.
SLICE, PLACES, BUCKET, CHUNK, ROWS = 4_000_000, 1_000_000, 2_000_000, 3_000_000, 250_000
_ODD = np.uint64(0x9E3779B97F4A7C15)


def _characters(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Code points of a column's texts end to end, in the narrowest type that holds them, and how many each text has."""
    column = column.cast(pa.large_string())
    _, offsets, data = column.buffers()
    offs = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = memoryview(data)[offs[0] : offs[-1]] if data is not None else b""
    sizes = pc.utf8_length(column).to_numpy().astype(np.int64)
    if sizes.sum() == len(raw):
        return np.frombuffer(raw, np.uint8), sizes
    text = str(raw, "utf-8")
    try:
        return np.frombuffer(text.encode("latin-1"), np.uint8), sizes
    except UnicodeEncodeError:
        chars = np.frombuffer(text.encode("utf-32-le"), np.uint32)
        return _narrow(chars), sizes


def _narrow(chars: np.ndarray) -> np.ndarray:
    """Code points in the narrowest type that holds them."""
    most = chars.max() if chars.itemsize > 1 and len(chars) else 0
    kind = np.uint8 if most < 1 << 8 else np.uint16 if most < 1 << 16 else np.uint32
    return chars.astype(kind) if np.dtype(kind).itemsize < chars.itemsize else chars


def _least(chars: np.ndarray, k: int) -> np.ndarray:
    """The least hash among the shorter substrings of the k-mer at every place."""
    m = min(max(1, k // 2), 8)
    h = np.zeros(len(chars) - m + 1, np.uint32)
    for j in range(m):
        h *= np.uint32(0x01000193)
        h += chars[j : len(chars) - m + 1 + j]
    h ^= h >> np.uint32(15)
    h *= np.uint32(0x9E3779B1)
    h ^= h >> np.uint32(16)
    have, want = 1, k - m + 1
    while have < want:
        step = min(have, want - have)
        h = np.minimum(h[:-step], h[step:])
        have += step
    return h


def _runs(chars: np.ndarray, sizes: np.ndarray, k: int, buckets: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(bucket, k-mers of each run, code points of its runs end to end)."""
    if len(chars) < k:
        return
    places = len(chars) - k + 1
    whole, ends = np.ones(places, bool), np.cumsum(sizes)
    for j in range(1, k):
        over = ends - j
        whole[over[(over >= 0) & (over < places)]] = False
    least = _least(chars, k)
    turn = np.ones(places + 1, bool)
    np.not_equal(least[1:], least[:-1], out=turn[1:-1])
    turn[1:-1] |= whole[1:] != whole[:-1]
    first, last = np.flatnonzero(whole & turn[:-1]), np.flatnonzero(whole & turn[1:])
    if not len(first):
        return
    bucket = (((least[first].astype(np.uint64) * _ODD) >> np.uint64(32)) * np.uint64(buckets)) >> np.uint64(32)
    bucket = bucket.astype(np.uint16 if buckets <= 1 << 16 else np.uint32)
    del least, turn, whole
    count = (last - first + 1).astype(np.uint32)
    order = np.argsort(bucket, kind="stable")
    first, count, bucket = first[order], count[order], bucket[order]
    size = count.astype(np.int64) + (k - 1)
    stop = np.cumsum(size)
    shift = first - (stop - size)
    cuts = np.concatenate([[0], np.flatnonzero(bucket[1:] != bucket[:-1]) + 1, [len(bucket)]]).tolist()
    lo = 0
    while lo < len(cuts) - 1:  # some buckets at once: places are bulky
        hi = lo + 1
        base = int(stop[cuts[lo]] - size[cuts[lo]])
        while hi < len(cuts) - 1 and stop[cuts[hi + 1] - 1] - base <= PLACES:
            hi += 1
        a, b = cuts[lo], cuts[hi]
        at = np.repeat(shift[a:b], size[a:b])
        at += np.arange(base, base + len(at))
        text = chars[at]
        for x, y in zip(cuts[lo:hi], cuts[lo + 1 : hi + 1]):
            yield int(bucket[x]), count[x:y], _narrow(text[stop[x] - size[x] - base : stop[y - 1] - base])
        lo = hi


def _cutter(k: int, buckets: int):
    """For ``mapInArrow`` over (text, side): runs by bucket, compressed."""

    def run(batches):
        codec = pa.Codec("zstd", 1)
        pack = lambda raw: codec.compress(raw, asbytes=True)
        for batch in batches:
            sides = batch.column(1)
            for side in (False, True):
                texts = pc.filter(batch.column(0), pc.and_(pc.equal(sides, side), pc.is_valid(batch.column(0))))
                if not len(texts):
                    continue
                total = np.cumsum(pc.binary_length(texts).to_numpy().astype(np.int64)) // SLICE
                starts = np.flatnonzero(np.concatenate([[True], total[1:] != total[:-1]])).tolist()
                for lo, hi in zip(starts, [*starts[1:], len(texts)]):
                    out: list[tuple] = []
                    for bucket, count, text in _runs(*_characters(texts.slice(lo, hi - lo)), k, buckets):
                        out.append((bucket, side, len(count), text.nbytes, pack(count.tobytes()), pack(text.tobytes())))
                    if out:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), _CUT.types)], names=_CUT.names)

    return run


_CUT = pa.schema([("bucket", pa.int32()), ("side", pa.bool_()), ("runs", pa.int64()), ("bytes", pa.int64()), ("counts", pa.binary()), ("chars", pa.binary())])
_CUT_SCHEMA = "bucket int, side boolean, runs long, bytes long, counts binary, chars binary"


def _tally(words: list[np.ndarray], weights: list[np.ndarray]) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Different rows of ``words``, and the sums of their weights."""
    n = len(words[0])
    if len(words) == 1:
        order = None
        key = words[0]
        if all(w is None for w in weights[1:]) and weights[0] is None:
            key = np.sort(key)
            at = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
            return [key[at]], [np.diff(at, append=n), *weights[1:]]
        order = np.argsort(key)
    else:
        h = words[0] * _ODD
        for w in words[1:]:
            h ^= h >> np.uint64(31)
            h += w
            h *= np.uint64(0xBF58476D1CE4E5B9)
        h ^= h >> np.uint64(30)
        h *= np.uint64(0x94D049BB133111EB)
        bits = np.uint64(max(1, n.bit_length()))
        h >>= bits
        h <<= bits
        h |= np.arange(n, dtype=np.uint64)
        h.sort()
        order = (h & ((np.uint64(1) << bits) - np.uint64(1))).astype(np.int64)
        h >>= bits
        same_hash = h[1:] == h[:-1]
    there = [w[order] for w in words]
    same = np.logical_and.reduce([w[1:] == w[:-1] for w in there])
    if len(words) > 1 and len(odd := np.flatnonzero(same_hash & ~same)):  # different rows of one hash: these few are put in order
        ends = np.append(np.flatnonzero(~same_hash), n - 1)
        group = np.unique(np.searchsorted(ends, odd))
        start = np.where(group > 0, ends[group - 1] + 1, 0)
        many = ends[group] + 1 - start
        rows = np.repeat(start - (np.cumsum(many) - many), many) + np.arange(many.sum())
        put = rows[np.lexsort([*(w[rows] for w in there), np.repeat(group, many)])]
        order[rows] = order[put]
        for w, own in zip(there, words):
            w[rows] = own[order[rows]]
        inner = rows[rows < n - 1]
        same[inner] = np.logical_and.reduce([w[inner + 1] == w[inner] for w in there])
    at = np.flatnonzero(np.concatenate([[True], ~same]))
    sums = [None if w is None else np.add.reduceat(w[order], at) for w in weights]
    if weights[0] is None:
        sums[0] = np.diff(at, append=n)
    return [w[at] for w in there], sums


class _Bucket:
    """K-mers of one bucket: what has come, in codes of the bucket's own alphabet, and what is counted.

    The alphabet begins with ASCII, so such text is its own code. A word holds codes in the order of memory.
    """

    def __init__(self, k: int, sides: bool):
        self.k, self.sides = k, sides
        self.code = np.full(0x110000, -1, np.int32)
        self.letters = np.zeros(0, np.uint32)
        self.clear()

    def clear(self) -> None:
        self.code[self.letters] = -1
        self.letters = np.arange(128, dtype=np.uint32)
        self.code[:128] = self.letters
        self.bits = 8
        self.waiting: list[tuple] = []
        self.many = 0
        self.counted: list[tuple] = []

    def add(self, side: bool, counts: np.ndarray, chars: np.ndarray) -> None:
        codes = chars
        if chars.max(initial=0) >= 128:
            codes = self.code[chars]
            if (codes < 0).any():
                new = np.unique(chars[codes < 0])
                if len(self.letters) + len(new) > 1 << self.bits:
                    self.settle()
                    wider = 16 if len(self.letters) + len(new) <= 1 << 16 else 32
                    self.counted = [(self._words(self._codes(words).ravel(), np.arange(len(words[0])) * self.k, wider), sums) for words, sums in self.counted]
                    self.bits = wider
                self.code[new] = np.arange(len(self.letters), len(self.letters) + len(new))
                self.letters = np.concatenate([self.letters, new.astype(np.uint32)])
                codes = self.code[chars]
        self.waiting.append((side, counts, codes.astype(f"<u{self.bits // 8}", copy=False)))
        self.many += int(counts.sum())
        if self.many >= CHUNK:
            self.settle()

    def _offsets(self, bits: int) -> list[int]:
        each = 64 // bits
        return [*range(0, max(1, self.k - each), each), self.k - each] if self.k > each else [0]

    def _words(self, codes: np.ndarray, first: np.ndarray, bits: int) -> list[np.ndarray]:
        """Words of the k-mers at some places."""
        each = 64 // bits
        raw = np.concatenate([codes.astype(f"<u{bits // 8}", copy=False), np.zeros(each, f"<u{bits // 8}")])
        at = np.ndarray(len(raw) - each + 1, "<u8", raw, 0, (bits // 8,))
        words = [at[first + o] if o else at[first] for o in self._offsets(bits)]
        if self.k < each:
            words[0] &= np.uint64((1 << bits * self.k) - 1)
        return words

    def _codes(self, words: list[np.ndarray]) -> np.ndarray:
        """Codes by row and character."""
        each = min(64 // self.bits, self.k)
        out = np.empty((len(words[0]), self.k), f"<u{self.bits // 8}")
        for w, o in zip(words, self._offsets(self.bits)):
            out[:, o : o + each] = np.ascontiguousarray(w).view(out.dtype).reshape(len(w), -1)[:, :each]
        return out

    def settle(self) -> None:
        """Count what has come; join counts when they are many."""
        if self.waiting:
            counts = np.concatenate([c for _, c, _ in self.waiting]).astype(np.int64)
            codes = np.concatenate([c for _, _, c in self.waiting])
            size = counts + self.k - 1
            first = np.repeat(np.cumsum(size) - size - (np.cumsum(counts) - counts), counts)
            first += np.arange(len(first))
            flag = None
            if self.sides:
                flag = np.repeat(np.concatenate([np.full(len(c), s) for s, c, _ in self.waiting]), counts).astype(np.int64)
            self.waiting, self.many = [], 0
            self.counted.append(_tally(self._words(codes, first, self.bits), [None, flag]))
        if len(self.counted) > 1 and sum(len(w[0]) for w, _ in self.counted[1:]) > max(CHUNK, len(self.counted[0][0][0])):
            self.join()

    def join(self) -> None:
        if len(self.counted) > 1:
            words = [np.concatenate(w) for w in zip(*(w for w, _ in self.counted))]
            sums = [None if s[0] is None else np.concatenate(s) for s in zip(*(s for _, s in self.counted))]
            self.counted = [_tally(words, sums)]

    def totals(self) -> Iterator[tuple[list[np.ndarray], list[np.ndarray]]]:
        """Different k-mers as words, and how often they occur."""
        self.settle()
        self.join()
        yield from self.counted

    def _text(self, codes: np.ndarray) -> pa.Array:
        """Rows of codes as strings."""
        n = len(codes)
        if self.bits == 8 and codes.max(initial=0) < 128:
            return pa.StringArray.from_buffers(n, pa.py_buffer(np.arange(0, (n + 1) * self.k, self.k, dtype=np.int32)), pa.py_buffer(codes))
        chars = self.letters[codes]
        size = np.full(n, self.k, np.int64)
        for least in (0x80, 0x800, 0x10000):
            size += (chars >= least).sum(1)
        ends = np.concatenate([[0], np.cumsum(size)]).astype(np.int32)
        return pa.StringArray.from_buffers(n, pa.py_buffer(ends), pa.py_buffer(chars.tobytes().decode("utf-32-le").encode()))

    def result(self) -> Iterator[pa.RecordBatch]:
        for words, sums in self.totals():
            sums = sums[: 1 + self.sides]
            for lo in range(0, len(words[0]), ROWS):
                codes, many = self._codes([w[lo : lo + ROWS] for w in words]), [x[lo : lo + ROWS] for x in sums]
                ascii_ = codes.max(1) < 128
                for rows in (ascii_, ~ascii_) if self.bits == 8 and not ascii_.all() else (slice(None),):
                    if len(part := codes[rows]):
                        yield pa.RecordBatch.from_arrays([self._text(part), *(pa.array(x[rows], pa.int64()) for x in many)], names=["kmer", "n", "n_side"][: 2 + self.sides])


def _filled(batches, k: int, sides: bool) -> Iterator[_Bucket]:
    """Buckets, one at a time, of runs in order of their buckets."""
    codec, here, at = pa.Codec("zstd", 1), _Bucket(k, sides), None
    for batch in batches:
        for bucket, side, runs, size, counts, chars in zip(*(batch.column(i).to_pylist() for i in range(4)), batch.column(4), batch.column(5)):
            if bucket != at:
                if at is not None:
                    yield here
                    here.clear()
                at = bucket
            many = np.frombuffer(codec.decompress(counts.as_buffer(), 4 * runs), "<u4")
            width = size // (int(many.sum()) + (k - 1) * runs)
            here.add(side, many, np.frombuffer(codec.decompress(chars.as_buffer(), size), f"<u{width}"))
    if at is not None:
        yield here


def _counter(k: int, sides: bool):
    """For ``mapInArrow`` over runs in order of their buckets: a row for each k-mer."""

    def run(batches):
        for bucket in _filled(batches, k, sides):
            yield from bucket.result()

    return run


def _histogram(k: int):
    """For ``mapInArrow`` over runs in order of their buckets: how many of the task's k-mers occur how often."""

    def run(batches):
        freq: Counter[int] = Counter()
        for bucket in _filled(batches, k, False):
            for _, sums in bucket.totals():
                for n, many in zip(*(x.tolist() for x in np.unique(sums[0], return_counts=True))):
                    freq[n] += many
        yield pa.RecordBatch.from_arrays([pa.array(list(freq), pa.int64()), pa.array(list(freq.values()), pa.int64())], names=["value", "freq"])

    return run


def _dealt(texts: DataFrame, text: str, k: int, side: str | None = None) -> DataFrame:
    """Runs of k-mers, each bucket's in one task and together."""
    spark = texts.sparkSession
    rows = texts.select(F.col(text).alias("text"), (F.coalesce(F.col(side), F.lit(False)) if side else F.lit(False)).alias("side")).where(F.length("text") >= k)
    many = rows.agg(F.sum(F.length("text"))).first()[0] or 0
    wide = partitions(spark)
    buckets = max(-(-many // BUCKET), min(wide, -(-many // (BUCKET // 40))), 1)
    cut = rows.mapInArrow(_cutter(k, buckets), _CUT_SCHEMA)
    return cut.repartition(min(buckets, max(wide, buckets // 4)), "bucket").sortWithinPartitions("bucket")


def tally(texts: DataFrame, text: str, k: int, side: str | None = None) -> DataFrame:
    """(kmer, n): how often each k-character substring occurs; with ``side``, a boolean column, also n_side: how often where it is true."""
    return _dealt(texts, text, k, side).mapInArrow(_counter(k, bool(side)), "kmer string, n long" + ", n_side long" * bool(side))


def histogram(texts: DataFrame, text: str, k: int) -> DataFrame:
    """(value, freq): how many different k-character substrings occur ``value`` times. Substrings are counted, but no row is made for each."""
    counted = _dealt(texts, text, k).mapInArrow(_histogram(k), "value long, freq long")
    return counted.groupBy("value").agg(F.sum("freq").alias("freq"))
