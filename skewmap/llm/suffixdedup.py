"""Removal of repeated byte strings with suffix arrays.

A byte goes if it is covered by a string of ``length`` bytes that also starts earlier (smaller key, or
same document and earlier start). Strings are judged on the input.

Only places that can repeat are sorted. Every window of ``length`` bytes has an anchor: the leftmost of its
``GRAM``-byte grams of smallest hash. Equal windows have equal anchors at equal places, so windows need to
be compared only with windows of the same anchor hash, and an anchor hash seen once settles its windows.
Consecutive windows of one anchor form a segment of at most 2 * length - GRAM bytes.

1. Segments as (anchor hash, segment hash, key, place) go to the task of their anchor hash, sorted. Equal
   segments are found in one pass: the first keeps its windows, the others lose them. If an anchor hash
   has one distinct segment, that is all.
2. Other distinct segments are candidates. Shards of bounded size get their bytes, and each shard builds a
   suffix array by Larsson-Sadakane refinement (groups that are still unsorted are refined by the ranks of
   the suffixes 8, 16, 32, ... bytes further on), takes common prefixes by Kasai's rule, and reads off the
   classes of equal windows and their first member.
3. An anchor hash with more candidates than a shard holds is spread over several shards; their sorted runs
   of distinct windows are merged by binary search into one another.
4. First windows come back to their documents by key; what no first window of a candidate or repeated
   segment keeps is removed.

A hot string is reduced at the start: a task sends each distinct segment of a batch once. An anchor hash that a
fixed-share sample of documents shows to have many distinct segments is dealt to tasks by segment as well,
and its segments are candidates without being counted; the sample only chooses the way, either gives the same result.
The pass of step 1 holds a bounded number of rows, however many an anchor has.

Segment and window identity is by hashes: 64 bits of anchor and 64 of segment, together 128 bits, and
128 bits for windows of step 3. Bytes are compared in step 2.

Defined results: null and empty texts have no bytes; texts shorter than ``length`` keep all; a null key
sorts before all others; rows repeating a key are told apart by their text's hash and stand in its order,
and equal rows are copies of one document, of which every row is treated as the first; an empty table
gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

LENGTH, GRAM = 100, 20
#: Bytes that are hashed at a time; a text over it goes in overlapping slices.
SLICE = 1 << 22
#: Candidates of one anchor hash that a shard takes, and bytes of a shard.
CHUNK, SHARD_BYTES = 10_000, 2_500_000
#: One document in ``SAMPLED`` is looked at for hot anchors; up to ``MOST_HOT`` are dealt by segment over ``SALTS`` tasks each.
SAMPLED, MOST_HOT, SALTS = 64, 4096, 32
_TABLE = np.random.default_rng(41).integers(1, 2**63, 256, dtype=np.uint64)


def _gram_hashes(raw: np.ndarray, gram: int) -> np.ndarray:
    """Hash of the ``gram`` bytes from each position, by doubling."""
    h, span, out, used = _TABLE[raw], 1, None, 0
    n = len(raw) - gram + 1
    left = gram
    while left:
        if left & 1:
            out = h[used : used + n].copy() if out is None else common.mix64(out * np.uint64(0x9E3779B97F4A7C15) + h[used : used + n])
            used += span
        left >>= 1
        if left:
            h = common.mix64(h[: len(h) - span] * np.uint64(0xD6E8FEB86659FD93) + h[span:])
            span *= 2
    return out


def anchors(raw: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Segments of a byte array: anchor hash, anchor position, first window, number of windows."""
    n = len(raw) - length + 1
    if n <= 0:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    h = _gram_hashes(raw, gram)
    place = np.uint64(SLICE * 2 - 1)
    key = (h & ~place) | np.arange(len(h), dtype=np.uint64)
    width, span, low = length - gram + 1, 1, key
    while span * 2 <= width:
        low = np.minimum(low[: len(low) - span], low[span:])
        span *= 2
    low = np.minimum(low[:n], low[width - span : width - span + n])
    at = (low & place).astype(np.int64)
    first = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
    count = np.diff(np.append(first, n))
    return h[at[first]], at[first], first, count


def _salts(anchor: np.ndarray, segment: np.ndarray, hot: np.ndarray) -> np.ndarray:
    """Which of a hot anchor's tasks a segment goes to; -1 for other anchors."""
    out = np.full(len(anchor), -1, np.int32)
    if len(hot):
        some = np.flatnonzero(hot[np.minimum(np.searchsorted(hot, anchor), len(hot) - 1)] == anchor)
        out[some] = (segment[some] % np.uint64(SALTS)).astype(np.int32)
    return out


def _segments(length: int, gram: int, hot: np.ndarray):
    """For ``mapInArrow`` over (key, mark, bytes): one row per distinct segment of a batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.only("suffixdedup")
        for batch in batches:
            raw, offs = common.utf8_view(batch.column(2))
            marks = batch.column(1).to_numpy(zero_copy_only=False)
            keys = batch.column(0).to_numpy(zero_copy_only=False)
            blob = memoryview(raw.tobytes())
            cols: list[tuple] = []
            for i in range(len(offs) - 1):
                lo, hi = int(offs[i]), int(offs[i + 1])
                for a in range(lo, max(lo + 1, hi - length + 1), SLICE):
                    b = min(hi, a + SLICE + length - 1)
                    h, at, first, count = anchors(raw[a:b], length, gram)
                    if not len(h):
                        continue
                    ends = (first + count + length - 1).tolist()
                    own = np.fromiter((xxhash.xxh3_64_intdigest(blob[a + x : a + y], seed=z) for x, y, z in zip(first.tolist(), ends, (at - first).tolist())), np.uint64, len(h))
                    cols.append((h, own, np.full(len(h), i), ((first + a - lo) << 8) | count))
            if not cols:
                continue
            h, own, row, at = (np.concatenate(x) for x in zip(*cols))
            order = np.lexsort((at, marks[row], keys[row], own, h))
            h, own, row, at = h[order], own[order], row[order], at[order]
            new = np.concatenate([[True], (h[1:] != h[:-1]) | (own[1:] != own[:-1])])
            h, own, row, at = h[new], own[new], row[new], at[new]
            for lo in range(0, len(h), 500_000):
                s = slice(lo, lo + 500_000)
                yield pa.RecordBatch.from_arrays([pa.array(h[s].view(np.int64)), pa.array(_salts(h[s], own[s], hot)), pa.array(own[s].view(np.int64)), pa.array(keys[row[s]]), pa.array(marks[row[s]]), pa.array(at[s])], ["anchor", "salt", "segment", "key", "mark", "at"])

    return run


def _firsts(chunk: int):
    """For ``mapInArrow`` over segments sorted by anchor, salt, segment, key, mark, place.

    Gives the first of each segment: chunk -1 if it is the only one of its anchor, else the chunk it goes to;
    ``spread`` tells whether its anchor has several chunks. Rows of an anchor are held until it is known to
    have more than a chunk; then they are given out as they come.
    """
    names = ["anchor", "salt", "segment", "key", "mark", "at"]

    def emit(cols: list[np.ndarray], given: int, more: bool) -> pa.RecordBatch:
        """Rows of whole groups; of the first one ``given`` rows are out already, the last of which stands first here."""
        anchor, salt = cols[0], cols[1]
        start = np.concatenate([[True], (anchor[1:] != anchor[:-1]) | (salt[1:] != salt[:-1])])
        begin = np.flatnonzero(start)
        group = np.cumsum(start) - 1
        size = np.diff(np.append(begin, len(anchor)))
        place = np.arange(len(anchor)) - begin[group]
        if given:
            size[0] += given - 1
            place[group == 0] += given - 1
        spread = (size[group] > chunk) | (salt >= 0)
        if more:
            spread[group == group[-1]] = True
        part = np.where((size[group] == 1) & ~spread, -1, place // chunk * (SALTS + 1) + salt + 1)
        keep = np.arange(len(anchor)) >= (given > 0)
        return pa.RecordBatch.from_arrays([pa.array(c[keep]) for c in (anchor, *cols[3:], part.astype(np.int32), spread)], ["anchor", "key", "mark", "at", "chunk", "spread"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] | None = None
        given = 0
        for batch in batches:
            cols = [batch.column(n).to_numpy(zero_copy_only=False) for n in names]
            if held is not None:
                cols = [np.concatenate([a, b]) for a, b in zip(held, cols)]
            if not len(cols[0]):
                continue
            anchor, salt, segment = cols[:3]
            cols = [c[np.concatenate([[True], (anchor[1:] != anchor[:-1]) | (salt[1:] != salt[:-1]) | (segment[1:] != segment[:-1])])] for c in cols]
            anchor, salt = cols[:2]
            other = np.flatnonzero((anchor != anchor[-1]) | (salt != salt[-1]))
            cut = int(other[-1]) + 1 if len(other) else 0
            if cut:
                yield emit([c[:cut] for c in cols], given, False)
                given = 0
            held = [c[cut:] for c in cols]
            count = len(held[0]) + max(0, given - 1)
            if count > chunk or held[1][0] >= 0:
                yield emit(held, given, True)
                given, held = count, [c[-1:] for c in held]
        if held is not None and len(held[0]) > (given > 0):
            yield emit(held, given, False)

    return run


def suffix_array(text: np.ndarray) -> np.ndarray:
    """Suffixes in order.

    Larsson-Sadakane refinement: the first order is by eight bytes; then each group of equal ranks is sorted by
    the rank of the suffix h bytes further on, h doubling, and groups of one are left alone.
    """
    n = len(text)
    if not n:
        return np.zeros(0, np.int64)
    word = np.zeros(n, np.uint64)
    for i in range(8):
        word[: n - i] |= text[i:].astype(np.uint64) << np.uint64(56 - 8 * i)
    order = np.argsort(word)
    s = word[order]
    new = np.concatenate([[True], s[1:] != s[:-1]])
    rank = np.empty(n, np.int64)
    rank[order] = np.maximum.accumulate(np.where(new, np.arange(n), 0))
    h = 8
    while True:
        starts = np.flatnonzero(new)
        size = np.diff(np.append(starts, n))
        open_ = np.repeat(size > 1, size)
        at = np.flatnonzero(open_)
        if not len(at):
            break
        suffix = order[at]
        # A suffix that ends within h bytes comes before all that go on, the shorter first.
        ahead = np.where(suffix < n - h, rank[np.minimum(suffix, max(0, n - 1 - h)) + min(h, n - 1)] + n + 1, n - suffix)
        group = rank[suffix]
        again = np.argsort(group * np.int64(2 * n + 2) + ahead)
        suffix, ahead, group = suffix[again], ahead[again], group[again]
        order[at] = suffix
        split = np.concatenate([[True], (group[1:] != group[:-1]) | (ahead[1:] != ahead[:-1])])
        rank[suffix] = np.maximum.accumulate(np.where(split, at, 0))
        new[at] = split
        h *= 2
    return order


def common_prefixes(text: np.ndarray, order: np.ndarray, most: int, lane: int = 64) -> np.ndarray:
    """Length, up to ``most``, of the prefix that each suffix shares with the one before it in order.

    Kasai's rule: going one byte on in the text, the common prefix shrinks by one at most. Lanes of ``lane``
    consecutive suffixes go on side by side, each starting anew.
    """
    n = len(order)
    before = np.full(n, -1, np.int64)
    before[order[1:]] = order[:-1]
    padded = np.concatenate([text, np.zeros(most + 1, np.uint8)])
    by_place = np.zeros(n, np.int64)
    starts = np.arange(0, n, lane)
    h = np.zeros(len(starts), np.int64)
    for step in range(lane):
        i = starts + step
        live = np.flatnonzero(i < n)
        i, j = i[live], before[i[live]]
        own = np.where(j < 0, 0, np.maximum(h[live] - 1, 0) if step else 0)
        go = np.flatnonzero(j >= 0)
        while len(go):
            a, b = i[go] + own[go], j[go] + own[go]
            same = (a < n) & (b < n) & (own[go] < most) & (padded[np.minimum(a, n)] == padded[np.minimum(b, n)])
            go = go[same]
            own[go] += 1
        h[live] = own
        by_place[i] = own
    return by_place[order]


def first_windows(segments: list[bytes], keys: np.ndarray, marks: np.ndarray, starts: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Windows of a shard that are the first of their class: segment, window in it, class in byte order.

    Windows never reach over a segment's end, so segments stand end to end without marks between them.
    """
    sizes = np.array([len(s) for s in segments], np.int64)
    text = np.frombuffer(b"".join(segments), np.uint8)
    order = suffix_array(text)
    shared = common_prefixes(text, order, length)
    owner = np.repeat(np.arange(len(segments)), sizes)
    place = np.arange(len(text)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    label = np.cumsum(np.concatenate([[True], shared[1:] < length])) - 1
    window = place[order] <= sizes[owner[order]] - length
    at, label = order[window], label[window]
    seg, off = owner[at], place[at]
    if not len(seg):
        return seg, off, label
    # Labels rise along the order, so the least standing of each class comes from one pass.
    by = np.lexsort((marks, keys))
    document = np.empty(len(keys), np.int64)
    document[by] = np.cumsum(np.concatenate([[False], (keys[by][1:] != keys[by][:-1]) | (marks[by][1:] != marks[by][:-1])]))
    standing = (document[seg] << 40) | (starts[seg] + off)
    begins = np.flatnonzero(np.concatenate([[True], label[1:] != label[:-1]]))
    least = np.repeat(np.minimum.reduceat(standing, begins), np.diff(np.append(begins, len(label))))
    first = standing == least
    return seg[first], off[first], label[first]


def merge_runs(runs: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """Merge of sorted runs (digests, standing) two by two; of equal digests the smallest standing stays.

    Each pair of runs is merged by looking up one run's digests in the other by binary search.
    """
    runs = [r for r in runs if len(r[0])]
    while len(runs) > 1:
        merged = []
        for i in range(0, len(runs) - 1, 2):
            (da, sa), (db, sb) = runs[i], runs[i + 1]
            at = np.minimum(np.searchsorted(da, db), len(da) - 1)
            both = da[at] == db
            sa = sa.copy()
            np.minimum.at(sa, at[both], sb[both])
            into = np.searchsorted(da, db[~both])
            merged.append((np.insert(da, into, db[~both]), np.insert(sa, into, sb[~both])))
        runs = merged + runs[len(runs) - len(runs) % 2 :]
    return runs[0] if runs else (np.zeros(0, "S16"), np.zeros(0, np.int64))


def _intervals(seg: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Runs of consecutive windows: segment, first window, number."""
    order = np.lexsort((off, seg))
    seg, off = seg[order], off[order]
    if not len(seg):
        return seg, off, off
    new = np.flatnonzero(np.concatenate([[True], (seg[1:] != seg[:-1]) | (off[1:] != off[:-1] + 1)]))
    return seg[new], off[new], np.diff(np.append(new, len(seg)))


KEPT = "key long, mark long, at long"


def _shards(length: int):
    """For ``applyInArrow`` on a shard's candidates (anchor, spread, key, mark, at, bytes): kept windows, and runs of spread anchors."""

    def run(table: pa.Table) -> pa.Table:
        segments = [x.as_py() for x in table.column("bytes")]
        get = lambda c: table.column(c).to_numpy()
        keys, marks, at, spread = get("key"), get("mark"), get("at"), get("spread")
        starts = at >> 8
        seg, off, _ = first_windows(segments, keys, marks, starts, length)
        hot = spread[seg]
        s, o, n = _intervals(seg[~hot], off[~hot])
        kept = pa.table({"key": keys[s], "mark": marks[s], "at": ((starts[s] + o) << 8) | n, "digest": pa.nulls(len(s), pa.binary())})
        s, o = seg[hot], off[hot]
        digests = [xxhash.xxh3_128_digest(segments[a][b : b + length]) for a, b in zip(s.tolist(), o.tolist())]
        runs = pa.table({"key": keys[s], "mark": marks[s], "at": ((starts[s] + o) << 8) | 1, "digest": pa.array(digests, pa.binary())})
        return pa.concat_tables([kept, runs])

    return run


def _merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Spread windows of a range of digests: sorted runs, merged by binary search; the first window of each digest stays."""
    runs, rows, n = [], [], 0
    for batch in batches:
        d = np.frombuffer(b"".join(batch.column(0).to_pylist()), ">u8").reshape(-1, 2) if batch.num_rows else np.zeros((0, 2), ">u8")
        key = np.rec.fromarrays([d[:, 0].astype(np.uint64), d[:, 1].astype(np.uint64)], names="a,b")
        cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in (1, 2, 3)]
        rows.append(cols)
        order = np.lexsort((cols[2], cols[1], cols[0], key.b, key.a))
        runs.append((key[order], n + order))
        n += len(d)
    if not n:
        return
    cols = [np.concatenate(x) for x in zip(*rows)]
    rank = np.empty(n, np.int64)
    by = np.lexsort((cols[2], cols[1], cols[0]))
    rank[by] = np.arange(n)
    firsts = []
    for key, at in runs:  # one entry per digest in each run
        new = np.concatenate([[True], (key.a[1:] != key.a[:-1]) | (key.b[1:] != key.b[:-1])])
        firsts.append((np.stack([key.a, key.b], 1)[new].astype(">u8").copy().view("S16").ravel(), rank[at][new]))
    _, standing = merge_runs(firsts)
    at = by[standing]
    yield pa.RecordBatch.from_arrays([pa.array(c[at]) for c in cols], ["key", "mark", "at"])


def _compress(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    pack = zstandard.ZstdCompressor(level=1)
    for batch in batches:
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([pack.compress(t) for t in common.byte_rows(batch.column(2))], pa.binary())], ["key", "mark", "z"])


def _cut_out(length: int):
    """For ``mapInArrow`` over documents with their candidates: the candidates' bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor()
        for batch in batches:
            keys, marks = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            out: list[tuple] = []
            for i, (z, found) in enumerate(zip(batch.column(2), batch.column(3))):
                text = unpack.decompress(z.as_py())
                for c in found.as_py():
                    lo, n = c["at"] >> 8, c["at"] & 255
                    out.append((c["anchor"], c["chunk"], c["spread"], keys[i], marks[i], c["at"], text[lo : lo + n + length - 1]))
            cols = list(zip(*out)) if out else [()] * 7
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.binary()))], ["anchor", "chunk", "spread", "key", "mark", "at", "bytes"])

    return run


def _finish(length: int, text_wanted: bool):
    """For ``mapInArrow`` over (key, mark, z, kept windows): what stays of each document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor()
        for batch in batches:
            out = []
            for z, kept in zip(batch.column(2), batch.column(3)):
                text = unpack.decompress(z.as_py())
                raw = np.frombuffer(text, np.uint8)
                n = len(raw)
                gone = np.zeros(n, bool)
                if n >= length:
                    edge = np.zeros(n - length + 2, np.int32)
                    at = kept.values.to_numpy() if kept.as_py() else np.zeros(0, np.int64)
                    np.add.at(edge, at >> 8, 1)
                    np.add.at(edge, (at >> 8) + (at & 255), -1)
                    lost = np.flatnonzero(np.cumsum(edge)[:-1] <= 0)
                    cover = np.zeros(n + 1, np.int32)
                    np.add.at(cover, lost, 1)
                    np.add.at(cover, lost + length, -1)
                    gone = np.cumsum(cover)[:-1] > 0
                stay = raw[~gone].tobytes()
                spans = int(np.count_nonzero(gone[1:] & ~gone[:-1])) + int(n > 0 and gone[0])
                out.append((n, int(gone.sum()), spans, hashlib.sha256(stay).hexdigest(), stay if text_wanted else None))
            cols = list(zip(*out)) if out else [()] * 5
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())))], ["key", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    return run


@common.cleaned
def remove_repeats(docs: DataFrame, key: str = "doc_id", text: str = "text", length: int = LENGTH, gram: int = GRAM, chunk: int = CHUNK, shard_bytes: int = SHARD_BYTES, with_text: bool = False) -> DataFrame:
    """One row per document: key, n_bytes, n_removed, n_spans, kept_sha256 (and ``kept``, the bytes that stay)."""
    spark = docs.sparkSession
    n = common.partitions(spark)
    rows = docs.select(F.coalesce(F.col(key).cast("long"), F.lit(-(2**63) + 1)).alias("key"), F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("mark"), F.col(text).cast("string").alias("t"))
    schema = "anchor long, salt int, segment long, key long, mark long, at long"
    sample = rows.where(F.pmod(F.xxhash64("key", "mark"), F.lit(SAMPLED)) == 0).mapInArrow(_segments(length, gram, np.zeros(0, np.uint64)), schema)
    seen = sample.groupBy("anchor").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") * SAMPLED >= chunk).orderBy(F.desc("n"), "anchor").limit(MOST_HOT)
    hot = np.sort(np.array([r["anchor"] for r in seen.collect()], np.int64).view(np.uint64))
    segments = rows.mapInArrow(_segments(length, gram, hot), schema).repartition(n, "anchor", "salt").sortWithinPartitions("anchor", "salt", "segment", "key", "mark", "at")
    firsts = common.materialise(segments.mapInArrow(_firsts(chunk), "anchor long, key long, mark long, at long, chunk int, spread boolean"), "firsts", compression="zstd")
    packed = rows.mapInArrow(_compress, "key long, mark long, z binary")
    candidates = firsts.where("chunk >= 0")
    total = candidates.agg(F.sum(F.col("at").bitwiseAND(255) + (length - 1))).first()[0] or 0
    shards = max(1, -(-total // shard_bytes))
    wanted = candidates.groupBy("key", "mark").agg(F.collect_list(F.struct("anchor", "chunk", "spread", "at")).alias("found"))
    cut = packed.join(wanted, ["key", "mark"]).mapInArrow(_cut_out(length), "anchor long, chunk int, spread boolean, key long, mark long, at long, bytes binary")
    cut = cut.withColumn("shard", F.pmod(F.xxhash64("anchor", F.when(F.col("spread"), F.col("chunk"))), F.lit(shards)))
    sorted_ = common.materialise(cut.groupBy("shard").applyInArrow(_shards(length), KEPT + ", digest binary"), "windows", compression="zstd")
    kept = sorted_.where(F.col("digest").isNull()).select("key", "mark", "at")
    spread = sorted_.where(F.col("digest").isNotNull())
    if spread.limit(1).count():
        merged = spread.select("digest", "key", "mark", "at").repartition(max(n, int(shards)), "digest").mapInArrow(_merge, KEPT)
        kept = kept.unionByName(merged)
    kept = kept.unionByName(firsts.where("chunk < 0").select("key", "mark", "at"))
    kept = kept.groupBy("key", "mark").agg(F.collect_list("at").alias("kept"))
    full = packed.join(kept, ["key", "mark"], "left").select("key", "mark", "z", F.coalesce("kept", F.array().cast("array<long>")).alias("kept"))
    out = full.mapInArrow(_finish(length, with_text), "key long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")
    out = out.withColumn("key", F.when(F.col("key") != -(2**63) + 1, F.col("key"))).withColumnRenamed("key", key)
    return out if with_text else out.drop("kept")


def op1_suffix_array_dedup(spark, sf_dir: str) -> DataFrame:
    return remove_repeats(common.documents(spark, sf_dir))
