"""Near-duplicate documents by an exact Jaccard join over five-word shingles that uses relations between sets.

Sets are fingerprinted first, and equal sets stand for one class. One document of a class puts the
first quarter of its shingles, in one global order, on index lists; two sets of similarity 0.75 or more
must meet on a list. The order is by hash, with shingles that a fixed-share sample shows to be common at the
end, so common passages rarely meet there; any order gives the same result, this one less work.

Skipping works at two levels. Index lists are cut into blocks by size and position, and whole blocks, then single
pairs, are skipped where size and position bound the overlap below what similarity needs. Answers are derived from
highly similar sets: every member of a list is first compared with the list's hub only, verified members join
the hub's component and have its answers, and afterwards only pairs in different components are still asked for.
Before texts are fetched, the number of common list entries bounds the overlap of a pair once more. All bounds are
lossless: no link between different components is missed, and no limit is set on lists or partners.

A list with over a thousandth of all entries is hot; there are less than a thousand. Their hubs, a few for each,
are sent to every task, so no task gets a hot list. Where a hot list is asked again, it is dealt in tiles of bounded
blocks, and no tile is made of two blocks of one component.

Shingles are 64-bit hashes. Defined results: fewer than five words make one shingle of them all; null,
empty and blank texts have no shingle and no link; equal texts are one class; rows are told apart by their
place, so rows that repeat an identifier are sets of their own; a null identifier sorts after all others and is
reported only where a component has no other; an empty table gives no rows; extra columns are ignored by
``components`` and kept by ``near_dedup``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

WORDS = 5
#: Similarity as a fraction of integers: 100 * intersection >= 75 * union.
SHARE = (75, 100)
#: Shingles that the sample can put at the end of the order, and in how many sampled documents they stand at least.
COMMON, SEEN = 500_000, 4
SAMPLED = 64
#: Bytes of texts that are cut into shingles at once.
PART = 1_500_000
#: Longer words are hashed one by one.
LONG = 64
#: A list of over one in ``HOT`` entries is hot; a tile of a hot list has two blocks of about ``TILE`` entries.
HOT, TILE = 1000, 20_000
#: Pairs left open are asked in so many rounds, the rest at once; up to ``MANY`` pairs are not worth a round.
ROUNDS, MANY = 4, 10_000
#: Lists up to this length give their pairs side by side, longer ones block by block.
SHORT = 64
_MULT = np.random.default_rng(20_231).integers(1, 2**63, WORDS, dtype=np.uint64) << np.uint64(1) | np.uint64(1)
_LENGTH = np.uint64(0x9E3779B97F4A7C15)
_SPACES = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])
#: The first bytes of eight, by how many.
_FEWER = np.array([(1 << 8 * i) - 1 for i in range(9)], np.uint64)


def _word_hashes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the lower-cased words of a column's texts, end to end, and how many each text has."""
    raw, offs = common.utf8_view(column)
    blob = raw.tobytes().lower() + bytes(LONG)
    raw = np.frombuffer(blob, np.uint8)[: len(raw)]
    if not len(raw):
        return np.zeros(0, np.uint64), np.zeros(len(offs) - 1, np.int64)
    space = _SPACES[raw]
    edge = np.zeros(len(raw) + 1, bool)
    edge[1:-1] = space[:-1]
    edge[offs] = True  # words do not go on from text to text
    first = np.flatnonzero(edge[:-1] & ~space)
    edge[1:-1] = space[1:]
    edge[offs] = True
    size = np.flatnonzero(edge[1:] & ~space) + 1 - first
    eights = np.ndarray(len(blob) - 7, "<u8", blob, strides=(1,))
    h = common.mix64((eights[first] & _FEWER[np.minimum(size, 8)]) + size.astype(np.uint64) * _MULT[0])
    some = np.flatnonzero((size > 8) & (size <= LONG))
    for at in range(8, LONG, 8):
        some = some[size[some] > at]
        if not len(some):
            break
        h[some] = common.mix64(h[some] * _MULT[1] + (eights[first[some] + at] & _FEWER[np.minimum(size[some] - at, 8)]))
    for i in np.flatnonzero(size > LONG).tolist():
        h[i] = xxhash.xxh3_64_intdigest(blob[first[i] : first[i] + size[i]])
    return h, np.diff(np.searchsorted(first, offs))


def shingled(column: pa.Array, words: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of a column's texts, in ascending order within each, end to end, and offsets of the texts."""
    h, many = _word_hashes(column)
    span = np.minimum(many, words)
    h = np.concatenate([h, np.zeros(words, np.uint64)])
    first = np.cumsum(many) - many
    size = np.where(many > 0, many - span + 1, 0)
    ends = np.concatenate([[0], np.cumsum(size)])
    at = np.repeat(first - ends[:-1], size) + np.arange(ends[-1])
    summed = h[: len(h) - words] * _MULT[0]
    for i in range(1, words):
        summed += h[i : len(h) - words + i] * _MULT[i]
    mixed = summed[at] if len(at) else np.zeros(0, np.uint64)
    for j in np.flatnonzero((many > 0) & (many < words)).tolist():  # one shingle of all words there are
        a, n = int(first[j]), int(many[j])
        mixed[ends[j]] = (h[a : a + n] * _MULT[:n]).sum(dtype=np.uint64)
    mixed = common.mix64(mixed + np.repeat(span.astype(np.uint64), size) * _LENGTH)
    for a, b in zip(ends[:-1].tolist(), ends[1:].tolist()):
        mixed[a:b].sort()
    fresh = np.ones(len(mixed), bool)
    fresh[1:] = mixed[1:] != mixed[:-1]
    fresh[ends[:-1][size > 0]] = True
    return mixed[fresh], np.concatenate([[0], np.cumsum(fresh)])[ends]


def shingles(text: bytes, words: int = WORDS) -> np.ndarray:
    """Distinct shingle hashes of a text in ascending order."""
    return shingled(pa.array([text], pa.binary()), words)[0]


def needed(a: np.ndarray | int, b: np.ndarray | int):
    """Least overlap of sets of sizes a and b at the similarity: inter * 100 >= 75 * (a + b - inter)."""
    num, den = SHARE
    return -(-(num * (a + b)) // (num + den))


def prefix_length(n: np.ndarray | int):
    num, den = SHARE
    return (n - -(-(n * num) // den) + 1) * (n > 0)


def _common_shingles(docs: DataFrame) -> np.ndarray:
    """Common shingles, the most common last. Their number is bounded by ``COMMON``; the order they give is not a filter."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [shingled(part)[0] for _, part in common.in_parts(batch.column(0), PART)]
            if found and (total := np.concatenate(found)).size:
                values, n = np.unique(total, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(values.view(np.int64)), pa.array(n)], ["token", "n"])

    sample = docs.where(F.pmod(F.xxhash64(F.col("id").cast("string"), F.lit(3)), F.lit(SAMPLED)) == 0).select("text")
    counts = sample.mapInArrow(count, "token long, n long").groupBy("token").agg(F.sum("n").alias("n")).where(F.col("n") >= SEEN)
    top = counts.orderBy(F.desc("n"), "token").limit(COMMON).toPandas()
    return top["token"].to_numpy(np.int64).view(np.uint64)[::-1].copy()


class Order:
    """Global order of shingles: hashes without their last bit, then the common ones by how common they are."""

    def __init__(self, common_: np.ndarray) -> None:
        by = np.argsort(common_, kind="stable")
        self.values, self.place = common_[by], by.astype(np.uint64)
        self.maybe = np.zeros(1 << 22, bool)
        self.maybe[(common_ >> np.uint64(42)).astype(np.int64)] = True

    def keys(self, tokens: np.ndarray) -> np.ndarray:
        out = tokens >> np.uint64(1)
        some = np.flatnonzero(self.maybe[(tokens >> np.uint64(42)).astype(np.int64)])
        if len(some) and len(self.values):
            at = np.minimum(np.searchsorted(self.values, tokens[some]), len(self.values) - 1)
            hit = self.values[at] == tokens[some]
            out[some[hit]] = (np.uint64(1) << np.uint64(63)) | self.place[at[hit]]
        return out


def _sets(order):
    """For ``mapInArrow`` from (id, tag, text): each document's set as (id, tag, mark, n, tokens), tokens being its index entries in order."""

    def entries(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.only("setjoin")
        ranks: Order = order.value
        seen: set[bytes] = set()
        for batch in batches:
            for row, part in common.in_parts(batch.column(2), PART):
                flat, offs = shingled(part)
                sizes = np.diff(offs)
                prints = [xxhash.xxh3_128_digest(flat[a:b]) if b > a else b"" for a, b in zip(offs[:-1].tolist(), offs[1:].tolist())]
                listed = np.zeros(len(prints), bool)
                for i, mark in enumerate(prints):
                    if mark and mark not in seen:  # equal sets of a task stand on the lists once
                        seen.add(mark)
                        listed[i] = True
                keys = ranks.keys(flat)
                for a, b in zip(offs[:-1][listed].tolist(), offs[1:][listed].tolist()):
                    keys[a:b].sort()
                taken = np.where(listed, prefix_length(sizes), 0)
                edges = np.concatenate([[0], np.cumsum(taken)])
                at = np.repeat(offs[:-1] - edges[:-1], taken) + np.arange(edges[-1])
                tokens = pa.ListArray.from_arrays(pa.array(edges.astype(np.int32)), pa.array(keys[at].view(np.int64)))
                ids, tags = batch.column(0).slice(row, len(part)), batch.column(1).slice(row, len(part))
                yield pa.RecordBatch.from_arrays([ids, tags, pa.array(prints, pa.binary()), pa.array(sizes, pa.int64()), tokens], ["id", "tag", "mark", "n", "tokens"])

    return entries


def _runs(batches: Iterator[pa.RecordBatch], names: list[str]) -> Iterator[tuple[list[np.ndarray], np.ndarray]]:
    """Whole runs of equal tokens of a stream sorted by token, many at a time, and where each run starts.

    Runs of one row are left out. A run is held until it is complete.
    """
    held: list[np.ndarray] | None = None

    def whole(cols: list[np.ndarray]):
        token = cols[0]
        start = np.concatenate([[True], token[1:] != token[:-1]])
        keep = ~(start & np.append(start[1:], True))
        if keep.any():
            yield [c[keep] for c in cols], np.flatnonzero(start[keep])

    for batch in batches:
        cols = [batch.column(n).to_numpy(zero_copy_only=False) for n in names]
        if held is not None:
            cols = [np.concatenate([a, b]) for a, b in zip(held, cols)]
        if not len(cols[0]):
            continue
        cut = int(np.searchsorted(cols[0], cols[0][-1]))  # the last run may go on
        if cut:
            yield from whole([c[:cut] for c in cols])
        held = [c[cut:] for c in cols]
    if held is not None and len(held[0]):
        yield from whole(held)


def _possible(size_a, pos_a, size_b, pos_b) -> np.ndarray:
    """Whether size and position allow the overlap: what both have before the entry, the entry, and what both have after it."""
    return np.minimum(pos_a, pos_b) + np.minimum(size_a - pos_a, size_b - pos_b) >= needed(size_a, size_b)


PAIR = "a long, b long, na long, nb long"


def _pair_batch(a, b, na, nb) -> pa.RecordBatch:
    swap = a > b
    return pa.RecordBatch.from_arrays([pa.array(np.where(swap, b, a)), pa.array(np.where(swap, a, b)), pa.array(np.where(swap, nb, na)), pa.array(np.where(swap, na, nb))], ["a", "b", "na", "nb"])


#: Two ways to cut sizes into classes, so that near sizes share one.
_SHIFTS, _BASE = (0.0, 0.5), 1.3


def _hub_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each entry with the hub, the entry of least rank, of its list and size class: one pair for an entry."""
    for (token, ids, at, rank), _ in _runs(batches, ["token", "id", "at", "rank"]):
        size, pos = at >> 24, at & 0xFFFFFF
        for shift in _SHIFTS:
            band = np.floor(np.log(size) / np.log(_BASE) + shift).astype(np.int64)
            order = np.lexsort((ids, rank, band, token))
            t, b = token[order], band[order]
            first = np.concatenate([[True], (t[1:] != t[:-1]) | (b[1:] != b[:-1])])
            hub = order[np.flatnonzero(first)[np.cumsum(first) - 1]]
            ok = (ids[hub] != ids[order]) & _possible(size[hub], pos[hub], size[order], pos[order])
            if ok.any():
                yield _pair_batch(ids[hub][ok], ids[order][ok], size[hub][ok], size[order][ok])


def _hot_hub_pairs(lists: DataFrame) -> DataFrame:
    """The same for hot lists, whose hubs, at most some dozens for each of less than ``HOT`` lists, go to every task."""
    size, pos = F.shiftright("at", 24), F.col("at").bitwiseAND(0xFFFFFF)
    num, den = SHARE
    out = None
    for shift in _SHIFTS:
        banded = lists.withColumn("band", F.floor(F.log(size) / float(np.log(_BASE)) + shift))
        hubs = banded.groupBy("token", "band").agg(F.min(F.struct("rank", "id", "at")).alias("hub"))
        other, place = F.shiftright("hub.at", 24), F.col("hub.at").bitwiseAND(0xFFFFFF)
        met = banded.join(F.broadcast(hubs), ["token", "band"]).where(F.col("id") != F.col("hub.id"))
        met = met.where((F.least(pos, place) + F.least(size - pos, other - place)) * (num + den) >= (size + other) * num)
        less = F.col("hub.id") < F.col("id")
        pairs = met.select(F.least("hub.id", "id").alias("a"), F.greatest("hub.id", "id").alias("b"), F.when(less, other).otherwise(size).alias("na"), F.when(less, size).otherwise(other).alias("nb"))
        out = pairs if out is None else out.unionByName(pairs)
    return out


def _tiles(lists: DataFrame) -> DataFrame:
    """Hot lists (token, id, at, component) as entries of tiles: token is the tile's number, half the side of it (2 if it has one).

    Blocks have about ``TILE`` entries, of one component if that has as many on the list. Entries go to as many
    tiles as their block has partners; blocks of one component are none to each other.
    """
    sizes = lists.groupBy("token", "component").agg(F.count(F.lit(1)).alias("n")).withColumn("group", F.when(F.col("n") >= TILE, F.col("component")))
    large = common.materialise(sizes.where("group is not null").select("token", "component", "group"), "large")
    groups = common.materialise(sizes.groupBy("token", "group").agg(F.sum("n").alias("n")).withColumn("parts", F.ceil(F.col("n") / TILE)), "groups")
    blocks = groups.select("token", "group", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).alias("part"), F.xxhash64("token", "group").alias("g"))
    a, b = blocks.select("token", F.struct("g", "part").alias("x"), "group"), blocks.select("token", F.struct("g", "part").alias("y"), F.col("group").alias("other"))
    tiles = a.join(b, "token").where((F.col("x") <= F.col("y")) & (F.col("group").isNull() | F.col("other").isNull() | (F.col("group") != F.col("other"))))
    pair = F.array(F.struct(F.col("x").alias("block"), F.lit(0).alias("half")), F.struct(F.col("y").alias("block"), F.lit(1).alias("half")))
    tiles = tiles.select("token", F.xxhash64("token", "x", "y").alias("tile"), F.when(F.col("x") == F.col("y"), F.array(F.struct(F.col("x").alias("block"), F.lit(2).alias("half")))).otherwise(pair).alias("sides"))
    sides = common.materialise(tiles.select("token", "tile", F.explode("sides").alias("s")).select("token", "tile", "s.block", "s.half"), "sides")
    named = lists.join(common.small(large), ["token", "component"], "left")
    counted = named.join(common.small(groups.select(F.col("token").alias("__t"), F.col("group").alias("__g"), "parts")), (F.col("token") == F.col("__t")) & F.col("group").eqNullSafe(F.col("__g")))
    own = counted.withColumn("block", F.struct(F.xxhash64("token", "group").alias("g"), F.pmod(F.xxhash64("id"), F.col("parts")).alias("part")))
    return own.join(common.small(sides), ["token", "block"]).select(F.col("tile").alias("token"), "id", "at", "component", "half")


def _short_pairs(cols: list[np.ndarray], starts: np.ndarray, ends: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:
    """The pairs of short lists that ``_cross_pairs`` asks for, of all lists side by side: entries one apart, two apart and so on."""
    num, den = SHARE
    many = ends - starts
    if not len(many):
        return
    where = np.repeat(starts - (np.cumsum(many) - many), many) + np.arange(many.sum())
    run = np.repeat(np.arange(len(many)), many)
    ids, at, comp, half = (c[where] for c in cols[1:])
    order = np.lexsort((ids, at, run))  # by size, then position, as the lists do
    ids, at, comp, half = ids[order], at[order], comp[order], half[order]
    size, pos = at >> 24, at & 0xFFFFFF
    last = np.repeat(np.cumsum(many), many)  # where an entry's list ends
    x = np.arange(len(ids))
    for apart in range(1, int(many.max())):
        x = x[x + apart < last[x]]
        y = x + apart
        ok = (comp[x] != comp[y]) & (size[y] * num <= size[x] * den) & ((half[x] == 2) | (half[x] != half[y])) & _possible(size[x], pos[x], size[y], pos[y])
        if ok.any():
            a, b = x[ok], y[ok]
            yield ids[a], ids[b], size[a], size[b]


def _cross_pairs(batches: Iterator[pa.RecordBatch], block: int = 2048) -> Iterator[pa.RecordBatch]:
    """Pairs of a list that are in different components, block by block; blocks that size and position rule out are skipped.

    Position rules a pair out for good, so every common entry of a pair that is possible is counted.
    """
    out: list[tuple] = []
    held = 0
    num, den = SHARE
    for cols, starts in _runs(batches, ["token", "id", "at", "component", "half"]):
        ends = np.append(starts[1:], len(cols[0]))
        mixed = np.minimum.reduceat(cols[3], starts) != np.maximum.reduceat(cols[3], starts)
        short = mixed & (ends - starts <= SHORT)
        for found in _short_pairs(cols, starts[short], ends[short]):
            out.append(found)
            held += len(found[0])
            if held > 200_000:
                yield _pair_batch(*(np.concatenate(z) for z in zip(*out)))
                out, held = [], 0
        mixed &= ~short
        for lo, hi in zip(starts[mixed].tolist(), ends[mixed].tolist()):
            ids, at, comp, half = (c[lo:hi] for c in cols[1:])
            order = np.lexsort((ids, at))  # by size, then position
            ids, at, comp, half = ids[order], at[order], comp[order], half[order]
            size, pos = at >> 24, at & 0xFFFFFF
            edges = [slice(i, min(i + block, len(ids))) for i in range(0, len(ids), block)]
            before = [int(pos[e].max()) for e in edges]
            after = [int((size[e] - pos[e]).max()) for e in edges]
            for i, a in enumerate(edges):
                most = size[a][-1] * den // num  # beyond it no set of this block has a partner
                for j in range(i, len(edges)):
                    b = edges[j]
                    if size[b][0] > most:
                        break
                    if min(before[i], before[j]) + min(after[i], after[j]) < needed(int(size[a][0]), int(size[b][0])):
                        continue
                    # Sizes rise along the list, so the first of a pair is the smaller.
                    ok = (comp[a][:, None] != comp[b][None, :]) & (size[b][None, :] * num <= size[a][:, None] * den)
                    if half[0] != 2:
                        ok &= half[a][:, None] != half[b][None, :]
                    if i == j:
                        ok = np.triu(ok, 1)
                    x, y = np.nonzero(ok)
                    fits = _possible(size[a][x], pos[a][x], size[b][y], pos[b][y])
                    x, y = x[fits], y[fits]
                    if len(x):
                        out.append((ids[a][x], ids[b][y], size[a][x], size[b][y]))
                        held += len(x)
                    if held > 200_000:
                        yield _pair_batch(*(np.concatenate(z) for z in zip(*out)))
                        out, held = [], 0
    if out:
        yield _pair_batch(*(np.concatenate(z) for z in zip(*out)))


def _overlap(a: np.ndarray, b: np.ndarray) -> int:
    """How many values two sets have in common."""
    both = np.concatenate([a, b])
    both.sort()
    return int(np.count_nonzero(both[1:] == both[:-1]))


def _verify(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """Links (a, b) among the pairs, by the sets themselves. A pair carries one text; its hub's is read once a group."""

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last_id, last = None, np.zeros(0, np.uint64)
        for batch in batches:
            for row, part in common.in_parts(batch.column(3), PART):
                a, b = batch.column(0).slice(row, len(part)).to_numpy(), batch.column(1).slice(row, len(part)).to_numpy()
                other, offs = shingled(part)
                fresh = np.concatenate([[True], a[1:] != a[:-1]])
                fresh[0] = a[0] != last_id
                starts = np.flatnonzero(fresh)
                own, ends = shingled(batch.column(2).slice(row, len(part)).take(pa.array(starts)))
                group = np.cumsum(fresh)  # 0: the set that the rows before had
                inter, size = np.empty(len(a), np.int64), np.empty(len(a), np.int64)
                for i, (g, lo, hi) in enumerate(zip(group.tolist(), offs[:-1].tolist(), offs[1:].tolist())):
                    if fresh[i]:
                        last = own[ends[g - 1] : ends[g]]
                    inter[i], size[i] = _overlap(last, other[lo:hi]), len(last) + hi - lo
                last_id, last = a[-1], last.copy()
                hit = inter * SHARE[1] >= SHARE[0] * (size - inter)
                yield pa.RecordBatch.from_arrays([pa.array(a[hit]), pa.array(b[hit])], ["a", "b"])

    left = texts.select(F.col("id").alias("a"), F.col("text").alias("ta"))
    right = texts.select(F.col("id").alias("b"), F.col("text").alias("tb"))
    full = pairs.select("a", "b").join(right, "b").join(left, "a").sortWithinPartitions("a").select("a", "b", "ta", "tb")
    return full.mapInArrow(check, "a long, b long")


def connected(edges: DataFrame) -> DataFrame:
    """(id, component): the smallest id that each end of an edge (a, b) reaches, by least labels and pointer jumping.

    Each round takes the least label among the neighbours and then the label of that label, so the number of
    rounds grows with the logarithm of a chain's length; labels are written out after each round.
    """
    both = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct()
    both = common.materialise(both, "edges")
    labels = common.materialise(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("id"), F.least("a", "m").alias("component")), "labels")
    while True:
        near = both.join(labels.select(F.col("id").alias("b"), "component"), "b").groupBy("a").agg(F.min("component").alias("m"))
        step = labels.join(near.withColumnRenamed("a", "id"), "id").select("id", F.col("component").alias("was"), F.least("component", "m").alias("c"))
        step = common.materialise(step, "labels")
        jump = step.select(F.col("id").alias("c"), F.col("c").alias("cc"))
        new = common.materialise(step.join(jump, "c", "left").select("id", "was", F.least("c", F.coalesce("cc", "c")).alias("component")), "labels")
        labels = new.select("id", "component")
        if not new.where(F.col("component") != F.col("was")).limit(1).count():
            return labels


@common.cleaned
def _components(docs: DataFrame, key: str, text: str) -> DataFrame:
    """One row per document: id, tag (hash of the text), node (the row's number), n_shingles, component (a node of it), component_id."""
    spark = docs.sparkSession
    n = common.partitions(spark)
    rows = docs.select(F.col(key).cast("long").alias("id"), F.xxhash64(F.col(text).cast("string")).alias("tag"), F.col(text).cast("string").alias("text"))
    order = common.shared(spark, Order(_common_shingles(rows)))
    made = rows.mapInArrow(_sets(order), "id long, tag long, mark binary, n long, tokens array<long>")
    made = common.materialise(made.withColumn("node", F.monotonically_increasing_id()), "sets")
    sets = common.materialise(made.select("node", "id", "tag", "mark", F.col("n").alias("n_shingles")), "marks")
    real = F.octet_length("mark") > 0
    classes = common.materialise(sets.where(real).groupBy("mark").agg(F.min("node").alias("rep"), F.min("id").alias("least"), F.count(F.lit(1)).alias("copies")), "classes")
    # An entry's rank is the smallest identifier of its class: what a copy was made from mostly has a smaller one.
    entries = made.select("node", "n", F.coalesce("id", F.lit(2**63 - 1)).alias("rank"), F.posexplode("tokens").alias("p", "token"))
    lists = entries.select("token", F.col("node").alias("id"), F.shiftleft("n", 24).bitwiseOR(F.col("p").cast("long")).alias("at"), "rank")

    def several(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for cols, _ in _runs(batches, ["token", "id", "at", "rank"]):
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], ["token", "id", "at", "rank"])

    lists = common.materialise(lists.repartition(n, "token").sortWithinPartitions("token").mapInArrow(several, "token long, id long, at long, rank long"), "shared")
    common.discard(made)
    # Lists hold one document of a class for each input task; from here on the class's first.
    rep = sets.where(real).join(classes.where(F.col("copies") > 1), "mark").where(F.col("node") != F.col("rep")).select(F.col("node").alias("id"), "rep", F.coalesce("least", F.lit(2**63 - 1)).alias("least"))
    lists = lists.join(rep, "id", "left").select("token", F.coalesce("rep", "id").alias("id"), "at", F.coalesce("least", "rank").alias("rank")).groupBy("token", "id").agg(F.min("at").alias("at"), F.min("rank").alias("rank"))
    lists = common.materialise(lists, "lists")
    total = lists.count()
    hot = common.materialise(lists.groupBy("token").count().where(F.col("count") * HOT > total).select("token"), "hot")
    some_hot = hot.limit(1).count() > 0
    cold = lists.join(F.broadcast(hot), "token", "left_anti") if some_hot else lists
    warm = lists.join(F.broadcast(hot), "token") if some_hot else None

    def prefix(size: str):
        return F.col(size) - F.ceil(F.col(size) * SHARE[0] / SHARE[1]) + 1

    bound = F.ceil((F.col("na") + F.col("nb")) * SHARE[0] / (SHARE[0] + SHARE[1])) - F.greatest(F.col("na") - prefix("na"), F.col("nb") - prefix("nb"))
    involved = lists.select(F.col("id").alias("node")).distinct().join(sets.select("node", F.col("id").alias("__id"), F.col("tag").alias("__tag")), "node")
    texts = rows.join(involved, F.col("id").eqNullSafe(F.col("__id")) & (F.col("tag") == F.col("__tag"))).select(F.col("node").alias("id"), "text")
    if sets.groupBy("id", "tag").count().where("count > 1").limit(1).count():  # rows equal in identifier and text
        texts = texts.dropDuplicates(["id"])
    texts = common.materialise(texts, "texts", compression="zstd")
    # The hubs: a pair needs only enough common entries to be worth a look, as what is passed over here is asked again below.
    hubs = cold.repartition(n, "token").sortWithinPartitions("token").mapInArrow(_hub_pairs, PAIR)
    hubs = hubs.unionByName(_hot_hub_pairs(warm)) if some_hot else hubs
    hubs = common.materialise(hubs.groupBy("a", "b").agg(F.count(F.lit(1)).alias("c"), F.first("na").alias("na"), F.first("nb").alias("nb")).where(F.col("c") / 2 >= F.least(bound, F.lit(4))).select("a", "b"), "hubs")
    links = common.materialise(_verify(hubs, texts), "links")
    labels = connected(links)
    # All other pairs: different components, and as many common entries as the similarity needs.
    tag = lambda x: x.join(labels, "id", "left").select("token", "id", "at", F.coalesce("component", "id").alias("component"))
    tagged = tag(cold).withColumn("half", F.lit(2))
    tagged = tagged.unionByName(_tiles(common.materialise(tag(warm), "warm"))) if some_hot else tagged
    cross = tagged.repartition(n, "token").sortWithinPartitions("token").mapInArrow(_cross_pairs, PAIR)
    cross = cross.groupBy("a", "b").agg(F.count(F.lit(1)).alias("c"), F.first("na").alias("na"), F.first("nb").alias("nb")).where(F.col("c") >= bound)
    open_ = common.materialise(cross.select("a", "b", (F.col("c") / (F.col("na") + F.col("nb"))).alias("near")), "cross")
    # Each round asks every set about its likeliest partner; links answer for all pairs that they connect.
    turn = 0
    while count := open_.count():
        turn += 1
        last = count <= MANY or turn > ROUNDS
        if not last:
            best = open_.groupBy("b").agg(F.max_by("a", F.struct("near", "a")).alias("a")).unionByName(open_.groupBy("a").agg(F.max_by("b", F.struct("near", "b")).alias("b"))).distinct()
            asked = common.materialise(best.select("a", "b"), "asked")
        else:
            asked = open_.select("a", "b")
        found = common.materialise(_verify(asked, texts), "links")
        if found.limit(1).count():
            labels = connected(labels.select(F.col("id").alias("a"), F.col("component").alias("b")).where("a != b").unionByName(found))
        if last:
            break
        ends = labels.select(F.col("id").alias("__a"), F.col("component").alias("ca")), labels.select(F.col("id").alias("__b"), F.col("component").alias("cb"))
        left = open_.join(asked, ["a", "b"], "left_anti").join(ends[0], F.col("a") == F.col("__a"), "left").join(ends[1], F.col("b") == F.col("__b"), "left")
        open_ = common.materialise(left.where(F.coalesce("ca", "a") != F.coalesce("cb", "b")).select("a", "b", "near"), "cross")
    # The smallest identifier of a component, then of every class, then of every row.
    linked = classes.select("rep", "least").join(labels.withColumnRenamed("id", "rep"), "rep")
    smallest = linked.groupBy("component").agg(F.min("least").alias("smallest"))
    linked = linked.join(smallest, "component").select("rep", "component", "smallest")
    known = classes.select("mark", "rep", "least").join(linked, "rep", "left").select("mark", F.coalesce("component", "rep").alias("component"), F.coalesce("smallest", "least").alias("component_id"))
    found = sets.join(known, "mark", "left")
    own = F.when(real, F.col("component_id")).otherwise(F.col("id"))
    return found.select("id", "tag", "node", "n_shingles", F.coalesce("component", "node").alias("component"), own.alias("component_id"))


def components(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per document: key, n_shingles, component_id."""
    return _components(docs, key, text).select(F.col("id").alias(key), "n_shingles", "component_id")


@common.cleaned
def _fewer(docs: DataFrame, key: str, text: str) -> DataFrame:
    """(__key, __text, stay): how many rows of a key and text stay, where not all do."""
    rows = _components(docs, key, text)
    first = rows.groupBy("component").agg(F.min(F.struct(F.col("id").isNull().alias("last"), "id", "tag", "node")).alias("first"), F.count(F.lit(1)).alias("n"))
    rows = rows.join(first.where("n > 1").select("component", F.col("first.node").alias("first")), "component")
    counted = rows.groupBy(F.col("id").alias("__key"), F.col("tag").alias("__text")).agg(F.count_if(F.col("node") == F.col("first")).alias("stay"), F.count(F.lit(1)).alias("n"))
    return counted.where("stay < n").drop("n")


def near_dedup(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with all its columns and one row of each component: the one of smallest key."""
    alike = {"__key": F.col(key).cast("long"), "__text": F.xxhash64(F.col(text).cast("string"))}
    return common.without(docs, alike, _fewer(docs, key, text))


def op8_ngram_jaccard_join(spark, sf_dir: str) -> DataFrame:
    return components(common.documents(spark, sf_dir))
