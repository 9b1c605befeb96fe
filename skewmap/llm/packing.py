"""Packing tokenised documents into sequences of fixed size by exact-complement hashing.

Documents are tokenised where they are read (each worker keeps a bounded table from word to ids) and cut
into pieces; texts do not move. What decides the packing is the histogram of piece lengths, at most one
row per token length, so it fits the driver whatever the input. The plan consumes it from the longest
length down: the gap that a piece leaves is looked up among single lengths, sums of two and sums of three
lengths, each combination as often as its parts are available; what is left over is placed best fit, longest
first. The plan is a short table of slots (length, range of ranks -> sequences, offset). A piece's rank among
the pieces of its length is its rank within its input partition plus the counts of earlier partitions, so
a length that a third of all pieces have needs no task of its own.

Defined results: null and empty texts are one token (the final id 0); documents over the size are cut
every ``size`` tokens and only they are cut; repeated identifiers are packed as separate documents; an
empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import gc
import re
import zlib
from collections.abc import Iterator
from operator import add

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from . import common

SIZE = 2048
VOCABULARY = "word_bpe_49k.json"
#: Bytes of text that are cut into words at a time.
PART = 4_000_000
#: Words, and parts of words, that a worker remembers before it starts anew: some 60 MB each.
REMEMBERED = 300_000

PIECES = "doc_id {key}, piece int, start long, length long, ids_crc32 long, part int, rank long"


#: Letters (A-Z are lower-cased already) and the marks after them; apostrophes and digits are left to the tokenizer.
_LATIN = re.compile(r"^([A-Za-zÀ-ÖØ-öø-ÿ]+)([!-&(-/:-@\[-`{-~]*)$|^(.*)$", re.M)


class WordIds(dict):
    """Places of white-space separated words in a store of their ids; place 0 is the end of a document, id 0, place 1 no word.

    A word met for the first time gets a place at once and its ids with the next ``learn``. A word of plain
    Latin letters with ASCII marks after them has the ids of the letters and those of the marks, as the
    tokenizer splits there; such parts are far fewer than words, and each ends with a token that ends a word,
    so many are encoded in one call. Other words are encoded as they are.
    """

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer
        from tokenizers.normalizers import Lowercase
        from tokenizers.pre_tokenizers import ByteLevel, Sequence, WhitespaceSplit

        self.whole, self.plain = Tokenizer.from_file(path), Tokenizer.from_file(path)
        # For parts that are one pre-token each and need no other normalisation.
        self.plain.normalizer = Lowercase()
        self.plain.pre_tokenizer = Sequence([WhitespaceSplit(), ByteLevel(add_prefix_space=False, use_regex=False)])
        size = self.whole.get_vocab_size()
        self.ends = np.zeros(size, bool)
        for token, i in self.whole.get_vocab().items():
            self.ends[i] = token.endswith("</w>")
        self.parts: dict[str, bytes] = {}
        self.reset()

    def reset(self) -> None:
        self.clear()
        self[b""] = 1
        self.pending: list[bytes] = []
        self.ids = np.zeros(1, "<u4")
        self.starts, self.sizes = np.zeros(2, np.int64), np.array([1, 0])

    def __missing__(self, word: bytes) -> int:
        place = len(self) + 1
        self[word] = place
        self.pending.append(word)
        return place

    def learn(self) -> None:
        """Find the ids of the words met since the last call."""
        if len(self.parts) > REMEMBERED:
            self.parts.clear()
        # One line a word, as words hold no line feed: parts of plain words, or the word as it is.
        found = _LATIN.findall(b"\n".join(self.pending).decode("utf-8", "replace")) if self.pending else []
        letters = [a.lower() if a else c for a, _, c in found]
        marks = [b for _, b, _ in found]
        others = {c for a, _, c in found if not a}
        parts = self.parts
        parts[""] = b""
        self._encode(list({*letters, *marks}.difference(parts, others)))
        for text in others.difference(parts):
            parts[text] = np.array(self.whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        get = parts.__getitem__
        blobs = list(map(add, map(get, letters), map(get, marks)))
        sizes = np.fromiter(map(len, blobs), np.int64, len(blobs)) // 4
        self.starts = np.concatenate([self.starts, len(self.ids) + np.cumsum(sizes) - sizes])
        self.sizes = np.concatenate([self.sizes, sizes])
        self.ids = np.concatenate([self.ids, np.frombuffer(b"".join(blobs), "<u4")])
        self.pending = []

    def _encode(self, new: list[str]) -> None:
        for lo in range(0, len(new), 20_000):
            some = new[lo : lo + 20_000]
            ids = np.array(self.plain.encode_batch_fast([" ".join(some)], add_special_tokens=False)[0].ids, "<u4")
            edges = [0, *((np.flatnonzero(self.ends[ids]) + 1) * 4).tolist()]
            if len(edges) != len(some) + 1:
                raise ValueError("the vocabulary has no word ends")
            blob = ids.tobytes()
            self.parts.update(zip(some, (blob[a:b] for a, b in zip(edges[:-1], edges[1:]))))

    def documents(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of documents, each with its end, one after the other, and where each begins.

        Texts are cut into words and equal words are numbered by Arrow; only a batch's different words are looked up here.
        """
        if len(self) > REMEMBERED:
            self.reset()
        words = pc.ascii_split_whitespace(_lowered(texts))
        coded = words.flatten().dictionary_encode()
        kinds = list(common.byte_rows(coded.dictionary))
        places = np.fromiter(map(self.__getitem__, kinds), np.int64, len(kinds))
        self.learn()
        at = places[coded.indices.to_numpy()] if len(coded) else np.zeros(0, np.int64)
        last = np.cumsum(np.diff(words.offsets.to_numpy()))  # words up to each document's end
        at = np.insert(at, last, 0)
        size = self.sizes[at]
        stop = np.cumsum(size)
        narrow = np.int32 if max(stop[-1], len(self.ids)) < 1 << 31 else np.int64
        ids = self.ids[np.repeat((self.starts[at] - (stop - size)).astype(narrow), size) + np.arange(stop[-1], dtype=narrow)]
        return ids, np.concatenate([[0], stop[last + np.arange(len(last))]])


_tables: dict[str, WordIds] = {}
common.remember("packing", _tables.clear)


def _lowered(texts: pa.Array) -> pa.Array:
    """Texts with A-Z lower-cased, which the tokenizer would do, but for those that could hold a special token; null is empty."""
    texts = texts.fill_null("")
    special = pc.match_substring(texts, "<|")
    lower = pc.ascii_lower(texts)
    return pc.if_else(special, texts, lower) if pc.any(special).as_py() else lower


def tokenise(path: str, size: int = SIZE):
    """Function for ``mapInArrow`` from (key, text) to pieces."""

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.only("packing")
        gc.disable()  # the tables hold millions of small objects and no cycles
        try:
            yield from cut(batches)
        finally:
            gc.enable()

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        ranks: dict[int, int] = {}
        table = _tables.get(path)
        if table is None:
            table = _tables[path] = WordIds(path)
        for batch in batches:
            keys = batch.column(0)
            out: list[tuple] = []
            for first, texts in common.in_parts(batch.column(1), PART):
                ids, begins = table.documents(texts)
                edges = begins.tolist()
                for i, (lo, hi) in enumerate(zip(edges[:-1], edges[1:]), first):
                    for piece, at in enumerate(range(lo, hi, size)):
                        own = ids[at : min(at + size, hi)]
                        r = ranks.get(len(own), 0)
                        ranks[len(own)] = r + 1
                        out.append((i, piece, at - lo, len(own), zlib.crc32(own), r))
            cols = list(zip(*out)) if out else [()] * 6
            yield pa.RecordBatch.from_arrays(
                [keys.take(pa.array(cols[0], pa.int64())), pa.array(cols[1], pa.int32()), pa.array(cols[2], pa.int64()), pa.array(cols[3], pa.int64()), pa.array(cols[4], pa.int64()), pa.array([part] * len(out), pa.int32()), pa.array(cols[5], pa.int64())],
                ["doc_id", "piece", "start", "length", "ids_crc32", "part", "rank"],
            )

    return pieces


def plan(histogram: dict[int, int], size: int = SIZE) -> list[tuple[tuple[tuple[int, int], ...], int]]:
    """Patterns ``(((length, copies), ...), sequences)`` that hold every piece of the histogram once."""
    left = np.zeros(size + 1, np.int64)
    for n, c in histogram.items():
        left[n] = c
    done: list[tuple[tuple[tuple[int, int], ...], int]] = []

    def consume(*lengths: int) -> int:
        need = {n: lengths.count(n) for n in lengths}
        times = min(int(left[n]) // k for n, k in need.items())
        if times:
            for n, k in need.items():
                left[n] -= times * k
            done.append((tuple(sorted(need.items(), reverse=True)), times))
        return times

    for a in range(size, 0, -1):
        gap = size - a
        if left[a] and gap == 0:
            consume(a)
        if left[a] and gap:
            consume(a, gap)
        if left[a] and gap > 1:  # pairs, the most available first
            b = np.arange((gap + 1) // 2, gap)
            both = np.minimum(left[b], left[gap - b])
            for i in np.argsort(-both, kind="stable"):
                if not left[a] or not both[i]:
                    break
                consume(a, int(b[i]), int(gap - b[i]))
    for a in range(size, 0, -1):
        gap = size - a
        if not left[a] or gap < 3:
            continue
        have = np.flatnonzero(left[: gap - 1])
        have = have[have > 0]
        for b in have[::-1]:
            if not left[a]:
                break
            rest = gap - int(b)
            c = have[(have <= b) & (have < rest)]
            c = c[left[rest - c] > 0]
            for x in c[::-1]:
                if not left[a]:
                    break
                consume(a, int(b), int(x), rest - int(x))
    # Residuals: best fit decreasing over classes of equal sequences.
    open_: dict[int, list[list]] = {}
    for n in range(size, 0, -1):
        while left[n]:
            gap = next((g for g in range(n, size) if open_.get(g)), None)
            if gap is None:
                fit, times = size // n, 1
                times = int(left[n]) // fit
                group = [[(n, fit)], times] if times else [[(n, int(left[n]))], 1]
            else:
                held, many = open_[gap].pop()
                fit = min(gap // n, int(left[n]))
                times = min(many, int(left[n]) // fit)
                if many > times:
                    open_[gap].append([held, many - times])
                group = [[*held, (n, fit)], times]
            left[n] -= group[0][-1][1] * group[1]
            room = size - sum(a * k for a, k in group[0])
            if room:
                open_.setdefault(room, []).append(group)
            else:
                done.append((tuple(group[0]), group[1]))
    done += [(tuple(held), many) for groups in open_.values() for held, many in groups]
    return done


def slots(patterns: list[tuple[tuple[tuple[int, int], ...], int]]) -> np.ndarray:
    """Rows (length, first rank, copies in a sequence, first sequence, offset) in order of length and rank."""
    used: dict[int, int] = {}
    rows, sequence = [], 0
    for parts, times in patterns:
        offset = 0
        for n, k in parts:
            rows.append((n, used.get(n, 0), k, sequence, offset))
            used[n] = used.get(n, 0) + k * times
            offset += n * k
        sequence += times
    return np.array(sorted(rows), np.int64).reshape(-1, 5)


@common.cleaned
def pack(docs: DataFrame, key: str = "doc_id", text: str = "text", size: int = SIZE, vocabulary: str | None = None) -> DataFrame:
    """One row per piece: key, piece, start, length, ids_crc32, sequence_id, offset."""
    import public_tokenizers

    rows = docs.select(F.col(key).alias("doc_id"), F.col(text).cast("string").alias("text"))
    schema = PIECES.format(key=rows.schema["doc_id"].dataType.simpleString())
    pieces = common.materialise(rows.mapInArrow(tokenise(vocabulary or public_tokenizers.path(VOCABULARY), size), schema), "pieces")
    counts = pieces.groupBy("length", "part").agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    counts = common.materialise(counts.withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0)).cast("long")), "counts")
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    table = slots(plan(histogram, size))
    order = [(int(a) << 44) | int(b) for a, b in table[:, :2]]
    starts = np.array(order, np.int64)

    @F.arrow_udf(T.StructType([T.StructField("sequence_id", T.LongType()), T.StructField("offset", T.LongType())]))
    def place(length: pa.Array, rank: pa.Array) -> pa.Array:
        n, r = length.to_numpy(zero_copy_only=False), rank.to_numpy(zero_copy_only=False)
        row = table[np.searchsorted(starts, (n.astype(np.int64) << 44) | r, "right") - 1]
        i = r - row[:, 1]
        return pa.StructArray.from_arrays([pa.array(row[:, 3] + i // row[:, 2]), pa.array(row[:, 4] + i % row[:, 2] * n)], ["sequence_id", "offset"])

    placed = pieces.join(counts.select("length", "part", "before"), ["length", "part"])
    placed = placed.withColumn("at", place(F.col("length"), F.col("rank") + F.col("before")))
    return placed.select(F.col("doc_id").alias(key), "piece", "start", "length", "ids_crc32", "at.sequence_id", "at.offset")


def op2_best_fit_packing(spark, sf_dir: str) -> DataFrame:
    return pack(common.documents(spark, sf_dir))
