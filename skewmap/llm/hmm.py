"""Language-model scores by a hidden Markov model trained with Baum-Welch.

States emit word classes. Each of the most frequent words is a class of its own (their number is a
parameter, so the emission table has a fixed size); every other word falls in one of a fixed number of
classes by its last bytes. Within a class a word has its add-one share of the training counts, one share
being kept for unknown words, so the model is a proper distribution over words and the end mark:

    log10 p(text) = forward log10 p(classes of the text) + sum of log10 p(word | class).

Texts are read twice: to count words, and to write every text as its words' classes, which is all that
training and scoring read. Training: in every round every task adds up the expected counts of its training
documents by the scaled forward-backward recursion, the counts are summed across partitions in two steps, and the
tables are made anew. Scoring is the scaled forward recursion, exact.

Word counts cover all training documents. Counts of the commonest words, a bounded number, go to every task; those
of all others come back to the documents through a join on the word, of which each batch of documents sends one
row with the list of its rows that hold it.

Defined results: null and empty texts are the end mark alone; an empty training set leaves N = V = 0 and
uniform classes; long texts are scored whole; a null identifier counts as a training row; rows that
repeat are scored alike (scores are rounded to millionths, as the last digits depend on what is scored beside); an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: The end mark as a word; no word holds white space.
END = b"\n"
#: Words whose classes a worker remembers before it starts anew.
REMEMBERED = 300_000
_held: dict[str, "Classes"] = {}
common.remember("hmm", _held.clear)


@dataclass
class Vocabulary:
    """Classes of words: 0 the end mark, then the frequent words, then the rest by their last bytes."""

    words: dict[bytes, int]
    counts: np.ndarray
    rest: int
    rest_tokens: np.ndarray
    rest_words: np.ndarray
    tokens: int
    distinct: int
    #: Counts of the commonest words without a class of their own.
    others: dict[bytes, int] = field(default_factory=dict)

    @property
    def classes(self) -> int:
        return len(self.counts) + self.rest

    @property
    def kind(self) -> str:
        """Type of stored classes."""
        return "<u2" if self.classes <= 1 << 16 else "<u4"

    def encode(self, words: list[bytes]) -> np.ndarray:
        """Classes of a text's words and its end."""
        known = _held.get("known")
        if known is None or known.of is not self.words or len(known) > REMEMBERED:
            known = _held["known"] = Classes(self)
        out = np.empty(len(words) + 1, np.int32)
        out[:-1] = np.fromiter(map(known.__getitem__, words), np.int32, len(words))
        out[-1] = 0
        return out

    def within(self) -> np.ndarray:
        """log10 of one share of each class; a word's own share is added as log10(count + 1)."""
        top = -np.log10(np.maximum(1.0, self.counts + 1.0))
        return np.concatenate([top, -np.log10(self.rest_tokens + self.rest_words + 1.0)])

    def spare(self) -> np.ndarray:
        """Add-one counts of each class: one a known word, and one for unknown words of the class."""
        return np.concatenate([np.ones(len(self.counts)), self.rest_words + 1.0])

    def base(self) -> np.ndarray:
        """Class probabilities of the unigram counts."""
        p = np.concatenate([self.counts, self.rest_tokens]) + self.spare()
        return p / p.sum()


class Classes(dict):
    """Classes of words; those of rare words are worked out when first met."""

    def __init__(self, vocabulary: Vocabulary) -> None:
        super().__init__(vocabulary.words)
        self.of = vocabulary.words
        self.first, self.rest = len(vocabulary.counts), vocabulary.rest

    def __missing__(self, word: bytes) -> int:
        c = self[word] = self.first + zlib.crc32(word[-3:]) % self.rest
        return c


@dataclass
class Model:
    start: np.ndarray
    move: np.ndarray
    emit: np.ndarray  # class x state


def initial(vocabulary: Vocabulary, states: int, seed: int = 7) -> Model:
    rng = np.random.default_rng(seed)
    move = np.full((states, states), 0.3 / states) + np.eye(states) * 0.7
    noise = rng.gamma(2.0, size=(vocabulary.classes, states))
    emit = vocabulary.base()[:, None] * noise
    return Model(np.full(states, 1 / states), move / move.sum(1, keepdims=True), emit / emit.sum(0))


def _steps(texts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Texts laid out step by step: classes of all texts' first tokens (longest text first), then all second ones, and so on."""
    order = np.argsort([-len(t) for t in texts], kind="stable")
    lengths = np.array([len(texts[i]) for i in order])
    alive = np.bincount(lengths, minlength=lengths.max() + 1)[::-1].cumsum()[::-1][1:]  # texts with more than t tokens, by t
    offsets = np.concatenate([[0], np.cumsum(alive)])
    flat = np.concatenate([texts[i] for i in order])
    row = np.repeat(np.arange(len(order)), lengths)
    step = np.arange(len(flat)) - np.repeat(np.cumsum(lengths) - lengths, lengths)
    out = np.empty(len(flat), flat.dtype)
    out[offsets[step] + row] = flat
    return out, offsets, order, lengths


#: Steps between scalings, by type: products of so many emissions stay within its range.
EVERY = {np.float64: 32, np.float32: 8}
TINY = {np.float64: 1e-300, np.float32: 1e-37}
#: Tokens of the pieces that longer texts are cut into.
PIECE = 512


@dataclass
class Pieces:
    """Texts side by side; a long one is cut into pieces that are worked on like texts of their own.

    What a piece does to any distribution over the states is a matrix, found for all pieces at once; products of them
    give each piece the distribution it begins with (``prior``) and the weight of what comes after it (``after``), so
    the recursions over pieces are those over the whole text, and exact. ``joints`` are the moves from piece to piece.
    """

    parts: list[np.ndarray]
    owner: np.ndarray
    first: np.ndarray
    prior: np.ndarray
    after: np.ndarray
    joints: np.ndarray


def _cut(model: Model, relative: np.ndarray, texts: list[np.ndarray], kind) -> Pieces:
    k = len(model.start)
    if max(map(len, texts), default=0) <= 2 * PIECE:
        n = len(texts)
        return Pieces(texts, np.arange(n), np.ones(n, bool), np.broadcast_to(model.start, (n, k)), np.ones((n, k)), np.zeros((k, k)))
    parts, owner, place = [], [], []
    for i, t in enumerate(texts):
        cuts = range(0, len(t), PIECE) if len(t) > 2 * PIECE else (0,)
        for j, lo in enumerate(cuts):
            parts.append(t[lo : lo + PIECE] if len(cuts) > 1 else t)
            owner.append(i)
            place.append(j)
    owner, place = np.array(owner), np.array(place)
    n, first = len(parts), place == 0
    prior, after, joints = np.tile(model.start, (n, 1)), np.ones((n, k)), np.zeros((k, k))
    long = np.flatnonzero(np.bincount(owner)[owner] > 1)
    does = np.zeros((n, k, k))
    does[long] = _matrices(model, relative, [parts[i] for i in long], kind)
    for j in range(1, place.max() + 1):  # forward: what each piece begins with
        now = np.flatnonzero(place == j)
        end = np.einsum("ni,nij->nj", prior[now - 1], does[now - 1])
        end /= end.sum(1, keepdims=True)
        prior[now] = end @ model.move
    for j in range(place.max(), 0, -1):  # backward: the weight of what comes after, and the moves between pieces
        now = np.flatnonzero(place == j)
        weight = np.einsum("nij,nj->ni", does[now], after[now])
        weight /= weight.sum(1, keepdims=True)
        after[now - 1] = weight @ model.move.T
        end = np.einsum("ni,nij->nj", prior[now - 1], does[now - 1])
        total = ((end @ model.move) * weight).sum(1)
        joints += (end / total[:, None]).T @ weight
    return Pieces(parts, owner, first, prior, after, joints)


def _matrices(model: Model, relative: np.ndarray, parts: list[np.ndarray], kind) -> np.ndarray:
    """For each piece, up to a factor, the variables at its end by the state that it begins in."""
    cls, offsets, order, _ = _steps(parts)
    e, k, every = np.take(relative, cls, axis=0), len(model.start), EVERY[kind]
    move, out = model.move.astype(kind), np.empty((len(parts), k, k))
    here = np.repeat(np.eye(k, dtype=kind)[:, None, :], len(parts), 1)  # state at the beginning, piece, state now
    steps, n = offsets.tolist(), len(parts)
    for t, (a, b) in enumerate(zip(steps[:-1], steps[1:])):
        if t:
            if b - a < n:
                out[order[b - a : n]] = here[:, b - a :].swapaxes(0, 1)
                n = b - a
            here = np.matmul(here[:, :n], move)
        here *= e[a:b]
        if t % every == every - 1:
            here *= (1 / np.maximum(here.max(0).max(1), TINY[kind]))[None, :, None]
    out[order[:n]] = here.swapaxes(0, 1)
    return out / out.max((1, 2), keepdims=True)


def forward(model: Model, texts: list[np.ndarray], keep: bool = False, kind=np.float64):
    """log10 probability of each text; with ``keep`` what ``expected`` goes back over.

    Emissions are taken relative to each class's greatest, so a step shrinks the variables little, and they are scaled
    every few steps only.
    """
    most = model.emit.max(1)
    relative = (model.emit / most[:, None]).astype(kind)
    pieces = _cut(model, relative, texts, kind)
    cls, offsets, order, lengths = _steps(pieces.parts)
    cls, move = cls.astype(np.intp), model.move.astype(kind)
    ones, tiny, every = np.ones(len(move), kind), kind(TINY[kind]), EVERY[kind]
    alpha, scales = np.empty((len(cls), len(move)), kind), {}
    logs, steps = np.zeros(len(order)), offsets.tolist()
    for t, (a, b) in enumerate(zip(steps[:-1], steps[1:])):
        here = alpha[a:b]
        if t:
            np.matmul(last[: b - a], move, out=here)
            here *= relative.take(cls[a:b], 0)
        else:
            np.multiply(relative.take(cls[a:b], 0), pieces.prior[order], out=here, casting="same_kind")
        if t % every == every - 1:
            scale = np.maximum(here @ ones, tiny)
            here *= (1 / scale)[:, None]
            scales[t] = scale
            if not keep:
                logs[: b - a] += np.log10(scale, dtype=np.float64)
        last = here
    ends = alpha[offsets[lengths - 1] + np.arange(len(order))]  # at the last token of each
    if keep:
        return pieces, order, cls, steps, relative, alpha, scales, ends
    row = np.arange(len(cls)) - np.repeat(offsets[:-1], np.diff(offsets))
    logs += np.log10(np.maximum(ends @ ones, tiny), dtype=np.float64) + np.bincount(row, np.log10(most)[cls], len(order))
    return np.bincount(pieces.owner[order], logs, len(texts))


def expected(model: Model, texts: list[np.ndarray], classes: int, kind=np.float64) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Baum-Welch counts of a batch: start, moves and emissions (class x state)."""
    # gamma becomes the posterior in place, from the last step down.
    pieces, order, cls, steps, relative, gamma, scales, ends = forward(model, texts, True, kind)
    k, back = len(model.start), np.ascontiguousarray(model.move.T.astype(kind))
    after = pieces.after[order].astype(kind)
    after /= np.maximum((ends * after).sum(1, keepdims=True), kind(TINY[kind]))
    moves, beta = np.zeros((k, k)), None
    for t in range(len(steps) - 2, -1, -1):
        a, b = steps[t], steps[t + 1]
        here, n = np.empty((b - a, k), kind), 0
        if beta is not None:
            n = len(beta)
            ahead = relative.take(cls[b : b + n], 0)
            ahead *= beta
            if t + 1 in scales:
                ahead *= (1 / scales[t + 1])[:, None]
            moves += gamma[a : a + n].T @ ahead
            np.matmul(ahead, back, out=here[:n])
        here[n:] = after[n : b - a]
        gamma[a:b] *= here
        beta = here
    moves = (moves + pieces.joints) * model.move
    emit = np.stack([np.bincount(cls, column, classes) for column in np.ascontiguousarray(gamma.T)], 1)
    first = gamma[: steps[1]][pieces.first[order]].astype(np.float64)
    return (first / first.sum(1, keepdims=True)).sum(0), moves, emit


def update(start: np.ndarray, moves: np.ndarray, emit: np.ndarray, spare: np.ndarray, shrink: float = 4.0) -> Model:
    """New tables from counts.

    ``shrink`` tokens of each class are dealt to the states by their sizes, so that classes seen a few times do
    not tie themselves to a state; the add-one counts ``spare`` of the classes are dealt likewise.
    """
    total = emit.sum(1, keepdims=True)
    share = emit.sum(0) / max(1e-300, emit.sum())
    held = total * (emit + shrink * share) / np.maximum(total + shrink, 1e-300)
    s, m, e = start + 1.0, moves + 1.0, held + np.maximum(share, 1e-9) * spare[:, None]
    return Model(s / s.sum(), m / m.sum(1, keepdims=True), e / e.sum(0))


def _in_groups(texts: list[np.ndarray], tokens: int) -> Iterator[list[np.ndarray]]:
    """Texts in groups of bounded size, whole, those of similar length together."""
    group, held = [], 0
    for t in sorted(texts, key=len):
        if group and held + len(t) > tokens:
            yield group
            group, held = [], 0
        group.append(t)
        held += len(t)
    if group:
        yield group


def _words(texts: pa.Array) -> pa.ListArray:
    """Words of each text after lower-casing A-Z; empty ones may stand at the ends of a text."""
    return pc.ascii_split_whitespace(pc.ascii_lower(texts.fill_null("")))


#: Bytes of text whose words are counted at a time.
COUNTED = 16_000_000


def _count_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for _, texts in common.in_parts(batch.column(0), COUNTED):
            found = pc.value_counts(_words(texts).flatten())
            word, n = found.field("values").cast(pa.binary()), found.field("counts")
            real = pc.not_equal(pc.binary_length(word), 0)
            yield pa.RecordBatch.from_arrays([pa.concat_arrays([word.filter(real), pa.array([END], pa.binary())]), pa.concat_arrays([n.filter(real), pa.array([len(texts)], pa.int64())])], ["word", "c"])


#: Rows of a block of the emission table; tasks beyond which blocks are summed in two steps.
BLOCK_ROWS, WIDE = 4096, 256


#: Tokens that are trained on or scored side by side.
TRAINED, SCORED = 400_000, 200_000


def _classes_of(column: pa.Array, kind: str) -> list[np.ndarray]:
    """Texts as arrays of classes."""
    raw, offs = common.utf8_view(column)
    flat, edges = raw.tobytes(), offs.tolist()
    return [np.frombuffer(flat, kind, (hi - lo) // np.dtype(kind).itemsize, lo) for lo, hi in zip(edges[:-1], edges[1:])]


def _counting(model, classes: int, kind: str):
    """For ``mapInArrow`` over texts as classes: a task's expected counts as blocks of the emission table, block -1 for start and moves."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.only("hmm")
        m, total = model.value, None
        for batch in batches:
            for group in _in_groups(_classes_of(batch.column(0), kind), TRAINED):
                got = expected(m, group, classes, np.float32)
                total = got if total is None else tuple(a + b for a, b in zip(total, got))
        if total is not None:
            start, moves, emit = total
            blocks = [emit[i : i + BLOCK_ROWS].astype(np.float32) for i in range(0, len(emit), BLOCK_ROWS)]
            ids = [-1, *range(len(blocks))]
            data = [np.concatenate([start, moves.ravel()]).tobytes(), *(b.tobytes() for b in blocks)]
            salt = [xxhash.xxh32_intdigest(data[0]) % 32] * len(ids)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int32()), pa.array(salt, pa.int32()), pa.array(data, pa.binary())], ["block", "salt", "counts"])

    return run


def _summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sums of a task's blocks: emissions travel as 4-byte numbers and are added up as 8-byte ones."""
    total: dict[int, np.ndarray] = {}
    for batch in batches:
        for block, data in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist()):
            own = np.frombuffer(data, np.float64 if block < 0 else np.float32)
            if block in total:
                total[block] += own
            else:
                total[block] = own.astype(np.float64)
    if total:
        data = [x.tobytes() if b < 0 else x.astype(np.float32).tobytes() for b, x in total.items()]
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int32()), pa.array([0] * len(total), pa.int32()), pa.array(data, pa.binary())], ["block", "salt", "counts"])


def _encode(vocabulary):
    """For ``mapInArrow`` over (id, text, train): each text as the classes of its words.

    A row also has the sum of log10(count + 1) of its words whose counts are at hand but have no class of their own,
    their number, and the other rare words that it is the first of its part of a batch to hold, each with the
    signatures of all rows of the part that hold it, as often as they do.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.only("hmm")
        for batch in batches:
            cuts = [*(lo for lo, _ in common.in_parts(batch.column(1))), batch.num_rows]
            for lo, hi in zip(cuts[:-1], cuts[1:]):
                yield coded(batch.slice(lo, hi - lo))

    def coded(batch: pa.RecordBatch) -> pa.RecordBatch:
        v = vocabulary.value
        top, n, marks = len(v.counts), batch.num_rows, _marks(batch)
        words = _words(batch.column(1))
        kind = words.flatten().dictionary_encode()
        kinds = list(common.byte_rows(kind.dictionary))
        cls = v.encode(kinds)[:-1]
        counts = np.fromiter(map(v.others.get, kinds, repeat(0)), np.int64, len(kinds))
        real = np.fromiter(map(len, kinds), np.int64, len(kinds)) > 0
        at, row = kind.indices.to_numpy(), np.repeat(np.arange(n), np.diff(words.offsets.to_numpy()))
        keep = real[at]
        at, row = at[keep], row[keep]
        size = np.bincount(row, minlength=n)
        flat = np.insert(cls[at], np.cumsum(size), 0).astype(v.kind)  # every text's end
        edges = np.concatenate([[0], np.cumsum(size + 1)]) * flat.itemsize
        codes = pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(edges.astype(np.int32)), pa.py_buffer(flat)])
        held = (cls >= top) & (counts > 0)
        sums = np.bincount(row, np.where(held, np.log10(counts + 1.0), 0.0)[at], n).astype(np.float64)
        numbers = np.bincount(row, held[at].astype(float), n).astype(np.int64)
        # Rare words in the order of the rows that hold them first, each with all its rows.
        rare = ((cls >= top) & ~held)[at]
        word, holder = at[rare], row[rare]
        order = np.argsort(word, kind="stable")
        word, holder = word[order], holder[order]
        begin = np.flatnonzero(np.concatenate([[True], word[1:] != word[:-1]])) if len(word) else np.zeros(0, np.int64)
        many = np.diff(np.append(begin, len(word)))
        first = holder[begin]
        by = np.argsort(first, kind="stable")
        many, begin = many[by], begin[by]
        ends = np.cumsum(many)
        picked = np.repeat(begin - (ends - many), many) + np.arange(len(word))
        lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]).astype(np.int32)), pa.array(marks[holder[picked]]))
        found = pa.StructArray.from_arrays([kind.dictionary.take(pa.array(word[begin])).cast(pa.binary()), lists], ["word", "rows"])
        outer = np.concatenate([[0], np.cumsum(np.bincount(first, minlength=n))]).astype(np.int32)
        return pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array(marks), batch.column(2), codes, pa.array(sums), pa.array(numbers), pa.ListArray.from_arrays(pa.array(outer), found)],
            ["id", "mark", "train", "codes", "others", "n_others", "rare"],
        )

    return run


def _marks(batch: pa.RecordBatch) -> np.ndarray:
    """Signature of each row's identifier and text; equal rows share one."""
    ids = batch.column(0).to_pylist()
    return np.array([xxhash.xxh3_64_intdigest(t, seed=xxhash.xxh32_intdigest(str(i))) for i, t in zip(ids, common.byte_rows(batch.column(1)))], np.uint64).view(np.int64)


def _scores(model, vocabulary):
    """For ``mapInArrow`` over (id, mark, classes, others, n_others): what each row's score needs beside its rare words' counts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.only("hmm")
        m, v = model.value, vocabulary.value
        within, top = v.within(), len(v.counts)
        own = np.concatenate([np.log10(v.counts + 1.0), np.zeros(v.rest)])
        known = np.concatenate([v.counts > 0, np.zeros(v.rest, bool)])
        for batch in batches:
            texts = _classes_of(batch.column(2), v.kind)
            n = np.array([len(t) for t in texts], np.int64)
            logs = np.zeros(len(texts))
            order = sorted(range(len(texts)), key=lambda i: len(texts[i]))
            done = 0
            for group in _in_groups([texts[i] for i in order], SCORED):
                logs[order[done : done + len(group)]] = forward(m, group)
                done += len(group)
            sums = np.array([(within[t].sum() + own[t].sum(), own[t].sum(), known[t].sum(), (t >= top).sum()) for t in texts]).reshape(-1, 4)
            held, count = batch.column(3).to_numpy(), batch.column(4).to_numpy()
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(n), pa.array(logs + sums[:, 0] + held), pa.array(sums[:, 1] + held), pa.array(sums[:, 2].astype(np.int64) + count), pa.array(sums[:, 3].astype(np.int64) - count)],
                ["id", "mark", "n_tokens", "model", "own", "known", "rare"],
            )

    return run


def fit_vocabulary(counts: DataFrame, frequent: int = 40_000, rest: int = 1024, others: int = 100_000) -> Vocabulary:
    """Frequent words, class totals and counts of ``others`` more words from a table (word, c); the driver gets as many rows."""
    totals = counts.agg(F.sum("c").alias("n"), F.count(F.lit(1)).alias("v")).first()
    end = F.col("word") == F.lit(END)
    ends = counts.where(end).agg(F.sum("c")).first()[0] or 0
    table = counts.where(~end).orderBy(F.desc("c"), "word").limit(frequent + others).toArrow()
    most = list(zip(common.byte_rows(table.column("word")), table.column("c").to_pylist()))
    top = most[:frequent]
    least = top[-1] if top else (b"", 0)
    tail = counts.where(~end & ((F.col("c") < least[1]) | ((F.col("c") == least[1]) & (F.col("word") > F.lit(least[0])))))
    by = tail.groupBy((F.crc32(F.substring("word", -3, 3)) % rest).cast("int").alias("g")).agg(F.sum("c").alias("c"), F.count(F.lit(1)).alias("v")).collect()
    tokens, words = np.zeros(rest), np.zeros(rest)
    for r in by:
        tokens[r["g"]], words[r["g"]] = r["c"], r["v"]
    return Vocabulary({w: i for i, (w, _) in enumerate(top, 1)}, np.array([ends, *(c for _, c in top)], float), rest, tokens, words, totals["n"] or 0, totals["v"] or 0, dict(most[frequent:]))


@common.cleaned
def score(docs: DataFrame, training, key: str = "doc_id", text: str = "text", states: int = 8, rounds: int = 14, frequent: int = 40_000, rest: int = 1024, others: int = 100_000) -> DataFrame:
    """One row per document: key, n_tokens, n_known, train_tokens, base_score, score. ``training`` is a boolean column."""
    spark = docs.sparkSession
    n = common.partitions(spark)
    rows = docs.select(F.col(key).alias("id"), F.col(text).cast("string").alias("t"), F.coalesce(training, F.lit(True)).alias("train"))
    counts = rows.where("train").select("t").mapInArrow(_count_words, "word binary, c long").groupBy("word").agg(F.sum("c").alias("c"))
    counts = common.materialise(counts, "words")
    v = fit_vocabulary(counts, frequent, rest, others)
    vocabulary = common.shared(spark, v)
    kind = rows.schema["id"].dataType.simpleString()
    texts = rows.select("id", "t", "train").mapInArrow(_encode(vocabulary), f"id {kind}, mark long, train boolean, codes binary, others double, n_others long, rare array<struct<word binary, rows array<long>>>")
    texts = common.materialise(texts, "classes", compression="zstd")
    learn = texts.where("train").select("codes")
    tasks = len(texts.inputFiles())  # at least as many files as tasks read them
    model, spare = initial(v, states), v.spare()
    for _ in range(rounds):
        handle = common.shared(spark, model)
        schema = "block int, salt int, counts binary"
        part = learn.mapInArrow(_counting(handle, v.classes, v.kind), schema)
        if tasks > WIDE:  # a block's sum in one task would have too many terms
            part = part.repartition(n, "block", "salt").mapInArrow(_summed, schema)
        part = part.repartition(n, "block").mapInArrow(_summed, schema)
        found = {r["block"]: np.frombuffer(r["counts"], np.float64 if r["block"] < 0 else np.float32) for r in part.collect()}  # the size of one emission table
        if not found:
            break
        first = found.pop(-1)
        emit = np.concatenate([found[i] for i in sorted(found)]).reshape(-1, states)
        model = update(first[:states], first[states:].reshape(states, states), emit, spare)
    handle = common.shared(spark, model)
    rare = texts.select(F.explode("rare").alias("x")).select("x.word", "x.rows").join(counts, "word", "left")
    rare = rare.select(F.explode("rows").alias("mark"), F.log10(F.coalesce("c", F.lit(0)) + 1).alias("x"), F.col("c").isNotNull().cast("long").alias("k"))
    rare = rare.groupBy("mark").agg(F.sum("x").alias("x"), F.sum("k").alias("k"), F.count(F.lit(1)).alias("all"))
    parts = texts.select("id", "mark", "codes", "others", "n_others").mapInArrow(_scores(handle, vocabulary), f"id {kind}, mark long, n_tokens long, model double, own double, known long, rare long")
    joined = parts.join(rare, "mark", "left")
    # Equal rows share a signature, under which their rare words are summed; each row has its part.
    part = F.coalesce(F.col("rare") / F.col("all"), F.lit(0.0))
    x, k = F.coalesce(F.col("x") * part, F.lit(0.0)), F.coalesce(F.round(F.col("k") * part).cast("long"), F.lit(0))
    unit = float(np.log10(v.tokens + v.distinct + 1))
    return joined.select(
        F.col("id").alias(key), "n_tokens", (F.col("known") + k).cast("long").alias("n_known"), F.lit(v.tokens).cast("long").alias("train_tokens"),
        (F.col("own") + x - F.col("n_tokens") * unit).alias("base_score"), F.round(F.col("model") + x, 6).alias("score"),
    )


def op6_lm_scoring(spark, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir).select("doc_id", "text")
    held = F.coalesce(common.residue("doc_id", 7) == 2, F.lit(False))
    found = score(docs, ~held)
    return found.select("doc_id", held.alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")
