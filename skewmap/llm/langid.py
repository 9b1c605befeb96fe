"""Language identification by prediction by partial matching over bytes.

Each language has a variable-order byte context tree (contexts of at most three bytes). A symbol
unseen in a context is reached through escapes (escape count = distinct symbols of the context,
seen symbols excluded below it), down to a uniform distribution over the 256 byte values. The
statistics are frozen after training, so the code length of a byte depends on its context alone and
a tree is laid out as code lengths of the symbols seen after each context, and the cost of escaping from it.
A text costs the sum of its bytes' code lengths; the cheapest language wins, ties go to the smaller name.

Defined results: null texts and texts without a letter give ``und`` and score 0; an empty training
set gives ``und`` for all; very long texts are scored whole in slices; extra columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from . import common

RESULT = T.StructType([T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])
SLICE = 1 << 18


@dataclass
class ContextTrees:
    """Frozen statistics of all languages, as sparse trees.

    ``symbols`` maps a byte to its symbol (bytes never trained share one); ``three``, ``two`` and ``one``
    map packed contexts to nodes, -1 where the context was not kept; ``places[node, symbol]`` is the row of
    ``bits`` with the symbol's code lengths in all languages. A symbol that no language has seen after a node has
    none (-1): it costs the node's ``escape`` and then what it costs in the node ``below``. Only ``bits`` and
    ``escape`` have a column for a language, so the trees grow with what was seen, not with its product
    with the number of symbols.
    """

    languages: list[str]
    symbols: np.ndarray
    size: int
    three: np.ndarray
    two: np.ndarray
    one: np.ndarray
    places: np.ndarray
    bits: np.ndarray
    escape: np.ndarray
    below: np.ndarray

    def nodes(self, p3: np.ndarray, p2: np.ndarray, p1: np.ndarray) -> np.ndarray:
        """The longest kept context of each byte."""
        pair = p2 * self.size + p1
        node = self.three[p3 * self.size * self.size + pair]
        node = np.where(node >= 0, node, self.two[pair])
        return np.where(node >= 0, node, self.one[p1])

    def costs(self, node: np.ndarray, now: np.ndarray) -> np.ndarray:
        """Bits of symbols after nodes under each language, escapes included."""
        at = self.places[node, now]
        cost = self.bits[at]
        open_ = np.flatnonzero(at < 0)
        cost[open_] = 0
        while len(open_):
            cost[open_] += self.escape[node[open_]]
            node[open_] = self.below[node[open_]]
            at = self.places[node[open_], now[open_]]
            found = at >= 0
            cost[open_[found]] += self.bits[at[found]]
            open_ = open_[~found]
        return cost

    def code_lengths(self, raw: np.ndarray, offs: np.ndarray) -> np.ndarray:
        """Bits of each row of a byte column under each language."""
        total = np.zeros((len(offs) - 1, len(self.languages)))
        pad = int(self.symbols[32])
        for lo in range(0, len(raw), SLICE):
            hi = min(lo + SLICE, len(raw))
            back = max(0, lo - 3)
            s = self.symbols[raw[back:hi]]
            s = np.concatenate([np.full(3 - (lo - back), pad, np.int32), s])
            first, last = np.searchsorted(offs, lo, "right") - 1, np.searchsorted(offs, hi, "left")
            p1, p2, p3, now = s[2:-1].copy(), s[1:-2].copy(), s[:-3].copy(), s[3:]
            begins = np.unique(offs[first:last])
            for k, prev in ((1, (p1, p2, p3)), (2, (p2, p3)), (3, (p3,))):
                at = begins + (k - 1) - lo
                at = at[(at >= 0) & (at < hi - lo)]
                for x in prev:
                    x[at] = pad
            cost = self.costs(self.nodes(p3, p2, p1), now)
            edges = np.clip(offs[first : last + 1], lo, hi) - lo
            rows = np.flatnonzero(edges[1:] > edges[:-1])
            if len(rows):
                total[first + rows] += np.add.reduceat(cost.astype(np.float64), edges[rows], axis=0)
        return total

    def predict(self, column: pa.Array) -> pa.StructArray:
        raw, offs = common.utf8_view(column)
        known = np.fromiter((common.has_letter(x) for x in common.byte_rows(column)), bool, len(column)) & bool(self.languages)
        if not self.languages:
            return pa.StructArray.from_arrays([pa.array(["und"] * len(column), pa.string()), pa.array(np.zeros(len(column)))], ["lang_pred", "score"])
        bits = self.code_lengths(raw, offs)
        best = bits.argmin(axis=1)
        gap = np.minimum(bits - bits[np.arange(len(best)), best][:, None], 1000.0)
        score = np.where(known, 1.0 / np.exp2(-gap).sum(axis=1), 0.0)
        names = np.where(known, np.array(self.languages, object)[best], "und")
        return pa.StructArray.from_arrays([pa.array(names, pa.string()), pa.array(score)], ["lang_pred", "score"])


def _grouped(key: np.ndarray, n: int, weights: np.ndarray) -> np.ndarray:
    return np.bincount(key, weights, n) if len(key) else np.zeros(n)


def train(texts: dict[str, list[bytes]], max_contexts: int = 20_000) -> ContextTrees:
    """Context trees from sample texts by language; the ``max_contexts`` most frequent three-byte contexts are kept."""
    langs = sorted(texts)
    streams = {k: np.frombuffer(b"".join(b"   " + t for t in texts[k]), np.uint8) for k in langs}
    used = np.unique(np.concatenate([np.frombuffer(b" ", np.uint8), *streams.values()]))
    a = len(used) + 1
    symbols = np.full(256, a - 1, np.int32)
    symbols[used] = np.arange(a - 1)
    merged = 256 - len(used)
    # The driver trains: a place of the stream takes two bytes, and what is derived from it is made for one language at a time.
    grams = {k: symbols[streams.pop(k)].astype(np.int16) for k in langs}
    wide = np.int32 if a * max(a * a, a + 2 * max_contexts + 1) < 1 << 31 else np.int64

    def pack(s: np.ndarray, n: int) -> np.ndarray:
        """Contexts of n symbols before each symbol from n on."""
        out = s[: len(s) - n].astype(wide)
        for i in range(1, n):
            out *= a
            out += s[i : len(s) - n + i]
        return out

    seen3 = [np.unique(pack(s, 3), return_counts=True) for s in grams.values() if len(s) > 3]
    keys = np.concatenate([k for k, _ in seen3]).astype(np.int64) if seen3 else np.zeros(0, np.int64)
    kept, where = np.unique(keys, return_inverse=True)
    weight = np.bincount(where, np.concatenate([c for _, c in seen3])) if seen3 else np.zeros(0)
    kept = np.sort(kept[np.lexsort((kept, -weight))[:max_contexts]])
    pairs = np.unique(np.concatenate([kept % (a * a), *[np.unique(pack(s, 2)) for s in grams.values() if len(s) > 2]]))
    pairs = pairs if len(pairs) <= max_contexts else np.unique(kept % (a * a))
    one, two, three = np.arange(a, dtype=np.int32), np.full(a * a, -1, np.int32), np.full(a**3, -1, np.int32)
    two[pairs] = a + np.arange(len(pairs))
    three[kept] = a + len(pairs) + np.arange(len(kept))
    # Nodes: contexts of one, two and three bytes, then the empty context, the root of all.
    nodes = a + len(pairs) + len(kept) + 1
    root = nodes - 1
    below = np.full(nodes, root, np.int32)
    below[a : a + len(pairs)] = pairs % a
    below[a + len(pairs) : root] = two[kept % (a * a)]
    # Entries: (node, symbol) that some language has seen; the root has all symbols.
    counted = {}
    for k, s in grams.items():
        parts = []  # nodes of longer contexts come after those of shorter ones, the root last
        for n, index in ((1, one), (2, two), (3, three)):
            if len(s) > n:
                at = index[pack(s, n)].astype(wide, copy=False)
                there = at >= 0
                at *= a
                at += s[n:]
                parts.append(np.unique(at[there], return_counts=True))
        parts.append((root * a + np.arange(a), np.bincount(s, minlength=a)))
        counted[k] = tuple(np.concatenate(x) for x in zip(*parts))
    entries = np.unique(np.concatenate([np.arange(root * a, root * a + a), *(f for f, _ in counted.values())]))
    places = np.full((nodes, a), -1, np.int32)
    node, symbol = entries // a, entries % a
    places[node, symbol] = np.arange(len(entries))
    base = np.full(a, 1 / 256)
    base[-1] = merged / 256
    escape = np.zeros((nodes, len(langs)), np.float32)
    bits = np.zeros((len(entries), len(langs)), np.float32)
    depth = [np.arange(root, nodes), np.arange(a), np.arange(a, a + len(pairs)), np.arange(a + len(pairs), root)]
    order_of = np.empty(nodes, np.int64)
    for d, some in enumerate(depth):
        order_of[some] = d
    for j, k in enumerate(langs):
        count = np.zeros(len(entries))
        flat, n = counted[k]
        count[np.searchsorted(entries, flat)] = n
        total, kinds = _grouped(node, nodes, count), _grouped(node, nodes, (count > 0).astype(float))
        p, gone = np.zeros(len(entries)), np.ones(nodes)
        for d in range(4):
            here = np.flatnonzero(order_of[node] == d)
            x, y, c = node[here], symbol[here], count[here]
            if d == 0:
                lower = base[y]
            else:  # a symbol after the shorter context: its own entry there, or what escapes lead to
                under, lower, factor = below[x].astype(np.int64), np.zeros(len(here)), np.ones(len(here))
                open_ = np.arange(len(here))
                while len(open_):
                    at = places[under[open_], y[open_]]
                    found = at >= 0
                    lower[open_[found]] = factor[open_[found]] * p[at[found]]
                    open_ = open_[~found]
                    factor[open_] *= gone[under[open_]]
                    under[open_] = below[under[open_]]
            rest = np.maximum(1e-12, 1.0 - _grouped(x, nodes, lower * (c > 0)))
            full = kinds == a
            share = kinds / np.maximum(1, total + kinds) / rest  # what an unseen symbol's lower probability is multiplied by
            share = np.where(total > 0, share, 1.0)
            own = c / np.maximum(1, total[x] + np.where(full[x], 0, kinds[x]))
            p[here] = np.where(c > 0, own, share[x] * lower)
            gone[depth[d]] = share[depth[d]]
        escape[:, j] = -np.log2(np.maximum(gone, 1e-12))
        p = np.maximum(p, 1e-12)
        last = symbol == a - 1
        p[last] /= max(1, merged)
        bits[:, j] = -np.log2(np.maximum(p, 1e-12))
    return ContextTrees(langs, symbols, a, three, two, one, places, bits, escape, below)


@dataclass
class LanguageIdentifier:
    """Fitted identifier; ``predict(column)`` gives a struct column (lang_pred, score)."""

    trees: ContextTrees
    handle: object

    @classmethod
    def fit(cls, labelled: DataFrame, text: str = "text", lang: str = "lang", key: str = "doc_id", max_docs: int = 1500, max_bytes: int = 1_500_000) -> LanguageIdentifier:
        """Train on at most ``max_docs`` documents and about ``max_bytes`` bytes of each language.

        The sample is the documents of smallest key hash, so it does not depend on file order. These
        bounds keep the driver's share and the broadcast table of fixed size.
        """
        spark = labelled.sparkSession
        order = Window.partitionBy("l").orderBy("h", "k")
        rows = (
            labelled.select(F.col(lang).cast("string").alias("l"), F.col(text).alias("t"), F.xxhash64(F.col(key).cast("string"), F.lit(11)).alias("h"), F.col(key).cast("string").alias("k"))
            .where(F.col("l").isNotNull() & F.col("t").isNotNull() & (F.octet_length("t") <= max_bytes))
        )
        # Hashes under a limit that leaves a few times max_docs of a language: the window is small whatever the input.
        sizes = rows.groupBy("l").agg(F.count(F.lit(1)).alias("docs")).collect()
        cond = F.lit(False)
        for r in sizes:
            limit = min(2**63 - 1, int(4 * max_docs / r["docs"] * 2**64) - 2**63)
            cond = cond | ((F.col("l") == r["l"]) & (F.col("h") <= F.lit(limit)))
        few = rows.where(cond).select("l", "h", "k", F.octet_length("t").cast("long").alias("n"))
        # Keys first and texts after: the window never carries the texts.
        chosen = few.withColumn("r", F.row_number().over(order)).where(F.col("r") <= max_docs)
        chosen = chosen.withColumn("sum", F.sum("n").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow))).where(F.col("sum") <= max_bytes)
        picked = chosen.agg(F.max("h").alias("h")).first()
        texts: dict[str, list[bytes]] = {}
        if picked and picked["h"] is not None:
            limits = {r["l"]: r["h"] for r in chosen.groupBy("l").agg(F.max("h").alias("h")).collect()}
            cond = F.lit(False)
            for k, h in limits.items():
                cond = cond | ((F.col("l") == k) & (F.col("h") <= h))
            for r in rows.where(cond).select("l", "t").collect():
                texts.setdefault(r["l"], []).append(r["t"].encode())
        trees = train(texts)
        return cls(trees, common.shared(spark, trees))

    def predict(self, column: Column) -> Column:
        handle = self.handle

        @F.arrow_udf(RESULT)
        def score(texts: pa.Array) -> pa.Array:
            common.only("langid")
            return handle.value.predict(texts)

        return score(column)


def op10_language_id(spark, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir).select("doc_id", "text", "lang")
    held = F.coalesce(common.residue("doc_id", 5) == 0, F.lit(False))
    model = LanguageIdentifier.fit(docs.where(~held))
    return docs.select("doc_id", held.alias("held_out"), model.predict(F.col("text")).alias("p")).select("doc_id", "held_out", "p.lang_pred", "p.score")
