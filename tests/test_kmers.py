"""K-mers that are counted by buckets, against counting one by one."""

import random
import tracemalloc
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from conftest import SF

from skewmap import queries
from skewmap.operators import kmertally
from skewmap.sources import tables


def brute(texts, k):
    return Counter(t[i : i + k] for t in texts if t for i in range(len(t) - k + 1))


@pytest.mark.parametrize("k", [1, 2, 3, 5, 8, 9, 12, 15, 16, 17, 31])
def test_counts(spark, monkeypatch, k):
    r = random.Random(k)
    many = "".join(chr(c) for c in (*range(0, 128), *range(0xE0, 0x180), 0x4E00, 0x1F600, 0x10FFFF))
    texts = [None, "", "a", "ab" * 40, "a" * 500, "".join(r.choices(many, k=900)), "".join(r.choices("acgt", k=700))]
    texts += ["".join(r.choices("ab ", k=r.randrange(60))) for _ in range(50)]
    df = spark.createDataFrame([(t,) for t in texts], "t string")
    assert {x["kmer"]: x["n"] for x in tables.kmer_counts(df, "t", k).collect()} == brute(texts, k)


@pytest.mark.parametrize("k", [3, 8, 12, 31])
def test_small_chunks_and_sides(k):
    """Counts that are joined, alphabets that grow past 256 letters, texts that are cut."""
    r = random.Random(k)
    parts = [["".join(r.choices("abc", k=200)) for _ in range(4)] + ["".join(chr(0x100 + x) for x in range(i * 90, i * 90 + 90)) for i in range(5)] for _ in range(2)]
    here = kmertally._Bucket(k, True)
    old, kmertally.CHUNK = kmertally.CHUNK, 300
    try:
        for side, texts in zip((False, True), parts):
            for t in texts:
                chars = np.frombuffer(t.encode("utf-32-le"), np.uint32)
                here.add(side, np.array([len(t) - k + 1], np.uint32), chars)
        got = {x["kmer"]: (x["n"], x["n_side"]) for b in here.result() for x in b.to_pylist()}
    finally:
        kmertally.CHUNK = old
    both, there = brute(parts[0] + parts[1], k), brute(parts[1], k)
    assert got == {x: (n, there[x]) for x, n in both.items()}


def test_equal_hashes_are_told_apart(monkeypatch):
    """With a hash that is always the same, rows are still counted by their words."""
    monkeypatch.setattr(kmertally, "_ODD", np.uint64(0))
    words = [np.array([5, 6, 5, 5, 6, 7], np.uint64), np.zeros(6, np.uint64)]
    got, (n, _) = kmertally._tally(words, [None, None])
    assert dict(zip(got[0].tolist(), n.tolist())) == {5: 3, 6: 2, 7: 1}


def test_one_long_text(spark):
    """A text of two million characters: passing over all of it for each k-mer would take hours."""
    text = "".join(random.Random(0).choices("abcdefgh ", k=2_000_000))
    df = spark.createDataFrame([(text,)], "t string")
    assert tables.kmers(df, "t", 12).count() == len(text) - 11
    assert tables.kmer_counts(df, "t", 12).count() == len({text[i : i + 12] for i in range(len(text) - 11)})


def test_memory_of_cutting_and_counting():
    """kmer12_counts (F20): a worker's arrays are some 30 times a slice of text at most, and what comes out is whole."""
    rng = np.random.default_rng(1)
    text = rng.integers(97, 123, kmertally.SLICE - 1).astype(np.uint8)
    text[::50] = 0xE4
    batch = pa.RecordBatch.from_arrays([pa.array([text.tobytes().decode("latin-1")]), pa.array([False])], names=["text", "side"])
    cut = kmertally._cutter(12, 300)
    list(cut([batch.slice(0, 0)]))
    tracemalloc.start()
    try:
        runs = list(cut([batch]))
        assert tracemalloc.get_traced_memory()[1] < 30 * kmertally.SLICE
        tracemalloc.reset_peak()
        whole = pa.Table.from_batches(runs).sort_by("bucket").to_batches()
        assert sum(sum(b.column("n").to_pylist()) for b in kmertally._counter(12, False)(iter(whole))) == len(text) - 11
    finally:
        tracemalloc.stop()


@pytest.mark.parametrize("name", ["kmer12", "fold10"])
def test_histograms_are_tallied_in_the_workers(spark, name):
    """F15 to F19: a histogram of counts makes no row for each k-mer, and is that of the counts."""
    made = queries.queries()[f"histogram_{name}"](spark, SF)
    assert "kmer" not in made._jdf.queryExecution().executedPlan().toString()
    counts, _, n = tables.workload(spark, SF, name)
    want = Counter(r[n] for r in counts.collect())
    assert {r["value"]: r["freq"] for r in made.collect()} == want and made.columns == ["value", "freq"]
    bits = queries.queries()[f"huffman_bits_{name}"](spark, SF).first()
    assert bits["num_keys"] == sum(want.values())
    plan = queries.queries()[f"gap_plan_{name}"](spark, SF)
    assert plan.count() == 1


def test_histogram_of_nothing(spark):
    df = spark.createDataFrame([(None,), ("",), ("short",)], "t string")
    assert kmertally.histogram(df, "t", 12).collect() == []
