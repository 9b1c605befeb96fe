"""bpk_table (F1, time): shards of small relations are built side by side, codes are made once for keys with the same odds."""

from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from skewmap import queries
from skewmap.operators import baselines, dealing, index
from skewmap.sources.keyvalue import KeyValueSpec

SF = "/root/testdata/sf0.001"
SPEC = KeyValueSpec(("k",), "v")


def _files(df) -> int:
    return len(list(Path(df._stored_at.removeprefix("file://")).glob("*.parquet")))


@pytest.fixture
def made(monkeypatch):
    """Stored tables by name."""
    found, real = {}, index.stored

    def stored(df, name="step", **options):
        out = real(df, name, **options)
        found.setdefault(name, out)
        return out

    for module in (index, baselines):
        monkeypatch.setattr(module, "stored", stored)
    return found


def test_shards_are_built_in_tasks_of_their_own(spark, made):
    """Four shards of a few bytes are four tasks for gates and maps, not one: each task writes a file."""
    df = spark.range(4000).select(F.col("id").alias("k"), F.when(F.col("id") % 5 == 0, F.col("id") % 9).otherwise(0).alias("v"))
    ix = index.build(df, SPEC, index.Plan(True, "fuse3", 2, 0.25, 2.25), shard_keys=1000)
    assert ix.manifest.shards == 4
    assert _files(made["gates"]) == _files(made["shards"]) == 4
    assert ix.lookup(df.select("k")).exceptAll(df).count() == 0


@pytest.mark.parametrize("method, name", [(baselines.PerfectHashTable, "perfect"), (baselines.best_model, "model")])
def test_shards_of_the_other_methods_too(spark, made, monkeypatch, method, name):
    monkeypatch.setattr(baselines, "SHARD_KEYS", 1000)
    df = spark.range(3000).select(F.col("id").alias("k"), (F.col("id") % 300 * (F.col("id") % 4)).alias("v"))
    ix = getattr(method, "build", method)(df, SPEC)
    assert _files(made[name]) == 3
    assert ix.lookup(df.select("k")).exceptAll(df).count() == 0
    assert ix.lookup(spark.range(-5, 5).select(F.col("id").alias("k"))).count() == 10


def test_by_shard_hands_over_whole_shards(spark):
    """Shards over many batches and several in a task."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        rows = spark.range(1000).select((F.col("id") % 9).alias("shard"), "id")

        def run(t):
            return t.slice(0, 1).select(["shard"]).append_column("n", [[t.num_rows]]).append_column("different", [[len(set(t.column("shard").to_pylist()))]])

        got = dealing.by_shard(rows, 9, run, "shard long, n long, different long").collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert sorted((r["shard"], r["n"], r["different"]) for r in got) == [(i, 112 if i == 0 else 111, 1) for i in range(9)]


def test_codes_are_made_once_for_a_model_without_weights():
    rng = np.random.default_rng(5)
    x = rng.integers(0, 2, (300, 8)).astype(np.float32)
    blank = baselines.Network(((rng.normal(size=(8, 4)).astype(np.float16), np.zeros(4, np.float16)), (np.zeros((4, 20), np.float16), rng.normal(size=20).astype(np.float16))))
    real = baselines.Network(((rng.normal(size=(8, 20)).astype(np.float16), rng.normal(size=20).astype(np.float16)),))
    for net, rows in ((blank, 1), (real, 300)):
        odds, like = baselines._key_odds(net, x)
        assert len(odds) == rows and (odds[like] == baselines._odds(net.scores(x))).all()
        symbol = rng.integers(0, 20, 300)
        length = baselines.key_codes(odds, baselines._guesses(odds, 0), 1)
        size, word = baselines._codeword(length, like, symbol)
        for i in range(300):
            by_size = sorted(range(20), key=lambda s: (length[like[i], s], s))
            at = by_size.index(symbol[i])
            assert size[i] == length[like[i], symbol[i]]
            assert word[i] == sum(2 ** int(size[i] - length[like[i], s]) for s in by_size[:at])


def test_ribbons_stand_end_to_end():
    h = np.unique(np.random.default_rng(2).integers(-(2**62), 2**62, 3000))
    for n in (1, 3):
        parts = baselines.ribbon_filter(h, n)
        assert baselines.ribbons_apart(b"".join(parts), n) == parts
    assert baselines.ribbons_apart(b"", 2) == [b"", b""] == baselines.ribbon_filter(h[:0], 2)
    # Bits are the parity of the band under the coefficients, at the last column, too.
    data = parts[0]
    columns = int(np.frombuffer(data, "<u4", 2)[1])
    bits = np.unpackbits(np.frombuffer(data, np.uint8, offset=8), bitorder="little", count=columns)
    some = np.random.default_rng(3).integers(-(2**62), 2**62, 5000)
    start, coeff = baselines._ribbon(some, int(np.frombuffer(data, "<u4", 1)[0]), columns)
    want = [sum(int(bits[s + j]) for j in range(64) if c >> j & 1) & 1 for s, c in zip(start.tolist(), coeff.tolist())]
    assert baselines.ribbon_get(data, some).tolist() == want


def test_the_comparison_leaves_no_tables(spark, made):
    rows = queries.method_table(spark, SF, ("uniform100_0.8",)).collect()
    assert [r["method"] for r in rows] == list(queries.METHODS) and all(r["mismatches"] == 0 and r["bpk"] > 0 for r in rows)
    assert {"shards", "perfect", "model"} <= set(made)
    assert not any(Path(x._stored_at.removeprefix("file://")).exists() for x in made.values())


def test_plans_do_not_carry_the_lineage_of_a_workload(spark, monkeypatch):
    """Driver memory: what methods get is a stored table, not the plan that made it."""
    plans, real = [], baselines.HashTable.build.__func__
    monkeypatch.setattr(baselines.HashTable, "build", classmethod(lambda cls, df, spec: plans.append(df._jdf.queryExecution().toString()) or real(cls, df, spec)))
    assert queries.method_table(spark, SF, ("zipf_0.8",), ("hash_table",)).first()["mismatches"] == 0
    assert len(plans) == 1 and "InMemoryRelation" not in plans[0] and "Join" not in plans[0]
