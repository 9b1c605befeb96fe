import datetime
from decimal import Decimal

import numpy as np
import pytest
from pyspark.sql import functions as F

from skewmap.operators import gates, hashing, huffman, index, measure, peeling, stats
from skewmap.operators.baselines import HashTable, ModelCodedMap, PerfectHashTable, perfect_hash, perfect_ids, ribbon_build, ribbon_get
from skewmap.operators.index import Plan, build, load_index
from skewmap.plans import planner
from skewmap.sources import tables
from skewmap.sources.keyvalue import DuplicateKeys, KeyValueSpec

SF = "/root/testdata/sf0.001"

GATES = [("xor", 2), ("fuse3", 3), ("fuse4", 1), ("bloom1", 3), ("bloom3", 5)]


def pairs(spark, values):
    return spark.createDataFrame([(i, v) for i, v in enumerate(values)], "k long, v string")


def exact(ix, df, keys=("k",), value="v"):
    return measure.mismatches(ix, df, keys, value).count() == 0


def test_hash_is_sparks(spark):
    rows = spark.range(-50, 50).select("id", F.xxhash64("id", F.lit(9).cast("long")).alias("h")).toPandas()
    assert (hashing.xxhash64(rows["id"].to_numpy(), 9).view(np.int64) == rows["h"].to_numpy()).all()


@pytest.mark.parametrize("family,param", GATES)
def test_gates_have_no_false_negatives_and_the_promised_rate(family, param):
    rng = np.random.default_rng(3)
    h = rng.integers(-(2**63), 2**63 - 1, 20_000)
    other = rng.integers(-(2**63), 2**63 - 1, 50_000)
    gate = gates.build(family, param, h)
    assert gates.probe(family, param, gate, h).all()
    from skewmap.functions.gatecost import FAMILIES

    eps = FAMILIES[family].eps(param)
    assert abs(gates.probe(family, param, gate, other).mean() - eps) < 4 * (eps * (1 - eps) / 50_000) ** 0.5 + 0.003
    bits = (len(gate) - 12) * 8 / len(h)
    assert bits <= FAMILIES[family].bits(eps) * 1.1 + 0.05
    assert len(gate) * 8 == FAMILIES[family].stored(param, len(h))  # the planner's cost is the gate's
    assert not gates.probe(family, param, gates.build(family, param, h[:0]), h).any()
    assert gates.probe(family, param, gates.build(family, param, h[:1]), h[:1]).all()


def test_registered_families_are_built_and_others_refused(spark):
    from skewmap.functions import gatecost

    with pytest.raises(ValueError):
        gates.build("cuckoo", 3, np.arange(10))
    with pytest.raises(ValueError):
        gates.build("fuse3", 0.4, np.arange(10))
    sorted_ = gatecost.GateFamily("sorted", (1,), lambda p: 1e-9, lambda e: 64.0, build=lambda p, h, seed: np.sort(h).tobytes(), probe=lambda p, g, h: np.isin(h, np.frombuffer(g, np.int64)))
    gatecost.register_gate_family(sorted_)
    curve = gatecost.register_gate_family(gatecost.GateFamily("curve", (1,), lambda p: 0.5, lambda e: 1.2))
    try:
        df = pairs(spark, ["a" if i % 9 else str(i % 4) for i in range(3000)])
        ix = build(df, KeyValueSpec(("k",), "v"), Plan(True, "sorted", 1, 1e-9, 64.0), shard_keys=800)
        assert ix.manifest.leaked == 0 and exact(ix, df)
        with pytest.raises(ValueError):
            build(df, KeyValueSpec(("k",), "v"), Plan(True, curve.name, 1, 0.5, 1.2))
    finally:
        gatecost.FAMILIES.pop("sorted")
        gatecost.FAMILIES.pop("curve")


def test_bloom_probe_as_column(spark):
    import struct

    keys = spark.range(2000).select(F.xxhash64("id").alias("h"))
    h = keys.toPandas()["h"].to_numpy()
    gate = gates.build("bloom3", 6, h[:1000])
    _, cells, _ = struct.unpack_from("<III", gate)
    raw = np.frombuffer(gate[12:] + b"\0" * (-len(gate[12:]) % 8), "<i8")
    words = F.array(*(F.lit(int(x)) for x in raw))
    got = keys.select(gates.might_contain(words, F.lit(cells), F.col("h"), 3).alias("m")).toPandas()["m"].to_numpy()
    assert (got == gates.probe("bloom3", 6, gate, h)).all()


@pytest.mark.parametrize("k,factor,words", [(3, 1.12, 2), (4, 1.06, 3), (3, 1.4, 1)])
def test_linear_systems(k, factor, words):
    rng = np.random.default_rng(1)
    sizes = [0, 1, 2, 40, 300, 300, 500]
    cells = [int(m * factor) + 14 for m in sizes]
    start = np.cumsum([0, *cells])
    at = np.array([start[b] + rng.choice(cells[b], k, replace=False) for b, m in enumerate(sizes) for _ in range(m)], np.int64)
    system, slot_system = np.repeat(np.arange(len(sizes)), sizes), np.repeat(np.arange(len(sizes)), cells)
    want = rng.integers(0, 2, len(at))
    values, solved = peeling.solve(at, want, system, slot_system, len(sizes), words)
    assert solved.sum() >= len(sizes) - 1
    assert (np.bitwise_xor.reduce(values[at], axis=1) == want)[solved[system]].all()


def test_contradictions_are_not_solved():
    at = np.array([[0, 1, 2], [0, 1, 2], [3, 4, 5], [3, 4, 5]])
    values, solved = peeling.solve(at, np.array([0, 1, 1, 1]), np.array([0, 0, 1, 1]), np.repeat([0, 1], 3), 2, 1)
    assert solved.tolist() == [False, True] and values[3:].sum() % 2 == 1
    # More cells set aside than there are bits for them: given up, not solved wrongly.
    rng = np.random.default_rng(2)
    at = np.array([rng.choice(410, 4, replace=False) for _ in range(400)])
    want = rng.integers(0, 2, 400)
    values, solved = peeling.solve(at, want, np.zeros(400, np.int64), np.zeros(410, np.int64), 1, 1)
    assert not solved[0] or (np.bitwise_xor.reduce(values[at], axis=1) == want).all()


@pytest.mark.parametrize("hashes", [3, 4])
@pytest.mark.parametrize("plan", [Plan(False), *(Plan(True, f, p, 0.2, 1.0) for f, p in GATES)], ids=lambda p: p.family or "plain")
def test_index_is_exact(spark, plan, hashes):
    values = ["a" if i % 7 else chr(98 + i % 5) for i in range(3000)]
    df = pairs(spark, values)
    ix = build(df, KeyValueSpec(("k",), "v"), plan, hashes=hashes, shard_keys=800)
    assert exact(ix, df)
    assert ix.manifest.shards > 1


@pytest.mark.parametrize("values", [[], ["x"], ["x"] * 50, [str(i) for i in range(300)], ["a"] * 150 + ["b"] * 150, [None] * 90 + ["a"] * 10, ["é", "😀", "", None, " "] * 5, [str(i) for f, i in zip([1, 1, 2, 3, 5, 8, 13, 21, 34, 55], range(10)) for _ in range(f)]], ids=["empty", "one", "constant", "unique", "tie", "null-dominant", "unicode", "fibonacci"])
@pytest.mark.parametrize("how", ["gap", "never", "always", "exhaustive", "entropy_fit"])
def test_degenerate_relations(spark, values, how):
    df = pairs(spark, values)
    if how in ("always", "entropy_fit") and not values:
        return
    ix = planner.build_index(df, KeyValueSpec(("k",), "v"), how)
    assert exact(ix, df)


def test_keys_and_values_of_many_types(spark):
    rows = [(float("nan"), None, 1), (-0.0, "x", 2), (1.5, "x", 3), (None, "x", 4), (None, None, 5)]
    df = spark.createDataFrame(rows, "a double, b string, v int")
    ix = build(df, KeyValueSpec(("a", "b"), "v"), Plan(False))
    assert exact(ix, df, ("a", "b"))
    assert ix.lookup(spark.createDataFrame([(0.0, "x")], "a double, b string")).first()["v"] == 2
    for kind, values in (
        ("decimal(18,4)", [Decimal("1.5000"), Decimal("2.2500")]), ("date", [datetime.date(2020, 1, 1), None]), ("timestamp_ntz", [datetime.datetime(2020, 1, 1, 5), datetime.datetime(2021, 1, 1)]),
        ("boolean", [True, False]), ("array<int>", [[1, 2], []]), ("struct<x:int>", [(1,), (2,)]), ("double", [1.5, float("inf")]),
    ):
        df = spark.createDataFrame([(i, values[i % 10 == 0]) for i in range(200)], f"k long, v {kind}")
        ix = build(df, KeyValueSpec(("k",), "v"), Plan(True, "xor", 2, 0.25, 2.46))
        assert ix.lookup(df.select("k")).schema["v"].dataType == df.schema["v"].dataType
        assert exact(ix, df), kind


def test_map_keys_are_refused(spark):
    df = spark.sql("select map('a', 1) as k, 1 as v")
    with pytest.raises(TypeError):
        build(df, KeyValueSpec(("k",), "v"), Plan(False))


def test_duplicate_policies(spark):
    df = spark.createDataFrame([(1, 5), (1, 7), (2, 3)], "k long, v long")
    with pytest.raises(DuplicateKeys):
        build(df, KeyValueSpec(("k",), "v"), Plan(False))
    for how, want in (("first", 5), ("sum", 12), ("max", 7)):
        ix = build(df, KeyValueSpec(("k",), "v", how), Plan(False))
        assert ix.lookup(spark.createDataFrame([(1,)], "k long")).first()["v"] == want
    with pytest.raises(ValueError):
        build(df, KeyValueSpec(("k",), "v", "other"), Plan(False))


def test_colliding_hashes_are_exceptions(spark, monkeypatch):
    from skewmap.operators import index as module

    df = spark.createDataFrame([(i, str(i % 3)) for i in range(40)], "k long, v string")
    monkeypatch.setattr(module, "key_hash", lambda d, keys, seed=0: F.xxhash64(F.floor(F.col("k") / 2)))
    ix = build(df, KeyValueSpec(("k",), "v"), Plan(False))
    assert ix.manifest.exceptions == 20
    assert exact(ix, df)


def test_repeated_probe_keys_and_uneven_shards(spark):
    df = pairs(spark, [str(i % 7) for i in range(5000)])
    ix = build(df, KeyValueSpec(("k",), "v"), Plan(False), shard_keys=900)
    asked = df.select("k").unionByName(spark.range(20_000).select(F.lit(17).cast("long").alias("k")))
    got = ix.lookup(asked)
    assert got.count() == 25_000 and got.where("k = 17 and v <> '3'").count() == 0
    assert ix.lookup(df.select("k").limit(0)).count() == 0


def test_absent_keys_get_some_value(spark):
    df = pairs(spark, ["a"] * 90 + ["b"] * 10)
    ix = planner.build_index(df, KeyValueSpec(("k",), "v"))
    got = ix.lookup(spark.range(10_000, 10_050).select(F.col("id").alias("k")))
    assert got.count() == 50
    with pytest.raises(ValueError):
        ix.lookup(df.select("k"), absent="null")


def test_save_and_load(spark, tmp_path):
    df = pairs(spark, ["a" if i % 9 else "b" for i in range(2000)])
    ix = planner.build_index(df, KeyValueSpec(("k",), "v"), "always", ("xor",))
    ix.save(f"file://{tmp_path}/ix")
    again = load_index(spark, f"file://{tmp_path}/ix")
    assert again.manifest == ix.manifest
    assert exact(again, df)
    from skewmap.sources import sqlfunctions

    sqlfunctions.register(spark)
    rows = spark.read.format("skewmap").load(f"{tmp_path}/ix").collect()
    assert sum(r["keys"] for r in rows) == 2000 and sum(r["map_bytes"] for r in rows) > 0


def test_building_is_deterministic(spark):
    df = pairs(spark, ["a" if i % 9 else str(i % 4) for i in range(3000)])
    a, b = (build(d, KeyValueSpec(("k",), "v"), Plan(True, "fuse3", 2, 0.25, 2.25)).shards.orderBy("shard").select("shard", "gate", "cells").collect() for d in (df.repartition(1), df.repartition(7)))
    assert a == b


def test_sizes_are_near_the_model(spark):
    df, keys, value = tables.workload(spark, "/root/testdata/sf0.01", "part_supp")
    spec = KeyValueSpec(tuple(keys), value)
    plan = planner.gap_plan(stats.profile(df, value), ("xor",))
    ix = build(df, spec, plan)
    got = {r["part"]: r["bpk"] for r in ix.measured_bits().collect()}
    runs = huffman.collect_runs(stats.freq_of_freq(stats.value_histogram(df, value)))
    want = {r["part"]: r["bpk"] for r in measure.model_bits_frame(spark, runs, plan).collect()}
    assert got["gate"] + got["map"] == pytest.approx(want["gate"] + want["map"], rel=0.1)
    assert measure.observed_fpr(ix) == pytest.approx(plan.eps, abs=0.02)
    plain = build(df, spec, Plan(False))
    assert measure.savings(plain, ix) > 0
    row = measure.lookup_latency(ix, df.select(*keys), 1).first()
    assert row["job_ns"] > 0 and row["in_shard_ns"] > 0


@pytest.mark.parametrize("name", ["lang", "toxic", "part_supp", "role", "doc_quality"])
@pytest.mark.parametrize("method", [HashTable, PerfectHashTable, ModelCodedMap])
def test_baselines_are_exact(spark, name, method):
    df, keys, value = tables.workload(spark, SF, name)
    ix = method.build(df, KeyValueSpec(tuple(keys), value))
    assert exact(ix, df, keys, value)
    assert measure.total_bpk(ix) > 0


def test_model_learns_a_correlation(spark):
    letters = "acgt"
    rows = [("".join(letters[(i >> (2 * j)) & 3] for j in range(6)), int((i & 3) == 0)) for i in range(4096)]
    df = spark.createDataFrame(rows, "k string, v int")
    from skewmap.operators.baselines import ordinal_features

    spec = KeyValueSpec(("k",), "v")
    seen = ModelCodedMap.build(df, spec, ((50,),), ordinal_features(F.col("k"), 6), 6)
    assert exact(seen, df)


def test_escaped_symbols(spark):
    df = spark.createDataFrame([(i, i % 90) for i in range(900)], "k long, v long")
    ix = ModelCodedMap.build(df, KeyValueSpec(("k",), "v"))
    assert exact(ix, df)
    # More values than the model has symbols, and most keys under the escape.
    df = spark.createDataFrame([(i, max(0, i - 900)) for i in range(2000)], "k long, v long")
    ix = ModelCodedMap.build(df, KeyValueSpec(("k",), "v"), ((), (50,)))
    assert ix.extra and exact(ix, df)


def test_perfect_hash_is_a_bijection():
    h = np.random.default_rng(5).integers(-(2**63), 2**63 - 1, 5000)
    ids = perfect_ids(*perfect_hash(h), h)
    assert sorted(ids.tolist()) == list(range(5000))


def test_ribbon():
    h = np.random.default_rng(6).integers(-(2**63), 2**63 - 1, 3000)
    bits = (h & 1).astype(np.uint8)
    assert (ribbon_get(ribbon_build(h, bits), h) == bits).all()
    assert (ribbon_get(b"", h) == 0).all()


def test_filter_equals(spark):
    df = pairs(spark, ["a" if i % 9 else "b" for i in range(500)])
    ix = planner.build_index(df, KeyValueSpec(("k",), "v"), "always", ("xor",))
    assert {r["k"] for r in ix.filter_equals(df.select("k"), "b").collect()} == set(range(0, 500, 9))


def test_plans_have_no_row_python_and_no_product(spark):
    df, keys, value = tables.workload(spark, SF, "lang")
    text = planner.plan_frame(stats.profile_frame(df, value), spark)._jdf.queryExecution().toString()
    assert "BatchEvalPython" not in text and "CartesianProduct" not in text
    ix = planner.build_index(df, KeyValueSpec(tuple(keys), value))
    text = ix.lookup(df.select(*keys))._jdf.queryExecution().executedPlan().toString()
    assert "BatchEvalPython" not in text and "CartesianProduct" not in text
    assert "ReadSchema: struct<doc_id:bigint>" in text


def test_planners_on_the_given_tables(spark):
    want = {"toxic": True, "quality": True, "lang": False, "lines_per_order": False, "part_supp": True, "user_hour": True}
    for name, gate in want.items():
        df, keys, value = tables.workload(spark, "/root/testdata/sf0.01", name)
        assert planner.gap_plan(stats.profile(df, value)).use_gate is gate, name
    df, _, value = tables.workload(spark, "/root/testdata/sf0.01", "lang")
    h = stats.entropy(stats.value_histogram(df, value)).first()["entropy"]
    assert planner.entropy_fit_plan(stats.profile(df, value), h).use_gate


def test_ranking_by_partitions_equals_one_window(spark, monkeypatch):
    hist = spark.createDataFrame([(str(i), i % 7 + 1) for i in range(500)] + [(None, 3)], "value string, freq long")
    one = {r["value"]: r["rank"] for r in huffman.ranked_values(hist, 501).collect()}
    monkeypatch.setattr(huffman, "SMALL", 10)
    many = {r["value"]: r["rank"] for r in huffman.ranked_values(hist, 501).collect()}
    assert one == many and sorted(one.values()) == list(range(501))


def test_sketch_profile_is_on_the_safe_side(spark):
    df = spark.range(50_000).select(F.when(F.col("id") % 10 < 9, 0).otherwise(F.col("id") % 97).alias("v"))
    a, b = stats.profile(df, "v"), stats.sketch_profile(df, "v", 0.1)
    assert b.alpha <= a.alpha and b.distinct_values >= a.distinct_values and b.alpha > a.alpha - 0.05


def test_exhaustive_measured(spark):
    df = pairs(spark, ["a" if i % 12 else "b" for i in range(4000)])
    plan, tried = planner.exhaustive_measured(df, KeyValueSpec(("k",), "v"), ("xor",))
    assert plan.use_gate and len(tried) == 9
    assert index.model_bits([(10, 1)])["map"] == 0
