import datetime

import pytest
from pyspark.sql import functions as F

from skewmap import queries
from skewmap.operators import baselines, joins
from skewmap.operators.stats import Profile
from skewmap.plans import planner, sweep
from skewmap.sources import sqlfunctions, tables
from skewmap.sources.keyvalue import KeyValueSpec
from skewmap.streaming import drift

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def cells(spark):
    return sweep.sweep(spark, 20_000, alphas=[0.5, 0.6, 0.66, 0.7, 0.75, 0.8, 0.9, 0.97]).cache()


def test_every_cell_is_within_its_bounds(cells):
    for r in sweep.containment(cells).collect():
        assert sum(v for k, v in r.asDict().items() if k.startswith(("below", "above"))) == 0


def test_a_gate_never_harms_and_little_is_forgone(cells):
    for r in sweep.decision_confusion(cells).collect():
        assert r["gated_harm"] == 0
        if r["dist"] == "unique" and r["family"] == "xor":
            assert 0.69 <= r["forgone_from"] and r["forgone_to"] <= 0.81 and r["forgone_most"] <= 0.2


def test_regret_is_small(cells):
    r = sweep.parameter_regret(cells).agg(F.max("regret"), F.max("steps")).first()
    assert r[0] <= 0.02 and r[1] <= 1


def test_the_heuristic_harms(spark):
    r = sweep.heuristic_harm(spark, 20_000, [0.5, 0.6, 0.7]).agg(F.min("saving")).first()[0]
    assert -1.05 < r < 0


def test_upper_bound_looseness(cells):
    t = sweep.tightness(cells).agg(F.bool_and("contained"), F.min("lower_slack")).first()
    assert t[0] and t[1] >= -1e-9


def test_registered_sweeps_hold_every_share_and_key(spark):
    q = queries.queries()
    got = q["alpha_sweep_model"](spark, SF).cache()
    assert {r[0] for r in got.select("alpha").distinct().collect()} == set(sweep.ALPHAS) and got.count() == 3 * (400 + 400 + 800 + 800)
    # A value of its own for each minority key and one dominant value: the ratio tells the number of keys.
    assert got.where("dist = 'unique' AND alpha = 0.5").agg(F.min("ratio"), F.max("ratio")).first()[:] == (50_001 / 100_000,) * 2
    assert {tuple(r)[2:] for r in q["bounds_containment_all"](spark, SF).collect()} == {(400, 0), (800, 0)}
    assert {round(100 * r["crossing"]) % 5 for r in q["crossing_alpha"](spark, SF).collect()} != {0}


def test_methods_are_compared_on_all_workloads(spark, monkeypatch):
    asked = []

    def table(spark, sf_dir, workloads, methods=queries.METHODS, repeats=1):
        asked.append((set(workloads), set(methods)))
        return spark.createDataFrame([("w", "gap", 1.0, 1.0, 1.0, 0), ("w", "model_coded", 2.0, 0.5, 2.0, 0)], "workload string, method string, bpk double, ns double, build_s double, mismatches long")

    monkeypatch.setattr(queries, "method_table", table)
    q = queries.queries()
    assert [q[n](spark, SF).count() for n in ("bpk_table", "pareto_front", "ratio_table")] == [2, 2, 2]
    cells = {f"{d}_{a}" for d in ("unique", "zipf", "uniform100") for a in (0.5, 0.8, 0.95)}
    for workloads, methods in asked:
        assert workloads >= cells | {"part_supp", "kmer12"} and len(methods) == 5
    assert {"gap_plan_kmer12", "lookup_gap_planned_kmer12"} <= set(q)


def test_model_coded_rows_take_the_best_architecture(spark, monkeypatch):
    made = []
    build = baselines.ModelCodedMap.build.__func__
    monkeypatch.setattr(baselines.ModelCodedMap, "build", classmethod(lambda cls, df, spec, arches=((),), *a, **k: made.append(arches) or build(cls, df, spec, arches, *a, **k)))
    got = queries.method_table(spark, SF, ("uniform100_0.95",), ("model_coded",)).collect()
    assert made == [baselines.ARCHES] and got[0]["mismatches"] == 0


def test_measured_sweep_is_what_is_built(spark):
    """Sizes of measured cells against indexes that are really built."""
    from skewmap.operators import index, measure
    from skewmap.operators.index import Plan
    from skewmap.sources.keyvalue import KeyValueSpec

    keys = tables.table(spark, "/root/testdata/sf0.01", "events", "event_id")
    cells = {(r["dist"], r["family"], r["param"]): r for r in sweep.measured_sweep(keys, "event_id", (0.8,)).collect()}
    for dist, family, param in (("zipf", "fuse3", 2), ("unique", "xor", 3), ("uniform100", "bloom3", 5)):
        df = tables.synthetic(keys, "event_id", 0.8, dist)
        made = index.relation(df, KeyValueSpec(("key",), "value"))
        plain = index.build_relation(made, Plan(False))
        gated = index.build_relation(made, Plan(True, family, param, cells[dist, family, param]["eps"]))
        assert gated.manifest.leaked == cells[dist, family, param]["leaked"]
        # Buckets whose first seeds are singular have a little more space.
        assert measure.savings(plain, gated) == pytest.approx(cells[dist, family, param]["saving"], abs=0.003)


def test_planner_never_harms_what_is_built(spark):
    keys = tables.table(spark, "/root/testdata/sf0.01", "events", "event_id")
    alphas = tuple(round(0.6 + 0.02 * i, 2) for i in range(20))
    cells = sweep.measured_sweep(keys, "event_id", alphas, families=("xor", "fuse3", "fuse4", "bloom1", "bloom3")).cache()
    assert all(r["gated_harm"] == 0 for r in sweep.decision_confusion(cells).collect())
    late = sweep.panels(cells).where("chosen.lower > 0").select("chosen.saving", "chosen.lower").collect()
    assert late and all(r["saving"] >= r["lower"] - 0.01 for r in late)
    points = sweep.epsilon_points(keys, "event_id", (0.9,), points=6).groupBy("dist", "kind").count().collect()
    assert {(r["dist"], r["kind"]) for r in points} == {(d, k) for d in sweep.DISTRIBUTIONS for k in ("measured", "continuous", "optimum")}


def test_sessions_are_by_time(spark):
    from skewmap.streaming import drift

    rows = [(0, "a"), (10, "b"), (20, "a"), (1820, "c"), (1819, "a"), (9000, "a")]
    df = spark.createDataFrame(rows, "s long, v string").select(F.timestamp_seconds("s").alias("ts"), "v")
    got = sorted((r["num_keys"], r["distinct_values"], r["dominant_count"]) for r in drift.session(df, "v").collect())
    assert got == [(1, 1, 1), (5, 3, 3)]
    by = drift.session(df.withColumn("u", F.lit(1)), "v", by=("u",)).select(*drift.session(df, "v").columns)
    assert sorted(map(tuple, by.collect())) == sorted(map(tuple, drift.session(df, "v").collect()))


def test_lookup_as_a_sql_function(spark):
    from skewmap.plans import planner
    from skewmap.sources import sqlfunctions
    from skewmap.sources.keyvalue import KeyValueSpec

    df = spark.createDataFrame([(i, f"n{i % 3}", i % 7) for i in range(500)], "a long, b string, v long")
    sqlfunctions.register_lookup(spark, "price_of", planner.build_index(df, KeyValueSpec(("a", "b"), "v")))
    df.createOrReplaceTempView("asked")
    assert spark.sql("select count(*) from asked where price_of(a, b) <> cast(v as string)").first()[0] == 0
    assert spark.sql("select price_of(bigint(8), 'n2')").first()[0] == "1"


def test_synthetic_shares_are_exact(spark):
    keys = tables.table(spark, SF, "events", "event_id")
    for dist, values in (("unique", 201), ("uniform100", 101), ("zipf", None)):
        df = tables.synthetic(keys, "event_id", 0.8, dist)
        assert df.count() == 1000 and df.where("value = 0").count() == 800
        if values:
            assert df.select("value").distinct().count() == values
    with pytest.raises(ValueError):
        tables.synthetic(keys, "event_id", 0.8, "other")


def test_readers(spark, tmp_path):
    (tmp_path / "p.csv").write_text("1,a\n2,b\n")
    assert tables.read_pairs(spark, f"file://{tmp_path}/p.csv", "csv", "k long, v string").count() == 2
    (tmp_path / "s.fa").write_text(">one\nacg\nt\n\n>two\nggg\n")
    assert [r["sequence"] for r in tables.read_sequences(spark, f"file://{tmp_path}/s.fa").orderBy("record").collect()] == ["acgt", "ggg"]
    df = spark.createDataFrame([("acgt",), ("ac",), (None,)], "t string")
    assert sorted(r["kmer"] for r in tables.kmers(df, "t", 3).collect()) == ["acg", "cgt"]
    assert sorted(r["kmer"] for r in tables.kmers(df, "t", 3, True).collect()) == ["acg", "acg"]


def test_asof(spark):
    t = lambda h: datetime.datetime(2024, 1, 1, h)
    e = spark.createDataFrame([(1, "a", t(1)), (2, "a", t(5)), (3, "b", t(5)), (4, "a", t(3))], "id long, u string, ts timestamp")
    c = spark.createDataFrame([("a", t(3), 10), ("a", t(4), None), ("c", t(1), 5)], "u string, ts timestamp, v int")
    assert {r["id"]: r["as_of"] for r in joins.asof(e, c, "u", "ts", "v").collect()} == {1: None, 2: None, 3: None, 4: 10}


def test_version_diff(spark):
    a = spark.createDataFrame([(1, "x"), (2, "y"), (3, None)], "k long, v string")
    b = spark.createDataFrame([(1, "x"), (3, "z"), (4, "w")], "k long, v string")
    assert {(r["k"], r["change"]) for r in joins.version_diff(a, b, ("k",), "v").collect()} == {(2, "removed"), (3, "changed"), (4, "added")}


def test_sql_functions(spark):
    sqlfunctions.register(spark)
    assert spark.sql("select sm_lower_bound(0.9, 0.25, 2.46, 0.01)").first()[0] == pytest.approx(0.9 * 1.089 * 0.75 - 0.1 * 2.46 - 0.01)
    assert spark.sql("select count(*) from gate_settings('xor')").first()[0] == 8
    r = spark.sql("select t.a, p.use_gate, p.param from values (0.9D), (0.5D) t(a), lateral plan_skewmap(t.a, 10, 10000, 'fuse3') p order by 1").collect()
    assert [x["use_gate"] for x in r] == [False, True]
    assert spark.sql("select count(*) from kmers('abcdef', 4)").first()[0] == 3
    r = spark.sql("select huffman_bits(f), empirical_entropy(f) from values (1L), (1L), (2L) t(f)").first()
    assert r[0] == 6 and r[1] == pytest.approx(1.5)


def test_stream_windows_equal_batch_and_late_rows_go(spark, tmp_path):
    e = tables.table(spark, SF, "events", "ts", "event_type").withColumn("ts", F.col("ts").cast("timestamp"))
    e.repartition(1).sortWithinPartitions("ts").write.parquet(f"{tmp_path}/in")
    batch = {(r["start"], r["value"]): r["freq"] for r in drift.tumbling(e, "event_type").collect()}
    stream = spark.readStream.schema(e.schema).parquet(f"{tmp_path}/in")
    q = drift.tumbling(stream, "event_type").writeStream.outputMode("complete").format("memory").queryName("drift_all").start()
    q.processAllAvailable()
    q.stop()
    assert {(r["start"], r["value"]): r["freq"] for r in spark.table("drift_all").collect()} == batch
    assert drift.drift(drift.sliding(e, "event_type")).count() > 0


def run_stream(spark, frame, name):
    frame.writeStream.format("memory").queryName(name).outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.table(name).collect()


def test_stream_repeats_and_intervals(spark, tmp_path):
    rows = [(1, "a", 1000), (1, "a", 1060), (2, "a", 1120), (3, "b", 5000)]  # past the first watermark, which is 0
    spark.createDataFrame(rows, "id long, k string, s long").write.json(f"file://{tmp_path}/in")
    stream = spark.readStream.schema("id long, k string, s long").json(f"file://{tmp_path}/in").select("id", "k", F.timestamp_seconds("s").alias("ts"))
    assert sorted(r["id"] for r in run_stream(spark, drift.deduplicated(stream, ["id"]), "once")) == [1, 2, 3]
    batch = spark.read.schema("id long, k string, s long").json(f"file://{tmp_path}/in").select("id", "k", F.timestamp_seconds("s").alias("ts"))
    assert drift.deduplicated(batch, ["id"]).count() == 3
    right = stream.select(F.col("k"), F.col("id").alias("other"), F.col("ts").alias("at"))
    got = run_stream(spark, drift.stream_interval(stream, right, "k", "ts", "at", "90 seconds"), "near")
    assert sorted((r["id"], r["other"]) for r in got) == [(1, 1), (1, 1), (1, 1), (1, 2), (2, 2), (3, 3)]


def test_replanning(spark):
    plan = planner.gap_plan(Profile(1000, 2, 900))
    assert plan.use_gate and drift.needs_replan(plan, Profile(1000, 2, 500)) and not drift.needs_replan(plan, Profile(10_000, 2, 9000))
    seen = []
    sink = drift.replan_sink(lambda: plan, lambda profile, new: seen.append(new))
    sink(spark.createDataFrame([("a", 90), ("b", 10)], "value string, freq long"), 0)
    sink(spark.createDataFrame([("b", 80)], "value string, freq long"), 1)
    assert len(seen) == 1 and not seen[0].use_gate


def test_stream_lookup_and_overlay(spark, tmp_path):
    df = spark.createDataFrame([(i, "a" if i % 6 else "b") for i in range(600)], "k long, v string")
    ix = planner.build_index(df, KeyValueSpec(("k",), "v"), "always", ("xor",))
    df.select("k").write.parquet(f"{tmp_path}/keys")
    stream = spark.readStream.schema("k long").parquet(f"{tmp_path}/keys")
    q = drift.stream_lookup(stream, ix).writeStream.format("memory").queryName("looked_up").start()
    q.processAllAvailable()
    q.stop()
    assert spark.table("looked_up").select("k", "v").exceptAll(df).count() == 0
    overlay = spark.createDataFrame([(1, "z", "put", 1), (1, "y", "put", 2), (2, None, "delete", 1), (9000, "n", "put", 1)], "k long, v string, op string, ts long")
    got = {r["k"]: r["v"] for r in drift.overlay_lookup(ix, overlay, df.select("k").where("k < 4").union(spark.createDataFrame([(9000,)], "k long"))).collect()}
    assert got == {0: "b", 1: "y", 2: None, 3: "a", 9000: "n"}
    new = drift.merged(df, overlay, ("k",), "v")
    assert new.count() == 600 and new.where("k = 2").count() == 0


def test_entry_and_registry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    q, o = e.queries(), e.oracle_sql()
    assert set(o) <= set(q) and len(q) > 200
