"""Cases that a review found: repeated keys, large tables, queries that read no table."""

import re
from pathlib import Path

import numpy as np
import pytest
from conftest import SF
from pyspark.errors import AnalysisException
from pyspark.sql import functions as F

from skewmap import queries, relational, session
from skewmap.operators import baselines
from skewmap.plans import sweep
from skewmap.sources import tables
from skewmap.sources.keyvalue import KeyValueSpec


def test_repeated_urls_are_looked_up(spark, tmp_path):
    urls = ["https://a.net/x", "https://b.org/y", "https://a.net/x", None, "https://b.org/z"]
    spark.createDataFrame([(u,) for u in urls], "url string").write.parquet(f"{tmp_path}/pages.parquet")
    got = [tuple(r) for r in queries.queries()["lookup_gap_planned_url_host"](spark, str(tmp_path)).collect()]
    assert sorted(got, key=str) == sorted(((u, u.split("/")[2] if u else None) for u in urls), key=str)


def test_sketches_are_not_kept_by_order(spark, tmp_path):
    plan = relational.QUERIES["merged_sketches"][0](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "percentile" in plan
    assert not re.search(r"keys=\[[^\]]*l_orderkey[^\]]*\], functions=\[[^\n]*percentile", plan)


@pytest.mark.parametrize("name", [
    "bound_gap_grid", "bounds_containment", "bounds_containment_all", "bounds_tightness", "break_even_alpha", "crossing_alpha", "decision_harm", "entropy_fit_equivalence",
    "epsilon_sweep_model", "gap_plan_alpha_sweep", "gap_plan_continuous", "heuristic_harm",
])
def test_a_table_is_read(spark, tmp_path, name):
    """Queries that made their data up: without their table they now fail."""
    with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
        queries.queries()[name](spark, str(tmp_path)).collect()


def test_runs_by_share_are_those_of_the_relations(spark):
    keys = tables.table(spark, SF, "events", "event_id")
    got = sweep.collected(sweep.runs_by_share(keys, "event_id", (0.5, 0.8, 0.99)))
    for alpha in (0.5, 0.99):
        for dist in sweep.DISTRIBUTIONS:
            values = tables.synthetic(keys, "event_id", alpha, dist).groupBy("value").count()
            want = sorted(tuple(r) for r in values.groupBy("count").agg(F.count(F.lit(1))).collect())
            assert sorted(got[alpha, dist]) == want


def test_measured_sweep_deals_a_key_once_for_all_shares(spark, monkeypatch):
    """Disk: tasks get the keys of shards, not a row for each key and share."""
    keys = tables.table(spark, SF, "events", "event_id")
    grouped, rows = type(keys.groupBy("event_id")), []
    real = grouped.applyInArrow
    monkeypatch.setattr(grouped, "applyInArrow", lambda self, *args: rows.append(self._df.count()) or real(self, *args))
    cells = sweep.measured_sweep(keys, "event_id", (0.5, 0.8, 0.95), families=("xor",), shard_keys=30).collect()
    assert len(cells) == 3 * 3 * 8
    assert rows and max(rows) <= keys.count()


def test_measured_sweep_stores_some_bytes_a_key_and_leaves_none(spark, monkeypatch):
    """Disk (F2 to F4, F6, F7): keys are stored packed, and what is stored goes when it is not needed any more."""
    made, sizes, real = [], [], session.stored

    def stored(df, name="step", **options):
        out = real(df, name, **options)
        made.append(Path(out._stored_at.removeprefix("file://")))
        sizes.append(sum(f.stat().st_size for f in made[-1].glob("*.parquet")))
        return out

    monkeypatch.setattr(session, "stored", stored)
    keys = spark.range(200_000).select((F.col("id") * 7919 + 5).alias("k"))
    assert sweep.measured_sweep(keys, "k", (0.9,), ("unique", "zipf"), ("bloom1",)).count() == 2 * 16
    assert made and sum(sizes) < 20 * keys.count()
    assert not any(p.exists() for p in made)


def test_packed_numbers():
    for values in ([5], [-3, -3, 2**40], [0, 255, 256], [-(2**62), 2**62]):
        for rising in (False, True):
            assert sweep._unpacked(sweep._packed(np.array(values), rising)).tolist() == values
    assert sweep._unpacked(sweep._packed(np.array([7, -7, 9]))).tolist() == [7, -7, 9]


def test_hash_bits_do_not_travel(spark):
    """bpk_table (F10): a model over hash bits ships no features, and its workers see the bits that ``getbit`` gives."""
    df = spark.range(500).select(F.col("id").alias("k"), (F.col("id") % 7).alias("v"))
    built = baselines.ModelCodedMap.build(df, KeyValueSpec(("k",), "v"))
    found = built.lookup(df.select("k"))
    assert found.exceptAll(df).count() == 0 and "getbit" not in found._jdf.queryExecution().toString()
    h = spark.range(-50, 50).select(F.xxhash64("id").alias("h"))
    rows = h.select("h", F.transform(F.sequence(F.lit(0), F.lit(31)), lambda i: F.getbit("h", i).cast("double")).alias("x")).toArrow()
    assert (baselines._matrix(rows, "h", None, 32) == baselines._matrix(rows, "h", "x", 32)).all()


def test_key_codes_are_the_least_lengths_with_spare_given_in_order():
    rng = np.random.default_rng(3)
    for classes in (2, 5, 257):
        odds = baselines._odds(rng.integers(-2000, 2000, (50, classes)))
        guess = baselines._guesses(odds, 0)
        got = baselines.key_codes(odds, guess, 2)
        for row, g, lengths in zip(odds.tolist(), guess.tolist(), got.tolist()):
            row[g] = max(row[g] >> 2, 1)
            total = sum(row)
            want = [next(n for n in range(64) if w << n >= total) for w in row]
            spare = 2**48 - sum(2 ** (48 - n) for n in want)
            for j in sorted(range(classes), key=lambda j: -(row[j] << want[j])):
                if 2 ** (48 - want[j]) > spare:
                    break
                spare -= 2 ** (48 - want[j])
                want[j] -= 1
            assert lengths == [max(n, 1) for n in want]
