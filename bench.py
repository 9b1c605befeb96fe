"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

``queries`` has wall-clock seconds; ``measures`` has, per workload and method, stored bits per key, nanoseconds
a key (whole lookup job net of the scan, and inside the shards alone), build seconds, wrong answers and the
planner's decision.
"""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))


def main() -> None:
    from pyspark.sql import SparkSession

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")

    from skewmap import queries as core
    from skewmap.operators import baselines, measure
    from skewmap.plans import planner
    from skewmap.session import ship
    from skewmap.sources import tables
    from skewmap.sources.keyvalue import KeyValueSpec

    ship(spark)
    seconds: dict[str, float] = {}
    measures: dict[str, dict] = {}

    def clock(name: str, run) -> None:
        began = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - began, 3)

    registered = core.queries()
    registered["profile_lang"](spark, sf_dir).collect()  # starts the workers
    for name in ("profile_part_supp", "entropy_part_supp", "gap_plan_part_supp", "entropy_fit_plan_part_supp", "gap_plan_alpha_sweep", "bounds_containment", "lookup_gap_planned_part_supp", "lookup_plain_part_supp", "lookup_perfect_hash_part_supp", "lookup_gap_planned_lines_per_order", "lookup_gap_planned_fold15", "fold12_counts"):
        clock(name, lambda: registered[name](spark, sf_dir))

    events = tables.table(spark, sf_dir, "events", "event_id")

    def compare(name: str, df, keys: tuple[str, ...], value: str, methods: dict, shown: set[str]) -> None:
        df = df.cache()
        df.count()
        spec = KeyValueSpec(keys, value)
        for method, make in methods.items():
            ix, took = measure.timed(lambda: make(df, spec))
            lat = measure.lookup_latency(ix, df.select(*keys), 2).first()
            plan = getattr(ix, "plan", None)
            measures[f"{name}/{method}"] = {
                "keys": df.count(), "bpk": round(measure.total_bpk(ix), 3), "parts": {r["part"]: round(r["bpk"], 3) for r in ix.measured_bits().collect()}, "net_ns": round(lat["net_ns"]),
                "in_shard_ns": lat["in_shard_ns"] and round(lat["in_shard_ns"]), "build_s": round(took, 3), "mismatches": measure.mismatches(ix, df, keys, value).count(),
                "gate": f"{plan.family} {plan.param:g}" if plan and plan.use_gate else "none",
            }
            if method in shown:  # the seconds that were summed before; all builds are in ``measures``
                seconds[f"build_{name}_{method}"] = round(took, 3)
        df.unpersist()

    # Both planners choose among binary fuse gates; ``gap_any`` among all families.
    planned = {"gap_planned": lambda d, s: planner.build_index(d, s, "gap", ("fuse3",)), "gap_any": lambda d, s: planner.build_index(d, s, "gap", core.GATED), "entropy_fit": lambda d, s: planner.build_index(d, s, "entropy_fit", ("fuse3",))}
    others = {"hash_table": baselines.HashTable.build, "perfect_hash": baselines.PerfectHashTable.build, "model_coded": baselines.best_model}
    for dist in ("uniform100", "zipf", "unique"):
        for alpha in (0.5, 0.8, 0.95):
            shown = {"gap_planned", "entropy_fit"} | (set(others) if alpha == 0.8 and dist != "unique" else set())
            compare(f"{dist}_{alpha}", tables.synthetic(events, "event_id", alpha, dist), ("key",), "value", planned | others, shown)
    for name in ("part_supp", "lines_per_order", "fold15"):
        df, keys, value = tables.workload(spark, sf_dir, name)
        compare(name, df, tuple(keys), value, planned, {"gap_planned", "entropy_fit"} if name != "fold15" else set())
    print(json.dumps({"metric": "total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": sf_dir.rstrip("/").rpartition("sf")[2], "measures": measures}))
    spark.stop()


if __name__ == "__main__":
    main()
