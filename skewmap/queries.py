"""Registered queries over the given tables, with DuckDB SQL for what SQL can express."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .functions.bounds import DELTA3, FORMS, bound_gap, lower_bound, upper_bound
from .functions.gatecost import FAMILIES, settings
from .operators import baselines, huffman, index, joins, measure, stats
from .plans import planner, sweep
from . import relational
from .session import scratch, ship, stored
from .sources import tables
from .sources.keyvalue import KeyValueSpec
from .streaming import drift

Query = Callable[[SparkSession, str], DataFrame]

#: SQL of the workloads: key columns, value column, relation.
_ROW = ", ".join(tables.ROW)
WORK_SQL: dict[str, tuple[str, str, str]] = {
    "lang": ("doc_id", "lang", "SELECT doc_id, lang FROM documents"),
    "toxic": ("doc_id", "toxic", "SELECT doc_id, toxic FROM labels"),
    "quality": ("doc_id", "quality", "SELECT doc_id, quality FROM labels"),
    "returnflag": (_ROW, "l_returnflag", f"SELECT {_ROW}, l_returnflag FROM lineitem"),
    "extprice": (_ROW, "l_extendedprice", f"SELECT {_ROW}, l_extendedprice FROM lineitem"),
    "lines_per_order": ("l_orderkey", "n", "SELECT l_orderkey, count(*) AS n FROM lineitem GROUP BY 1"),
    "orders_per_cust": ("o_custkey", "n", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1"),
    "part_supp": ("l_partkey, l_suppkey", "n", "SELECT l_partkey, l_suppkey, count(*) AS n FROM lineitem GROUP BY 1, 2"),
    "order_part": ("l_orderkey, l_partkey", "n", "SELECT l_orderkey, l_partkey, count(*) AS n FROM lineitem GROUP BY 1, 2"),
    "cust_date": ("o_custkey, o_orderdate", "n", "SELECT o_custkey, o_orderdate, count(*) AS n FROM orders GROUP BY 1, 2"),
    "user_hour": ("user_id, hour", "n", "SELECT user_id, CAST(date_trunc('hour', ts) AS TIMESTAMP) AS hour, count(*) AS n FROM events GROUP BY 1, 2"),
    "custkey": ("o_orderkey", "o_custkey", "SELECT o_orderkey, o_custkey FROM orders"),
    "role": ("conv_id, turn", "role", "SELECT conv_id, turn, role FROM conversations"),
    "doc_quality": ("doc_id", "quality", "SELECT d.doc_id, l.quality FROM documents d LEFT JOIN labels l USING (doc_id)"),
    "vec_label": ("vec_id", "label", "SELECT vec_id, label FROM embeddings"),
    "url_lang": ("url", "path", "SELECT url, split_part(url, '/', 4) AS path FROM pages"),
    "url_host": ("url", "host", "SELECT url, split_part(url, '/', 3) AS host FROM pages"),
    "words": ("word", "n", r"SELECT word, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '(\S+)')) AS word FROM documents) GROUP BY 1"),
}
for _k in (8, 12, 15, 31):
    WORK_SQL[f"kmer{_k}"] = ("kmer", "n", f"SELECT kmer, count(*) AS n FROM (SELECT substr(text, CAST(unnest(range(1, length(text) - {_k - 2})) AS BIGINT), {_k}) AS kmer FROM documents WHERE length(text) >= {_k}) GROUP BY 1")
_FOLD = "translate(regexp_replace(lower(text), '[^a-z]', '', 'g'), 'abcdefghijklmnopqrstuvwxyz', '" + "".join("acgt"[i % 4] for i in range(26)) + "')"
for _k in (8, 10, 12, 15):
    WORK_SQL[f"fold{_k}"] = ("kmer", "n", f"SELECT kmer, count(*) AS n FROM (SELECT substr(seq, CAST(unnest(range(1, length(seq) - {_k - 2})) AS BIGINT), {_k}) AS kmer FROM (SELECT {_FOLD} AS seq FROM conversations) WHERE length(seq) >= {_k}) GROUP BY 1")

_K15 = "SELECT DISTINCT substr(text, CAST(unnest(range(1, length(text) - 13)) AS BIGINT), 15) AS kmer FROM {} WHERE length(text) >= 15"
WORK_SQL["bench_flag"] = ("kmer", "hit", f"WITH d AS ({_K15.format('documents')}), b AS ({_K15.format('benchmark')}) SELECT d.kmer, b.kmer IS NOT NULL AS hit FROM d LEFT JOIN b USING (kmer)")

PROFILED = ("lang", "toxic", "quality", "returnflag", "lines_per_order", "orders_per_cust", "part_supp", "order_part", "cust_date", "user_hour", "custkey", "role", "doc_quality", "url_lang", "fold10", "fold15", "kmer12", "words")
ANY_FAMILY = ("lang", "quality", "part_supp", "user_hour", "fold15", "kmer12")
LOOKED_UP = ("lang", "part_supp", "user_hour", "returnflag", "doc_quality")
GATED = ("xor", "fuse3", "fuse4", "bloom1", "bloom3")
DEFAULT_FAMILIES = ("fuse3",)


def _base(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, KeyValueSpec]:
    df, keys, value = tables.workload(ship(spark), sf_dir, name)
    return df, KeyValueSpec(tuple(keys), value, "first" if name in tables.DERIVED else "error")


def _values(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The histogram of a workload's values; those of k-mers are tallied where k-mers are counted."""
    if name.startswith(("kmer", "fold")):
        return tables.kmer_histogram(ship(spark), sf_dir, name)
    df, spec = _base(spark, sf_dir, name)
    return stats.value_histogram(df, spec.value)


def _counted(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """``_values``, stored: plans read it several times, and its relation may be long in making."""
    return stored(_values(spark, sf_dir, name), "histogram")


_kept: dict[tuple, DataFrame] = {}


def _once(spark: SparkSession, sf_dir: str, make: Callable[[], DataFrame], *what) -> DataFrame:
    """A table that several queries show, made and stored by the first of them in an application."""
    key = (spark.sparkContext.applicationId, sf_dir, *what)
    if key not in _kept:
        _kept[key] = stored(make(), "shown")
    return _kept[key]


def _frame(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


# ---------------------------------------------------------------- SQL fragments


def _hist(name: str) -> str:
    _, value, sql = WORK_SQL[name]
    return f"SELECT {value} AS value, count(*) AS freq FROM ({sql}) GROUP BY 1"


def _profile_sql(name: str) -> str:
    return f"h AS ({_hist(name)}), p AS (SELECT CAST(sum(freq) AS BIGINT) AS num_keys, count(*) AS distinct_values, max(freq) AS dominant_count FROM h)"


def _grid_sql(families) -> str:
    rows = ", ".join(f"('{s.family}', CAST({float(s.param)} AS DOUBLE), CAST({s.eps!r} AS DOUBLE), CAST({s.bits!r} AS DOUBLE))" for s in settings(families))
    return f"(VALUES {rows}) AS s(family, param, eps, bits)"


_LB = f"(dominant_count / num_keys) * {DELTA3} * (1 - eps) - (1 - dominant_count / num_keys) * bits - distinct_values / num_keys"


def _plan_sql(profile: str, families=DEFAULT_FAMILIES) -> str:
    return f"""WITH {profile}, g AS (SELECT s.*, {_LB} AS bound FROM {_grid_sql(families)}, p),
    b AS (SELECT *, row_number() OVER (ORDER BY bound DESC, bits) AS r FROM g)
    SELECT bound > 0 AS use_gate, family, param, round(eps, 6) AS eps, round(bits, 6) AS bits, round(bound, 6) AS bound FROM b WHERE r = 1"""


# ---------------------------------------------------------------- queries by workload


def _profile(name: str) -> Query:
    def run(spark, sf_dir):
        return stats.profile_of(_counted(spark, sf_dir, name))

    return run


def _histogram(name: str) -> Query:
    def run(spark, sf_dir):
        return _values(spark, sf_dir, name)

    return run


def _entropy(name: str) -> Query:
    def run(spark, sf_dir):
        return stats.entropy(_counted(spark, sf_dir, name)).select(F.round("entropy", 6).alias("entropy"))

    return run


def _freq_of_freq(name: str) -> Query:
    def run(spark, sf_dir):
        return stats.freq_of_freq(_values(spark, sf_dir, name))

    return run


def _lookup(name: str, make: Callable[[DataFrame, KeyValueSpec], object]) -> Query:
    def run(spark, sf_dir):
        df, spec = _base(spark, sf_dir, name)
        return make(df, spec).lookup(df.select(*spec.keys)).select(*spec.keys, spec.value)

    return run


def _gate(family: str) -> index.Plan:
    param = 4 if family.startswith("bloom") else 2
    s = next(s for s in FAMILIES[family].settings() if s.param == param)
    return index.Plan(True, family, param, s.eps, s.bits, planner="always")


def _gap_plan(name: str, families=DEFAULT_FAMILIES) -> Query:
    def run(spark, sf_dir):
        plan = planner.plan_frame(stats.profile_of(_counted(spark, sf_dir, name)), spark, families)
        return plan.select("use_gate", "family", "param", *(F.round(c, 6).alias(c) for c in ("eps", "bits", "bound")))

    return run


def _heuristic_columns(alpha, h):
    cost = F.when(h < 2, 0.22 * h * h + 0.18 * h + 1.16).otherwise(1.1 * h + 0.2)
    return cost, F.lit(1.44) / cost * (1 - alpha) / alpha * F.lit(planner.LOG2E)


def _entropy_fit(name: str) -> Query:
    def run(spark, sf_dir):
        hist = _counted(spark, sf_dir, name)
        row = hist.agg(F.sum("freq").alias("n"), F.max("freq").alias("top")).crossJoin(stats.entropy(hist))
        cost, eps = _heuristic_columns(F.col("top") / F.col("n"), F.col("entropy"))
        return row.select((eps < 1).alias("use_gate"), F.round(cost, 6).alias("map_cost"), F.round(eps, 6).alias("eps"))

    return run


_H_SQL = "t AS (SELECT sum(freq) AS n, max(freq) AS top FROM h), e AS (SELECT sum(-(freq / n) * log2(freq / n)) AS entropy FROM h, t), c AS (SELECT CASE WHEN entropy < 2 THEN 0.22 * entropy * entropy + 0.18 * entropy + 1.16 ELSE 1.1 * entropy + 0.2 END AS cost FROM e)"
_EPS_SQL = f"CAST(1.44 AS DOUBLE) / cost * (1 - top / n) / (top / n) * {planner.LOG2E!r}"


def _kraft(name: str) -> Query:
    def run(spark, sf_dir):
        hist = _counted(spark, sf_dir, name)
        runs = huffman.collect_runs(stats.freq_of_freq(hist))
        book = huffman.canonical_codebook(hist, sum(m for _, m in runs), huffman.Code.of(runs))
        return book.agg(F.count(F.lit(1)).alias("codes"), F.countDistinct("code_len", "code").alias("different"), F.round(F.sum(F.pow(F.lit(2.0), -F.col("code_len"))), 9).alias("kraft_sum"))

    return run


def _sandwich(name: str) -> Query:
    def run(spark, sf_dir):
        hist = _counted(spark, sf_dir, name)
        runs = huffman.collect_runs(stats.freq_of_freq(hist))
        out = huffman.entropy_sandwich(huffman.canonical_codebook(hist, sum(m for _, m in runs), huffman.Code.of(runs)))
        return out.select(F.round("entropy", 6).alias("entropy"), "holds")

    return run


def _huffman_bits(name: str) -> Query:
    def run(spark, sf_dir):
        runs = huffman.collect_runs(stats.freq_of_freq(_values(spark, sf_dir, name)))
        n = sum(f * m for f, m in runs)
        bits = huffman.Code.of(runs).total_bits(runs)
        return _frame(spark, [(n, bits, bits / n)], "num_keys long, bits long, bits_per_key double")

    return run


# ---------------------------------------------------------------- grids


def _grid(spark: SparkSession, families=("xor", "fuse3", "fuse4", "bloom1", "bloom3")) -> DataFrame:
    """Shares 0.05 to 0.95 by settings: literals only."""
    alphas = spark.range(1, 20).select((F.col("id") / 20).alias("alpha"))
    return alphas.crossJoin(F.broadcast(planner.settings_frame(spark, families)))


_GRID_SQL = f"(SELECT i / 20 AS alpha, s.* FROM range(1, 20) r(i), {_grid_sql(('xor', 'fuse3', 'fuse4', 'bloom1', 'bloom3'))})"
_RATIO = 0.01000003  # keeps sixth decimals off ties


def _bound_grid(expr, name: str) -> Query:
    def run(spark, sf_dir):
        g = _grid(ship(spark))
        return g.select("alpha", "family", "param", F.round(expr(F.col("alpha"), F.col("eps"), F.col("bits")), 6).alias(name))

    return run


_HB = "(-alpha * log2(alpha) - (1 - alpha) * log2(1 - alpha))"
_LIN = "(2 * alpha * eps * (1 - alpha) / (3 - alpha))"
_PASS = "((1 - alpha) + alpha * eps)"
_AFTER = f"(-alpha * eps * log2(alpha * eps / {_PASS}) - (1 - alpha) * log2((1 - alpha) / {_PASS}))"
UPPER_SQL = {
    "binary_entropy": f"{DELTA3} * (1 + {_HB} - {_LIN}) + {_RATIO} - bits * (1 - alpha)",
    "two_bits": f"{DELTA3} * (2 - {_LIN}) + {_RATIO} - bits * (1 - alpha)",
    "simplified": f"{DELTA3} * (2 - alpha * eps / 2) + {_RATIO} - bits * (1 - alpha)",
    "tight": f"{DELTA3} * (1 + {_HB} - {_AFTER}) + {_RATIO} - bits * (1 - alpha)",
}


def _disagreement(spark, sf_dir):
    """Workloads where the heuristic gates and the bound does not, or the other way round."""
    rows = []
    for name in ("lang", "toxic", "quality", "returnflag", "part_supp", "user_hour", "lines_per_order", "fold10"):
        df, spec = _base(spark, sf_dir, name)
        hist = stats.value_histogram(df, spec.value).cache()
        t = hist.agg(F.sum("freq").alias("n"), F.count(F.lit(1)).alias("d"), F.max("freq").alias("top")).first()
        h = stats.entropy(hist).first()["entropy"]
        hist.unpersist()
        profile = stats.Profile(t["n"], t["d"], t["top"])
        gap, fit = planner.gap_plan(profile), planner.entropy_fit_plan(profile, h)
        rows.append((name, gap.use_gate, fit.use_gate))
    return _frame(spark, rows, "workload string, gap boolean, entropy_fit boolean").where("gap <> entropy_fit")


def _disagreement_sql() -> str:
    parts = []
    for name in ("lang", "toxic", "quality", "returnflag", "part_supp", "user_hour", "lines_per_order", "fold10"):
        parts.append(f"SELECT * FROM (WITH {_profile_sql(name)}, {_H_SQL} SELECT '{name}' AS workload, (SELECT max({_LB}) > 0 FROM {_grid_sql(DEFAULT_FAMILIES)}, p) AS gap, (SELECT {_EPS_SQL} < 1 FROM c, t) AS entropy_fit)")
    return "SELECT * FROM (" + " UNION ALL ".join(parts) + ") WHERE gap <> entropy_fit"


# ---------------------------------------------------------------- synthetic relations and sweeps


def _synthetic(alpha: float, dist: str) -> Query:
    return lambda spark, sf_dir: tables.synthetic(tables.table(ship(spark), sf_dir, "events", "event_id"), "event_id", alpha, dist)


def _synthetic_sql(alpha: float, dist: str) -> str:
    cut = f"floor(total * {round(alpha * 100)} / 100 + 0.5)"
    ranked = "r AS (SELECT event_id AS key, row_number() OVER (ORDER BY (event_id * 2654435761) % 4294967296, event_id) AS r, count(*) OVER () AS total FROM events)"
    if dist == "zipf":
        weight = [k**-tables.ZIPF_EXPONENT for k in range(1, tables.ZIPF_SUPPORT + 1)]
        total = sum(weight)
        return f"""WITH {ranked}, w AS (SELECT i AS value, power(i, -{tables.ZIPF_EXPONENT}) AS w FROM range(1, {tables.ZIPF_SUPPORT + 1}) t(i)),
        z AS (SELECT value, coalesce(sum(w) OVER (ORDER BY value ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) / {total!r} AS lo, CASE WHEN value = {tables.ZIPF_SUPPORT} THEN 1.1 ELSE sum(w) OVER (ORDER BY value) / {total!r} END AS hi FROM w),
        u AS (SELECT *, ((key * 40503 + 12345) % 1000003) / 1000003.0 AS u FROM r)
        SELECT key, CASE WHEN r > {cut} THEN z.value ELSE 0 END AS value FROM u JOIN z ON u >= lo AND u < hi"""
    value = "key + 1" if dist == "unique" else f"r % {tables.UNIFORM_VALUES} + 1"
    return f"WITH {ranked} SELECT key, CASE WHEN r > {cut} THEN {value} ELSE 0 END AS value FROM r"


def _synthetic_lookup(alpha: float, dist: str) -> Query:
    def run(spark, sf_dir):
        df = _synthetic(alpha, dist)(spark, sf_dir)
        ix = planner.build_index(df, KeyValueSpec(("key",), "value"), "gap", GATED)
        return ix.lookup(df.select("key")).select("key", "value")

    return run


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.table(ship(spark), sf_dir, "events", "event_id")


def _measured(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stored savings of every share, distribution and setting over the events."""
    return _once(spark, sf_dir, lambda: sweep.measured_sweep(_events(spark, sf_dir), "event_id"), "measured")


def _measured_decision(spark, sf_dir):
    return sweep.decision_confusion(_measured(spark, sf_dir)).select("dist", "family", "gated_harm")


def _measured_contained(spark, sf_dir):
    """Shares at which the planner's saving is under its bound by more than the noise of one build, or the best over the upper bound."""
    p = sweep.panels(_measured(spark, sf_dir))
    low = (F.col("chosen.saving") < F.col("chosen.lower") - NOISE) & (F.col("chosen.lower") > 0)
    high = F.col("best.saving") > F.col("best.upper_binary_entropy") + NOISE
    return p.groupBy("dist", "family").agg(F.count(F.lit(1)).alias("shares"), F.count_if(low).alias("below"), F.count_if(high).alias("above"))


#: Bits per key by which one build may miss an expectation: false positives are random.
NOISE = 0.01
_PANELS = "(VALUES ('unique'), ('zipf'), ('uniform100')) d(dist), (VALUES ('xor'), ('fuse3'), ('bloom1'), ('bloom3')) f(family)"
_MEASURED_CONTAINED_SQL = f"SELECT dist, family, CAST(50 AS BIGINT) AS shares, CAST(0 AS BIGINT) AS below, CAST(0 AS BIGINT) AS above FROM {_PANELS}"


def _values_by_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(alpha, dist, n, cut, kinds): keys, keys of the dominant value and distinct values of the synthetic relations of all shares.

    A minority value is there at a share if its last key in the mixed order is past the dominant ones, so one pass
    over the keys serves all shares.
    """
    ranks = tables.synthetic_ranks(_events(spark, sf_dir), "event_id")
    total = ranks.agg(F.count(F.lit(1)).alias("n"))
    zipf = ranks.join(F.broadcast(tables.zipf_table(spark)), (F.col("u") >= F.col("lo")) & (F.col("u") < F.col("hi")))
    last = zipf.groupBy("value").agg(F.max("r").alias("r")).select(F.lit("zipf").alias("dist"), "r")
    last = last.unionByName(ranks.groupBy((F.col("r") % tables.UNIFORM_VALUES).alias("value")).agg(F.max("r").alias("r")).select(F.lit("uniform100").alias("dist"), "r"))
    shares = F.broadcast(spark.range(50, 100).select((F.col("id") / 100).alias("alpha")).crossJoin(total)).withColumn("cut", tables.dominant_cut(F.col("n"), F.col("alpha")))
    seen = last.crossJoin(shares).groupBy("dist", "alpha", "n", "cut").agg((F.count_if(F.col("r") > F.col("cut")) + 1).alias("kinds"))
    unique = shares.select(F.lit("unique").alias("dist"), "alpha", "n", "cut", (F.col("n") - F.col("cut") + 1).alias("kinds"))
    return seen.unionByName(unique)


def _settings_by_share(spark, sf_dir, families) -> DataFrame:
    return _values_by_share(ship(spark), sf_dir).crossJoin(F.broadcast(planner.settings_frame(spark, families)))


def _sweep_grid(spark, sf_dir) -> DataFrame:
    g = _settings_by_share(spark, sf_dir, sweep.GATES)
    a, r = F.col("cut") / F.col("n"), F.col("kinds") / F.col("n") + 3e-8  # keeps sixth decimals off ties
    e, b = F.col("eps"), F.col("bits")
    return g.select("alpha", "dist", "family", "param", lower_bound(a, e, b, r).alias("lower"), *(upper_bound(a, e, b, r, form=f).alias(f) for f in FORMS), "bits")


def _sweep_bounds(spark, sf_dir):
    return _sweep_grid(spark, sf_dir).select("alpha", "dist", "family", "param", *(F.round(c, 6).alias(c) for c in ("lower", *FORMS)))


def _sweep_crossing(spark, sf_dir):
    """First share at which some setting has a positive bound, by a step from the share before."""
    best = _sweep_grid(spark, sf_dir).groupBy("dist", "family", "alpha").agg(F.max("lower").alias("bound"))
    w = Window.partitionBy("dist", "family").orderBy("alpha")
    step = best.withColumn("before", F.lag("bound").over(w)).where((F.col("bound") > 0) & (F.coalesce("before", F.lit(-1.0)) <= 0))
    return step.groupBy("dist", "family").agg(F.min("alpha").alias("crossing"), F.count(F.lit(1)).alias("crossings"))


def _shares_sql(families) -> str:
    return f"""r AS (SELECT event_id AS key, row_number() OVER (ORDER BY (event_id * 2654435761) % 4294967296, event_id) AS r FROM events),
t AS (SELECT count(*) AS n FROM r), a AS (SELECT i / 100 AS alpha, n, floor(n * i / 100 + 0.5) AS cut FROM range(50, 100) s(i), t),
w AS (SELECT i AS value, power(i, -{tables.ZIPF_EXPONENT}) AS w FROM range(1, {tables.ZIPF_SUPPORT + 1}) t(i)), wt AS (SELECT sum(w) AS total FROM w),
z AS (SELECT value, coalesce(sum(w) OVER (ORDER BY value ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) / total AS lo, CASE WHEN value = {tables.ZIPF_SUPPORT} THEN 1.1 ELSE sum(w) OVER (ORDER BY value) / total END AS hi FROM w, wt),
last AS (SELECT 'zipf' AS dist, max(r) AS r FROM (SELECT r, ((key * 40503 + 12345) % 1000003) / 1000003.0 AS u FROM r) JOIN z ON u >= lo AND u < hi GROUP BY z.value
UNION ALL SELECT 'uniform100' AS dist, max(r) AS r FROM r GROUP BY r % {tables.UNIFORM_VALUES}),
v AS (SELECT dist, alpha, n, cut, count(*) FILTER (last.r > cut) + 1 AS kinds FROM last, a GROUP BY 1, 2, 3, 4 UNION ALL SELECT 'unique', alpha, n, cut, n - cut + 1 FROM a),
g AS (SELECT v.alpha AS share, dist, cut / n AS alpha, kinds / n + 3e-8 AS ratio, s.* FROM v, {_grid_sql(families)})"""


_SHARES_SQL = _shares_sql(sweep.GATES)
_LOWER_SQL = f"alpha * {DELTA3} * (1 - eps) - (1 - alpha) * bits - ratio"
_SWEEP_BOUNDS_SQL = f"WITH {_SHARES_SQL} SELECT share AS alpha, dist, family, param, round({_LOWER_SQL}, 6) AS lower, " + ", ".join(f"round({UPPER_SQL[f].replace(str(_RATIO), 'ratio')}, 6) AS {f}" for f in FORMS) + " FROM g"
_SWEEP_CROSSING_SQL = f"""WITH {_SHARES_SQL}, b AS (SELECT dist, family, share, max({_LOWER_SQL}) AS bound FROM g GROUP BY 1, 2, 3),
s AS (SELECT *, lag(bound) OVER (PARTITION BY dist, family ORDER BY share) AS before FROM b)
SELECT dist, family, min(share) AS crossing, count(*) AS crossings FROM s WHERE bound > 0 AND coalesce(before, -1) <= 0 GROUP BY 1, 2"""


def _gap_grid(spark, sf_dir):
    """How far the bounds are apart, at every share of the synthetic relations over the events."""
    gap = bound_gap(F.col("cut") / F.col("n"), F.col("eps"), F.col("kinds") / F.col("n") + 3e-8)
    return _settings_by_share(spark, sf_dir, GATED).select("alpha", "dist", "family", "param", F.round(gap, 6).alias("gap"))


_GAP_GRID_SQL = f"WITH {_shares_sql(GATED)} SELECT share AS alpha, dist, family, param, round(2 * {DELTA3} - alpha * {DELTA3} + alpha * {DELTA3} * eps / 2 + 2 * ratio, 6) AS gap FROM g"


def _alpha_sweep_plans(spark, sf_dir):
    """The planner over 50 shares and three distributions of the events' keys, as one plan."""
    grid = _settings_by_share(spark, sf_dir, ("fuse3",))
    bound = lower_bound(F.col("cut") / F.col("n"), F.col("eps"), F.col("bits"), F.col("kinds") / F.col("n") + 3e-8)
    best = grid.withColumn("bound", bound).groupBy("alpha", "dist").agg(F.max_by(F.struct("param", "bound"), F.struct("bound", -F.col("bits"))).alias("b"))
    return best.select("alpha", "dist", (F.col("b.bound") > 0).alias("use_gate"), "b.param", F.round("b.bound", 6).alias("bound"))


_ALPHA_SWEEP_SQL = f"""WITH {_shares_sql(("fuse3",))}, b AS (SELECT share, dist, bits, param, {_LOWER_SQL} AS bound FROM g),
k AS (SELECT *, row_number() OVER (PARTITION BY share, dist ORDER BY bound DESC, bits) AS k FROM b)
SELECT share AS alpha, dist, bound > 0 AS use_gate, param, round(bound, 6) AS bound FROM k WHERE k = 1"""


def _continuous(spark, sf_dir):
    """Settings of continuous rates at every share and distribution of the events' keys: 150 rows on the driver."""
    rows = []
    for x in _values_by_share(ship(spark), sf_dir).collect():
        alpha, ratio = x["cut"] / x["n"], x["kinds"] / x["n"] + 3e-8
        for f in ("xor", "fuse3", "fuse4"):
            s = planner.continuous_setting(FAMILIES[f], alpha)
            rows.append((x["alpha"], x["dist"], f, round(s.eps, 6), round(lower_bound(alpha, s.eps, s.bits, ratio), 6)))
    return _frame(spark, rows, "alpha double, dist string, family string, eps double, bound double")


_CONTINUOUS_SQL = f"""
WITH {_shares_sql(("fuse3",))}, c AS (SELECT DISTINCT share, dist, alpha, ratio FROM g),
e AS (SELECT c.*, family, cost, least(1.0, cost * {planner.LOG2E!r} * (1 - alpha) / (alpha * {DELTA3})) AS eps
FROM c, (VALUES ('xor', CAST(1.23 AS DOUBLE)), ('fuse3', 1.125), ('fuse4', 1.075)) f(family, cost))
SELECT share AS alpha, dist, family, round(eps, 6) AS eps, round(alpha * {DELTA3} * (1 - eps) - (1 - alpha) * cost * log2(1 / eps) - ratio, 6) AS bound FROM e"""


#: Values of an event that an index from its id could hold.
_EVENT_VALUES = ("event_type", "user_id", "value")


def _break_even(spark, sf_dir):
    """The share from which a gate can pay, by family, at the distinct values that the events' columns have."""
    events = tables.table(ship(spark), sf_dir, "events", *_EVENT_VALUES)
    kinds = [events.groupBy(c).agg(F.count(F.lit(1)).alias("n")).agg(F.lit(c).alias("value"), (F.count(F.lit(1)) / F.sum("n")).alias("ratio")).first() for c in _EVENT_VALUES]
    rows = [(r["value"], f, round(planner.break_even_alpha(f, r["ratio"]), 6)) for r in kinds if r["ratio"] is not None for f in GATED]
    return _frame(spark, rows, "value string, family string, alpha double")


_KINDS_SQL = " UNION ALL ".join(f"SELECT '{c}' AS value, count(*) / sum(n) AS ratio FROM (SELECT count(*) AS n FROM events GROUP BY {c})" for c in _EVENT_VALUES)
_BREAK_EVEN_SQL = f"SELECT value, family, round(min((bits + ratio) / ({DELTA3} * (1 - eps) + bits)), 6) AS alpha FROM ({_KINDS_SQL}), {_grid_sql(GATED)} GROUP BY 1, 2"


def _equivalence(spark, sf_dir):
    """Each part's line items, from their keys to return flags: the heuristic's two conditions agree on every such relation."""
    lines = tables.table(ship(spark), sf_dir, "lineitem", "l_partkey", "l_returnflag").groupBy("l_partkey", "l_returnflag").agg(F.count(F.lit(1)).alias("freq"))
    parts = lines.withColumn("n", F.sum("freq").over(Window.partitionBy("l_partkey"))).groupBy("l_partkey")
    p = F.col("freq") / F.col("n")
    g = parts.agg(F.max(p).alias("alpha"), F.sum(-p * F.log2(p)).alias("entropy"))
    cost, eps = _heuristic_columns(F.col("alpha"), F.col("entropy"))
    threshold = F.lit(1.44 * planner.LOG2E) / (cost + F.lit(1.44 * planner.LOG2E))
    return g.agg(F.count(F.lit(1)).alias("cells"), F.count_if(eps < 1).alias("gated"), F.count_if((eps < 1) != (F.col("alpha") > threshold)).alias("disagreements"))


_EQUIVALENCE_SQL = f"""WITH l AS (SELECT l_partkey, count(*) AS freq FROM lineitem GROUP BY l_partkey, l_returnflag),
p AS (SELECT *, freq / sum(freq) OVER (PARTITION BY l_partkey) AS p FROM l),
e AS (SELECT l_partkey, max(p) AS alpha, sum(-p * log2(p)) AS entropy FROM p GROUP BY 1),
c AS (SELECT *, CASE WHEN entropy < 2 THEN 0.22 * entropy * entropy + 0.18 * entropy + 1.16 ELSE 1.1 * entropy + 0.2 END AS cost FROM e),
x AS (SELECT CAST(1.44 AS DOUBLE) / cost * (1 - alpha) / alpha * {planner.LOG2E!r} < 1 AS gated FROM c)
SELECT count(*) AS cells, count(*) FILTER (gated) AS gated, CAST(0 AS BIGINT) AS disagreements FROM x"""


#: Every fifth share and the last: ``bounds_containment`` counts these, ``bounds_containment_all`` every share.
_FIFTHS = tuple(round(0.5 + 0.05 * i, 2) for i in range(10)) + (0.99,)


def _runs(spark: SparkSession, sf_dir: str, alphas=sweep.ALPHAS) -> DataFrame:
    return sweep.runs_by_share(_events(spark, sf_dir), "event_id", alphas)


def _cells(spark: SparkSession, sf_dir: str, alphas=sweep.ALPHAS) -> DataFrame:
    """The cost model's savings on the synthetic relations over the events."""
    return sweep.sweep_of(_runs(spark, sf_dir, alphas))


def _containment(spark, sf_dir, alphas=_FIFTHS):
    c = sweep.containment(_cells(spark, sf_dir, alphas))
    return c.select("dist", "family", "cells", (F.col("below_lower") + sum((F.col(f"above_{f}") for f in FORMS), F.lit(0))).cast("long").alias("outside"))


_CONTAINMENT_SQL = "SELECT dist, family, cells, CAST(0 AS BIGINT) AS outside FROM (VALUES ('unique'), ('zipf'), ('uniform100')) d(dist), (VALUES ('xor', CAST(88 AS BIGINT)), ('fuse3', 88), ('bloom1', 176), ('bloom3', 176)) f(family, cells)"

_CONTAINMENT_ALL_SQL = "SELECT dist, family, cells, CAST(0 AS BIGINT) AS outside FROM (VALUES ('unique'), ('zipf'), ('uniform100')) d(dist), (VALUES ('xor', CAST(400 AS BIGINT)), ('fuse3', 400), ('bloom1', 800), ('bloom3', 800)) f(family, cells)"


def _no_harm(spark, sf_dir):
    return sweep.decision_confusion(_cells(spark, sf_dir)).select("dist", "family", "gated_harm")


_NO_HARM_SQL = "SELECT dist, family, CAST(0 AS BIGINT) AS gated_harm FROM (VALUES ('unique'), ('zipf'), ('uniform100')) d(dist), (VALUES ('xor'), ('fuse3'), ('bloom1'), ('bloom3')) f(family)"


def _regret(spark, sf_dir):
    return sweep.parameter_regret(sweep.sweep(ship(spark))).agg((F.max("regret") <= 0.02).alias("small_regret"), (F.max("steps") <= 1).alias("near"))


# ---------------------------------------------------------------- methods compared


SYNTHETIC = tuple(f"{dist}_{alpha}" for dist in sweep.DISTRIBUTIONS for alpha in (0.5, 0.8, 0.95))
#: The last three are k-mer tables of high, low and middle skew.
NATURAL = ("part_supp", "lang", "lines_per_order", "fold15", "fold8", "kmer12")
METHODS = ("gap", "entropy_fit", "hash_table", "perfect_hash", "model_coded")
#: Keys of a workload up to which all methods' answers are compared at the same time; beyond, one after the other.
TOGETHER_KEYS = 1 << 20


def method_table(spark: SparkSession, sf_dir: str, workloads=("part_supp", "lang"), methods=METHODS, repeats: int = 1) -> DataFrame:
    """(workload, method, bpk, ns, build_s, mismatches) of each method on each workload."""
    rows = []
    for name in workloads:
        with scratch():
            rows += _method_rows(spark, sf_dir, name, methods, repeats)
    return _frame(spark, rows, "workload string, method string, bpk double, ns double, build_s double, mismatches long")


def _method_rows(spark: SparkSession, sf_dir: str, name: str, methods: tuple[str, ...], repeats: int) -> list[tuple]:
    """Builds and lookups are timed one at a time; what is not timed, sizes and comparisons, is then run side by side."""
    df, spec = _base(spark, sf_dir, name) if name in WORK_SQL else (_synthetic(float(name.split("_")[1]), name.split("_")[0])(spark, sf_dir), KeyValueSpec(("key",), "value"))
    df = stored(df, "workload")  # a cached one would bring its whole lineage into the plans of some fifty jobs
    together = len(methods) if df.count() <= TOGETHER_KEYS else 1
    timed = []
    for method in methods:
        make = {
            "gap": lambda: planner.build_index(df, spec, "gap", ("fuse3",)), "entropy_fit": lambda: planner.build_index(df, spec, "entropy_fit", ("fuse3",)),
            "hash_table": lambda: baselines.HashTable.build(df, spec), "perfect_hash": lambda: baselines.PerfectHashTable.build(df, spec), "model_coded": lambda: baselines.best_model(df, spec),
        }[method]
        ix, took = measure.timed(make)
        timed.append((method, ix, measure.lookup_latency(ix, df.select(*spec.keys), repeats, inside=False).first()["net_ns"], took))
    with ThreadPoolExecutor(max(1, together)) as pool:
        return list(pool.map(lambda t: (name, t[0], measure.total_bpk(t[1]), t[2], t[3], measure.mismatches(t[1], df, spec.keys, spec.value).count()), timed))


def _compared(spark, sf_dir):
    """All methods on the synthetic relations of every distribution and share, and on the natural workloads."""
    table = method_table
    return _once(spark, sf_dir, lambda: table(ship(spark), sf_dir, SYNTHETIC + NATURAL), "methods", table)


def _exact_table(spark, sf_dir):
    return method_table(ship(spark), sf_dir).select("workload", "method", "mismatches")


_EXACT_SQL = "SELECT workload, method, CAST(0 AS BIGINT) AS mismatches FROM (VALUES ('part_supp'), ('lang')) w(workload), (VALUES ('gap'), ('entropy_fit'), ('hash_table'), ('perfect_hash'), ('model_coded')) m(method)"


def _bijection(spark, sf_dir):
    df, spec = _base(spark, sf_dir, "part_supp")
    ids = baselines.PerfectHashTable.build(df, spec).ids(df.select(*spec.keys))
    return ids.agg(F.min("id").alias("least"), F.max("id").alias("most"), F.countDistinct("id").alias("different"))


def _no_false_negatives(family: str) -> Query:
    def run(spark, sf_dir):
        df, spec = _base(spark, sf_dir, "part_supp")
        ix = index.build(df, spec, _gate(family))
        top = stats.profile(df, spec.value).dominant
        minority = df.where(~F.col(spec.value).eqNullSafe(F.lit(top)))
        wrong = ix.lookup(minority.select(*spec.keys)).where(F.col(spec.value).eqNullSafe(F.lit(top)))
        return minority.agg(F.count(F.lit(1)).alias("minority")).crossJoin(wrong.agg(F.count(F.lit(1)).alias("rejected")))

    return run


# ---------------------------------------------------------------- relational surroundings


def _alpha_cube(how: str) -> Query:
    def run(spark, sf_dir):
        d = tables.table(ship(spark), sf_dir, "documents", "lang", "source")
        return getattr(d, how)("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("lang") == "en").alias("dominant")).select("lang", "source", "n", F.round(F.col("dominant") / F.col("n"), 6).alias("alpha"))

    return run


def _savings_pivot(spark, sf_dir):
    g = _grid(ship(spark), ("xor", "fuse3"))
    lb = lower_bound(F.col("alpha"), F.col("eps"), F.col("bits"), F.lit(_RATIO))
    return g.withColumn("lb", lb).groupBy("alpha").pivot("family", ["fuse3", "xor"]).agg(F.round(F.max("lb"), 6))


def _asof(spark, sf_dir):
    e = tables.table(ship(spark), sf_dir, "events", "event_id", "ts", "user_id", "event_type", "value")
    changes = e.where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("value").alias("value"))
    return joins.asof(e.select("event_id", "user_id", "ts"), changes, "user_id", "ts", "value").select("event_id", "as_of")


_ASOF_SQL = """WITH c AS (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'purchase' GROUP BY 1, 2)
SELECT e.event_id, c.value AS as_of FROM events e ASOF LEFT JOIN c ON e.user_id = c.user_id AND e.ts >= c.ts"""


def _interval(spark, sf_dir):
    e = tables.table(ship(spark), sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    a = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("ts").alias("t0"), F.col("user_id").alias("u0"))
    b = e.where("event_type <> 'purchase'").select("event_id", "ts", "user_id")
    return joins.interval(a, b, "t0", "ts", 3600, F.col("u0") == F.col("user_id")).select("purchase_id", "event_id")


_INTERVAL_SQL = """SELECT a.event_id AS purchase_id, b.event_id FROM events a JOIN events b ON a.user_id = b.user_id
AND a.event_type = 'purchase' AND b.event_type <> 'purchase' AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 3600000000"""


def _version_diff(spark, sf_dir):
    d = tables.table(ship(spark), sf_dir, "documents", "doc_id", "lang")
    old = d.where("doc_id % 10 <> 1")
    new = d.where("doc_id % 10 <> 2").withColumn("lang", F.when(F.col("doc_id") % 10 == 3, "xx").otherwise(F.col("lang")))
    return joins.version_diff(old, new, ("doc_id",), "lang")


_VERSION_SQL = """WITH o AS (SELECT doc_id, lang FROM documents WHERE doc_id % 10 <> 1), n AS (SELECT doc_id, CASE WHEN doc_id % 10 = 3 THEN 'xx' ELSE lang END AS lang FROM documents WHERE doc_id % 10 <> 2)
SELECT doc_id, o.lang AS old, n.lang AS new, CASE WHEN o.doc_id IS NULL THEN 'added' WHEN n.doc_id IS NULL THEN 'removed' ELSE 'changed' END AS change
FROM (SELECT doc_id, lang, doc_id AS k FROM o) o FULL JOIN n USING (doc_id) WHERE o.lang IS DISTINCT FROM n.lang""".replace("o.doc_id IS NULL", "o.k IS NULL").replace("n.doc_id IS NULL", "n.k IS NULL").replace("FULL JOIN n USING", "FULL JOIN (SELECT doc_id, lang, doc_id AS k FROM n) n USING")


def _drift(kind: str) -> Query:
    def run(spark, sf_dir):
        e = tables.table(ship(spark), sf_dir, "events", "ts", "event_type").withColumn("ts", F.col("ts").cast("timestamp"))
        out = drift.session(e, "event_type") if kind == "session" else drift.drift({"tumbling": drift.tumbling, "sliding": drift.sliding}[kind](e, "event_type"))
        epoch = lambda c: F.unix_micros(c) / 1000000
        return out.select(epoch("start").cast("long").alias("start_s"), "num_keys", "distinct_values", "dominant_count", F.round("alpha", 6).alias("alpha"))

    return run


_SESSION_SQL = """WITH o AS (SELECT epoch_us(ts) AS t, event_type, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (ORDER BY ts) < 1800000000 THEN 0 ELSE 1 END AS fresh FROM events),
s AS (SELECT *, sum(fresh) OVER (ORDER BY t RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS s FROM o),
c AS (SELECT s, event_type, count(*) AS freq, min(t) AS a FROM s GROUP BY 1, 2)
SELECT CAST(floor(min(a) / 1000000) AS BIGINT) AS start_s, CAST(sum(freq) AS BIGINT) AS num_keys, count(*) AS distinct_values, max(freq) AS dominant_count, round(max(freq) / sum(freq), 6) AS alpha FROM c GROUP BY s"""


def _drift_sql(kind: str) -> str:
    if kind == "session":
        return _SESSION_SQL
    if kind == "tumbling":
        rows = "SELECT CAST(floor(epoch(ts) / 86400) AS BIGINT) * 86400 AS start_s, event_type FROM events"
    else:
        rows = "SELECT (CAST(floor(epoch(ts) / 43200) AS BIGINT) - k) * 43200 AS start_s, event_type FROM events, (VALUES (0), (1)) s(k)"
    return f"WITH c AS (SELECT start_s, event_type, count(*) AS freq FROM ({rows}) GROUP BY 1, 2) SELECT start_s, CAST(sum(freq) AS BIGINT) AS num_keys, count(*) AS distinct_values, max(freq) AS dominant_count, round(max(freq) / sum(freq), 6) AS alpha FROM c GROUP BY 1"


def _sketch(spark, sf_dir):
    """Sketch profiles beside exact ones: the share's limit is below, the value count's above."""
    rows = []
    for name in ("lang", "part_supp", "returnflag"):
        df, spec = _base(spark, sf_dir, name)
        a, b = stats.profile(df, spec.value), stats.sketch_profile(df, spec.value, 0.2)
        rows.append((name, a.num_keys == b.num_keys, b.alpha <= a.alpha + 1e-12, b.distinct_values >= a.distinct_values))
    return _frame(spark, rows, "workload string, same_count boolean, share_below boolean, values_above boolean")


def _heuristic_harm(spark, sf_dir):
    """Whether the heuristic harms somewhere, by how much at most (about a bit), on the synthetic relations over the events."""
    return sweep.heuristic_harm(ship(spark), given=sweep.collected(_runs(spark, sf_dir))).agg((F.min("saving") < 0).alias("harms"), (F.min("saving") > -1.05).alias("about_a_bit"))


def _exhaustive(name: str) -> Query:
    def run(spark, sf_dir):
        runs = huffman.collect_runs(stats.freq_of_freq(_values(spark, sf_dir, name)))
        _, tried = planner.exhaustive_plan(runs, ("xor", "fuse3", "fuse4", "bloom1", "bloom3"))
        return _frame(spark, [(s.family, float(s.param), saving) for s, saving in tried], "family string, param double, saving double")

    return run


def _predicted(spark, sf_dir):
    """Bits saved in all at N = 1,000,000: at least and at most."""
    from .functions.bounds import predict_savings

    g = _grid(ship(spark))
    low, high = predict_savings(F.lit(1_000_000.0), F.col("alpha"), F.col("eps"), F.col("bits"), F.lit(_RATIO))
    return g.select("alpha", "family", "param", F.round(low, 1).alias("at_least"), F.round(high, 1).alias("at_most"))


def _fpr(spark, sf_dir):
    """Dominant keys that pass each gate, against the promised rate."""
    df, spec = _base(spark, sf_dir, "part_supp")
    df = df.cache()
    rows = [(f, abs(measure.observed_fpr(index.build(df, spec, p := _gate(f))) - p.eps) < 0.02) for f in GATED]
    df.unpersist()
    return _frame(spark, rows, "family string, as_promised boolean")


def _ordinal_model(spark, sf_dir):
    """Model-coded map of folded 8-mers with the place of each letter as features."""
    df, spec = _base(spark, sf_dir, "fold8")
    return baselines.ModelCodedMap.build(df, spec, ((50,),), baselines.ordinal_features(F.col("kmer"), 8), 8).lookup(df.select("kmer"))


def _vector_model(spark, sf_dir):
    """Model-coded map of vector labels, the vector being part of the key and the model's features."""
    df = tables.table(ship(spark), sf_dir, "embeddings", "vec_id", "embedding", "label")
    spec = KeyValueSpec(("vec_id", "embedding"), "label")
    features = F.transform("embedding", lambda x: x.cast("double"))
    return baselines.ModelCodedMap.build(df, spec, ((),), features, 64).lookup(df.select("vec_id", "embedding")).select("vec_id", "label")


# ---------------------------------------------------------------- registry


def queries() -> dict[str, Query]:
    q: dict[str, Query] = {}
    for name in PROFILED:
        q[f"profile_{name}"], q[f"histogram_{name}"], q[f"entropy_{name}"], q[f"freq_of_freq_{name}"] = _profile(name), _histogram(name), _entropy(name), _freq_of_freq(name)
        q[f"gap_plan_{name}"], q[f"entropy_fit_plan_{name}"] = _gap_plan(name), _entropy_fit(name)
        q[f"codebook_kraft_{name}"], q[f"entropy_sandwich_{name}"], q[f"huffman_bits_{name}"] = _kraft(name), _sandwich(name), _huffman_bits(name)
    for name in ANY_FAMILY:
        q[f"gap_plan_any_family_{name}"] = _gap_plan(name, GATED)
    for name in LOOKED_UP:
        q[f"lookup_plain_{name}"] = _lookup(name, lambda d, s: planner.build_index(d, s, "never"))
        q[f"lookup_gap_planned_{name}"] = _lookup(name, lambda d, s: planner.build_index(d, s, "gap", GATED))
        q[f"lookup_entropy_fit_{name}"] = _lookup(name, lambda d, s: planner.build_index(d, s, "entropy_fit", ("fuse3",)))
        q[f"lookup_hash_table_{name}"] = _lookup(name, baselines.HashTable.build)
        q[f"lookup_perfect_hash_{name}"] = _lookup(name, baselines.PerfectHashTable.build)
        q[f"lookup_model_coded_{name}"] = _lookup(name, baselines.ModelCodedMap.build)
    for family in GATED:
        q[f"lookup_gated_{family}_part_supp"] = _lookup("part_supp", lambda d, s, f=family: index.build(d, s, _gate(f)))
        q[f"gate_no_false_negatives_{family}"] = _no_false_negatives(family)
    q["lookup_gated_fuse3_four_hashes_part_supp"] = _lookup("part_supp", lambda d, s: index.build(d, s, _gate("fuse3"), hashes=4))
    for name in ("extprice", "custkey", "role", "url_host", "order_part", "fold15", "kmer12", "lines_per_order", "bench_flag"):
        q[f"lookup_gap_planned_{name}"] = _lookup(name, lambda d, s: planner.build_index(d, s, "gap", GATED))
    q["perfect_hash_is_bijection"] = _bijection
    q["lower_bound_grid"] = _bound_grid(lambda a, e, b: lower_bound(a, e, b, F.lit(_RATIO)), "bound")
    for form in FORMS:
        q[f"upper_bound_grid_{form}"] = _bound_grid(lambda a, e, b, f=form: upper_bound(a, e, b, F.lit(_RATIO), form=f), "bound")
    q["bound_gap_grid"] = _gap_grid
    q |= {"gap_plan_alpha_sweep": _alpha_sweep_plans, "break_even_alpha": _break_even, "gap_plan_continuous": _continuous, "entropy_fit_equivalence": _equivalence, "plan_disagreement": _disagreement}
    for dist in sweep.DISTRIBUTIONS:
        for alpha in (0.5, 0.8, 0.95):
            q[f"synthetic_{dist}_{round(alpha * 100)}"] = _synthetic(alpha, dist)
            q[f"lookup_synthetic_{dist}_{round(alpha * 100)}"] = _synthetic_lookup(alpha, dist)
    q |= {
        "alpha_sweep_model": lambda s, d: sweep.sweep(ship(s)), "epsilon_sweep_model": lambda s, d: sweep.epsilon_sweep(ship(s), given=sweep.collected(_runs(s, d, (0.7, 0.9)))), "bounds_containment": _containment, "bounds_containment_all": lambda s, d: _containment(s, d, sweep.ALPHAS), "decision_harm": _no_harm,
        "parameter_regret": _regret, "crossing_alpha": lambda s, d: sweep.crossing(_cells(s, d)), "bounds_tightness": lambda s, d: sweep.tightness(_cells(s, d)), "heuristic_harm": _heuristic_harm,
        "exhaustive_plan_part_supp": _exhaustive("part_supp"), "exactness_by_method": _exact_table, "sketch_profile": _sketch,
        "bpk_table": _compared, "pareto_front": lambda s, d: measure.pareto_front(_compared(s, d)), "ratio_table": lambda s, d: measure.ratio_table(_compared(s, d), "gap"),
    }
    q |= {"predicted_savings": _predicted, "gate_rates": _fpr, "lookup_model_coded_ordinal_fold8": _ordinal_model, "lookup_model_coded_features_vec_label": _vector_model}
    for k in ("kmer8", "kmer12", "kmer15", "kmer31", "fold8", "fold12"):
        q[f"{k}_counts"] = lambda s, d, k=k: tables.workload(ship(s), d, k)[0]
    q["benchmark_kmer_flags"] = lambda s, d: tables.workload(ship(s), d, "bench_flag")[0].groupBy("hit").agg(F.count(F.lit(1)).alias("n"))
    q |= {"alpha_cube": _alpha_cube("cube"), "alpha_rollup": _alpha_cube("rollup"), "savings_pivot": _savings_pivot, "asof_value": _asof, "interval_events": _interval, "version_diff": _version_diff}
    q |= {f"drift_{k}": _drift(k) for k in ("tumbling", "sliding", "session")}
    q |= {
        "measured_sweep": _measured, "measured_decision": _measured_decision, "measured_containment": _measured_contained, "sweep_bounds": _sweep_bounds, "sweep_crossing": _sweep_crossing,
        "measured_decision_detail": lambda s, d: sweep.decision_confusion(_measured(s, d)), "measured_agreement": lambda s, d: sweep.agreement(_measured(s, d)), "measured_crossing": lambda s, d: sweep.crossing(_measured(s, d)),
        "measured_tightness": lambda s, d: sweep.tightness(_measured(s, d)), "epsilon_points": lambda s, d: sweep.epsilon_points(_events(s, d), "event_id"),
    }
    q |= {name: run for name, (run, _) in relational.QUERIES.items()}
    q["panel_regret"] = lambda s, d: relational._panels(s, d, _grid, _RATIO)
    return q


def oracle_sql() -> dict[str, str]:
    o: dict[str, str] = {}
    for name in PROFILED:
        o[f"profile_{name}"] = f"WITH {_profile_sql(name)} SELECT p.*, (SELECT value FROM h ORDER BY freq DESC, value NULLS LAST LIMIT 1) AS dominant FROM p"
        o[f"histogram_{name}"] = _hist(name)
        o[f"entropy_{name}"] = f"WITH h AS ({_hist(name)}), t AS (SELECT sum(freq) AS n FROM h) SELECT round(sum(-(freq / n) * log2(freq / n)), 6) AS entropy FROM h, t"
        o[f"freq_of_freq_{name}"] = f"SELECT freq, count(*) AS multiplicity FROM ({_hist(name)}) GROUP BY 1"
        o[f"gap_plan_{name}"] = _plan_sql(_profile_sql(name))
        o[f"entropy_fit_plan_{name}"] = f"WITH h AS ({_hist(name)}), {_H_SQL} SELECT {_EPS_SQL} < 1 AS use_gate, round(cost, 6) AS map_cost, round({_EPS_SQL}, 6) AS eps FROM c, t"
        o[f"codebook_kraft_{name}"] = f"SELECT count(*) AS codes, count(*) AS different, CAST(1.0 AS DOUBLE) AS kraft_sum FROM ({_hist(name)})"
        o[f"entropy_sandwich_{name}"] = f"WITH h AS ({_hist(name)}), t AS (SELECT sum(freq) AS n FROM h) SELECT round(sum(-(freq / n) * log2(freq / n)), 6) AS entropy, true AS holds FROM h, t"
    for name in ANY_FAMILY:
        o[f"gap_plan_any_family_{name}"] = _plan_sql(_profile_sql(name), GATED)
    for key in queries():
        if key.startswith("lookup_synthetic_"):
            _, _, dist, a = key.split("_")
            o[key] = _synthetic_sql(int(a) / 100, dist)
        elif key.startswith("lookup_"):
            name = next(w for w in sorted(WORK_SQL, key=len, reverse=True) if key.endswith(f"_{w}"))
            o[key] = WORK_SQL[name][2]
        elif key.startswith("synthetic_"):
            _, dist, a = key.split("_")
            o[key] = _synthetic_sql(int(a) / 100, dist)
        elif key.endswith("_counts"):
            o[key] = WORK_SQL[key.removesuffix("_counts")][2]
        elif key.startswith("gate_no_false_negatives_"):
            o[key] = f"WITH {_profile_sql('part_supp')} SELECT p.num_keys - p.dominant_count AS minority, CAST(0 AS BIGINT) AS rejected FROM p"
        elif key.startswith("upper_bound_grid_"):
            o[key] = f"SELECT alpha, family, param, round({UPPER_SQL[key.removeprefix('upper_bound_grid_')]}, 6) AS bound FROM {_GRID_SQL}"
    o["perfect_hash_is_bijection"] = f"SELECT CAST(0 AS BIGINT) AS least, count(*) - 1 AS most, count(*) AS different FROM ({WORK_SQL['part_supp'][2]})"
    o["lower_bound_grid"] = f"SELECT alpha, family, param, round(alpha * {DELTA3} * (1 - eps) - (1 - alpha) * bits - {_RATIO}, 6) AS bound FROM {_GRID_SQL}"
    o["bound_gap_grid"] = _GAP_GRID_SQL
    o |= {"gap_plan_alpha_sweep": _ALPHA_SWEEP_SQL, "break_even_alpha": _BREAK_EVEN_SQL, "gap_plan_continuous": _CONTINUOUS_SQL, "plan_disagreement": _disagreement_sql()}
    o["entropy_fit_equivalence"] = _EQUIVALENCE_SQL
    o |= {"bounds_containment": _CONTAINMENT_SQL, "bounds_containment_all": _CONTAINMENT_ALL_SQL, "decision_harm": _NO_HARM_SQL, "parameter_regret": "SELECT true AS small_regret, true AS near", "heuristic_harm": "SELECT true AS harms, true AS about_a_bit", "exactness_by_method": _EXACT_SQL}
    low, high = f"alpha * {DELTA3} * (1 - eps) - (1 - alpha) * bits - {_RATIO}", UPPER_SQL["binary_entropy"]
    o["predicted_savings"] = f"SELECT alpha, family, param, round(1000000 * ({low}), 1) AS at_least, round(1000000 * ({high}), 1) AS at_most FROM {_GRID_SQL}"
    o["gate_rates"] = "SELECT family, true AS as_promised FROM (VALUES ('xor'), ('fuse3'), ('fuse4'), ('bloom1'), ('bloom3')) f(family)"
    o["sketch_profile"] = "SELECT workload, true AS same_count, true AS share_below, true AS values_above FROM (VALUES ('lang'), ('part_supp'), ('returnflag')) w(workload)"
    o["benchmark_kmer_flags"] = f"SELECT hit, count(*) AS n FROM ({WORK_SQL['bench_flag'][2]}) GROUP BY 1"
    for how in ("cube", "rollup"):
        o[f"alpha_{how}"] = f"SELECT lang, source, count(*) AS n, round(count(*) FILTER (lang = 'en') / count(*), 6) AS alpha FROM documents GROUP BY {how}(lang, source)"
    lb = f"alpha * {DELTA3} * (1 - eps) - (1 - alpha) * bits - {_RATIO}"
    o["savings_pivot"] = f"SELECT alpha, round(max({lb}) FILTER (family = 'fuse3'), 6) AS fuse3, round(max({lb}) FILTER (family = 'xor'), 6) AS xor FROM {_GRID_SQL} GROUP BY alpha"
    o |= {"asof_value": _ASOF_SQL, "interval_events": _INTERVAL_SQL, "version_diff": _VERSION_SQL}
    o |= {f"drift_{k}": _drift_sql(k) for k in ("tumbling", "sliding", "session")}
    o |= {"measured_decision": _NO_HARM_SQL, "measured_containment": _MEASURED_CONTAINED_SQL, "sweep_bounds": _SWEEP_BOUNDS_SQL, "sweep_crossing": _SWEEP_CROSSING_SQL}
    o |= {name: sql for name, (_, sql) in relational.QUERIES.items()}
    o["panel_regret"] = f"""WITH g AS (SELECT *, alpha * {DELTA3} * (1 - eps) - (1 - alpha) * bits - {_RATIO} AS bound FROM {_GRID_SQL}),
    r AS (SELECT *, max(bound) OVER (PARTITION BY alpha) - bound AS regret, CAST(row_number() OVER (PARTITION BY alpha, family ORDER BY bound DESC, param) AS INTEGER) AS place FROM g)
    SELECT alpha, family, place, param, round(regret, 6) AS regret FROM r WHERE place <= 2"""
    return o


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gap-planned index of part and supplier pairs to line counts, looked up for every key."""
    df, spec = _base(spark, sf_dir, "part_supp")
    return planner.build_index(df, spec, "gap", GATED).lookup(df.select(*spec.keys)).select(*spec.keys, spec.value)


__all__ = ["flagship", "method_table", "oracle_sql", "queries"]
