"""Deciding whether to gate an index, and how, before building anything.

The gap planner maximises the lower bound on savings over gate settings and gates only when it is positive; it
needs the dominant share and the number of distinct values alone. The entropy-fit planner is the earlier
heuristic with a regression of map cost on entropy; the exhaustive planner tries every setting.
"""

from __future__ import annotations

import math
from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.bounds import DELTA3, lower_bound
from ..functions.gatecost import FAMILIES, GateFamily, Setting, settings
from ..operators.index import SHARD_KEYS, Plan, build, build_relation, model_bits, relation, shard_count
from ..operators.stats import Profile
from ..sources.keyvalue import KeyValueSpec

LOG2E = math.log2(math.e)


def settings_frame(spark: SparkSession, families: Iterable[str]) -> DataFrame:
    """(family, param, eps, bits): one row a setting."""
    rows = [(s.family, float(s.param), s.eps, s.bits) for s in settings(families)]
    return spark.createDataFrame(rows, "family string, param double, eps double, bits double")


def plan_frame(profile: DataFrame, spark: SparkSession, families: Iterable[str] = ("fuse3",), delta: float = DELTA3) -> DataFrame:
    """The decision as a plan over a one-row profile: use_gate, family, param, eps, bits, bound.

    Settings are a handful of literal rows; the product with the one profile row is the planner's grid.
    Ties go to fewer bits, then to the family's name.
    """
    grid = settings_frame(spark, families).crossJoin(F.broadcast(profile))
    alpha, ratio = F.col("dominant_count") / F.col("num_keys"), F.col("distinct_values") / F.col("num_keys")
    scored = grid.withColumn("bound", lower_bound(alpha, F.col("eps"), F.col("bits"), ratio, delta))
    best = scored.agg(F.max_by(F.struct("family", "param", "eps", "bits", "bound"), F.struct("bound", -F.col("bits"))).alias("b"))
    return best.select((F.col("b.bound") > 0).alias("use_gate"), "b.family", "b.param", "b.eps", "b.bits", "b.bound")


def _scored(profile: Profile, choices: list[Setting], delta: float, l0: float) -> list[tuple[float, Setting]]:
    return [(lower_bound(profile.alpha, s.eps, s.bits, profile.ratio, delta, l0), s) for s in choices]


def gate_keys(profile: Profile, shard_keys: int = SHARD_KEYS) -> float:
    """Keys of each gate of an index to be built: a shard's share of the minority keys."""
    return (profile.num_keys - profile.dominant_count) / shard_count(profile.num_keys, shard_keys)


def gap_plan(profile: Profile, families: Iterable[str] = ("fuse3",), delta: float = DELTA3, mode: str = "discrete", l0: float = 1, keys: float | None = None) -> Plan:
    """Gate at the setting of the greatest lower bound, if that is positive.

    ``keys``: keys of each gate (``gate_keys``), to plan with what gates of that size take when stored; without
    it they cost what they do at large.
    """
    if profile.distinct_values <= 1 or not profile.num_keys:
        return Plan(False, planner="gap")
    if mode == "continuous":
        choices = [s for f in families if (s := continuous_setting(FAMILIES[f], profile.alpha, delta, l0))]
    else:
        choices = settings(families, keys)
    bound, best = min(_scored(profile, choices, delta, l0), key=lambda x: (-x[0], x[1].bits, x[1].family), default=(0.0, None))
    if best is None or bound <= 0:
        return Plan(False, bound=bound, planner="gap")
    return Plan(True, best.family, best.param, best.eps, best.bits, bound, "gap")


def continuous_setting(family: GateFamily, alpha: float, delta: float = DELTA3, l0: float = 1) -> Setting | None:
    """Setting of greatest lower bound with a continuous rate: in closed form for logarithmic costs, else by ternary search."""
    if not 0 < alpha <= 1:
        return None
    if alpha == 1:
        eps = 1e-9
    elif family.log_cost:
        eps = min(1.0, family.log_cost * LOG2E * (1 - alpha) / (alpha * delta * l0))
    else:
        low, high = 1e-6, 1 - 1e-6
        gain = lambda e: lower_bound(alpha, e, family.bits(e), 0, delta, l0)
        for _ in range(60):
            a, b = low + (high - low) / 3, high - (high - low) / 3
            low, high = (a, high) if gain(a) < gain(b) else (low, b)
        eps = (low + high) / 2
    bits = family.bits(eps) if eps < 1 else 0.0
    return Setting(family.name, -math.log2(eps) if family.log_cost else bits, eps, bits)


def break_even_alpha(family: str, ratio: float = 0.0, delta: float = DELTA3) -> float:
    """Dominant share from which some setting of the family has a positive bound; below it planning can be skipped."""
    found = [(s.bits + ratio) / (delta * (1 - s.eps) + s.bits) for s in FAMILIES[family].settings() if s.eps < 1]
    return min(found)


# ---------------------------------------------------------------- the earlier heuristic


def entropy_fit_cost(h: float) -> float:
    """Bits per key of a coded map by the published regression on entropy."""
    return 0.22 * h * h + 0.18 * h + 1.16 if h < 2 else 1.1 * h + 0.2


def heuristic_total_bits(num_keys: int, alpha: float, eps: float, gate_cost: float, map_cost: float) -> float:
    """Bits that the heuristic expects of a gated map."""
    return gate_cost * (1 - alpha) * num_keys * math.log2(1 / eps) + map_cost * num_keys * ((1 - alpha) + eps * alpha)


def heuristic_ratio(alpha: float, eps: float, gate_cost: float, map_cost: float) -> float:
    """The heuristic gates where this is below 1."""
    return gate_cost / map_cost * (1 - alpha) / alpha * math.log2(1 / eps) + eps


def heuristic_eps(alpha: float, gate_cost: float, map_cost: float) -> float:
    return gate_cost / map_cost * (1 - alpha) / alpha * LOG2E if alpha else math.inf


def heuristic_threshold(gate_cost: float, map_cost: float) -> float:
    return gate_cost * LOG2E / (map_cost + gate_cost * LOG2E)


def entropy_fit_plan(profile: Profile, entropy: float, family: str = "ideal_bloom") -> Plan:
    """The heuristic with a logarithmic gate cost; discrete families round log2(1/eps) to a whole number of bits."""
    gate_cost = FAMILIES[family].log_cost
    eps = heuristic_eps(profile.alpha, gate_cost, entropy_fit_cost(entropy))
    if profile.distinct_values <= 1 or eps >= 1:
        return Plan(False, planner="entropy_fit", eps=eps)
    if family == "ideal_bloom":
        return Plan(True, family, -math.log2(eps) if eps else 30.0, eps, FAMILIES[family].bits(max(eps, 1e-9)), planner="entropy_fit")
    r = min(8, max(1, round(-math.log2(eps)))) if eps > 0 else 8
    return Plan(True, family, r, 2.0**-r, FAMILIES[family].bits(2.0**-r), planner="entropy_fit")


# ---------------------------------------------------------------- exhaustive search


def exhaustive_plan(runs: list[tuple[int, int]], families: Iterable[str] = ("fuse3",), delta: float = DELTA3, keys: float | None = None) -> tuple[Plan, list[tuple[Setting, float]]]:
    """Best setting by the cost model, and every setting's saving per key over the ungated map."""
    n = sum(f * m for f, m in runs)
    alone = model_bits(runs, delta=delta)
    base = alone["map"] + alone["code_lengths"]
    out = []
    for s in settings(families, keys):
        terms = model_bits(runs, s.eps, s.bits, delta)
        out.append((s, (base - terms["map"] - terms["gate"] - terms["code_lengths"]) / n))
    best, saving = max(out, key=lambda x: (x[1], -x[0].bits))
    plan = Plan(True, best.family, best.param, best.eps, best.bits, saving, "exhaustive") if saving > 0 else Plan(False, bound=saving, planner="exhaustive")
    return plan, out


def exhaustive_measured(df: DataFrame, spec: KeyValueSpec, families: Iterable[str] = ("fuse3",), **options) -> tuple[Plan, list[tuple[Plan, float]]]:
    """Builds the ungated map and every setting, and takes the smallest by stored bits."""
    tried, made = [], relation(df, spec)
    for plan in [Plan(False, planner="exhaustive"), *(Plan(True, s.family, s.param, s.eps, s.bits, planner="exhaustive") for s in settings(families))]:
        size = build_relation(made, plan, **options).measured_bits().groupBy().sum("bpk").first()[0]
        tried.append((plan, size))
    return min(tried, key=lambda x: x[1])[0], tried


PLANNERS = ("gap", "entropy_fit", "exhaustive", "never", "always")


def build_index(df: DataFrame, spec: KeyValueSpec, planner: str = "gap", families: Iterable[str] = ("fuse3",), delta: float = DELTA3, **options):
    """Profile, plan, build: the whole way from a relation to an index. The relation is read once and stored."""
    made = relation(df, spec, options.pop("seed", 0))
    prof, families = made.profile, tuple(families)
    keys = gate_keys(prof, options.get("shard_keys", SHARD_KEYS))
    if planner == "gap":
        plan = gap_plan(prof, families, delta, keys=keys)
    elif planner == "entropy_fit":
        plan = entropy_fit_plan(prof, made.entropy, families[0])
    elif planner == "exhaustive":
        plan = exhaustive_plan(made.runs, families, delta, keys)[0] if made.runs else Plan(False, planner="exhaustive")
    elif planner == "never":
        plan = Plan(False, planner="never")
    elif planner == "always":
        bound, best = max(_scored(prof, settings(families, keys), delta, 1), key=lambda x: x[0])
        plan = Plan(True, best.family, best.param, best.eps, best.bits, bound, "always")
    else:
        raise ValueError(f"planner is one of {PLANNERS}")
    return build_relation(made, plan, **options)


def explain(profile: Profile, families: Iterable[str] = ("fuse3",), delta: float = DELTA3) -> str:
    """Table of settings with the lower bound and two upper bounds, and the decision with its reason."""
    from ..functions.bounds import upper_bound

    rows = [f"{'family':>12} {'param':>6} {'eps':>9} {'bits':>7} {'lower':>8} {'entropy':>8} {'simple':>8}"]
    for bound, s in _scored(profile, settings(families), delta, 1):
        ups = [upper_bound(profile.alpha, s.eps, s.bits, profile.ratio, delta, f) for f in ("binary_entropy", "simplified")]
        rows.append(f"{s.family:>12} {s.param:>6g} {s.eps:>9.5f} {s.bits:>7.3f} {bound:>8.4f} {ups[0]:>8.4f} {ups[1]:>8.4f}")
    plan = gap_plan(profile, families, delta)
    rows.append(f"gate: {plan.family} {plan.param:g}, at least {plan.bound:.4f} bits a key saved" if plan.use_gate else f"no gate: the best lower bound is {plan.bound:.4f}")
    return "\n".join(rows)
