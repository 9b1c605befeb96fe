import heapq
import math
from collections import Counter

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from skewmap.functions import bounds
from skewmap.functions.gatecost import FAMILIES
from skewmap.operators.huffman import Code
from skewmap.operators.index import model_bits
from skewmap.operators.stats import Profile
from skewmap.plans import planner

FREQS = st.lists(st.integers(1, 5000), min_size=1, max_size=40)


def runs_of(freqs):
    return sorted(Counter(freqs).items())


def heap_bits(freqs):
    h, total = list(freqs), 0
    heapq.heapify(h)
    while len(h) > 1:
        x = heapq.heappop(h) + heapq.heappop(h)
        total += x
        heapq.heappush(h, x)
    return total


@given(FREQS)
@settings(max_examples=200, deadline=None)
def test_code_is_optimal_and_complete(freqs):
    runs = runs_of(freqs)
    code = Code.of(runs)
    assert code.total_bits(runs) == heap_bits(freqs)
    assert sum(code.counts) == len(freqs)
    assert len(freqs) == 1 or sum(c * 2.0**-n for n, c in zip(code.lengths, code.counts)) == 1
    ranks = np.arange(len(freqs))
    size, word = code.encode(ranks)
    assert len({(a, b) for a, b in zip(size.tolist(), word.tolist())}) == len(freqs)


@pytest.mark.parametrize("freqs", [[1, 1, 2, 3, 5, 8, 13, 21, 34, 55], [1] * 1000, [7], [5, 5], [108, 21, 31, 14, 50, 13], [9, 21, 31, 14, 50, 13]])
def test_code_on_known_shapes(freqs):
    assert Code.of(runs_of(freqs)).total_bits(runs_of(freqs)) == heap_bits(freqs)


def test_tree_depth_may_fall_by_two():
    assert Code.of(runs_of([108, 21, 31, 14, 50, 13])).longest == 5
    assert Code.of(runs_of([9, 21, 31, 14, 50, 13])).longest == 3


@given(FREQS)
@settings(max_examples=100, deadline=None)
def test_mean_length_within_a_bit_of_entropy(freqs):
    n = sum(freqs)
    h = -sum(f / n * math.log2(f / n) for f in freqs)
    mean = Code.of(runs_of(freqs)).total_bits(runs_of(freqs)) / n
    assert h - 1e-9 <= mean <= h + 1 + 1e-9


@given(FREQS, st.sampled_from(["xor", "fuse3", "fuse4", "bloom1", "bloom3"]), st.integers(0, 7))
@settings(max_examples=200, deadline=None)
def test_bounds_hold_and_codebooks_stay_close(freqs, family, i):
    freqs = freqs if len(freqs) > 1 else freqs + [1]  # one symbol has length 0 and is never gated
    runs = runs_of(freqs)
    n, d, top = sum(freqs), len(freqs), max(freqs)
    s = FAMILIES[family].settings()[i]
    alone = model_bits(runs)
    leaked = max(1, round(s.eps * top))
    gated = model_bits(runs, s.eps, s.bits)
    assert abs(alone["code_lengths"] - gated["code_lengths"]) <= d
    eps = leaked / top  # the rate that really leaks this many
    saving = (alone["map"] + alone["code_lengths"] - gated["map"] - gated["gate"] - gated["code_lengths"]) / n
    assert bounds.lower_bound(top / n, eps, s.bits, d / n) <= saving + 1e-9
    for form in ("tight", "binary_entropy", "two_bits"):
        assert saving <= bounds.upper_bound(top / n, eps, s.bits, d / n, form=form) + 1e-9


@given(st.floats(0.01, 0.99), st.floats(0.001, 0.999), st.floats(0, 5), st.floats(0, 1))
@settings(max_examples=200, deadline=None)
def test_gap_is_upper_less_lower_and_positive(a, e, b, r):
    gap = bounds.bound_gap(a, e, r)
    assert gap > 0
    assert math.isclose(gap, bounds.upper_bound(a, e, b, r) - bounds.lower_bound(a, e, b, r), abs_tol=1e-9)


@given(st.floats(0, 1e6))
def test_logarithm_inequality(z):
    assert -math.log1p(z) <= -2 * z / (2 + z) + 1e-9


@given(st.floats(0.01, 0.99), st.floats(0, 12))
def test_heuristic_conditions_agree(alpha, h):
    cost = planner.entropy_fit_cost(h)
    eps = planner.heuristic_eps(alpha, 1.44, cost)
    threshold = planner.heuristic_threshold(1.44, cost)
    if abs(eps - 1) > 1e-9:
        assert (eps < 1) == (alpha > threshold)
        if eps < 1:
            assert planner.heuristic_ratio(alpha, eps, 1.44, cost) < 1 + 1e-12


def test_regression_meets_itself():
    assert math.isclose(planner.entropy_fit_cost(2 - 1e-12), planner.entropy_fit_cost(2), abs_tol=1e-9)


@pytest.mark.parametrize("alpha", [0.72, 0.8, 0.9, 0.97])
@pytest.mark.parametrize("family", ["xor", "fuse3", "fuse4"])
def test_continuous_rate_is_near_the_discrete_one(alpha, family):
    p = Profile(100_000, 100, round(alpha * 100_000))
    a, b = planner.gap_plan(p, (family,)), planner.gap_plan(p, (family,), mode="continuous")
    assert b.bound >= a.bound - 1e-12
    assert abs(math.log2(1 / b.eps) - a.param) <= 1.0


def test_numeric_search_matches_closed_form():
    from dataclasses import replace

    f = FAMILIES["xor"]
    a, b = planner.continuous_setting(f, 0.9), planner.continuous_setting(replace(f, log_cost=None), 0.9)
    assert math.isclose(a.eps, b.eps, rel_tol=1e-4)


def test_break_even():
    assert planner.break_even_alpha("xor") == pytest.approx(0.693, abs=1e-3)
    assert planner.break_even_alpha("fuse3") == pytest.approx(0.674, abs=1e-3)


def test_registered_family_is_planned_with():
    from skewmap.functions.gatecost import GateFamily, register_gate_family

    register_gate_family(GateFamily("cheap", (1, 2), lambda r: 2.0**-r, lambda e: 0.5 * math.log2(1 / e), None, 0.5))
    try:
        assert planner.gap_plan(Profile(1000, 2, 800), ("xor", "cheap")).family == "cheap"
    finally:
        FAMILIES.pop("cheap")


def test_no_gate_for_one_value_or_none():
    assert not planner.gap_plan(Profile(1000, 1, 1000)).use_gate
    assert not planner.gap_plan(Profile(0, 0, 0)).use_gate
    assert not planner.gap_plan(Profile(1000, 1000, 1)).use_gate


def test_explain_tells_the_decision():
    assert "gate: fuse3" in planner.explain(Profile(10_000, 3, 9_000))
    assert "no gate" in planner.explain(Profile(10_000, 3, 4_000))
