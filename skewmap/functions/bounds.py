"""Bounds on the bits per key that a gate saves, as Columns or as floats.

Every function takes floats or Columns alike: the arithmetic is written once and the few functions beyond
it are chosen by argument type. ``ratio`` is distinct values over keys; ``delta`` the overhead of the linear
system.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

DELTA3, DELTA4 = 1.089, 1.024


def _log2(x):
    return F.log2(x) if isinstance(x, Column) else math.log2(x)


def _plogp(x):
    """x log2(1/x), 0 at 0."""
    if isinstance(x, Column):
        return F.when(x > 0, -x * F.log2(x)).otherwise(0.0)
    return -x * math.log2(x) if x > 0 else 0.0


def lower_bound(alpha, eps, bits, ratio, delta=DELTA3, l0=1):
    """Bits per key saved at least, in expectation; ``l0`` is the dominant value's code length, at least 1."""
    return alpha * delta * l0 * (1 - eps) - (1 - alpha) * bits - ratio


FORMS = ("tight", "binary_entropy", "two_bits", "simplified")


def upper_bound(alpha, eps, bits, ratio, delta=DELTA3, form="simplified"):
    """Bits per key saved at most, in one of four forms.

    ``binary_entropy`` has the entropy of the dominant share and a linear term for the leaked keys;
    ``two_bits`` takes that entropy for one bit; ``simplified`` also takes the linear term's factor for a half
    (for a share over a third it can lie below ``two_bits``); ``tight`` keeps the exact difference of the two
    entropies, at the expected number of leaked keys.
    """
    rest = ratio - bits * (1 - alpha)
    if form == "tight":
        passed = (1 - alpha) + alpha * eps
        before = _plogp(alpha) + _plogp(1 - alpha)
        after = passed * (_plogp(alpha * eps / passed) + _plogp((1 - alpha) / passed))
        return delta * (1 + before - after) + rest
    linear = 2 * alpha * eps * (1 - alpha) / (3 - alpha)
    if form == "binary_entropy":
        return delta * (1 + _plogp(alpha) + _plogp(1 - alpha) - linear) + rest
    if form == "two_bits":
        return delta * (2 - linear) + rest
    if form == "simplified":
        return delta * (2 - alpha * eps / 2) + rest
    raise ValueError(f"unknown form {form!r}; one of {FORMS}")


def bound_gap(alpha, eps, ratio, delta=DELTA3):
    """Simplified upper bound minus lower bound; positive for every share and rate."""
    return 2 * delta - alpha * delta + alpha * delta * eps / 2 + 2 * ratio


def predict_savings(num_keys, alpha, eps, bits, ratio, delta=DELTA3, form="binary_entropy"):
    """Range of bits saved in all, for planning capacity: (at least, at most)."""
    return num_keys * lower_bound(alpha, eps, bits, ratio, delta), num_keys * upper_bound(alpha, eps, bits, ratio, delta, form)
