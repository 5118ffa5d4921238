"""Scores and measures, as Column expressions and as plain functions; all logarithms are base 2."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def kl2(x: Column, y: Column) -> Column:
    """Divergence in bits of a coin of frequency x from one of probability y; null where it is infinite."""
    part = lambda a, b: F.when(a <= 0, F.lit(0.0)).when(b > 0, a * F.log2(a / b))
    return part(x, y) + part(1 - x, 1 - y)


def kl2_value(x: float, y: float) -> float:
    total = 0.0
    for a, b in ((x, y), (1 - x, 1 - y)):
        if a > 0:
            if b <= 0:
                return math.inf
            total += a * math.log2(a / b)
    return total


def penalty(score: str, size: int, n: float, items: int) -> float:
    """What one more itemset of `size` costs beyond its share of the score, a row: 0 for BIC."""
    return size * math.log2(items) / n if score == "mdl" else 0.0


def bic(log_likelihood: float, k: int, n: float) -> float:
    return -log_likelihood + k / 2 * math.log2(n)


def set_bits(n: float, items: int, approximate: bool = False) -> float:
    """Bits for an itemset's frequency, size and place, besides its items."""
    return math.log2(n) + (math.log2(math.e) if approximate else items * math.log2(1 + 1 / items)) + 1


def mdl(log_likelihood: float, k: int, total_items: int, n: float, items: int, approximate: bool = False) -> float:
    return -log_likelihood + set_bits(n, items, approximate) * k + math.log2(items) * total_items + 1


def score(kind: str, log_likelihood: float, k: int, total_items: int, n: float, items: int) -> float:
    n, items = max(n, 1), max(items, 1)  # no rows, or none with an item: nothing to describe
    return bic(log_likelihood, k, n) if kind == "bic" else mdl(log_likelihood, k, total_items, n, items)


def branch_bound(fr: float, est: float, fr_full: float, est_full: float) -> float:
    """What no superset's surprise exceeds whose frequency lies in [fr_full, fr] and estimate in [est_full, est]."""
    return max(kl2_value(fr, est_full), kl2_value(fr_full, est))


def binomial_two_tailed(f: int, d: int, p: float) -> float:
    """Probability under Binomial(d, p) of f, of what lies beyond it, and of the other end's outcomes that are no likelier."""
    if p <= 0 or p >= 1:
        return float((f == 0) if p <= 0 else (f == d))
    log_choose = lambda k: math.lgamma(d + 1) - math.lgamma(k + 1) - math.lgamma(d - k + 1)
    mass = lambda k: math.exp(log_choose(k) + k * math.log(p) + (d - k) * math.log1p(-p))
    at = mass(f) * (1 + 1e-9)
    if f >= d * p:
        near = math.fsum(mass(k) for k in range(f, d + 1))
        far = math.fsum(m for k in range(0, math.ceil(d * p)) if k < f and (m := mass(k)) <= at)
    else:
        near = math.fsum(mass(k) for k in range(0, f + 1))
        far = math.fsum(m for k in range(math.floor(d * p) + 1, d + 1) if k > f and (m := mass(k)) <= at)
    return min(1.0, near + far)


def stirling_bits(f: Column, d: Column, p: Column) -> Column:
    """d times the divergence of f / d from p: what the logarithm of the binomial mass is near to."""
    return d * kl2(f / d, p)


def log_gamma(x: np.ndarray) -> np.ndarray:
    """Logarithm of the gamma function for x > 0, by Stirling's series at x + 8."""
    x = np.asarray(x, float)
    y = x + 8
    series = (y - 0.5) * np.log(y) - y + 0.5 * math.log(2 * math.pi) + 1 / (12 * y) - 1 / (360 * y**3) + 1 / (1260 * y**5) - 1 / (1680 * y**7)
    return series - sum(np.log(x + k) for k in range(8))


def binomial_two_tailed_many(f: np.ndarray, d: np.ndarray, p: np.ndarray) -> np.ndarray:
    """`binomial_two_tailed` for many at once: tails are summed outwards until their terms vanish, the far tail's
    start is found by bisection, so that the work follows the square root of d.
    """
    f, d, p = (np.asarray(v, float) for v in (f, d, p))
    out = np.where(p <= 0, f == 0, f == d).astype(float)
    live = np.flatnonzero((p > 0) & (p < 1))
    f, d, p = f[live], d[live], p[live]
    mass = lambda k: np.exp(log_gamma(d + 1) - log_gamma(k + 1) - log_gamma(d - k + 1) + k * np.log(p) + (d - k) * np.log1p(-p))

    def outwards(k: np.ndarray, up: np.ndarray) -> np.ndarray:
        some = (k >= 0) & (k <= d)
        k = np.clip(k, 0, d)
        term = np.where(some, mass(k), 0.0)
        total = term.copy()
        while (term > 1e-17 * total).any():
            with np.errstate(divide="ignore", invalid="ignore"):
                step = np.where(up, (d - k) / (k + 1) * (p / (1 - p)), k / (d - k + 1) * ((1 - p) / p))
            term = term * step
            k = k + np.where(up, 1, -1)
            total += term
        return total

    right = f >= d * p
    at = mass(f) * (1 + 1e-9)
    # far tail: on the left the last k below the mean that is no likelier than f, on the right the first one
    lo = np.where(right, -1.0, np.floor(d * p))
    hi = np.where(right, np.minimum(np.ceil(d * p) - 1, f - 1) + 1, d + 1.0)
    lo = np.where(right, lo, np.maximum(lo, f))
    while ((hi - lo) > 1).any():
        middle = np.floor((lo + hi) / 2)
        open_ = (hi - lo) > 1
        small = mass(np.clip(middle, 0, d)) <= at
        go = np.where(right, small, ~small)
        lo = np.where(open_ & go, middle, lo)
        hi = np.where(open_ & ~go, middle, hi)
    far = outwards(np.where(right, lo, hi), ~right)
    out[live] = np.minimum(1.0, outwards(f, right) + far)
    return out
