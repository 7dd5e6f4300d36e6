"""Chi-square distribution on the driver: thresholds become literals of the plan."""

from __future__ import annotations

import functools
import math


def cdf(m: int, x: float) -> float:
    """P(chi-square with m degrees of freedom <= x), by series or continued fraction."""
    if x <= 0:
        return 0.0
    a, t = m / 2, x / 2
    front = math.exp(a * math.log(t) - t - math.lgamma(a))
    if t < a + 1:
        term = total = 1 / a
        n = a
        while abs(term) > abs(total) * 1e-16:
            n += 1
            term *= t / n
            total += term
        return total * front
    tiny = 1e-300
    b = t + 1 - a
    c, d = 1 / tiny, 1 / b
    h = d
    for i in range(1, 10_000):
        an = -i * (i - a)
        b += 2
        d = 1 / (an * d + b or tiny)
        c = b + an / c or tiny
        h *= d * c
        if abs(d * c - 1) < 1e-16:
            break
    return 1 - front * h


@functools.lru_cache
def quantile(m: int, p: float) -> float:
    """Smallest x with cdf(m, x) >= p, by bisection."""
    if not 0 <= p < 1:
        raise ValueError("p must lie in [0, 1)")
    lo, hi = 0.0, 1.0
    while cdf(m, hi) < p:
        hi *= 2
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if cdf(m, mid) < p else (lo, mid)
    return hi
