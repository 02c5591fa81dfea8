"""Tails of the normal, t and F distributions, in plain Python (no SciPy)."""

from __future__ import annotations

import math


def norm_cdf(x: float) -> float:
    return 0.5 * math.erfc(-x / math.sqrt(2))


def incomplete_beta(a: float, b: float, x: float) -> float:
    """Regularised, by the continued fraction on the side where it converges fast."""
    if x <= 0 or x >= 1:
        return 0.0 if x <= 0 else 1.0
    if x > (a + 1) / (a + b + 2):
        return 1 - incomplete_beta(b, a, 1 - x)
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x)) / a
    value = 1.0
    for k in range(int(100 + 5 * math.sqrt(max(a, b))), 0, -1):  # from the innermost term outwards
        m, odd = divmod(k, 2)
        top = -(a + m) * (a + b + m) if odd else m * (b - m)
        value = 1 + top * x / ((a + k - 1) * (a + k)) / value
    return front / value


def t_sf(t: float, df: float) -> float:
    """P(T > t)."""
    if df <= 0 or math.isnan(t):
        return float("nan")
    tail = 0.5 * incomplete_beta(df / 2, 0.5, df / (df + t * t))
    return tail if t >= 0 else 1 - tail


def f_sf(f: float, d1: float, d2: float) -> float:
    """P(F > f)."""
    return 1.0 if f <= 0 else incomplete_beta(d2 / 2, d1 / 2, d2 / (d2 + d1 * f))


def t_quantile(p: float, df: float) -> float:
    """By bisection of the tail."""
    lo, hi = -1e6, 1e6
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if 1 - t_sf(mid, df) < p else (lo, mid)
    return (lo + hi) / 2
