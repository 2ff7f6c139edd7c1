"""Gamma distribution: regularised incomplete integral and its inverse, without scipy."""

from __future__ import annotations

import math
from statistics import NormalDist


def cdf(x: float, shape: float, scale: float) -> float:
    """P(X <= x): series below shape + 1, continued fraction above."""
    if x <= 0:
        return 0.0
    z = x / scale
    front = math.exp(shape * math.log(z) - z - math.lgamma(shape))
    if z < shape + 1:
        term = total = 1 / shape
        k = shape
        while abs(term) > abs(total) * 1e-15:
            k += 1
            term *= z / k
            total += term
        return min(1.0, total * front)
    tiny = 1e-300
    b = z + 1 - shape
    c, d = 1 / tiny, 1 / b
    h = d
    for i in range(1, 10_000):
        a = -i * (i - shape)
        b += 2
        d = 1 / (a * d + b or tiny)
        c = b + a / c or tiny
        h *= d * c
        if abs(d * c - 1) < 1e-15:
            break
    return max(0.0, 1 - front * h)


def quantile(q: float, shape: float, scale: float) -> float:
    """Inverse of ``cdf``: bisection inside a bracket grown from a normal approximation."""
    if not (shape > 0 and scale > 0) or not 0 < q < 1:
        return math.nan
    g = NormalDist().inv_cdf(q)
    guess = shape * max(1e-12, 1 - 1 / (9 * shape) + g / (3 * math.sqrt(shape))) ** 3
    low, high = 0.0, max(guess, 1e-300)
    while cdf(high, shape, 1.0) < q:
        low, high = high, high * 2
    for _ in range(200):
        mid = (low + high) / 2
        if cdf(mid, shape, 1.0) < q:
            low = mid
        else:
            high = mid
        if high - low <= 1e-15 * high:
            break
    return (low + high) / 2 * scale
