"""Upper tail of the gamma distribution in logarithms, and its critical values.

A metric of x bits over n rows with df degrees of freedom is judged by a gamma distribution of shape df/2 and scale
1/(n ln 2); far tails underflow, so everything is kept as a natural logarithm.
"""

from __future__ import annotations

import functools
import math

LN2 = math.log(2.0)


def log_upper(shape: float, x: float) -> float:
    """ln of the regularised upper incomplete gamma function Q(shape, x)."""
    if x <= 0.0:
        return 0.0
    front = shape * math.log(x) - x - math.lgamma(shape)
    if x < shape + 1.0:  # series of the lower function
        term = total = 1.0 / shape
        k = shape
        while term > total * 1e-17:
            k += 1.0
            term *= x / k
            total += term
        lower = math.exp(min(0.0, front + math.log(total)))
        return math.log1p(-lower) if lower < 1.0 else -math.inf
    tiny = 1e-300  # continued fraction of the upper function
    b = x + 1.0 - shape
    c, d = 1.0 / tiny, 1.0 / b
    h = d
    for i in range(1, 100_000):
        an = -i * (i - shape)
        b += 2.0
        d = an * d + b
        d = 1.0 / (d if abs(d) > tiny else tiny)
        c = b + an / c
        c = c if abs(c) > tiny else tiny
        step = d * c
        h *= step
        if abs(step - 1.0) < 1e-15:
            break
    return min(0.0, front + math.log(h))


def log_p(bits: float, df: float, n: float) -> float:
    """ln of the probability of more than ``bits`` under independence; certain if there is nothing to test."""
    return log_upper(df / 2.0, bits * n * LN2) if df > 0 and n > 0 else 0.0


@functools.lru_cache(maxsize=65_536)
def critical_bits(df: float, n: float, alpha: float) -> float:
    """Bits above which the tail is below ``alpha``: p < alpha if and only if bits > the value."""
    if df <= 0 or n <= 0:
        return math.inf
    goal, low, high = math.log(alpha), 0.0, max(1.0, df)
    while log_upper(df / 2.0, high) > goal:
        high *= 2.0
    for _ in range(200):
        middle = (low + high) / 2.0
        if middle in (low, high):
            break
        low, high = (middle, high) if log_upper(df / 2.0, middle) > goal else (low, middle)
    return high / (n * LN2)
