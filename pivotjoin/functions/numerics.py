"""Special functions that the fits need."""

from __future__ import annotations

import math
from collections.abc import Callable


def digamma(x: float) -> float:
    out = 0.0
    while x < 8:
        out -= 1 / x
        x += 1
    f = 1 / (x * x)
    return out + math.log(x) - 0.5 / x - f * (1 / 12 - f * (1 / 120 - f * (1 / 252 - f * (1 / 240 - f / 132))))


def trigamma(x: float) -> float:
    out = 0.0
    while x < 8:
        out += 1 / (x * x)
        x += 1
    f = 1 / (x * x)
    return out + 1 / x + f / 2 + f / x * (1 / 6 - f * (1 / 30 - f * (1 / 42 - f / 30)))


def gamma_q(a: float, x: float) -> float:
    """Upper regularised incomplete gamma function."""
    if x <= 0:
        return 1.0
    front = math.exp(min(700.0, -x + a * math.log(x) - math.lgamma(a)))
    if x < a + 1:
        term = total = 1 / a
        n = a
        while abs(term) > abs(total) * 1e-16:
            n += 1
            term *= x / n
            total += term
        return max(0.0, min(1.0, 1 - total * front))
    b = x + 1 - a
    c, d = 1e300, 1 / b
    h = d
    for i in range(1, 10_000):
        an = -i * (i - a)
        b += 2
        d = 1 / (an * d + b or 1e-300)
        c = b + an / c or 1e-300
        h *= d * c
        if abs(d * c - 1) < 1e-15:
            break
    return max(0.0, min(1.0, front * h))


def gamma_p(a: float, x: float) -> float:
    return 1 - gamma_q(a, x)


def chi2_sf(x: float, dof: float) -> float:
    """Probability that a chi-square variable exceeds x."""
    return gamma_q(dof / 2, x / 2)


def bisect(f: Callable[[float], float], lo: float, hi: float, steps: int = 200) -> float:
    """Root of an increasing function."""
    for _ in range(steps):
        mid = (lo + hi) / 2
        if f(mid) < 0:
            lo = mid
        else:
            hi = mid
        if hi - lo <= 1e-15 * max(1.0, abs(hi)):
            break
    return (lo + hi) / 2


def chi2_isf(q: float, dof: float) -> float:
    """The value that a chi-square variable exceeds with probability q."""
    hi = dof + 10
    while chi2_sf(hi, dof) > q:
        hi *= 2
    return bisect(lambda x: q - chi2_sf(x, dof), 0.0, hi)


def beta_p(a: float, b: float, x: float) -> float:
    """Regularised incomplete beta function, by its continued fraction."""
    if x <= 0 or x >= 1:
        return float(x >= 1)
    if x > (a + 1) / (a + b + 2):
        return 1 - beta_p(b, a, 1 - x)
    front = math.exp(a * math.log(x) + b * math.log1p(-x) + math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b)) / a
    c, d = 1.0, 1 / (1 - (a + b) * x / (a + 1) or 1e-300)
    h = d
    for m in range(1, 1000):
        for num in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 / (1 + num * d or 1e-300)
            c = 1 + num / c or 1e-300
            h *= c * d
        if abs(c * d - 1) < 1e-15:
            break
    return front * h


def inverse_digamma(y: float) -> float:
    x = math.exp(y) + 0.5 if y >= -2.22 else -1 / (y - digamma(1.0))
    for _ in range(50):
        step = (digamma(x) - y) / trigamma(x)
        x = max(x - step, x / 10)
        if abs(step) < 1e-13 * x:
            break
    return x
