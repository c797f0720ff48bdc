"""Sample-size forms of the methods, up to their constants, and lower bounds."""

from __future__ import annotations

import math


def small_support(c: int, eps: float, alpha: float, delta: float) -> float:
    return c * c * math.log(1 / delta) / (eps * eps * alpha * alpha)


def tree(d: int, eps: float, alpha: float, delta: float, full: bool = False) -> float:
    """``full`` keeps the factors of the budgets and repetitions that the short form drops."""
    short = d * math.log(d / delta) / (alpha**2 * eps**5)
    return short * math.log(2 / eps) * math.log(1 / delta) if full else short


def chain(d: int, eps: float, alpha: float, delta: float, full: bool = False) -> float:
    short = d * math.log(d / delta) / (alpha**2 * eps**2)
    return short * math.log2(d) if full else short


def star(d: int, eps: float, alpha: float, delta: float) -> float:
    return d * math.log(d / delta) / (alpha**2 * eps**2)


def gini(b: int, g: float, eps: float, alpha: float, delta: float) -> float:
    return 2 ** (4 * b) * max(1 - g, 2.0**-b, eps) * math.log(1 / delta) / (alpha**4 * eps**2)


def collision(b: int, k: int, eps: float, alpha: float, delta: float) -> float:
    return 2 ** (4 * b) * k * k * math.log(1 / delta) / (alpha**4 * eps**2)


def lower_pairs_noninteractive(d: int) -> float:
    return float(d * d)


def lower_pairs_sequential(d: int, eps: float) -> float:
    return d / eps


def in_theorem(alpha: float, eps: float) -> bool:
    """Whether the stated ranges (alpha below 1, eps at most 1/2) hold."""
    return 0 < alpha < 1 and 0 < eps <= 0.5
