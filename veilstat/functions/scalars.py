"""Entropies of probability arrays, projections to the simplex, and small formulas."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def tidy(x: Column) -> Column:
    """Six digits, and no negative zero."""
    return F.round(x, 6) + F.lit(0.0)


def array_sum(a: Column, of=lambda p: p) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, p: s + of(p))


def shannon_of(a: Column) -> Column:
    return -array_sum(a, lambda p: F.when(p > 0, p * F.ln(p)).otherwise(0.0))


def power_sum(a: Column, gamma: float) -> Column:
    return array_sum(a, lambda p: F.when(p > 0, F.pow(p, F.lit(float(gamma)))).otherwise(0.0))


def gini_of(a: Column) -> Column:
    return 1 - power_sum(a, 2)


def collision_of(a: Column) -> Column:
    return -F.ln(power_sum(a, 2))


def tsallis_of(a: Column, gamma: float) -> Column:
    if gamma <= 0:
        raise ValueError("gamma must be positive")
    return shannon_of(a) if gamma == 1 else (1 - power_sum(a, gamma)) / (gamma - 1)


def renyi_of(a: Column, gamma: float) -> Column:
    if gamma <= 0:
        raise ValueError("gamma must be positive")
    return shannon_of(a) if gamma == 1 else F.ln(power_sum(a, gamma)) / (1 - gamma)


def clip_norm(v: Column) -> Column:
    """Negative parts go, the rest is scaled to sum 1; uniform where nothing is left."""
    pos = F.transform(v, lambda p: F.greatest(p, F.lit(0.0)))
    return F.when(array_sum(pos) > 0, F.transform(pos, lambda p: p / array_sum(pos))).otherwise(F.transform(v, lambda p: 1.0 / F.size(v)))


def project_simplex(v: Column) -> Column:
    """Euclidean projection: the threshold is the largest mean excess over sorted prefixes."""
    down = F.reverse(F.array_sort(v))
    excess = F.transform(F.sequence(F.lit(1), F.size(v)), lambda k: (array_sum(F.slice(down, 1, k)) - 1.0) / k)
    theta = F.array_max(excess)
    return F.transform(v, lambda p: F.greatest(p - theta, F.lit(0.0)))


def project(v: list[float]) -> list[float]:
    """The same projection on the driver."""
    total, theta = 0.0, -math.inf
    for k, x in enumerate(sorted(v, reverse=True), 1):
        total += x
        theta = max(theta, (total - 1) / k)
    return [max(x - theta, 0.0) for x in v]


def entropy(p) -> float:
    return -sum(x * math.log(x) for x in p if x > 0)


def keep_rate(alpha: float | None, b: int) -> float:
    """Chance to report the true hash of b bits under alpha-local privacy; 1 without privacy."""
    return 1.0 if alpha is None else (math.exp(alpha) - 1) / (2**b + math.exp(alpha) - 1)


def keep_rate_of(alpha: Column, b: Column) -> Column:
    """The same where users choose their privacy and bits."""
    return (F.exp(alpha) - 1) / (F.pow(F.lit(2.0), b) + F.exp(alpha) - 1)


def hadamard_sign(row: Column, x: Column) -> Column:
    """Entry of the sign matrix: +1 or -1 by the parity of common bits."""
    return (1 - 2 * (F.bit_count(row.cast("long").bitwiseAND(x.cast("long"))) % 2)).cast("int")
