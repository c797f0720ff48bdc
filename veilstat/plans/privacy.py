"""Exact privacy ratios: enumerate inputs and reports of every mechanism."""

from __future__ import annotations

import math
from itertools import product

from ..functions.scalars import keep_rate
from ..operators.small_support import hadamard_order, rr_keep


def hash_reports(b: int, alpha: float) -> list[list[float]]:
    """Chance of each report for each true hash."""
    size, lam = 1 << b, keep_rate(alpha, b)
    return [[lam * (x == y) + (1 - lam) / size for y in range(size)] for x in range(size)]


def rr_reports(c: int, alpha: float) -> list[list[float]]:
    p = rr_keep(c, alpha)
    return [[p if x == y else (1 - p) / (c - 1) for y in range(c)] for x in range(c)]


def hadamard_reports(c: int, alpha: float) -> list[list[float]]:
    """Reports are (row, bit); the row is public and uniform."""
    rows, flip = hadamard_order(c), 1 / (1 + math.exp(alpha))
    return [[(1 - flip if bit == 1 - 2 * (bin(r & (x + 1)).count("1") % 2) else flip) / rows for r in range(rows) for bit in (1, -1)] for x in range(c)]


def unary_reports(c: int, alpha: float) -> list[list[float]]:
    f = 1 / (1 + math.exp(alpha / 2))
    return [[math.prod((1 - f) if bit == (s == x) else f for s, bit in enumerate(bits)) for bits in product((0, 1), repeat=c)] for x in range(c)]


def ratio(table: list[list[float]]) -> float:
    """Largest log ratio of a report's chances over two inputs: the alpha that is spent."""
    return max(math.log(max(col) / min(col)) for col in zip(*table, strict=True))
