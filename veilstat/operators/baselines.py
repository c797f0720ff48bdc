"""Baselines of the hash method whose cost depends on the alphabet."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.coins import uniform
from ..functions.scalars import project
from .small_support import rr_debias, rr_encode, unary_debias, unary_encode


def private_histogram(df: DataFrame, id_col: str, code: str, c: int, alpha: float, mechanism: str = "rr", private: str = "noise") -> list[float]:
    """Projected frequencies of codes 0..c-1; the driver gets c counts."""
    if mechanism == "rr":
        got = {r["report"]: r["n"] for r in df.select(rr_encode(F.col(code), c, alpha, private, F.col(id_col)).alias("report")).groupBy("report").agg(F.count("*").alias("n")).collect()}
        return project(rr_debias([float(got.get(k, 0)) for k in range(c)], alpha))
    bits = df.select(unary_encode(F.col(code), c, alpha, private, F.col(id_col)).alias("u"))
    got = bits.agg(F.count("*").alias("n"), *[F.sum(F.get("u", F.lit(k))).alias(f"s{k}") for k in range(c)]).first()
    return project(unary_debias([float(got[f"s{k}"] or 0) for k in range(c)], float(got["n"]), alpha)) if got["n"] else [1.0 / c] * c


def plugin_gini(df: DataFrame, id_col: str, code: str, c: int, alpha: float, mechanism: str = "rr", private: str = "noise") -> float:
    return 1 - math.fsum(p * p for p in private_histogram(df, id_col, code, c, alpha, mechanism, private))


def two_stage_gini(df: DataFrame, id_col: str, code: str, c: int, alpha: float, public: str = "pub", private: str = "noise", cut: float = 1.0) -> float:
    """Sequential rival: half of the users send c-bit noise, the rest report the estimate at their symbol.

    The second half's answer is a number in [0, cut], sent as one bit of a fair scale whose
    truth is kept with chance e^alpha / (1 + e^alpha); the mean estimates the collision probability.
    """
    half = uniform(public, "half", F.col(id_col)) < 0.5
    p = private_histogram(df.where(half), id_col, code, c, alpha, "unary", private)
    value = F.get(F.array(*[F.lit(min(max(x, 0.0), cut)) for x in p]), F.col(code))
    keep = math.exp(alpha) / (1 + math.exp(alpha))
    one = uniform(private, "scale", F.col(id_col)) < value / F.lit(cut)
    sent = F.when(uniform(private, "answer", F.col(id_col)) < F.lit(keep), one).otherwise(~one)
    got = df.where(~half).select(sent.cast("double").alias("s")).agg(F.avg("s")).first()[0]
    q = ((got if got is not None else 0.5) - (1 - keep)) / (2 * keep - 1) * cut
    return 1 - q


def all_pairs_collision(df: DataFrame, cols: list[str]) -> DataFrame:
    """Equal pairs among all pairs of rows, from counts."""
    n = df.groupBy(*cols).agg(F.count("*").cast("double").alias("n"))
    return n.agg((F.sum(F.col("n") * (F.col("n") - 1)) / (F.sum("n") * (F.sum("n") - 1))).alias("p2"))


def unobserved_clique(d: int, pairs: list[tuple[int, int]]) -> list[int]:
    """Variables of which no pair is observed: greedy, fewest conflicts first."""
    near = {i: {j for p in pairs if i in p for j in p if j != i} for i in range(d)}
    out: list[int] = []
    for i in sorted(range(d), key=lambda v: (len(near[v]), v)):
        if not near[i] & set(out):
            out.append(i)
    return sorted(out)
