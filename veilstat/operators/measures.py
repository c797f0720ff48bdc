"""Exact entropy and information measures: one aggregation to a histogram, one to a number.

The histogram's partial counts combine before the shuffle, so a value that a third of all
rows share costs one row a task.
"""

from __future__ import annotations

import math
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.scalars import tidy




def histogram(df: DataFrame, cols: list[str], by: list[str] = (), weight: str | None = None) -> DataFrame:
    """Counts (or weights) ``n`` of each value of ``cols``; nulls are a value."""
    return df.groupBy(*by, *cols).agg((F.sum(weight) if weight else F.count("*")).cast("double").alias("n"))


def h_of(n: str = "n") -> Column:
    """Shannon entropy of counts: ln N - sum n ln n / N."""
    return F.ln(F.sum(n)) - F.sum(F.when(F.col(n) > 0, F.col(n) * F.ln(n)).otherwise(0.0)) / F.sum(n)


def power_of(gamma: float, n: str = "n") -> Column:
    """sum p^gamma from counts."""
    return F.sum(F.pow(F.col(n), F.lit(float(gamma)))) / F.pow(F.sum(n), F.lit(float(gamma)))


def p2_of(n: str = "n") -> Column:
    return F.sum(F.col(n) * F.col(n)) / (F.sum(n) * F.sum(n))


def shannon(df: DataFrame, cols: list[str], base: float = math.e, by: list[str] = (), weight: str | None = None) -> DataFrame:
    h = histogram(df, cols, by, weight)
    return (h.groupBy(*by) if by else h.groupBy()).agg(tidy(h_of() / math.log(base)).alias("h"))


def tsallis(df: DataFrame, cols: list[str], gamma: float) -> DataFrame:
    """Order gamma > 0; order 1 is Shannon's."""
    if gamma <= 0:
        raise ValueError("gamma must be positive")
    h = histogram(df, cols)
    return h.agg(tidy(h_of() if gamma == 1 else (1 - power_of(gamma)) / (gamma - 1)).alias("t"))


def renyi(df: DataFrame, cols: list[str], gamma: float) -> DataFrame:
    if gamma <= 0:
        raise ValueError("gamma must be positive")
    h = histogram(df, cols)
    return h.agg(tidy(h_of() if gamma == 1 else F.ln(power_of(gamma)) / (1 - gamma)).alias("r"))


def gini(df: DataFrame, cols: list[str], by: list[str] = (), weight: str | None = None) -> DataFrame:
    h = histogram(df, cols, by, weight)
    return (h.groupBy(*by) if by else h.groupBy()).agg(tidy(1 - p2_of()).alias("g"))


def collision(df: DataFrame, cols: list[str], unbiased: bool = False) -> DataFrame:
    """-log of the collision probability; ``unbiased`` counts pairs of different rows."""
    h = histogram(df, cols)
    rate = F.sum(F.col("n") * (F.col("n") - 1)) / (F.sum("n") * (F.sum("n") - 1)) if unbiased else p2_of()
    return h.agg(tidy(rate).alias("p2"), tidy(-F.ln(rate)).alias("c"))


def effective_number(df: DataFrame, cols: list[str], by: list[str] = (), weight: str | None = None) -> DataFrame:
    """Concentration sum of squared shares and its inverse."""
    h = histogram(df, cols, by, weight)
    return (h.groupBy(*by) if by else h.groupBy()).agg(tidy(p2_of()).alias("concentration"), tidy(1 / p2_of()).alias("effective"))


def _terms(df: DataFrame, sets: list[tuple[str, ...]]) -> DataFrame:
    """Entropies of several column sets from the finest histogram: one pass over the rows."""
    every = sorted({c for s in sets for c in s})
    fine = histogram(df, every)
    rows = None
    for k, s in enumerate(sets):
        part = fine.groupBy(*s).agg(F.sum("n").alias("n")).agg(h_of().alias("h")).withColumn("k", F.lit(k))
        rows = part if rows is None else rows.unionByName(part)
    return rows


def mutual_information(df: DataFrame, a: str, b: str) -> DataFrame:
    """I(a; b) by grouping sets over the pair's histogram."""
    fine = histogram(df, [a, b])
    fine.createOrReplaceTempView("pair_histogram")
    sets = df.sparkSession.sql(
        f"SELECT grouping_id(`{a}`, `{b}`) AS k, sum(n) AS n FROM pair_histogram GROUP BY `{a}`, `{b}` GROUPING SETS ((`{a}`), (`{b}`), (`{a}`, `{b}`))"
    )
    return sets.groupBy("k").agg(h_of().alias("h")).agg(tidy(F.sum(F.when(F.col("k") == 0, -F.col("h")).otherwise(F.col("h")))).alias("mi"))


def conditional_mi(df: DataFrame, a: str, b: str, c: str) -> DataFrame:
    """I(a; b | c) = H(a,c) + H(b,c) - H(a,b,c) - H(c)."""
    terms = _terms(df, [(a, c), (b, c), (a, b, c), (c,)])
    return terms.agg(tidy(F.sum(F.when(F.col("k") < 2, F.col("h")).otherwise(-F.col("h")))).alias("cmi"))


def pair_cells(df: DataFrame, variables: list[str]) -> DataFrame:
    """(i, j, a, b, n) of all pairs of variables: rows explode to pairs, counts combine in the task."""
    pairs = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.col(variables[i]).cast("string").alias("a"), F.col(variables[j]).cast("string").alias("b")) for i, j in combinations(range(len(variables)), 2)])
    return df.select(F.inline(pairs)).groupBy("i", "j", "a", "b").agg(F.count("*").cast("double").alias("n"))


def mi_from_cells(cells: DataFrame) -> DataFrame:
    """(i, j, mi) from pair cells; the marginals are coarser sums of the same cells."""
    joint = cells.groupBy("i", "j").agg(h_of().alias("hab"))
    ha = cells.groupBy("i", "j", "a").agg(F.sum("n").alias("n")).groupBy("i", "j").agg(h_of().alias("ha"))
    hb = cells.groupBy("i", "j", "b").agg(F.sum("n").alias("n")).groupBy("i", "j").agg(h_of().alias("hb"))
    return joint.join(ha, ["i", "j"]).join(hb, ["i", "j"]).select("i", "j", (F.col("ha") + F.col("hb") - F.col("hab")).alias("mi"))


def mi_matrix(df: DataFrame, variables: list[str]) -> DataFrame:
    return mi_from_cells(pair_cells(df, variables))


def marginal_entropies(df: DataFrame, variables: list[str]) -> DataFrame:
    """(i, h) of every variable in one pass."""
    long = df.select(F.inline(F.array(*[F.struct(F.lit(i).alias("i"), F.col(v).cast("string").alias("a")) for i, v in enumerate(variables)])))
    return long.groupBy("i", "a").agg(F.count("*").cast("double").alias("n")).groupBy("i").agg(h_of().alias("h"))


def continuity_bound(l1: float, c: int) -> float:
    """Bound of the entropy difference of two distributions on c symbols at distance l1."""
    return 0.0 if l1 <= 0 else l1 * math.log(c / l1)


def l1_target(eps: float, c: int) -> float:
    """Largest distance (at most 1/2) whose bound is within eps."""
    lo, hi = 0.0, 0.5
    if continuity_bound(hi, c) <= eps:
        return hi
    for _ in range(80):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if continuity_bound(mid, c) <= eps else (lo, mid)
    return lo
