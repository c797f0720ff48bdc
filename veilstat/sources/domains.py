"""Public alphabets: values to codes 0..c-1.

Under local privacy a domain has to be public, never learnt from the rows. The hash method
needs none.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Categorical:
    """Code = place in ``values``; anything else, null too, is the last code."""

    values: tuple

    @property
    def size(self) -> int:
        return len(self.values) + 1

    def code(self, c: Column) -> Column:
        out = F.array_position(F.array(*[F.lit(v) for v in self.values]), c)
        return F.when(out > 0, out - 1).otherwise(len(self.values)).cast("int")


@dataclass(frozen=True)
class Binned:
    """Code = number of edges that the value reaches; null is the last code."""

    edges: tuple

    @property
    def size(self) -> int:
        return len(self.edges) + 2

    def code(self, c: Column) -> Column:
        reached = sum((F.when(c.cast("double") >= F.lit(float(e)), 1).otherwise(0) for e in self.edges), F.lit(0))
        return F.when(c.isNull(), len(self.edges) + 1).otherwise(reached).cast("int")


@dataclass(frozen=True)
class Sign:
    size: int = 2

    def code(self, c: Column) -> Column:
        return F.when(c > 0, 1).otherwise(0).cast("int")


@dataclass(frozen=True)
class Calendar:
    part: str  # month, quarter, hour
    size: int = 24

    def code(self, c: Column) -> Column:
        return {"month": F.month(c) - 1, "quarter": F.quarter(c) - 1, "hour": F.hour(c)}[self.part].cast("int")


def encode(df: DataFrame, domains: dict) -> DataFrame:
    """Codes of the named columns, others dropped."""
    return df.select(*[d.code(F.col(c)).alias(c) for c, d in domains.items()])
