"""Connected components of an edge table by alternating large and small stars.

Each round is a few aggregations and joins over the edges; node labels only ever fall to
the smallest id, and a hub with a third of all edges is an aggregation of its minimum, not
a list. Rounds are cut with tables in the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stage


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.lit(0))).first())


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, label): label is the smallest node of its component. Nodes without edges are absent.

    ``edges`` has two columns of one orderable type; loops, repeats and either direction are
    fine; nulls are dropped. An empty table gives an empty result.
    """
    u, v = edges.columns
    e = edges.where(F.col(u) != F.col(v)).select(F.greatest(u, v).alias("a"), F.least(u, v).alias("b")).distinct()
    e = stage(e, "edges")
    before = _state(e)
    for _ in range(most_rounds if before[0] else 0):
        both = e.select("a", "b").union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        e = stage(small.union(low.select("a", F.col("m").alias("b"))).distinct(), "edges")
        now = _state(e)
        if now == before:
            break
        before = now
    else:
        if before[0]:
            raise RuntimeError("components did not settle")
    return e.select(F.col("a").alias("node"), F.col("b").alias("label")).union(e.select(F.col("b").alias("node"), F.col("b").alias("label")).distinct())
