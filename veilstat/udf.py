"""UDFs, UDAFs, UDTFs and SQL functions for users who prefer SQL."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def entropy_udaf():
    """Shannon entropy of codes, as a grouped aggregate."""

    @F.pandas_udf("double")
    def entropy(code: pd.Series) -> float:
        n = code.value_counts(dropna=False).to_numpy()
        p = n / n.sum() if len(n) else np.zeros(0)
        return float(-(p * np.log(p)).sum()) + 0.0

    return entropy


def hadamard_inverse_udf():
    """Inverse transform of sums by public row: a fast Walsh-Hadamard transform of each array."""

    @F.pandas_udf("array<double>")
    def inverse(rows: pd.Series) -> pd.Series:
        def one(v):
            a = np.array(v, dtype=np.float64)
            h = 1
            while h < len(a):
                a = a.reshape(-1, 2, h)
                a = np.stack((a[:, 0] + a[:, 1], a[:, 0] - a[:, 1]), axis=1).reshape(-1)
                h *= 2
            return (a / len(a)).tolist()

        return rows.map(one)

    return inverse


def pair_blocks(df: DataFrame, variables: list[str], c: int) -> DataFrame:
    """(i, j, a, b, n) of all pairs by blocks: each Arrow batch becomes one-hot columns and a matrix product."""
    d = len(variables)

    def count(batches):
        total = np.zeros((d * c, d * c))
        for batch in batches:
            hot = np.zeros((batch.num_rows, d * c), dtype=np.float32)
            for k in range(d):
                hot[np.arange(batch.num_rows), k * c + batch.column(k).to_numpy()] = 1
            total += hot.T @ hot
        x, y = np.nonzero(total)
        keep = x // c < y // c
        x, y = x[keep], y[keep]
        yield pa.RecordBatch.from_arrays([pa.array((x // c).astype(np.int32)), pa.array((y // c).astype(np.int32)), pa.array((x % c).astype(np.int32)), pa.array((y % c).astype(np.int32)), pa.array(total[x, y])], ["i", "j", "a", "b", "n"])

    part = df.select(*[F.col(v).cast("int").alias(v) for v in variables]).mapInArrow(count, "i int, j int, a int, b int, n double")
    return part.groupBy("i", "j", "a", "b").agg(F.sum("n").alias("n"))


def star_hub_per_group(edges: DataFrame, group: str) -> DataFrame:
    """(group, hub): the variable with the largest sum of informations; groups are edge lists of few variables."""

    def hub(pdf: pd.DataFrame) -> pd.DataFrame:
        s = pd.concat([pdf[["i", "mi"]].rename(columns={"i": "v"}), pdf[["j", "mi"]].rename(columns={"j": "v"})]).groupby("v")["mi"].sum()
        return pd.DataFrame({group: [pdf[group].iloc[0]], "hub": [int(s.index[(s == s.max()).to_numpy().argmax()])]})

    return edges.groupBy(group).applyInPandas(hub, f"{group} {edges.schema[group].dataType.simpleString()}, hub int")


class RandomTree:
    def eval(self, d: int, seed: str):
        from veilstat.operators.workloads import random_tree

        for t in random_tree(d, seed):
            yield t["node"], t["parent"], float(t["p"]), float(t["r"])


class SpanningTree:
    """Heaviest spanning tree of an array of (i, j, mi)."""

    def eval(self, edges):
        from veilstat.operators.structure import kruskal

        mi = {(e["i"], e["j"]): e["mi"] for e in edges}
        for i, j in kruskal(max(max(e) for e in mi) + 1 if mi else 0, mi):
            yield i, j, mi[(i, j)]


class LocateInChain:
    """Left neighbour's place of a new value in an ordered array: the bisection on positions."""

    def eval(self, order, new):
        lo, hi = 0, len(order) - 1
        while hi - lo > 1:
            mid = (lo + hi + 1) // 2
            lo, hi = (lo, mid) if new < order[mid] else (mid, hi)
        yield (lo,)


def register_all(spark: SparkSession) -> None:
    spark.udf.register("entropy_of", entropy_udaf())
    spark.udf.register("hadamard_inverse", hadamard_inverse_udf())
    spark.udtf.register("random_tree", F.udtf(RandomTree, returnType="node int, parent int, p double, r double"))
    spark.udtf.register("spanning_tree", F.udtf(SpanningTree, returnType="i int, j int, mi double"))
    spark.udtf.register("locate_in_chain", F.udtf(LocateInChain, returnType="place int"))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION keep_rate(alpha DOUBLE, b INT) RETURNS DOUBLE RETURN (exp(alpha) - 1) / (pow(2D, b) + exp(alpha) - 1)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION coin(seed STRING, purpose STRING, id STRING) RETURNS DOUBLE RETURN CAST(conv(substring(md5(concat_ws('|', seed, purpose, id)), 1, 8), 16, 10) AS DOUBLE) / 4294967296D")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION debias(rate DOUBLE, lambda DOUBLE, b INT) RETURNS DOUBLE RETURN (pow(2D, b) * rate - 1) / (lambda * lambda * (pow(2D, b) - 1))")
