"""Near-duplicate vectors: int8 tile products with rigorous error bounds.

Unit vectors are rounded to int8 codes with one step for the whole table. The product of
two codes differs from the cosine by at most e_i + e_j + e_i * e_j, where e is a vector's
own rounding error, so only pairs whose code product reaches the threshold less that bound
can link; these alone are recomputed in double precision. Code products are sums of
integers below 2^24 (or 2^53) and therefore exact in floating-point matrix products.

Equal vectors are folded into one row with a weight first. Distinct vectors are dealt into
blocks of about ``BLOCK`` rows and every pair of blocks is one tile of bounded size. A tile
returns a count for each vector and a spanning forest of its links, never all pairs. Work
grows with the square of the distinct vectors: the method compares all pairs.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import only, stage
from .components import components

BLOCK = 4096
STRIP = 512


def quantise(unit: np.ndarray, step: float) -> tuple[np.ndarray, np.ndarray]:
    """int8 codes and each vector's rounding error (Euclidean, rounded up)."""
    codes = np.clip(np.rint(unit / step), -127, 127).astype(np.int8)
    return codes, np.linalg.norm(unit - codes * step, axis=1) * (1 + 1e-9) + 1e-12


def links(a: np.ndarray, b: np.ndarray, threshold: float, step: float, same: bool):
    """Yield (row indices, column indices) of linked pairs, strip by strip; with ``same`` a is b and each pair comes both ways."""
    qa, ea = quantise(a, step)
    qb, eb = quantise(b, step)
    kind = np.float32 if a.shape[1] * 127 * 127 < 1 << 24 else np.float64
    right = np.ascontiguousarray(qb.T.astype(kind))
    left = qa.astype(kind)
    worst = eb.max()
    for at in range(0, len(a), STRIP):
        rows = slice(at, min(at + STRIP, len(a)))
        need = (threshold - ea[rows].max() - worst - ea[rows].max() * worst) / (step * step)
        product = left[rows] @ right
        r, c = np.nonzero(product >= need)
        if not len(r):
            continue
        bound = ea[rows][r] + eb[c] + ea[rows][r] * eb[c]
        possible = product[r, c] * (step * step) + bound >= threshold
        r, c = r[possible], c[possible]
        if same:
            apart = r + at != c
            r, c = r[apart], c[apart]
        if len(r) * 8 > product.size:
            keep = (a[rows] @ b.T)[r, c] >= threshold
        else:
            keep = np.concatenate([np.einsum("ij,ij->i", a[rows][r[i : i + 32768]], b[c[i : i + 32768]]) >= threshold for i in range(0, len(r), 32768)]) if len(r) else np.zeros(0, bool)
        yield r[keep] + at, c[keep]


def join_labels(labels: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Labels after joining the sets of x[i] and y[i]; a label is the smallest index of its set."""
    while True:
        lx, ly = labels[x], labels[y]
        apart = lx != ly
        if not apart.any():
            return labels
        np.minimum.at(labels, np.maximum(lx, ly)[apart], np.minimum(lx, ly)[apart])
        while (labels[labels] != labels).any():
            labels = labels[labels]
        x, y = x[apart], y[apart]


def _tile(threshold: float, step: float):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        lo, hi = int(pdf["lo"].iloc[0]), int(pdf["hi"].iloc[0])
        pdf = pdf.sort_values(["block", "rep"], kind="stable")
        ids, weight = pdf["rep"].to_numpy(), pdf["w"].to_numpy()
        raw = np.array(pdf["v"].tolist(), dtype=np.float64)
        scale = np.abs(raw).max(axis=1, keepdims=True)
        raw = raw / scale
        unit = raw / np.linalg.norm(raw, axis=1, keepdims=True)
        first = int((pdf["block"] == lo).sum())
        a, b, shift = (unit, unit, 0) if lo == hi else (unit[:first], unit[first:], first)
        counts, labels = np.zeros(len(ids), dtype=np.int64), np.arange(len(ids))
        if len(a) and len(b):
            for r, c in links(a, b, threshold, step, lo == hi):
                c = c + shift
                counts += np.bincount(r, weight[c], minlength=len(ids)).astype(np.int64)
                if lo != hi:
                    counts += np.bincount(c, weight[r], minlength=len(ids)).astype(np.int64)
                labels = join_labels(labels, r, c)
        linked = np.flatnonzero(counts)
        return pd.DataFrame({"a": ids[linked], "b": ids[labels[linked]], "n": counts[linked]})

    return run


def near_vectors(table: DataFrame, threshold: float = 0.9, block: int = BLOCK) -> DataFrame:
    """vec_id, n_links, component_id, kept for every row of ``table`` (vec_id, embedding).

    Vectors that are null, empty, zero, or hold null or non-finite components link with
    nothing, as do rows with a null id (their component is null and kept is null) and
    vectors of different dimension. Equal vectors link. An id that repeats with another
    vector shares its links. Other columns are ignored; an empty table gives none.
    """
    table = only(table, "vec_id", "embedding")
    sound = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("embedding", lambda x: x != 0)
    good = table.where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & sound)
    folded = stage(good.groupBy(F.col("embedding").alias("v")).agg(F.min("vec_id").alias("rep"), F.count("*").alias("w")), "vectors")
    size = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))
    n, top = folded.agg(F.count("*"), F.max(F.array_max(F.transform("v", lambda x: F.abs(x.cast("double")))) / size)).first()
    step = (top or 1.0) / 127
    blocks = max(1, -(-(n or 0) // block))
    dealt = folded.withColumn("block", F.pmod(F.xxhash64("rep"), F.lit(blocks)).cast("int"))
    tiles = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).select(
        "rep", "w", "v", "block", F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"), F.size("v").alias("dim")
    )
    found = tiles.repartition(max(1, min(blocks * (blocks + 1) // 2, 100_000)), "dim", "lo", "hi").groupBy("dim", "lo", "hi").applyInPandas(_tile(threshold, step), "a long, b long, n long")
    found = stage(found, "tile-links")
    labels = components(found.select("a", "b"))
    counts = found.groupBy(F.col("a").alias("rep")).agg(F.sum("n").alias("n"))
    reps = folded.join(counts, "rep", "left").join(labels.withColumnRenamed("node", "rep"), "rep", "left")
    reps = reps.select("v", (F.coalesce("n", F.lit(0)) + F.col("w") - 1).alias("n_links"), F.coalesce("label", "rep").alias("component_id"))
    joined = table.join(reps, table.embedding == reps.v, "left")
    component = F.when(F.col("vec_id").isNotNull(), F.coalesce("component_id", F.col("vec_id")))
    return joined.select("vec_id", F.when(F.col("vec_id").isNull(), 0).otherwise(F.coalesce("n_links", F.lit(0))).cast("long").alias("n_links"), component.cast("long").alias("component_id")).withColumn("kept", F.col("vec_id") == F.col("component_id"))
