"""Synthetic samples keyed by given rows: every row is a user who draws one vector or symbol."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.coins import draw, uniform

#: Vectors of six binary variables for exact checks: (parents, chances). The first chance is the root's, others are flips.
TREE6 = ((-1, 0, 0, 1, 1, 2), (0.5, 0.05, 0.1, 0.15, 0.08, 0.2))
CHAIN6 = ((-1, 0, 1, 2, 3, 4), (0.5, 0.04, 0.09, 0.06, 0.1, 0.02))
STAR6 = ((2, 2, -1, 2, 2, 2), (0.05, 0.1, 0.5, 0.15, 0.2, 0.3))


def tree_order(parents) -> list[int]:
    """Variables with parents before children."""
    out: list[int] = []
    while len(out) < len(parents):
        out += [i for i, p in enumerate(parents) if i not in out and (p < 0 or p in out)]
    return out


def flip_vectors(users: DataFrame, parents, chances, seed: str = "vec") -> DataFrame:
    """user_id and v0.. of a binary tree: a child is its parent, flipped with its chance."""
    df = users
    for i in tree_order(parents):
        coin = F.when(uniform(seed, f"x{i}", F.col("user_id")) < F.lit(chances[i]), 1).otherwise(0)
        df = df.withColumn(f"v{i}", (coin if parents[i] < 0 else (coin + F.col(f"v{parents[i]}")) % 2).cast("int"))
    return df


def packed(df: DataFrame, d: int) -> DataFrame:
    """The vector as one array column x."""
    return df.select(*[c for c in df.columns if not (c[:1] == "v" and c[1:].isdigit())], F.array(*[F.col(f"v{i}") for i in range(d)]).alias("x"))


def exponential(u: Column, k: int = 1000) -> Column:
    """Inverse distribution function of p_i proportional to e^-i, i = 1..k."""
    return F.least(F.lit(k), F.ceil(-F.ln(1 - u))).cast("int")


# Random trees with prescribed marginals


def normal(seed: str, i: int, j: int) -> float:
    u, v = draw(seed, "n1", i, j), draw(seed, "n2", i, j)
    return math.sqrt(-2 * math.log(1 - u)) * math.cos(2 * math.pi * v)


def random_tree(d: int, seed: str, lo: float = 0.0, hi: float = 1.0, strong: bool = False) -> list[dict]:
    """Rows (node, parent, p, r): the heaviest spanning tree of normal weights, rooted at 0.

    ``r`` moves the joint of a child and its parent off independence, uniform over the range
    that keeps all four cells positive. ``strong`` fixes p = 1/2 and flips of 1 to 20 %.
    """
    from .structure import kruskal

    edges = kruskal(d, {(i, j): normal(seed, i, j) for i in range(d) for j in range(i + 1, d)})
    near: dict[int, list[int]] = {i: [] for i in range(d)}
    for i, j in edges:
        near[i].append(j)
        near[j].append(i)
    p = [0.5 if strong else lo + (hi - lo) * draw(seed, "p", i) for i in range(d)]
    rows, stack, seen = [], [(0, -1)], {0}
    while stack:
        i, parent = stack.pop(0)
        r = 0.0
        if parent >= 0:
            a, b = p[parent], p[i]
            low, high = -min((1 - a) * (1 - b), a * b), min((1 - a) * b, a * (1 - b))
            u = draw(seed, "r", i)
            r = 0.25 - (0.01 + 0.19 * u) / 2 if strong else low + (high - low) * u
        rows.append({"node": i, "parent": parent, "p": p[i], "r": r})
        for j in sorted(near[i]):
            if j not in seen:
                seen.add(j)
                stack.append((j, i))
    return rows


def joint(a: float, b: float, r: float) -> list[float]:
    """Cells 00, 01, 10, 11."""
    return [(1 - a) * (1 - b) + r, (1 - a) * b - r, a * (1 - b) - r, a * b + r]


class ClosedForm:
    """A source that answers from the tree's parameters: pair joints are products along paths."""

    def __init__(self, rows: list[dict]):
        self.p = {t["node"]: t["p"] for t in rows}
        self.pairs = 0
        self.corr: dict[tuple[int, int], float] = {}
        done: list[int] = []
        for t in rows:  # parents first
            i, parent = t["node"], t["parent"]
            for j in done:
                # Along a path of binary variables covariances multiply, over the variances between.
                if j == parent:
                    cov = t["r"]
                else:
                    q = self.p[parent]
                    cov = self.corr[(min(j, parent), max(j, parent))] * t["r"] / (q * (1 - q)) if 0 < q < 1 else 0.0
                self.corr[(min(i, j), max(i, j))] = cov
            done.append(i)

    def marginals(self, variables):
        from ..functions.scalars import entropy

        return {i: entropy((self.p[i], 1 - self.p[i])) for i in variables}

    def mi(self, pairs):
        from .small_support import pair_information

        self.pairs += len(pairs)
        return {q: pair_information([max(x, 0.0) for x in joint(self.p[q[0]], self.p[q[1]], self.corr[q])], 2) for q in pairs}


def conditional(a: float, b: float, r: float) -> tuple[float, float]:
    """Chances of 1 of a child with chance b, given that its parent with chance a is 0 or 1."""
    cells = joint(a, b, r)
    return cells[1] / (1 - a) if a < 1 else 0.0, cells[3] / a if a > 0 else 0.0


def tree_vectors(users: DataFrame, rows: list[dict], seed: str = "w1") -> DataFrame:
    """user_id, x: each variable from its parent by the conditional of their joint."""
    p = {t["node"]: t["p"] for t in rows}
    df = users
    for t in rows:
        i, parent = t["node"], t["parent"]
        coin = uniform(seed, f"x{i}", F.col("user_id"))
        if parent < 0:
            one = coin < F.lit(p[i])
        else:
            zero, full = conditional(p[parent], p[i], t["r"])
            one = coin < F.when(F.col(f"v{parent}") == 1, F.lit(full)).otherwise(F.lit(zero))
        df = df.withColumn(f"v{i}", F.when(one, 1).otherwise(0))
    return packed(df, len(rows))


_STEP = np.uint64(0x9E3779B97F4A7C15)


def _coins(base: np.ndarray, i: int) -> np.ndarray:
    """Coins in [0, 1) of users with a 64-bit hash each, for variable i: a counter-based generator."""
    with np.errstate(over="ignore"):
        x = base + np.uint64(i + 1) * _STEP
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        x = x ^ (x >> np.uint64(31))
    return (x >> np.uint64(11)).astype(np.float64) / float(1 << 53)


def _sampled(users: DataFrame, d: int, seed: str, fill) -> DataFrame:
    """user_id, x with the coins of many variables drawn in batches; ``fill(x, base)`` writes x[:, i]."""
    keyed = users.select("user_id", F.xxhash64(F.lit(seed), F.col("user_id").cast("string")).alias("base"))
    kind = keyed.schema["user_id"].dataType.simpleString()

    def run(batches):
        for batch in batches:
            base = batch.column(1).to_numpy().view(np.uint64)
            x = np.zeros((len(base), d), np.int32)
            fill(x, base)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, d, dtype=np.int32)), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays([batch.column(0), lists], ["user_id", "x"])

    return keyed.mapInArrow(run, f"user_id {kind}, x array<int>")


def sampled_vectors(users: DataFrame, rows: list[dict], seed: str = "w1") -> DataFrame:
    """As ``tree_vectors``, for trees of many variables: coins from a hash of the user, no plan step a variable."""
    return _sampled(users, len(rows), seed, _tree_fill(rows))


def _tree_fill(rows: list[dict]):
    p = {t["node"]: t["p"] for t in rows}

    def fill(x, base):
        for t in rows:
            i, parent = t["node"], t["parent"]
            zero, one = conditional(p[parent], p[i], t["r"]) if parent >= 0 else (p[i], p[i])
            x[:, i] = _coins(base, i) < (np.where(x[:, parent] == 1, one, zero) if parent >= 0 else one)

    return fill


def pair_ones(users: DataFrame, rows: list[dict], seed: str = "w1") -> tuple[int, np.ndarray]:
    """(users, ones): how many users of ``sampled_vectors`` have a 1 at both i and j, for all i and j.

    Bits are drawn and multiplied in the same task, so no vector leaves it; a task sends the
    products in blocks of rows, which are added up by block.
    """
    d, fill, block = len(rows), _tree_fill(rows), 64
    keyed = users.select(F.xxhash64(F.lit(seed), F.col("user_id").cast("string")).alias("base"))
    names = ["block", "n", "ones"]

    def count(batches):
        n, ones = 0, np.zeros((d, d), np.int64)
        for batch in batches:
            base = batch.column(0).to_numpy().view(np.uint64)
            x = np.zeros((d, len(base)), np.float32)  # a variable's bits lie together
            fill(x.T, base)
            ones += (x @ x.T).astype(np.int64)  # exact: a batch has fewer than 2^24 rows
            n += len(base)
        for k in range(0, d, block):
            yield pa.RecordBatch.from_arrays([pa.array([k // block]), pa.array([n]), pa.array([ones[k : k + block].tobytes()], pa.binary())], names)

    def add(batches):
        sums: dict[int, list] = {}
        for batch in batches:
            for k, n, raw in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                one = np.frombuffer(raw, np.int64)
                sums[k] = [sums[k][0] + n, sums[k][1] + one] if k in sums else [n, one]
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int64()), pa.array([n for n, _ in sums.values()], pa.int64()), pa.array([v.tobytes() for _, v in sums.values()], pa.binary())], names)

    schema = "block long, n long, ones binary"
    size, out = 0, np.zeros((d, d), np.int64)
    for r in keyed.mapInArrow(count, schema).repartition("block").mapInArrow(add, schema).toLocalIterator():
        size = r["n"]
        out[r["block"] * block : (r["block"] + 1) * block] = np.frombuffer(r["ones"], np.int64).reshape(-1, d)
    return size, out


class OnesSource:
    """A source that answers questions about binary variables from counts of ``pair_ones``."""

    def __init__(self, n: int, ones: np.ndarray):
        n, both, one = max(n, 1), ones.astype(float), np.diag(ones).astype(float)

        def part(k):  # -p ln p of counts
            p = np.maximum(k, 0) / n
            return -p * np.log(np.where(p > 0, p, 1))

        self.h = part(one) + part(n - one)
        joint = part(both) + part(one[:, None] - both) + part(one[None, :] - both) + part(n - one[:, None] - one[None, :] + both)
        self.w = np.maximum(self.h[:, None] + self.h[None, :] - joint, 0.0)
        self.pairs = 0

    def marginals(self, variables):
        return {i: float(self.h[i]) for i in variables}

    def mi(self, pairs):
        self.pairs += len(pairs)
        return {q: float(self.w[q]) for q in pairs}


def chain_vectors(users: DataFrame, moves: list[float], c: int, seed: str = "chain") -> DataFrame:
    """user_id, x of a chain over c symbols: uniform first, then the same symbol or, with the step's chance, another one alike."""

    def fill(x, base):
        x[:, 0] = _coins(base, 0) * c
        for i in range(1, len(moves)):
            coin = _coins(base, i)
            other = np.minimum((coin / moves[i] * (c - 1)).astype(np.int32), c - 2) + 1 if moves[i] else 0
            x[:, i] = np.where(coin < moves[i], (x[:, i - 1] + other) % c, x[:, i - 1])

    return _sampled(users, len(moves), seed, fill)
