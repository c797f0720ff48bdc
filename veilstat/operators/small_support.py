"""Private histograms of small alphabets, and entropies and informations from them.

Users report one randomised symbol (or one bit); reports are counted by question in one
aggregation; the driver sees question x symbol counts only, de-biases, projects to the
simplex and forms entropies. Joint cells are estimated once and marginalised, so mutual
information is never negative.
"""

from __future__ import annotations

import math
from itertools import product

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.coins import uniform
from ..functions.scalars import entropy, hadamard_sign, project
from .measures import l1_target
from .protocol import UserPool

# Mechanisms on the user's side


def rr_keep(c: int, alpha: float) -> float:
    return math.exp(alpha) / (math.exp(alpha) + c - 1)


def rr_encode(x: Column, c: int, alpha: float, seed: str, *ids) -> Column:
    """c-ary randomised response: the true symbol, or one of the others alike."""
    other = F.floor(uniform(seed, "other", *ids) * F.lit(c - 1)).cast("int")
    return F.when(uniform(seed, "keep", *ids) < F.lit(rr_keep(c, alpha)), x).otherwise(F.when(other >= x, other + 1).otherwise(other)).cast("int")


def rr_debias(counts: list[float], alpha: float) -> list[float]:
    c, n = len(counts), sum(counts)
    if not n or c < 2:
        return [1.0 / c] * c if not n else [1.0]
    p = rr_keep(c, alpha)
    q = (1 - p) / (c - 1)
    return [(k / n - q) / (p - q) for k in counts]


def hadamard_order(c: int) -> int:
    """Rows of the sign matrix: the least power of two above c."""
    return 1 << c.bit_length()


def hadamard_encode(x: Column, c: int, alpha: float, public: str, private: str, *ids) -> tuple[Column, Column]:
    """(public row, one bit): the sign of the user's symbol in a public row, flipped with chance 1 / (1 + e^alpha)."""
    row = F.floor(uniform(public, "row", *ids) * F.lit(hadamard_order(c))).cast("int")
    sign = hadamard_sign(row, x + 1)
    flip = uniform(private, "flip", *ids) < F.lit(1 / (1 + math.exp(alpha)))
    return row, F.when(flip, -sign).otherwise(sign).cast("int")


def hadamard_debias(sums: dict[int, float], n: float, c: int, alpha: float) -> list[float]:
    """Frequencies from the sum of signs in each public row."""
    scale = (math.exp(alpha) + 1) / (math.exp(alpha) - 1)
    return [scale * sum(s * (1 - 2 * (bin(r & (x + 1)).count("1") % 2)) for r, s in sums.items()) / n if n else 1.0 / c for x in range(c)]


def unary_encode(x: Column, c: int, alpha: float, seed: str, *ids) -> Column:
    """One-hot bits, each flipped with chance 1 / (1 + e^(alpha/2)); alpha-private as two bits differ."""
    flip = F.lit(1 / (1 + math.exp(alpha / 2)))
    return F.array(*[F.when(uniform(seed, f"bit{s}", *ids) < flip, 1 - F.when(x == s, 1).otherwise(0)).otherwise(F.when(x == s, 1).otherwise(0)).cast("int") for s in range(c)])


def unary_debias(ones: list[float], n: float, alpha: float) -> list[float]:
    f = 1 / (1 + math.exp(alpha / 2))
    return [(k / n - f) / (1 - 2 * f) for k in ones]


def choose_mechanism(cells: int, alpha: float | None) -> str:
    """The smaller variance of the two single-report mechanisms."""
    if alpha is None:
        return "none"
    e = math.exp(alpha)
    return "rr" if (e + cells - 2) / (e - 1) ** 2 <= ((e + 1) / (e - 1)) ** 2 else "hadamard"


def users_needed(eps: float, cells: int, alpha: float, delta: float, mechanism: str = "auto") -> int:
    """Users for an expected distance whose entropy bound is eps, times log(1/delta)."""
    e = math.exp(alpha)
    mechanism = choose_mechanism(cells, alpha) if mechanism == "auto" else mechanism
    var = (e + cells - 2) / (e - 1) ** 2 if mechanism == "rr" else ((e + 1) / (e - 1)) ** 2
    t = l1_target(eps, cells)
    return math.ceil(cells * cells * var * max(1.0, math.log(1 / delta)) / (t * t))


# Questions to a pool

#: Questions that are broadcast at most; more are joined by shuffle.
BROADCAST_QUESTIONS = 200_000


def question_table(spark, questions: list[tuple[int, ...]]) -> DataFrame:
    """(query_id, q0, q1, ...): the coordinates that each question asks for."""
    arity = len(questions[0])
    names = ", ".join(f"q{k} int" for k in range(arity))
    table = spark.createDataFrame(pd.DataFrame(np.array(questions, np.int32).reshape(-1, arity), columns=[f"q{k}" for k in range(arity)]).rename_axis("query_id").reset_index(), f"query_id int, {names}")
    return F.broadcast(table) if len(questions) <= BROADCAST_QUESTIONS else table


def cell_of(c: int, arity: int) -> Column:
    """Cell number of a user's coordinates q0, q1, ... in base c."""
    cell = F.lit(0)
    for k in range(arity):
        cell = cell * c + F.get(F.col("x"), F.col(f"q{k}"))
    return cell.cast("int")


def _counts(reports: DataFrame, key: str, cells: int, value: Column) -> dict[int, list[float]]:
    """An array of sums for every question: one aggregation, a row a question to the driver."""
    sums = [F.sum(F.when(F.col(key) == k, value).otherwise(0)).cast("double").alias(f"s{k}") for k in range(cells)]
    got = reports.groupBy("query_id").agg(F.count("*").cast("double").alias("n"), *sums).toPandas()
    return dict(zip(got["query_id"].tolist(), got[["n", *[f"s{k}" for k in range(cells)]]].values.tolist(), strict=True))


def cell_histograms(pool: UserPool, questions: list[tuple[int, ...]], c: int, alpha: float | None, width: int, private: str, public: str = "pub") -> dict[tuple[int, ...], list[float]]:
    """Cell probabilities of each tuple of coordinates, one batch of users each, all in one job.

    ``width`` is in slots. Questions are a table that joins the users by arithmetic slot
    number; only a row of counts for each question comes back to the driver.
    """
    if not questions:
        return {}
    arity = len(questions[0])
    cells = c**arity
    mechanism = choose_mechanism(cells, alpha)
    bits = 1 if mechanism == "hadamard" else math.ceil(math.log2(cells))
    _, rows = pool.allot(questions, width, arity, bits, alpha)
    rows = rows.join(question_table(pool.users.sparkSession, questions), "query_id").select("user_id", "query_id", cell_of(c, arity).alias("cell"))
    out = {}
    if mechanism == "hadamard":
        row, bit = hadamard_encode(F.col("cell"), cells, alpha, public, private, F.col("user_id"))
        got = _counts(rows.select("query_id", row.alias("row"), bit.alias("bit")), "row", hadamard_order(cells), F.col("bit"))
        for k, q in enumerate(questions):
            n, *sums = got.get(k, [0.0] * (1 + hadamard_order(cells)))
            out[q] = project(hadamard_debias(dict(enumerate(sums)), n, cells, alpha))
        return out
    report = F.col("cell") if mechanism == "none" else rr_encode(F.col("cell"), cells, alpha, private, F.col("user_id"))
    got = _counts(rows.select("query_id", report.alias("report")), "report", cells, F.lit(1))
    for k, q in enumerate(questions):
        n, *counts = got.get(k, [0.0] * (1 + cells))
        raw = ([x / n for x in counts] if n else [1.0 / cells] * cells) if mechanism == "none" else rr_debias(counts, alpha)
        out[q] = project(raw)
    return out


def marginal(p: list[float], c: int, arity: int, keep: tuple[int, ...]) -> list[float]:
    out: dict[tuple, float] = {}
    for at, x in zip(product(range(c), repeat=arity), p, strict=True):
        k = tuple(at[i] for i in keep)
        out[k] = out.get(k, 0.0) + x
    return [out[k] for k in sorted(out)]


def corrected_entropy(p: list[float], n: float | None = None) -> float:
    """Plug-in entropy; with ``n`` samples, plus the first-order bias of (cells seen - 1) / 2n."""
    return entropy(p) + (max(0, sum(x > 0 for x in p) - 1) / (2 * n) if n else 0.0)


def pair_information(p: list[float], c: int) -> float:
    return max(0.0, entropy(marginal(p, c, 2, (0,))) + entropy(marginal(p, c, 2, (1,))) - entropy(p))


def triple_information(p: list[float], c: int, given: int) -> float:
    """I of the two other coordinates given coordinate ``given`` from triple cells."""
    a, b = (k for k in range(3) if k != given)
    return max(0.0, entropy(marginal(p, c, 3, (a, given))) + entropy(marginal(p, c, 3, (b, given))) - entropy(p) - entropy(marginal(p, c, 3, (given,))))


class PrivateSource:
    """Entropies, informations and conditional informations, a batch of users for each.

    ``split_batches`` asks other users for each entropy of an information, so that the terms
    err independently; the value may then be negative and is cut at 0. ``bias_correction``
    adds the first-order bias of plug-in entropies (single entropies and split ones).
    """

    def __init__(self, pool: UserPool, c: int, alpha: float | None, width: int, private: str = "noise", split_batches: bool = False, bias_correction: bool = False):
        self.pool, self.c, self.alpha, self.width, self.private = pool, c, alpha, width, private
        self.split, self.correct = split_batches, bias_correction
        self.pairs = self.triples = 0

    def slots(self, arity: int) -> int:
        """Slots of a question about ``arity`` coordinates."""
        return self.width

    def _histograms(self, questions):
        arity = len(questions[0]) if questions else 1
        return cell_histograms(self.pool, questions, self.c, self.alpha, self.slots(arity), self.private)

    def _entropies(self, questions) -> dict[tuple[int, ...], float]:
        n = self.pool.expected(self.slots(len(questions[0]))) if self.correct and questions else None
        return {q: corrected_entropy(p, n) for q, p in self._histograms(questions).items()}

    def marginals(self, variables: list[int]) -> dict[int, float]:
        return {q[0]: h for q, h in self._entropies([(i,) for i in variables]).items()}

    def mi(self, pairs: list[tuple[int, int]]) -> dict[tuple[int, int], float]:
        self.pairs += len(pairs)
        if not self.split:
            return {q: pair_information(p, self.c) for q, p in self._histograms(pairs).items()}
        joint = self._entropies(pairs)
        first, second = (self._term([(q[k],) for q in pairs]) for k in (0, 1))
        return {q: max(0.0, first[k] + second[k] - joint[q]) for k, q in enumerate(pairs)}

    def _term(self, questions) -> list[float]:
        """Entropies of questions that may repeat, each from users of its own."""
        n = self.pool.expected(self.slots(1)) if self.correct else None
        out: dict[int, float] = {}
        rest = list(enumerate(questions))
        while rest:  # a round takes every question once
            seen: dict[tuple, int] = {}
            for k, q in rest:
                seen.setdefault(q, k)
            rest = [(k, q) for k, q in rest if seen[q] != k]
            out |= {seen[q]: corrected_entropy(p, n) for q, p in self._histograms(list(seen)).items()}
        return [out[k] for k in range(len(questions))]

    def cmi(self, triples: list[tuple[int, int, int]]) -> dict[tuple[int, int, int], list[float]]:
        """For (i, j, k): [I(j;k|i), I(i;k|j), I(i;j|k)], all from the same users' triples."""
        self.triples += len(triples)
        return {q: [triple_information(p, self.c, g) for g in range(3)] for q, p in self._histograms(triples).items()}


#: Share of the allowed error of an information that each of its entropies may have.
TERMS = {1: 1, 2: 3, 3: 4}


class GoodSource(PrivateSource):
    """Answers within ``eps`` except with chance ``delta`` over a whole run of at most ``calls`` questions.

    Every question gets as many users as the sample bound asks for at error eps (shared among
    the entropies of an information) and failure chance delta / calls. Too few users in the
    pool raise PoolExhausted; nothing is answered from less.
    """

    def __init__(self, pool: UserPool, c: int, alpha: float, eps: float, delta: float, calls: int, private: str = "noise"):
        super().__init__(pool, c, alpha, 0, private)
        self.eps, self.delta, self.calls = eps, delta, calls

    def users(self, arity: int) -> int:
        return users_needed(self.eps / TERMS[arity], self.c**arity, self.alpha, self.delta / self.calls)

    def slots(self, arity: int) -> int:
        return max(1, math.ceil(self.users(arity) * self.pool.slots / max(1, self.pool.size())))


def tree_source(pool: UserPool, d: int, c: int, alpha: float, eps: float, delta: float, kappa: float = 1.0) -> GoodSource:
    """Errors of eps / 2 and a chance of delta / d^2 for each answer; ``kappa`` shrinks eps for constants."""
    return GoodSource(pool, c, alpha, eps / kappa / 2, delta, d * d)


def chain_source(pool: UserPool, d: int, c: int, alpha: float, eps: float, delta: float, kappa: float = 1.0) -> GoodSource:
    return GoodSource(pool, c, alpha, eps / kappa, delta, d * (2 + math.ceil(math.log2(max(2, d)))) + 2 * d)


def star_source(pool: UserPool, d: int, c: int, alpha: float, eps: float, delta: float, kappa: float = 1.0) -> GoodSource:
    return GoodSource(pool, c, alpha, eps / kappa, delta, 3 * d)


def count_cells(users: DataFrame, questions: list[tuple[int, ...]], c: int) -> np.ndarray:
    """Counts of every cell of every question (rows) over all users' x.

    A task turns its rows into cell numbers, question by question, or all pairs at once by a
    product of one-hot columns, and sends its counts packed by blocks of questions.
    """
    arity = len(questions[0])
    asked = np.array(questions, np.int32).reshape(-1, arity)
    cells, block = c**arity, 4096
    d = int(asked.max()) + 1
    all_pairs = arity == 2 and len(asked) > d * d // 8

    def count(batches):
        total = np.zeros((d * c, d * c) if all_pairs else (len(asked), cells), np.int64)
        for batch in batches:
            flat = batch.column(0).flatten().to_numpy(zero_copy_only=False)
            x = flat.reshape(batch.num_rows, -1)[:, :d] if batch.num_rows else np.zeros((0, d), np.int32)
            if all_pairs:
                hot = np.zeros((len(x), d * c), np.float32)
                hot[np.repeat(np.arange(len(x)), d), (np.arange(d) * c + x).ravel()] = 1
                total += (hot.T @ hot).astype(np.int64)
                continue
            for k, q in enumerate(asked):
                cell = x[:, q[0]].astype(np.int64)
                for i in q[1:]:
                    cell = cell * c + x[:, i]
                total[k] += np.bincount(cell, minlength=cells)
        if all_pairs:
            at = asked * c
            total = np.stack([total[at[:, 0] + a, at[:, 1] + b] for a in range(c) for b in range(c)], axis=1)
        for k in range(0, len(asked), block):
            yield pa.RecordBatch.from_arrays([pa.array([k // block]), pa.array([np.ascontiguousarray(total[k : k + block]).tobytes()], pa.binary())], ["block", "counts"])

    def add(batches):
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for k, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                one = np.frombuffer(raw, np.int64)
                sums[k] = sums[k] + one if k in sums else one
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int64()), pa.array([v.tobytes() for v in sums.values()], pa.binary())], ["block", "counts"])

    told = users.select("x").mapInArrow(count, "block long, counts binary").repartition("block").mapInArrow(add, "block long, counts binary")
    out = np.zeros((len(asked), cells), np.int64)
    for r in told.toLocalIterator():
        out[r["block"] * block : (r["block"] + 1) * block] = np.frombuffer(r["counts"], np.int64).reshape(-1, cells)
    return out


class ExactSource:
    """The same answers from every row of ``users`` (x ARRAY<INT>), for ablations: one pass per batch."""

    def __init__(self, users: DataFrame, c: int):
        self.users, self.c = users, c
        self.pairs = self.triples = 0

    def _cells(self, questions: list[tuple[int, ...]]) -> dict[tuple[int, ...], list[float]]:
        if not questions:
            return {}
        counts = count_cells(self.users, questions, self.c).astype(float)
        return dict(zip(questions, (counts / np.maximum(counts.sum(axis=1, keepdims=True), 1)).tolist(), strict=True))

    def marginals(self, variables):
        return {q[0]: entropy(p) for q, p in self._cells([(i,) for i in variables]).items()}

    def mi(self, pairs):
        self.pairs += len(pairs)
        return {q: pair_information(p, self.c) for q, p in self._cells(pairs).items()}

    def cmi(self, triples):
        self.triples += len(triples)
        return {q: [triple_information(p, self.c, g) for g in range(3)] for q, p in self._cells(triples).items()}


class CountedSource(ExactSource):
    """The same for few variables, from one histogram of whole vectors: at most c^d rows come to the driver."""

    def __init__(self, users: DataFrame, c: int):
        super().__init__(users, c)
        got = users.groupBy("x").agg(F.count("*").cast("double").alias("n")).collect()
        self.x, self.n = np.array([r["x"] for r in got], np.int64), np.array([r["n"] for r in got])

    def _cells(self, questions):
        out = {}
        for q in questions:
            cell = np.zeros(len(self.n), np.int64)
            for i in q if len(self.n) else ():
                cell = cell * self.c + self.x[:, i]
            out[q] = (np.bincount(cell, self.n, self.c ** len(q)) / max(self.n.sum(), 1)).tolist()
        return out
