"""Packing documents into as few fixed-length sequences as possible.

Documents become pieces of at most ``capacity`` tokens. Only the histogram of piece lengths
(at most ``capacity`` rows) reaches the driver, where the configuration linear program over
it, min sum x_c with every length covered, is solved by multiplicative weights: the price of
a length is its size times a weight that grows with the share of the length that is still
uncovered, an unbounded-knapsack dynamic program prices patterns, and each length, from the
largest, takes the near-best pattern that it leads for as much as its lengths still need.
Every pattern taken covers a length to its end, so the support has no more patterns than
there are lengths, as a vertex has, and little is lost when it is rounded down to whole
sequences. The program runs again on what rounding leaves; the last few sequences are filled
one by one. Any prices give a lower bound of the program, which the plan reports.
The plan is a list of patterns with multiplicities, of bounded size, and each piece finds its
place from its rank within its length, so no sequence is ever gathered in one place.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import raw_bytes, small_batches, stage, texts_of, tidy
from .unit_encoder import UnitEncoder

#: Knapsack programs of one solution at most, and solutions: of all pieces, then of what rounding leaves.
ROUNDS, PASSES = 400, 3
#: Rates at which weights grow that are tried until a plan meets the lower bound.
RATES = (0.01, 0.05)
#: Pieces that one ranking bucket holds on average.
BUCKET = 20_000

Pattern = tuple[tuple[int, int], ...]


@dataclass
class Plan:
    """Patterns with their times, how many sequences come from the rounded program, and a lower bound of all."""

    steps: list[tuple[Pattern, int]] = field(default_factory=list)
    rounded: int = 0
    bound: int = 0

    @property
    def sequences(self) -> int:
        return sum(times for _, times in self.steps)


def knapsack(value: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Best value of each capacity 0..capacity with unlimited items of size 1..capacity, and the size taken first.

    ``value[l]`` is the price of size l (index 0 unused, 0 for absent sizes). Of equal choices
    the largest size is taken; -1 says that one token of the room stays free.
    """
    best = np.zeros(capacity + 1)
    take = np.zeros(capacity + 1, dtype=np.int64)
    v = value[1:]
    for c in range(1, capacity + 1):
        options = best[:c] + v[:c][::-1]  # by the room that is left
        k = int(options.argmax())
        if options[k] > best[c - 1]:
            best[c], take[c] = options[k], c - k
        else:
            best[c], take[c] = best[c - 1], -1
    return best, take


def _pattern(first: int, room: int, take: np.ndarray) -> Pattern:
    counts = {first: 1}
    while room > 0:
        k = int(take[room])
        if k > 0:
            counts[k] = counts.get(k, 0) + 1
            room -= k
        elif k < 0:
            room -= 1
        else:
            break
    return tuple(sorted(counts.items()))


def fractional(need: np.ndarray, capacity: int, rate: float = RATES[0], rounds: int = ROUNDS) -> tuple[dict[Pattern, float], float]:
    """(patterns with fractional multiplicities, a lower bound of the sequences) for ``need`` (index = length).

    The patterns cover ``need`` exactly unless ``rounds`` programs do not suffice.
    """
    left, weight = need.astype(float), np.ones(len(need))
    x: dict[Pattern, float] = {}
    bound, slack = 0.0, 0.0
    length = np.arange(len(need))
    for _ in range(rounds):
        sizes = np.flatnonzero(left > 1e-9)
        if not len(sizes):
            break
        price = np.zeros(capacity + 1)
        price[sizes] = sizes * weight[sizes]
        best, take = knapsack(price, capacity)
        bound = max(bound, float((need * price).sum() / best[capacity]))
        worth = price[sizes] + best[capacity - sizes]
        taken = 0.0
        for size in sizes[worth >= (1 - slack) * best[capacity]][::-1].tolist():
            pattern = _pattern(size, capacity - size, take)
            amount = min(left[s] / k for s, k in pattern)
            if amount > 1e-9:
                x[pattern] = x.get(pattern, 0.0) + amount
                taken += amount
                for s, k in pattern:
                    left[s] -= k * amount
        weight *= np.exp(rate * left / np.maximum(need, 1))
        weight /= weight.max()
        if taken * capacity < 0.02 * float((left * length).sum()):
            slack = max(2 * slack, 0.001)  # the best patterns want lengths that are used up
    return x, bound


def _fill(room: int, left: np.ndarray) -> list[int]:
    """Sizes that fill ``room`` as full as a few tries find: one, two, or the largest and again."""
    out = []
    while room > 0:
        fits = np.flatnonzero(left[: room + 1])
        if not len(fits):
            break
        if fits[-1] == room:
            out.append(room)
            break
        other = room - fits
        exact = fits[(left[other] > 0) & ((other != fits) | (left[fits] > 1))]
        if len(exact):
            out += [int(exact[-1]), int(room - exact[-1])]
            break
        out.append(int(fits[-1]))
        left[fits[-1]] -= 1
        room -= int(fits[-1])
    return out


def _filled(left: np.ndarray, capacity: int) -> list[tuple[Pattern, int]]:
    """(pattern, times) that use up ``left``, the largest size first, each as full as a few tries find."""
    out = []
    while len(sizes := np.flatnonzero(left)):
        first = int(sizes[-1])
        rest = left.copy()
        rest[first] -= 1
        counts: dict[int, int] = {first: 1}
        for s in _fill(capacity - first, rest):
            counts[s] = counts.get(s, 0) + 1
        times = min(int(left[s]) // k for s, k in counts.items())
        out.append((tuple(sorted(counts.items())), times))
        for s, k in counts.items():
            left[s] -= times * k
    return out


def _rounded(need: np.ndarray, capacity: int, rate: float, rounds: int) -> Plan:
    left, out = need.astype(np.int64).copy(), Plan()
    for _ in range(PASSES):
        if not left.any():
            break
        x, bound = fractional(left, capacity, rate, rounds)
        out.bound = out.bound or int(np.ceil(bound - 1e-6))
        placed = out.rounded
        for pattern, amount in sorted(x.items(), key=lambda kv: (-kv[1], kv[0])):
            times = min(int(amount + 1e-9), *(int(left[s]) // k for s, k in pattern))
            if times:
                out.steps.append((pattern, times))
                out.rounded += times
                for s, k in pattern:
                    left[s] -= times * k
        if out.rounded == placed:
            break
    out.steps += _filled(left, capacity)
    return out


def plan(need: np.ndarray, capacity: int, rounds: int = ROUNDS) -> Plan:
    """A plan whose sizes add up to exactly ``need``, of the fewest sequences that the rates give.

    Where filling one by one alone takes fewer (met on a few hundred pieces), that stands.
    """
    made = Plan()
    for k, rate in enumerate(RATES):
        got = _rounded(need, capacity, rate, rounds)
        made = got if not k or got.sequences < made.sequences else made
        if made.sequences <= made.bound:
            return made
    alone = Plan(_filled(need.astype(np.int64).copy(), capacity), 0, made.bound)
    return alone if alone.sequences < made.sequences else made


def lay_out(steps, capacity: int) -> dict[str, np.ndarray]:
    """For every length, rank intervals with the sequences and offsets that they fill; sorted by length, then rank."""
    used = np.zeros(capacity + 1, dtype=np.int64)
    rows, base = [], 0
    for pattern, times in steps:
        at = 0
        for size, k in pattern:
            rows.append((size, used[size], base, k, at))
            used[size] += times * k
            at += size * k
        base += times
    rows.sort()
    cols = np.array(rows, dtype=np.int64).reshape(-1, 5).T
    return dict(zip(("size", "rank", "base", "per", "at"), cols, strict=True)) | {"sequences": np.int64(base)}


def token_pieces(docs: DataFrame, path: str, capacity: int = 2048, end_id: int = 0) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of every document's ids with ``end_id`` appended.

    Documents of up to ``capacity`` ids are one piece; longer ones are cut so that only the
    first piece may be shorter. A null or empty text has the end id alone. Rows are
    independent: repeated and null ids give the pieces of each row. An empty table gives an
    empty result; columns other than doc_id and text are ignored.
    """
    small_batches(docs.sparkSession)
    ids = docs.schema["doc_id"].dataType.simpleString()
    end = np.array([end_id], "<u4").tobytes()
    width = 4 * capacity

    def cut(batches):
        encoder = UnitEncoder(path, "byte")
        for batch in batches:
            rows, piece, start, length, crc = [], [], [], [], []
            for first, ids, counts in encoder.encode_rows(*raw_bytes(texts_of(batch.column(1)))):
                raw, stops = ids.tobytes(), 4 * np.cumsum(counts)
                for k, (at, stop) in enumerate(zip((stops - 4 * counts).tolist(), stops.tolist(), strict=True)):
                    got = raw[at:stop] + end
                    head = len(got) % width or width
                    bounds = [0, *range(head, len(got) + 1, width)]
                    for p in range(len(bounds) - 1):
                        a, b = bounds[p], bounds[p + 1]
                        rows.append(first + k)
                        piece.append(p)
                        start.append(a // 4)
                        length.append((b - a) // 4)
                        crc.append(zlib.crc32(got[a:b]))
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(rows, pa.int64())), pa.array(piece, pa.int32()), *[pa.array(c, pa.int64()) for c in (start, length, crc)]], ["doc_id", "piece", "start", "length", "ids_crc32"])
        tidy()

    return docs.select("doc_id", "text").mapInArrow(cut, f"doc_id {ids}, piece int, start long, length long, ids_crc32 long")


def pack(pieces: DataFrame, capacity: int = 2048, rounds: int = ROUNDS) -> DataFrame:
    """``pieces`` (a staged table) with sequence_id and offset.

    Every row gets a place; rows that are equal in all columns are interchangeable. An
    empty table gives an empty result.
    """
    spark = pieces.sparkSession
    need = np.zeros(capacity + 1, dtype=np.int64)
    for r in pieces.groupBy("length").count().collect():  # at most ``capacity`` rows
        need[r["length"]] = r["count"]
    table = spark.sparkContext.broadcast(lay_out(plan(need, capacity, rounds).steps, capacity))
    names = pieces.columns
    buckets = max(1, -(-int(need.sum()) // BUCKET))
    keyed = pieces.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(buckets)))
    held = keyed.groupBy("length", "bucket").agg(F.count("*").alias("held"))
    before = held.withColumn("before", F.sum("held").over(Window.partitionBy("length").orderBy("bucket")) - F.col("held")).drop("held")
    order = Window.partitionBy("length", "bucket").orderBy("doc_id", "piece", "start", "ids_crc32")
    ranked = keyed.withColumn("nth", F.row_number().over(order)).join(before, ["length", "bucket"])
    ranked = ranked.select(*pieces.columns, (F.col("before") + F.col("nth") - 1).alias("rank"))
    n = len(names)
    at_length, wide = pieces.columns.index("length"), np.int64(1) << np.int64(44)

    def place(batches):
        t = table.value
        keys = t["size"] * wide + t["rank"]
        for batch in batches:
            length, rank = batch.column(at_length).to_numpy(), batch.column(n).to_numpy()
            k = np.searchsorted(keys, length * wide + rank, side="right") - 1
            nth = rank - t["rank"][k]
            sequence, slot = t["base"][k] + nth // t["per"][k], nth % t["per"][k]
            yield pa.RecordBatch.from_arrays([*batch.columns[:n], pa.array(sequence), pa.array(t["at"][k] + slot * length)], [*names, "sequence_id", "offset"])

    schema = ", ".join(f"`{c}` {k}" for c, k in pieces.dtypes)
    return ranked.mapInArrow(place, f"{schema}, sequence_id long, offset long")


def pack_documents(docs: DataFrame, path: str, capacity: int = 2048, end_id: int = 0) -> DataFrame:
    """Pieces of all documents with their places; see :func:`token_pieces` and :func:`pack`.

    Null texts, empty texts, null or repeated ids, empty tables and other columns are as there.
    """
    return pack(stage(token_pieces(docs, path, capacity, end_id), "pieces"), capacity)
