"""Gini and collision entropy from salted hashes of a few bits: one round, no alphabet.

Users are paired at random; both hash their value with the pair's salt to b bits, keep it
with a chance that gives alpha-local privacy, else report at random. The rate of equal
reports, corrected for chance and noise, is the collision probability; Gini entropy is one
minus it and collision entropy its negative logarithm.

With ``pairing="permute"`` only (pair, report) crosses the shuffle; bucket ranks shuffle ids and
values, as the salt is known only once the ranks are. The server adds up two counters.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.coins import SPAN, hash_bits, symbol, uniform
from ..functions.scalars import keep_rate, tidy

BUCKET = 1024


def value_of(cols: list[str]) -> Column:
    """One text of several columns; lengths keep them apart, nulls are symbols."""
    parts = [F.concat(F.length(symbol(c)).cast("string"), F.lit(":"), symbol(c)) for c in cols]
    return parts[0] if len(parts) == 1 else F.concat_ws("|", *parts)


def assign_pairs(df: DataFrame, id_col: str, public: str, by: list[str] = (), pairing: str = "bucket_rank", rows: int | None = None) -> DataFrame:
    """Adds ``bucket`` and ``idx``; the two users of a pair share both, leftovers are alone in theirs.

    ``bucket_rank``: random buckets of about a thousand users, ranked by coin: no row order
    is used, and a bucket is the unit of the one shuffle. ``permute``: ids 0..n-1, a keyed
    affine bijection, no shuffle before the match. ``adjacent``: ids 0..n-1 as they come,
    for rows that are independent draws only.
    """
    if pairing == "bucket_rank":
        n = rows if rows is not None else df.count()
        buckets = max(1, -(-n // BUCKET))
        df = df.withColumn("bucket", F.floor(uniform(public, "bucket", F.col(id_col)) * F.lit(buckets)).cast("long"))
        order = Window.partitionBy(*by, "bucket").orderBy(uniform(public, "rank", F.col(id_col)), id_col)
        return df.withColumn("idx", F.floor((F.row_number().over(order) - 1) / 2).cast("long"))
    n = rows if rows is not None else df.count()
    if pairing == "permute":
        df = df.withColumn("place", permuted(F.col(id_col).cast("long"), max(n, 1), public)).where("place IS NOT NULL")
    elif pairing == "adjacent":
        df = df.withColumn("place", F.col(id_col).cast("long"))
    else:
        raise ValueError(f"no pairing named {pairing}")
    return df.select("*", F.lit(0).cast("long").alias("bucket"), F.floor(F.col("place") / 2).cast("long").alias("idx")).drop("place")


#: Rounds of the keyed permutation, and how often a place outside the range is put through it again.
ROUNDS, WALKS = 4, 4


def sides(n: int) -> tuple[int, int]:
    """Two sides of a rectangle of n places or a few more."""
    a = math.isqrt(max(n - 1, 0)) + 1
    return a, -(-n // a)


def permuted(x: Column, n: int, public: str) -> Column:
    """Places 0..n-1 of ids 0..n-1 under a permutation that the public seed keys.

    An id is a cell of a rectangle that has at most sqrt(n) cells more than ids; rounds shift
    the row by a coin of the column and the column by a coin of the row, in turns. A cell
    beyond the ids goes through the rounds again; one id in about n^2 is still outside after
    WALKS of them and has no place (null). An id outside 0..n-1 is an error. The rounds are
    a fold, as a nested expression would double with every step.
    """
    a, b = sides(n)
    x = F.when((x >= 0) & (x < n), x).otherwise(F.raise_error(F.lit("ids must be 0 to n - 1")).cast("long"))

    def shift(name: str, r: Column, of: Column, side: int) -> Column:
        word = F.md5(F.concat_ws("|", F.lit(public), F.concat(F.lit(name), r.cast("string")), of.cast("string")))
        return F.floor(F.conv(F.substring(word, 1, 8), 16, 10).cast("double") / F.lit(SPAN) * side).cast("long")

    def step(s: Column, t: Column) -> Column:
        r = t % ROUNDS
        moved = s["y"] * b + s["x"]
        row = F.struct(((s["y"] + shift("row", r, s["x"], a)) % a).alias("y"), s["x"].alias("x"), s["place"].alias("place"))
        column = F.struct(s["y"].alias("y"), ((s["x"] + shift("column", r - 1, s["y"], b)) % b).alias("x"), s["place"].alias("place"))
        # A third kind of step ends a walk: it takes the cell as the place.
        return F.when(s["place"] < n, s).when(t < 0, F.struct(s["y"].alias("y"), s["x"].alias("x"), moved.alias("place"))).when(r % 2 == 0, row).otherwise(column)

    steps = [t for _ in range(WALKS) for t in (*range(ROUNDS), -1)]
    start = F.struct(F.floor(x / b).cast("long").alias("y"), (x % b).cast("long").alias("x"), F.lit(n).cast("long").alias("place"))
    place = F.aggregate(F.array(*[F.lit(t) for t in steps]), start, step, lambda s: s["place"])
    return F.when(place < n, place)


def reports(df: DataFrame, id_col: str, cols: list[str], b: int, alpha: float | None, public: str, private: str, keep: list[str] = ()) -> DataFrame:
    """bucket, idx, report: what leaves the users."""
    return df.select(*keep, "bucket", "idx", report_of(id_col, cols, b, alpha, public, private).alias("report"))


def report_of(id_col: str, cols: list[str], b: int, alpha: float | None, public: str, private: str) -> Column:
    """The report of a user with bucket and idx."""
    if b < 1 or (alpha is not None and alpha <= 0):
        raise ValueError("b must be at least 1 and alpha positive")
    salted = hash_bits(public, b, F.concat_ws(":", "bucket", "idx"), value_of(cols))
    if alpha is not None:
        noise = F.floor(uniform(private, "draw", F.col(id_col)) * F.lit(1 << b)).cast("int")
        salted = F.when(uniform(private, "keep", F.col(id_col)) < F.lit(keep_rate(alpha, b)), salted).otherwise(noise)
    return salted


def match(sent: DataFrame, by: list[str] = ()) -> DataFrame:
    """n_pairs and hits; (bucket, idx) groups lie where the pairing put them."""
    pairs = sent.groupBy(*by, "bucket", "idx").agg(F.count("*").alias("m"), F.min("report").alias("lo"), F.max("report").alias("hi")).where("m = 2")
    return (pairs.groupBy(*by) if by else pairs).agg(F.count("*").alias("n_pairs"), F.coalesce(F.sum(F.when(F.col("lo") == F.col("hi"), 1).otherwise(0)), F.lit(0)).alias("hits"))


def debias(counted: DataFrame, b: int, alpha: float | None, k: int | None = None, clamp: bool = True, as_printed: bool = False) -> DataFrame:
    """p2, gini, collision, their clamp flag and the standard error of p2.

    ``as_printed`` takes the corrected rate for the Gini entropy itself, which it is not.
    """
    size, lam = 1 << b, keep_rate(alpha, b)
    scale = size / (lam * lam * (size - 1))
    cbar = F.try_divide(F.col("hits"), F.col("n_pairs"))
    raw = (size * cbar - 1) / (lam * lam * (size - 1))
    floor = F.lit(1.0 / k) if k else 1 / F.greatest(F.col("n_pairs"), F.lit(1)).cast("double")
    p2 = F.least(F.greatest(raw, floor), F.lit(1.0)) if clamp else raw
    gini, coll = 1 - p2, -F.ln(F.when(p2 > 0, p2))
    if as_printed:
        gini = raw
        coll = -F.ln(F.when(1 - raw > 0, 1 - raw))
    err = scale * F.sqrt(cbar * (1 - cbar) / F.when(F.col("n_pairs") > 0, F.col("n_pairs")))
    return counted.select("*", tidy(raw).alias("p2_raw"), tidy(gini).alias("gini"), tidy(coll).alias("collision"), tidy(err).alias("stderr"), (raw < floor).alias("clamped"))


def collision_sketch(df: DataFrame, id_col: str, cols: list[str], b: int = 1, alpha: float | None = None, *, public: str = "pub", private: str = "noise", by: list[str] = (), pairing: str = "bucket_rank", clamp: bool = True, k: int | None = None, as_printed: bool = False) -> DataFrame:
    """One row (or one a group) of n_pairs, hits, p2_raw, gini, collision, stderr, clamped.

    With ``by``, pairs form inside a group and the group is public. An odd user out is not
    contacted. Groups without pairs are absent; an empty table gives zero pairs and nulls.
    """
    paired = assign_pairs(df.select(id_col, *dict.fromkeys([*by, *cols])), id_col, public, by, pairing)
    return debias(match(reports(paired, id_col, cols, b, alpha, public, private, by), by), b, alpha, k, clamp, as_printed)


def boosted(df: DataFrame, id_col: str, cols: list[str], batches: int, b: int = 1, alpha: float | None = None, public: str = "pub", private: str = "noise") -> DataFrame:
    """Median of the estimates of independent batches of users."""
    dealt = df.withColumn("batch", F.floor(uniform(public, "batch", F.col(id_col)) * F.lit(batches)).cast("int"))
    each = collision_sketch(dealt, id_col, cols, b, alpha, public=public, private=private, by=["batch"])
    return each.agg(F.sum("n_pairs").alias("n_pairs"), tidy(F.percentile("gini", 0.5)).alias("gini"))


def raw_pairs(df: DataFrame, id_col: str, cols: list[str], public: str = "pub", bits: int | None = None) -> DataFrame:
    """The rival without privacy: equal raw samples among disjoint pairs, log2 of the alphabet in bits each."""
    paired = assign_pairs(df.select(id_col, *cols), id_col, public)
    counted = match(paired.select("bucket", "idx", value_of(cols).alias("report")))
    p2 = F.col("hits") / F.col("n_pairs")
    out = counted.select("*", tidy(p2).alias("p2"), tidy(1 - p2).alias("gini"), tidy(-F.ln(F.when(p2 > 0, p2))).alias("collision"))
    return out.withColumn("total_bits", (F.col("n_pairs") * 2 * bits).cast("long")) if bits else out


def pairs_within_task(df: DataFrame, id_col: str, cols: list[str], b: int = 1, alpha: float | None = None, public: str = "pub", private: str = "noise") -> DataFrame:
    """Pairs formed inside a task in coin order: no shuffle of users at all, two counters a task.

    Rows are sorted by coin within their partition and neighbours form pairs, whose salt is
    the first one's id; hashes and noise are expressions. Valid where an input partition is
    no cluster of equal values.
    """
    import numpy as np
    import pyarrow as pa

    size = 1 << b
    value = value_of(cols)
    sorted_rows = df.select(uniform(public, "rank", F.col(id_col)).alias("u"), F.col(id_col).cast("string").alias("id"), value.alias("v")).sortWithinPartitions("u", "id")

    def pair(batches):  # (first, second) neighbours; an odd one waits for the next batch
        held = None
        for batch in batches:
            table = pa.Table.from_batches([batch] if held is None else [held, batch]).combine_chunks()
            n = table.num_rows // 2
            first, second = table.take(np.arange(0, 2 * n, 2)), table.take(np.arange(1, 2 * n, 2))
            rest = table.slice(2 * n).to_batches()
            held = rest[0] if rest else None
            yield from pa.table([first["id"], first["v"], second["id"], second["v"]], names=["id", "v", "id2", "v2"]).to_batches()

    pairs = sorted_rows.select("id", "v").mapInArrow(pair, "id string, v string, id2 string, v2 string")

    def report(who: str, v: str) -> Column:
        salted = hash_bits(public, b, F.col("id"), F.col(v))
        return F.when(F.expr("true") if alpha is None else uniform(private, "keep", F.col(who)) < F.lit(keep_rate(alpha, b)), salted).otherwise(F.floor(uniform(private, "draw", F.col(who)) * F.lit(size)).cast("int"))

    counted = pairs.agg(F.count("*").alias("n_pairs"), F.coalesce(F.sum((report("id", "v") == report("id2", "v2")).cast("long")), F.lit(0)).alias("hits"))
    return debias(counted, b, alpha)
