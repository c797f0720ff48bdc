"""Users, rounds and the ledger.

Every row is a user with one sample. Users are dealt to random slots once; each question is
put to a slot range of its own, so nobody is asked twice, and a layout that is partitioned
by slot reads each user once over a whole adaptive run.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.coins import uniform

SLOTS = 1 << 20


def slot(id_col: str, seed: str, slots: int = SLOTS) -> Column:
    return F.floor(uniform(seed, "slot", F.col(id_col)) * F.lit(slots)).cast("long")


class PoolExhausted(RuntimeError):
    """No slots are left for another question."""


@dataclass
class Batch:
    """One job's questions: question k of the batch has slots [start + k * width, start + (k + 1) * width)."""

    round: int
    start: int
    width: int
    questions: list = field(default_factory=list)
    #: What each contacted user shows and sends, as the mechanism says: coordinates, bits, privacy.
    observed: int = 0
    bits: int = 0
    alpha: float | None = None

    @property
    def end(self) -> int:
        return self.start + self.width * len(self.questions)

    def number(self) -> Column:
        """Question number of a user from the slot: arithmetic in place of a range join."""
        return F.floor((F.col("slot") - F.lit(self.start)) / F.lit(self.width)).cast("int")


class UserPool:
    """Hands out disjoint slot ranges of ``users`` (user_id, slot, ...)."""

    def __init__(self, users: DataFrame, slots: int = SLOTS, first: int = 0):
        self.users, self.slots, self.next = users, slots, first
        self.batches: list[Batch] = []

    @classmethod
    def of(cls, df: DataFrame, id_col: str, seed: str, slots: int = SLOTS) -> UserPool:
        return cls(df.withColumn("slot", slot(id_col, seed, slots)), slots)

    @classmethod
    def prepare(cls, df: DataFrame, id_col: str, seed: str, path: str, slots: int = SLOTS, buckets: int = 64) -> UserPool:
        """The layout for adaptive runs: written once, partitioned by slot bucket, so that a slot range is a partition filter."""
        df.withColumn("slot", slot(id_col, seed, slots)).withColumn("slot_bucket", F.floor(F.col("slot") * buckets / slots).cast("int")).write.mode("overwrite").partitionBy("slot_bucket").parquet(path)
        pool = cls(df.sparkSession.read.parquet(path), slots)
        pool.buckets = buckets
        return pool

    def size(self) -> int:
        """Users of the pool, counted once."""
        if not hasattr(self, "_size"):
            self._size = self.users.count()
        return self._size

    def expected(self, width: int) -> float:
        """Users that a slot range of ``width`` holds on average."""
        return self.size() * width / self.slots

    def allot(self, questions: list, width: int, observed: int = 0, bits: int = 0, alpha: float | None = None) -> tuple[Batch, DataFrame]:
        """The next slot ranges, and their users with ``query_id``; the mechanism says what it takes from each user."""
        batch = Batch(len(self.batches) + 1, self.next, width, list(questions), observed, bits, alpha)
        if batch.end > self.slots:
            raise PoolExhausted(f"{batch.end} slots wanted of {self.slots}")
        self.next = batch.end
        self.batches.append(batch)
        rows = self.users.where(F.col("slot").between(batch.start, batch.end - 1))
        if buckets := getattr(self, "buckets", None):
            rows = rows.where(F.col("slot_bucket").between(batch.start * buckets // self.slots, (batch.end - 1) * buckets // self.slots))
        return batch, rows.withColumn("query_id", batch.number())

    def ledger(self) -> DataFrame:
        """user_id, round, query_id, width, bits, alpha of everyone contacted, as the mechanisms declared them."""
        parts = [
            self.users.where(F.col("slot").between(b.start, b.end - 1)).select(
                "user_id", F.lit(b.round).alias("round"), b.number().alias("query_id"), F.lit(b.observed).alias("width"), F.lit(b.bits).alias("bits"), F.lit(b.alpha).cast("double").alias("alpha")
            )
            for b in self.batches
        ]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out


def contacted_twice(ledger: DataFrame) -> DataFrame:
    """Users who were asked more than once: empty in every valid run."""
    return ledger.groupBy("user_id").agg(F.count("*").alias("times")).where("times > 1")


def criteria(ledger: DataFrame) -> DataFrame:
    """Samples, rounds, questions, bits of one user and of all, width, privacy."""
    return ledger.agg(
        F.countDistinct("user_id").alias("samples"),
        F.countDistinct("round").alias("rounds"),
        F.countDistinct("round", "query_id").alias("queries"),
        F.max("bits").cast("long").alias("max_bits"),
        F.sum("bits").cast("long").alias("total_bits"),
        F.max("width").cast("long").alias("max_width"),
        F.max("alpha").alias("alpha"),
    )
