"""Exact duplicates by composable polynomial fingerprints, confirmed text against text.

A text's bytes are cut into chunks; each chunk is hashed alone and the chunk hashes are
combined by length-shifted arithmetic, H(AB) = H(A) + r^|A| * H(B) modulo a prime, so the
chunks of a huge document can be hashed anywhere and in any order: texts longer than one
chunk are dealt to the tasks chunk by chunk, and only sums of shifted hashes meet. Four bases
modulo 2^31 - 1 and the length make the fingerprint.

Equal fingerprints only propose copies. The chunks of every member of a group are then
compared with the same chunks of the group's first text; a group in which any chunk differs
is regrouped by the SHA-256 of its texts.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WHITE, only, raw_bytes, sized, small_batches, stage, text_slices, tidy

PRIME = (1 << 31) - 1
#: Fixed bases of the four polynomials.
BASES = (1_000_003, 480_729_587, 1_366_217_011, 2_011_434_689)
CHUNK = 1 << 16
#: Members of one group that are compared in one task.
GROUP_SHARE = 512
#: Rows from which a group's size and first id are sent to its rows, where few groups are that large.
HOT = 2048


def normalised(text: Column) -> Column:
    """Each run of ASCII white space as one space; null as empty."""
    return F.regexp_replace(F.coalesce(text, F.lit("")), WHITE, " ")


def _powers(base: int, n: int, prime: int) -> np.ndarray:
    out = np.ones(n, dtype=np.uint64)
    at = 1
    while at < n:  # doubling: r^(at..2at) = r^at * r^(0..at)
        step = min(at, n - at)
        out[at : at + step] = out[:step] * np.uint64(pow(base, at, prime)) % np.uint64(prime)
        at += step
    return out


class Fingerprinter:
    """Polynomial hashes of byte strings for each base; ``prime`` is smaller in tests only."""

    def __init__(self, prime: int = PRIME, chunk: int = CHUNK):
        self.prime, self.chunk = prime, chunk
        self.tables = [_powers(b % prime, chunk, prime) for b in BASES]

    def chunk_hash(self, data: np.ndarray) -> tuple[int, ...]:
        """Hashes of one chunk; bytes count one more than their value, so zero bytes count too."""
        x = data.astype(np.uint64) + np.uint64(1)
        return tuple(int((x * t[: len(x)]).sum() % np.uint64(self.prime)) for t in self.tables)

    def combine(self, left: tuple, right: tuple) -> tuple:
        """(length, hashes) of two neighbouring pieces; associative, (0, zeros) is neutral."""
        n = left[0]
        return (n + right[0], tuple((a + pow(b % self.prime, n, self.prime) * h) % self.prime for a, h, b in zip(left[1], right[1], BASES, strict=True)))

    def of(self, data: np.ndarray) -> tuple:
        total = (0, (0,) * len(BASES))
        for at in range(0, len(data), self.chunk):
            piece = data[at : at + self.chunk]
            total = self.combine(total, (len(piece), self.chunk_hash(piece)))
        return total

    def of_rows(self, data: np.ndarray, offsets: np.ndarray, long_too: bool = True) -> np.ndarray:
        """rows x (length, hashes). Rows within one chunk are hashed together, longer ones chunk by chunk, if at all."""
        lengths = np.diff(offsets)
        out = np.zeros((len(lengths), 1 + len(BASES)), dtype=np.int64)
        out[:, 0] = lengths
        short = (lengths <= self.chunk) & (lengths > 0)
        if short.any():
            place = np.arange(len(data)) - np.repeat(offsets[:-1], lengths)
            place[place >= self.chunk] = 0  # of longer rows, not used
            x = data.astype(np.uint64) + np.uint64(1)
            starts = offsets[:-1][lengths > 0]
            for k, table in enumerate(self.tables):
                out[lengths > 0, 1 + k] = np.add.reduceat(x * table[place], starts) % np.uint64(self.prime)
        for i in np.flatnonzero(lengths > self.chunk) if long_too else ():
            out[i, 1:] = self.of(data[offsets[i] : offsets[i + 1]])[1]
        return out


def combine_chunks(chunks: DataFrame, prime: int = PRIME) -> DataFrame:
    """Fingerprints of documents stored as chunk rows (doc_key, chunk_no, start, n_bytes, h1..h4).

    ``start`` is the chunk's byte offset; the shift r^start is built from the bits of the
    offset, so chunks of one document may sit in any partitions and only sums are shuffled.
    """

    def shift(base: int) -> Column:
        powers = F.array(*[F.lit(pow(base % prime, 1 << bit, prime)).cast("long") for bit in range(48)])
        bit_set = lambda bit: F.pmod(F.floor(F.col("start") / F.pow(F.lit(2.0), bit)).cast("long"), F.lit(2)) == 1
        used = F.transform(powers, lambda x, bit: F.when(bit_set(bit), x).otherwise(F.lit(1).cast("long")))
        return F.aggregate(used, F.lit(1).cast("long"), lambda out, x: out * x % F.lit(prime))

    moved = chunks.select("doc_key", "n_bytes", *[(F.col(f"h{k}") * shift(b) % F.lit(prime)).alias(f"h{k}") for k, b in enumerate(BASES, 1)])
    return moved.groupBy("doc_key").agg(F.sum("n_bytes").alias("n_bytes"), *[(F.sum(f"h{k}") % F.lit(prime)).alias(f"h{k}") for k in range(1, len(BASES) + 1)])


PRINT = ["n_bytes", "h1", "h2", "h3", "h4"]
_HASHES = ", ".join(f"{c} long" for c in PRINT)


def _key() -> Column:
    return F.xxhash64(F.coalesce("text", F.lit(""))).alias("key")


def _same_row(a: DataFrame, b: DataFrame) -> Column:
    """Rows of one id and text hash; null ids match each other."""
    return a.doc_id.eqNullSafe(b.doc_id) & (a.key == b.key)


def fingerprints(docs: DataFrame, prime: int = PRIME, chunk: int = CHUNK) -> DataFrame:
    """doc_id, text_sha256, key and the fingerprint of every row's normalised text (a staged table).

    ``key`` tells the texts of one id apart, before they are normalised. Texts of up to ``chunk`` bytes are hashed where
    they are read. Longer ones leave as rows of a chunk each, which are hashed in as many
    tasks as there are and combined.
    """
    small_batches(docs.sparkSession)
    ids = docs.schema["doc_id"].dataType.simpleString()
    text = normalised(F.col("text")).alias("text")
    rows = docs.select("doc_id", text, _key()).select("doc_id", "text", F.sha2("text", 256).alias("text_sha256"), "key")
    names = ["doc_id", "text_sha256", "key", *PRINT, "start", "chunk"]

    def run(batches):
        make = Fingerprinter(prime, chunk)
        for batch in batches:
            for part, data, offs in text_slices(batch):
                got = make.of_rows(data, offs, long_too=False)
                long = np.flatnonzero(np.diff(offs) > chunk)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), part.column(3), *[pa.array(got[:, k]) for k in range(5)], pa.nulls(len(got), pa.int64()), pa.nulls(len(got), pa.binary())], names)
                for i in long.tolist():
                    starts = np.arange(0, offs[i + 1] - offs[i], chunk)
                    at = pa.array(np.full(len(starts), i))
                    raw = [data[offs[i] + a : min(offs[i] + a + chunk, offs[i + 1])].tobytes() for a in starts.tolist()]
                    size = pa.array([len(x) for x in raw], pa.int64())
                    none = [pa.nulls(len(starts), pa.int64())] * 4
                    yield pa.RecordBatch.from_arrays([*(part.column(c).take(at) for c in (0, 2, 3)), size, *none, pa.array(starts), pa.array(raw, pa.binary())], names)
        tidy()

    def hash_chunks(batches):
        make = Fingerprinter(prime, chunk)
        for batch in batches:
            data, offs = raw_bytes(batch.column(3))
            got = make.of_rows(data, offs)
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], *[pa.array(got[:, k]) for k in range(5)]], ["doc_id", "key", "start", *PRINT])
        tidy()

    told = stage(rows.mapInArrow(run, f"doc_id {ids}, text_sha256 string, key long, {_HASHES}, start long, chunk binary"), "fingerprints")
    whole = told.where("start IS NULL").drop("start", "chunk")
    chunks = told.where("start IS NOT NULL").select("doc_id", "key", "start", "chunk").repartition("doc_id", "key", "start")
    hashed = chunks.mapInArrow(hash_chunks, f"doc_id {ids}, key long, start long, {_HASHES}").dropDuplicates(["doc_id", "key", "start"])
    combined = combine_chunks(hashed.withColumn("doc_key", F.struct("doc_id", "key")), prime)
    combined = stage(combined.select("doc_key.*", *PRINT), "long-fingerprints")
    long = whole.where(F.col("n_bytes") > chunk).select("doc_id", "text_sha256", "key")
    long = long.join(sized(combined), _same_row(long, combined)).select(long.doc_id, "text_sha256", long.key, *PRINT)
    return whole.where(F.col("n_bytes") <= chunk).unionByName(long)


def differing(docs: DataFrame, prints: DataFrame, chunk: int = CHUNK) -> DataFrame:
    """Fingerprints under which some text differs from the first one; usually none.

    Texts meet as streams of chunks: each chunk of a member with the same chunk of the first
    text. Members of a group are dealt over shares of about ``GROUP_SHARE`` rows, and the
    first text is sent to each share, so that a group with a third of all rows spreads out.
    """
    groups = prints.groupBy(*PRINT).agg(F.count("*").alias("n")).where("n > 1").withColumn("shares", F.ceil(F.col("n") / GROUP_SHARE).cast("long"))
    groups = stage(groups.drop("n"), "groups")
    # Only rows in groups of two or more carry their text on; rows of one id and text hash are looked up once.
    members = stage(prints.join(sized(groups, None), PRINT).select("doc_id", "key", *PRINT, "shares").distinct(), "group-members")
    lead = members.groupBy(*PRINT).agg(F.min(F.struct(F.isnull("doc_id").alias("late"), "doc_id", "key")).alias("lead"))
    is_first = F.col("doc_id").eqNullSafe(F.col("lead.doc_id")) & (F.col("key") == F.col("lead.key"))
    members = stage(members.join(lead, PRINT).select("doc_id", "key", *PRINT, "shares", is_first.alias("is_first")), "group-members")
    texts = docs.select("doc_id", "text", _key())
    found = texts.join(sized(members), _same_row(texts, members)).select(members.doc_id, members.key, *PRINT, "shares", "is_first", F.encode(normalised(F.col("text")), "UTF-8").alias("raw"))
    number = F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.lit(0), F.floor((F.col("n_bytes") - 1) / chunk)))).alias("number")
    chunks = found.select("*", number).withColumn("chunk", F.expr(f"substring(raw, cast(number * {chunk} + 1 as int), {chunk})")).drop("raw")
    first = chunks.where("is_first").select(*PRINT, "number", F.col("chunk").alias("first_chunk"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("shares") - 1)).alias("share")).dropDuplicates([*PRINT, "number", "share"])
    others = chunks.withColumn("share", F.pmod(F.xxhash64("doc_id", "key"), F.col("shares")))
    return others.join(first, [*PRINT, "number", "share"]).where("chunk <> first_chunk").select(*PRINT).distinct()


def exact_groups(docs: DataFrame, prime: int = PRIME, chunk: int = CHUNK) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 for every row of ``docs``.

    Texts are equal when identical once white space runs are single spaces; null counts as
    empty. The row with the smallest doc_id stays (null ids come last; a group of null ids
    alone has a null keep_id and keeps all its rows). Rows that repeat an id and text are
    counted each. An empty table gives an empty result; other columns are ignored.
    """
    docs = only(docs, "doc_id", "text")
    prints = fingerprints(docs, prime, chunk)
    odd = stage(differing(docs, prints, chunk), "fingerprint-collisions").withColumn("odd", F.lit(True))
    keyed = prints.join(sized(odd, None), PRINT, "left")
    keyed = keyed.withColumn("which", F.when(F.col("odd"), F.col("text_sha256")).otherwise("")).drop("odd")
    by = [*PRINT, "which"]
    groups = keyed.groupBy(*by).agg(F.min("doc_id").alias("keep_id"), F.count("*").alias("group_size"))
    groups = stage(groups.where("group_size > 1"), "groups")

    # Few groups are large: those are sent to their rows, which a salt then deals over all tasks.
    hot = groups.where(F.col("group_size") >= HOT)
    sent = sized(hot, None)
    many = sent is hot  # too many to be sent: the join splits them as it finds them
    salt = F.lit(0).cast("long").alias("salt")
    if not many:
        sent = sent.select(*by, F.col("keep_id").alias("hot_id"), F.col("group_size").alias("hot_size"))
        keyed = keyed.join(sent, by, "left").withColumn("salt", F.when(F.col("hot_size").isNotNull(), 1 + F.pmod(F.xxhash64("doc_id", "text_sha256"), F.lit(1 << 20))).otherwise(F.lit(0)).cast("long"))
        groups = groups.where(F.col("group_size") < HOT)
    else:
        keyed = keyed.select("*", F.lit(None).cast("long").alias("hot_size"), F.col("doc_id").alias("hot_id"), salt)
    out = keyed.join(groups.select("*", salt), [*by, "salt"], "left")
    size = F.coalesce("hot_size", "group_size", F.lit(1).cast("long"))
    keep = F.when(F.col("hot_size").isNotNull(), F.col("hot_id")).when(F.col("group_size").isNotNull(), F.col("keep_id")).otherwise(F.col("doc_id"))
    return out.select("doc_id", keep.alias("keep_id"), size.alias("group_size"), F.coalesce(F.col("doc_id") == keep, keep.isNull()).alias("kept"), "text_sha256")
