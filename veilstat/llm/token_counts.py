"""Token counts of whole texts by a two-tier map-side lookup.

Tier one is a compact hash table of the most frequent pre-token units and their token
lengths, at most ``FREQUENT`` entries, broadcast to every task. It is found from all
documents: each task keeps a bounded summary of its own units (the heaviest ``SUMMARY``),
a task's summary travels as one row, and summaries are merged in two levels; nothing else
of a text is ever shuffled. Tier two is a
worker's own bounded cache, in which units that tier one misses are encoded once. Both
tiers change speed only; every count is the tokenizer's.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import only, raw_bytes, small_batches, texts_of, tidy
from .packed import squeeze, unsqueeze
from .unit_encoder import SLICE, UnitEncoder, slices

FREQUENT = 16_384
SUMMARY = 2_048
#: A task's counter is pruned to its heavier half when it holds this many units.
COUNTER = 100_000


def _summaries(path: str, style: str):
    def run(batches):
        encoder, counts = UnitEncoder(path, style, counts_only=True), Counter()
        for batch in batches:
            data, offs = raw_bytes(texts_of(batch.column(0)))
            for a, b in slices(offs, SLICE):
                for unit, n in encoder.weigh(data[offs[a] : offs[b]], offs[a : b + 1] - offs[a]):
                    counts[unit] += n
                if len(counts) > COUNTER:
                    counts = Counter(dict(counts.most_common(COUNTER // 2)))
        yield _packed(counts, SUMMARY)
        tidy()

    return run


def _packed(counts: Counter, most: int) -> pa.RecordBatch:
    """The heaviest units and their counts as one row."""
    top = [(u, n) for u, n in sorted(counts.items(), key=lambda x: (-x[1], x[0]))[:most] if len(u) <= 64]
    sizes = np.array([len(u) for u, _ in top], np.uint32)
    blob = squeeze(np.frombuffer(b"".join(u for u, _ in top), np.uint8), sizes, np.array([n for _, n in top], np.int64))
    return pa.RecordBatch.from_arrays([pa.array([blob], pa.binary())], ["units"])


def _unpacked(blob: bytes) -> list[tuple[bytes, int]]:
    raw, sizes, n = unsqueeze(blob)
    data, ends = raw.tobytes(), np.cumsum(sizes).tolist()
    return [(data[b - s : b], k) for b, s, k in zip(ends, sizes.tolist(), n.tolist(), strict=True)]


def _merged(most: int):
    def run(batches):
        counts: Counter = Counter()
        for batch in batches:
            for blob in batch.column(0).to_pylist():
                counts.update(dict(_unpacked(blob)))
        if counts:
            yield _packed(counts, most)

    return run


def frequent_units(docs: DataFrame, path: str, style: str, most: int = FREQUENT) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes, checks and token lengths of the corpus's heaviest units; at most ``most`` reach the driver.

    Each task sends its summary as one row; the rows are merged in two levels, of about the
    square root of the tasks each, and a merge passes on four times ``most`` units.
    """
    told = only(docs, "text").mapInArrow(_summaries(path, style), "units binary")
    some = told.repartition(max(1, int(docs.rdd.getNumPartitions() ** 0.5))).mapInArrow(_merged(4 * most), "units binary")
    got = some.coalesce(1).mapInArrow(_merged(most), "units binary").first()
    top = [u for u, _ in _unpacked(got[0])] if got else []
    encoder = UnitEncoder(path, style, counts_only=True)
    encoder.encode(*raw_bytes(pa.array(top, pa.binary())))
    return encoder.known_units()


def token_counts(docs: DataFrame, path: str, limit: int = 2048, style: str = "word") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every row; a null text is an empty one.

    ``style`` is ``word`` (white space dropped, ends of words marked) or ``byte`` (byte
    level). Repeated rows and rows whose id is null give a row each; an empty table gives an
    empty result.
    """
    small_batches(docs.sparkSession)
    table = docs.sparkSession.sparkContext.broadcast(frequent_units(docs, path, style))

    def count(batches):
        encoder = UnitEncoder(path, style, counts_only=True, frequent=table.value)
        for batch in batches:
            data, offs = raw_bytes(texts_of(batch.column(1)))
            n = [counts for _, _, counts in encoder.encode_rows(data, offs)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.diff(offs)), pa.array(np.concatenate(n) if n else np.zeros(0, np.int64))], ["doc_id", "n_bytes", "n_tokens"])
        tidy()

    ids = docs.schema["doc_id"].dataType.simpleString()
    counted = only(docs, "doc_id", "text").mapInArrow(count, f"doc_id {ids}, n_bytes long, n_tokens long")
    return counted.withColumn("over_limit", F.col("n_tokens") > limit)
