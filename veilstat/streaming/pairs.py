"""The hash method as a stream: matching pairs with bounded state, running estimates, windowed entropies.

The pair of a user comes from a bijection of ids, not from arrival, so any order of arrival
gives the same pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.coins import hash_bits, symbol


def pair_reports(events: DataFrame, id_col: str, value: str, b: int = 1, public: str = "pub") -> DataFrame:
    """pair, member, report, ts: pairs of dense ids, neighbours by id."""
    pair = F.floor(F.col(id_col) / 2).cast("long")
    v = symbol(value)
    return events.select("ts", pair.alias("pair"), (F.col(id_col) % 2).cast("int").alias("member"), hash_bits(public, b, pair, v).alias("report"))


def match_with_state(reports: DataFrame, wait: int = 31 * 86_400_000, watermark: str = "1 hour") -> DataFrame:
    """pair, hit: the state of a pair is its first report, for ``wait`` milliseconds of event time.

    A pair whose second report has not come when the watermark passes the end of the wait is
    dropped with hit -1, so the state holds no more than the unmatched users of that span.
    """

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame({"pair": [key[0]], "hit": [-1]})
            return
        member, first, since = state.get if state.exists else (None, None, 0)
        out = []
        for pdf in batches:
            for m, r, t in zip(pdf["member"].tolist(), pdf["report"].tolist(), pdf["ts"], strict=True):
                if member is None:
                    member, first, since = m, r, int(t.timestamp() * 1000)
                elif m != member and first is not None:
                    out.append(int(r == first))
                    first = None
        if out:
            if state.exists:
                state.remove()
            yield pd.DataFrame({"pair": [key[0]] * len(out), "hit": out})
        elif member is not None:
            state.update((int(member), int(first), int(since)))
            state.setTimeoutTimestamp(max(since + wait, state.getCurrentWatermarkMs() + 1))

    timed = reports.withWatermark("ts", watermark)
    return timed.groupBy("pair").applyInPandasWithState(step, "pair long, hit int", "member int, first int, since long", "append", GroupStateTimeout.EventTimeTimeout)


def match_by_join(reports: DataFrame, apart: str = "31 days") -> DataFrame:
    """pair, hit by a stream-stream join of the two members within an interval."""
    a = reports.where("member = 0").select(F.col("pair").alias("pa"), F.col("report").alias("ra"), F.col("ts").alias("ta")).withWatermark("ta", "1 hour")
    b = reports.where("member = 1").select(F.col("pair").alias("pb"), F.col("report").alias("rb"), F.col("ts").alias("tb")).withWatermark("tb", "1 hour")
    j = a.join(b, F.expr(f"pa = pb AND tb BETWEEN ta - INTERVAL {apart} AND ta + INTERVAL {apart}"))
    return j.select(F.col("pa").alias("pair"), (F.col("ra") == F.col("rb")).cast("int").alias("hit"))


def match_by_aggregation(reports: DataFrame) -> DataFrame:
    """pair, n, lo, hi, for whole results (complete mode): a pair is matched when n is 2.

    Its state is a row for every pair that ever came, so it suits streams that end; the forms
    with a timeout or a watermark keep what is still unmatched.
    """
    return reports.groupBy("pair").agg(F.count("*").alias("n"), F.min("report").alias("lo"), F.max("report").alias("hi"))


def windowed_counts(events: DataFrame, key: str, size: str, slide: str | None = None, watermark: str = "1 hour") -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.withWatermark("ts", watermark).groupBy(w.alias("w"), key).agg(F.count("*").alias("n"))


def session_counts(events: DataFrame, user: str, gap: str = "30 minutes", watermark: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", watermark).groupBy(F.session_window("ts", gap).alias("w"), user).agg(F.count("*").alias("n"))


def once(events: DataFrame, id_col: str, watermark: str = "1 hour") -> DataFrame:
    """A user who reports again within the watermark is heard once."""
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark([id_col])
