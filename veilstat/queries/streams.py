"""Streams over the events table, run to the end of what is there (``availableNow``)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.scalars import tidy as tidy_col
from ..operators import measures as M
from ..registry import query
from ..streaming import pairs as P
from .relational import scratch
from .sqltext import h, hash_bits, tidy

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def source(spark, d, files: int = 4) -> DataFrame:
    """The events as a stream of a few files; timestamps as UTC instants.

    Files of one write come in no sure order, so streams that drop late rows take one file.
    """
    path = scratch(spark)
    e = spark.read.parquet(f"{d}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp_ltz"))
    e.repartitionByRange(files, "ts").sortWithinPartitions("ts").write.parquet(path)
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", 1).parquet(path)


def drain(df: DataFrame, mode: str) -> DataFrame:
    """Run to the end into a table of the shared folder (or, for whole results, the last state) and read it."""
    spark = df.sparkSession
    out, at = scratch(spark), scratch(spark)
    if mode == "append":
        df.writeStream.format("parquet").option("path", out).option("checkpointLocation", at).trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(out)

    def put(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/{n:08d}")  # a batch that runs again replaces itself
        latest[0] = max(latest[0], n)

    latest = [-1]
    df.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", at).trigger(availableNow=True).start().awaitTermination()
    if mode == "complete":
        return spark.read.schema(df.schema).parquet(f"{out}/{latest[0]:08d}")
    return spark.read.option("recursiveFileLookup", "true").schema(df.schema).parquet(out)


_HOUR = "date_trunc('hour', ts)"


@query("stream_histogram", f"SELECT CAST(epoch({_HOUR}) AS BIGINT) AS start, {tidy(h())} AS h FROM (SELECT {_HOUR} AS ts, event_type, CAST(count(*) AS DOUBLE) AS n FROM events GROUP BY 1, 2) GROUP BY ts")
def stream_histogram(spark, d):
    """Entropy of event types in each hour."""
    n = drain(P.windowed_counts(source(spark, d), "event_type", "1 hour"), "complete")
    return n.select(F.unix_timestamp("w.start").alias("start"), F.col("n").cast("double").alias("n")).groupBy("start").agg(tidy_col(M.h_of()).alias("h"))


@query("stream_sliding_entropy", f"SELECT start, {tidy(h())} AS h FROM (SELECT start, event_type, CAST(count(*) AS DOUBLE) AS n FROM (SELECT event_type, floor(epoch(ts) / 900)::BIGINT * 900 - 900 * unnest(range(4)) AS start FROM events) GROUP BY 1, 2) GROUP BY start")
def stream_sliding_entropy(spark, d):
    n = drain(P.windowed_counts(source(spark, d), "event_type", "1 hour", "15 minutes"), "complete")
    return n.select(F.unix_timestamp("w.start").alias("start"), F.col("n").cast("double").alias("n")).groupBy("start").agg(tidy_col(M.h_of()).alias("h"))


@query("stream_session_entropy", f"""WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 30 MINUTE OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
    s AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g), c AS (SELECT user_id, k, CAST(count(*) AS DOUBLE) AS n FROM s GROUP BY 1, 2)
    SELECT count(*) AS sessions, {tidy(h())} AS h FROM c""")
def stream_session_entropy(spark, d):
    """Entropy of the sessions' shares of all events."""
    n = drain(P.session_counts(source(spark, d, 1), "user_id"), "complete").select(F.col("n").cast("double").alias("n"))
    return n.agg(F.count("*").alias("sessions"), tidy_col(M.h_of()).alias("h"))


_REP = f"WITH r AS (SELECT event_id // 2 AS pair, {hash_bits('pub', 1, 'event_id // 2', 'event_type')} AS report FROM events), m AS (SELECT pair, min(report) = max(report) AS hit FROM r GROUP BY pair HAVING count(*) = 2)"
_RES = f"{_REP} SELECT count(*) AS n_pairs, count(*) FILTER (WHERE hit) AS hits FROM m"


def _result(hits: DataFrame) -> DataFrame:
    return hits.agg(F.count("*").alias("n_pairs"), F.coalesce(F.sum(F.col("hit").cast("long")), F.lit(0)).alias("hits"))


@query("stream_pair_state", _RES)
def stream_pair_state(spark, d):
    """State is one report a pair, until its partner comes or 31 days of events have passed."""
    return _result(drain(P.match_with_state(P.pair_reports(source(spark, d, 1), "event_id", "event_type")), "append").where("hit >= 0"))


@query("stream_pair_join", _RES)
def stream_pair_join(spark, d):
    """Members may be as far apart as the table is long, so no pair is lost."""
    span = spark.read.parquet(f"{d}/events.parquet").agg(F.datediff(F.max("ts"), F.min("ts"))).first()[0] or 0
    return _result(drain(P.match_by_join(P.pair_reports(source(spark, d, 1), "event_id", "event_type"), f"{span + 1} days"), "append"))


@query("stream_pair_agg", _RES)
def stream_pair_agg(spark, d):
    last = drain(P.match_by_aggregation(P.pair_reports(source(spark, d), "event_id", "event_type")), "complete")
    return _result(last.where("n = 2").select((F.col("lo") == F.col("hi")).cast("int").alias("hit")))


@query("stream_contact_once", "SELECT count(DISTINCT event_id) AS users FROM events")
def stream_contact_once(spark, d):
    """Every event sent twice is heard once."""
    s = source(spark, d, 1)
    twice = s.select("event_id", "ts").withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("copy")
    return drain(P.once(twice, "event_id"), "append").agg(F.count("*").alias("users"))


@query("stream_running_counts", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def stream_running_counts(spark, d):
    return drain(source(spark, d).groupBy("event_type").agg(F.count("*").alias("n")), "complete")
