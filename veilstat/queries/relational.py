"""Scans, filters, joins, aggregations, windows, sorts and set operations that the methods use."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.coins import uniform
from ..functions.scalars import tidy as tidy_col
from ..operators import measures as M
from ..operators import structure as T
from ..operators.collision import assign_pairs, reports
from ..operators.protocol import slot
from ..registry import query
from ..sources import domains
from ..sources.tables import line_users, load, load_any, range_users, register_views, scratch
from .collision import pairs_sql, symbols
from .sqltext import KEY, coin, counts, h, hash_bits, p2, tidy


# Scans, sources


@query("scan_pruned", "SELECT l_returnflag, count(*) AS n FROM lineitem WHERE l_quantity >= 25 GROUP BY 1")
def scan_pruned(spark, d):
    """Two columns are read and the filter reaches the scan."""
    return load(spark, d, "lineitem").where("l_quantity >= 25").groupBy("l_returnflag").agg(F.count("*").alias("n"))


@query("scan_csv_roundtrip", f"SELECT {tidy(h())} AS h, CAST(sum(n) AS BIGINT) AS users FROM ({counts('orders', 'o_orderpriority')})")
def scan_csv_roundtrip(spark, d):
    path = scratch(spark)
    load(spark, d, "orders", "o_orderkey", "o_orderpriority").write.csv(path, header=True)
    n = M.histogram(load_any(spark, path, "csv", "o_orderkey long, o_orderpriority string", header=True), ["o_orderpriority"])
    return n.agg(tidy_col(M.h_of()).alias("h"), F.sum("n").cast("long").alias("users"))


for _fmt in ("json", "orc"):

    @query(f"scan_{_fmt}_roundtrip", f"SELECT {tidy(h())} AS h FROM ({counts('customer', 'c_mktsegment')})")
    def _roundtrip(spark, d, fmt=_fmt):
        path = scratch(spark)
        load(spark, d, "customer", "c_custkey", "c_mktsegment").write.format(fmt).save(path)
        return M.shannon(load_any(spark, path, fmt, "c_custkey long, c_mktsegment string"), ["c_mktsegment"])


_SL = f"CAST(floor({coin('pub', 'slot', 'o_orderkey')} * 1024) AS BIGINT)"


@query("scan_partitioned_slots", f"SELECT count(*) AS users, min({_SL}) AS low, max({_SL}) AS high FROM orders WHERE {_SL} BETWEEN 128 AND 255")
def scan_partitioned_slots(spark, d):
    """A layout by slot bucket: a slot range is a partition filter."""
    from ..operators.protocol import UserPool

    pool = UserPool.prepare(load(spark, d, "orders", "o_orderkey"), "o_orderkey", "pub", scratch(spark), slots=1024, buckets=16)
    pool.next = 128
    _, rows = pool.allot([0], 128)
    return rows.agg(F.count("*").alias("users"), F.min("slot").alias("low"), F.max("slot").alias("high"))


@query("filter_slot_range", f"SELECT o_orderkey, {_SL} AS slot FROM orders WHERE {_SL} BETWEEN 10 AND 19")
def filter_slot_range(spark, d):
    return load(spark, d, "orders", "o_orderkey").withColumn("slot", slot("o_orderkey", "pub", 1024)).where("slot BETWEEN 10 AND 19")


@query("virtual_users", f"SELECT count(*) AS n, {tidy('avg(u)')} AS mean FROM (SELECT {coin('pub', 'v', 'i')} AS u FROM (SELECT unnest(range(5000)) AS i))")
def virtual_users(spark, d):
    return range_users(spark, 5000).select(uniform("pub", "v", F.col("user_id")).alias("u")).agg(F.count("*").alias("n"), tidy_col(F.avg("u")).alias("mean"))


@query("sql_entropy", f"SELECT {tidy(h())} AS h FROM ({counts('events', 'event_type')})")
def sql_entropy(spark, d):
    """The SQL façade: views, and the same plan."""
    register_views(spark, d, "events")
    return spark.sql("SELECT round(ln(sum(n)) - sum(n * ln(n)) / sum(n), 6) AS h FROM (SELECT event_type, CAST(count(*) AS DOUBLE) AS n FROM events GROUP BY event_type)")


# Projections, predicates


@query("encode_attributes", "SELECT o_orderkey, CASE o_orderpriority WHEN '1-URGENT' THEN 0 WHEN '2-HIGH' THEN 1 ELSE 2 END AS priority, CAST(o_totalprice >= 100000 AS INT) + CAST(o_totalprice >= 200000 AS INT) AS price, month(o_orderdate)::INT - 1 AS month FROM orders")
def encode_attributes(spark, d):
    o = load(spark, d, "orders", "o_orderkey", "o_orderpriority", "o_totalprice", "o_orderdate")
    return o.select("o_orderkey", domains.Categorical(("1-URGENT", "2-HIGH")).code(F.col("o_orderpriority")).alias("priority"), domains.Binned((100000, 200000)).code(F.col("o_totalprice")).alias("price"), domains.Calendar("month").code(F.col("o_orderdate")).alias("month"))


@query("pack_bits", "SELECT vec_id, CAST(" + " + ".join(f"(CASE WHEN embedding[{i + 1}] > 0 THEN {(1 << i) - (1 << 64) * (i == 63)}::HUGEINT ELSE 0 END)" for i in range(64)) + " AS BIGINT) AS word FROM embeddings")
def pack_bits(spark, d):
    """Binary variables as bits of a word: all 64, the last in the sign."""
    word = F.lit(0).cast("long")
    for i in range(64):
        word = word.bitwiseOR(F.shiftleft(domains.Sign().code(F.col("embedding")[i]).cast("long"), i))
    return load(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", word.alias("word"))


_BIT = [f"CAST(embedding[{i + 1}] > 0 AS INT)" for i in range(4)]


@query("observe_pair", f"SELECT vec_id, CAST(vec_id % 2 AS INT) AS q, CASE WHEN vec_id % 2 = 0 THEN {_BIT[0]} ELSE {_BIT[1]} END AS a, CASE WHEN vec_id % 2 = 0 THEN {_BIT[2]} ELSE {_BIT[3]} END AS b FROM embeddings")
def observe_pair(spark, d):
    """Two coordinates leave each user: which ones, the question tells."""
    x = load(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", F.transform("embedding", lambda v: F.when(v > 0, 1).otherwise(0)).alias("x"), (F.col("vec_id") % 2).cast("int").alias("q"))
    at = lambda *qs: F.get("x", F.get(F.array(*[F.lit(q) for q in qs]), F.col("q")))
    return x.select("vec_id", "q", at(0, 1).alias("a"), at(2, 3).alias("b"))


@query("observe_triplet", f"SELECT {_BIT[0]} AS a, {_BIT[1]} AS b, {_BIT[3]} AS c, count(*) AS n FROM embeddings GROUP BY 1, 2, 3")
def observe_triplet(spark, d):
    x = load(spark, d, "embeddings", "embedding").select(F.transform("embedding", lambda v: F.when(v > 0, 1).otherwise(0)).alias("x"))
    return x.select(F.get("x", F.lit(0)).alias("a"), F.get("x", F.lit(1)).alias("b"), F.get("x", F.lit(3)).alias("c")).groupBy("a", "b", "c").agg(F.count("*").alias("n"))


@query("bernoulli_sample", f"SELECT count(*) AS n, sum(o_orderkey)::BIGINT AS keys FROM orders WHERE {coin('pub', 'take', 'o_orderkey')} < 0.1")
def bernoulli_sample(spark, d):
    """A sample that a retried task draws alike."""
    return load(spark, d, "orders", "o_orderkey").where(uniform("pub", "take", F.col("o_orderkey")) < 0.1).agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("keys"))


@query("null_safe_match", "SELECT count(*) FILTER (WHERE a IS NOT DISTINCT FROM b) AS same, count(*) FILTER (WHERE a = b) AS plain FROM (SELECT nullif(l_returnflag, 'A') AS a, nullif(lag(l_returnflag) OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate), 'A') AS b FROM lineitem)")
def null_safe_match(spark, d):
    w = Window.orderBy("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")
    x = load(spark, d, "lineitem").select(F.nullif("l_returnflag", F.lit("A")).alias("a"), F.nullif(F.lag("l_returnflag").over(w), F.lit("A")).alias("b"))
    return x.agg(F.count_if(F.col("a").eqNullSafe(F.col("b"))).alias("same"), F.count_if(F.coalesce(F.col("a") == F.col("b"), F.lit(False))).alias("plain"))


@query("predicate_mix", "SELECT count(*) AS n FROM part WHERE p_type IN (SELECT min(p_type) FROM part UNION SELECT max(p_type) FROM part) AND p_size BETWEEN 5 AND 30 AND p_name LIKE '%a%' AND regexp_matches(p_brand, '[13]')")
def predicate_mix(spark, d):
    p = load(spark, d, "part")
    ends = p.agg(F.min("p_type").alias("a"), F.max("p_type").alias("b")).select(F.explode(F.array("a", "b")).alias("p_type")).distinct()
    return p.where(F.col("p_size").between(5, 30) & F.col("p_name").like("%a%") & F.col("p_brand").rlike("[13]")).join(F.broadcast(ends), "p_type", "left_semi").agg(F.count("*").alias("n"))


# Joins


@query("join_broadcast_domain", "SELECT n_regionkey, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def join_broadcast_domain(spark, d):
    n = F.broadcast(load(spark, d, "nation", "n_nationkey", "n_regionkey"))
    return load(spark, d, "customer", "c_nationkey").join(n, F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_regionkey").agg(F.count("*").alias("n"))


@query("join_vector_build", f"SELECT {tidy(h())} AS h FROM ({counts('(SELECT l_returnflag, o_orderpriority, c_mktsegment FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey)', 'l_returnflag', 'o_orderpriority', 'c_mktsegment')})")
def join_vector_build(spark, d):
    o = load(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderpriority").join(load(spark, d, "customer", "c_custkey", "c_mktsegment").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey"))
    v = load(spark, d, "lineitem", "l_orderkey", "l_returnflag").join(o.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey"))
    return M.shannon(v, ["l_returnflag", "o_orderpriority", "c_mktsegment"])


_SALTED = hash_bits("pub", 1, "concat_ws(':', bucket, idx)", symbols("x"))
_PR = f"WITH {pairs_sql(f'SELECT {KEY} AS user_id, l_linestatus AS x FROM lineitem', 'user_id')}, r AS (SELECT user_id, bucket, idx, {_SALTED} AS report FROM p)"


@query("join_pair_reports", f"{_PR} SELECT count(*) AS n_pairs, count(*) FILTER (WHERE a.report = b.report) AS hits FROM r AS a JOIN r AS b ON a.bucket = b.bucket AND a.idx = b.idx AND a.user_id < b.user_id")
def join_pair_reports(spark, d):
    """The match as a self-join; the grouped form shuffles once less."""
    df = assign_pairs(line_users(spark, d, "l_linestatus"), "user_id", "pub")
    r = reports(df, "user_id", ["l_linestatus"], 1, None, "pub", "noise", ["user_id"])
    a, b = r.alias("a"), r.alias("b")
    j = a.join(b, (F.col("a.bucket") == F.col("b.bucket")) & (F.col("a.idx") == F.col("b.idx")) & (F.col("a.user_id") < F.col("b.user_id")))
    return j.agg(F.count("*").alias("n_pairs"), F.count_if(F.col("a.report") == F.col("b.report")).alias("hits"))


@query("join_slot_range", f"WITH q AS (SELECT unnest(range(8)) AS query_id), u AS (SELECT {_SL} AS slot FROM orders) SELECT query_id::INT AS query_id, count(*) AS users FROM u JOIN q ON slot >= 100 + query_id * 20 AND slot < 120 + query_id * 20 GROUP BY 1")
def join_slot_range(spark, d):
    """A range join as integer division and an equality."""
    q = spark.range(8).select(F.col("id").cast("int").alias("query_id"))
    u = load(spark, d, "orders", "o_orderkey").select(slot("o_orderkey", "pub", 1024).alias("slot")).where("slot >= 100").withColumn("query_id", F.floor((F.col("slot") - 100) / 20).cast("int"))
    return u.join(F.broadcast(q), "query_id").groupBy("query_id").agg(F.count("*").alias("users"))


@query("join_asof_epoch", "SELECT epoch, count(*) AS n FROM (SELECT floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 21600)::BIGINT AS epoch FROM events) GROUP BY 1")
def join_asof_epoch(spark, d):
    """Each event with the last public seed in force, seeds every six hours: union and a running last value."""
    e = load(spark, d, "events", "event_id", "ts").select(F.unix_timestamp(F.col("ts").cast("timestamp_ltz")).alias("t"), F.lit(None).cast("long").alias("epoch"), F.lit(1).alias("is_event"))
    start = F.unix_timestamp(F.lit("2024-01-01 00:00:00").cast("timestamp_ntz").cast("timestamp_ltz"))
    day = F.floor(F.col("t") / 86400)
    first, last = e.agg(F.min(day), F.max(day)).first()  # seeds for every day that has events
    seeds = spark.range(4 * (first or 0), 4 * ((last or 0) + 1)).select((F.col("id") * 21600).alias("t"))
    seeds = seeds.select("t", F.floor((F.col("t") - start) / 21600).alias("epoch"), F.lit(0).alias("is_event"))
    # Six hours divide a day, so that every day holds a seed at its start: days are independent.
    w = Window.partitionBy("day").orderBy("t", "is_event").rowsBetween(Window.unboundedPreceding, 0)
    u = e.unionByName(seeds).withColumn("day", day).withColumn("epoch", F.last("epoch", ignorenulls=True).over(w))
    return u.where("is_event = 1").groupBy("epoch").agg(F.count("*").alias("n"))


@query("join_semi_contacted", f"SELECT count(*) AS n FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity >= 45)")
def join_semi_contacted(spark, d):
    asked = load(spark, d, "lineitem", "l_orderkey", "l_quantity").where("l_quantity >= 45").select(F.col("l_orderkey").alias("o_orderkey"))
    return load(spark, d, "orders", "o_orderkey").join(asked, "o_orderkey", "left_semi").agg(F.count("*").alias("n"))


@query("join_anti_fresh", "SELECT count(*) AS n FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem WHERE l_quantity >= 45)")
def join_anti_fresh(spark, d):
    asked = load(spark, d, "lineitem", "l_orderkey", "l_quantity").where("l_quantity >= 45").select(F.col("l_orderkey").alias("o_orderkey"))
    return load(spark, d, "orders", "o_orderkey").join(asked, "o_orderkey", "left_anti").agg(F.count("*").alias("n"))


@query("join_all_pairs", "SELECT a.n_nationkey AS i, b.n_nationkey AS j FROM nation AS a JOIN nation AS b ON a.n_nationkey < b.n_nationkey")
def join_all_pairs(spark, d):
    """All pairs of a bounded set of variables, never of users."""
    n = load(spark, d, "nation", "n_nationkey")
    return n.select(F.col("n_nationkey").alias("i")).join(F.broadcast(n.select(F.col("n_nationkey").alias("j"))), F.col("i") < F.col("j"))


@query("join_left_labels", "SELECT coalesce(CAST(quality AS VARCHAR), '∅') AS quality, count(*) AS n FROM documents AS d LEFT JOIN labels AS l ON d.doc_id = l.doc_id GROUP BY 1")
def join_left_labels(spark, d):
    j = load(spark, d, "documents", "doc_id").join(load(spark, d, "labels", "doc_id", "quality"), "doc_id", "left")
    return j.groupBy(F.coalesce(F.col("quality").cast("string"), F.lit("∅")).alias("quality")).agg(F.count("*").alias("n"))


@query("join_outer_edges", "WITH a(i, j) AS (VALUES (0, 1), (1, 2), (2, 3)), b(i, j) AS (VALUES (0, 1), (1, 3), (2, 3)) SELECT coalesce(a.i, b.i) AS i, coalesce(a.j, b.j) AS j, a.i IS NOT NULL AS found, b.i IS NOT NULL AS true_edge FROM a FULL JOIN b ON a.i = b.i AND a.j = b.j")
def join_outer_edges(spark, d):
    a = spark.createDataFrame([(0, 1), (1, 2), (2, 3)], "i int, j int").withColumn("f", F.lit(True))
    b = spark.createDataFrame([(0, 1), (1, 3), (2, 3)], "i int, j int").withColumn("t", F.lit(True))
    return a.join(b, ["i", "j"], "full_outer").select("i", "j", F.coalesce("f", F.lit(False)).alias("found"), F.coalesce("t", F.lit(False)).alias("true_edge"))


@query("join_lateral_queries", "SELECT n_nationkey, q, n_nationkey * q AS asked FROM nation, LATERAL (SELECT unnest(range(1, 3 + n_regionkey)) AS q)")
def join_lateral_queries(spark, d):
    register_views(spark, d, "nation")
    return spark.sql("SELECT n_nationkey, q, n_nationkey * q AS asked FROM nation, LATERAL (SELECT explode(sequence(1L, 2L + n_regionkey)) AS q)")


# Aggregations

_X = "CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END"


@query("hist_reports", f"SELECT CAST(floor({coin('pub', 'q', KEY)} * 4) AS INT) AS query_id, l_returnflag AS report, count(*) AS n FROM lineitem GROUP BY 1, 2")
def hist_reports(spark, d):
    u = line_users(spark, d, "l_returnflag").select(F.floor(uniform("pub", "q", F.col("user_id")) * 4).cast("int").alias("query_id"), F.col("l_returnflag").alias("report"))
    return u.groupBy("query_id", "report").agg(F.count("*").alias("n"))


@query("hist_reports_sortagg", "SELECT l_returnflag AS report, max(l_linestatus) AS top, count(*) AS n FROM lineitem GROUP BY 1")
def hist_reports_sortagg(spark, d):
    """A string maximum is no hashable buffer: Spark sorts."""
    return load(spark, d, "lineitem", "l_returnflag", "l_linestatus").groupBy(F.col("l_returnflag").alias("report")).agg(F.max("l_linestatus").alias("top"), F.count("*").alias("n"))


@query("support_distinct", "SELECT count(DISTINCT l_partkey) AS k, count(DISTINCT l_suppkey) AS s FROM lineitem")
def support_distinct(spark, d):
    return load(spark, d, "lineitem", "l_partkey", "l_suppkey").agg(F.countDistinct("l_partkey").alias("k"), F.countDistinct("l_suppkey").alias("s"))


@query("support_approx")
def support_approx(spark, d):
    return load(spark, d, "lineitem", "l_partkey").agg(F.approx_count_distinct("l_partkey", 0.02).alias("k"))


@query("agg_filtered_hits", f"{_PR}, m AS (SELECT bucket, idx, min(report) AS lo, max(report) AS hi FROM r GROUP BY 1, 2 HAVING count(*) = 2) SELECT count(*) FILTER (WHERE lo = hi AND lo = 0) AS zeros, count(*) FILTER (WHERE lo = hi AND lo = 1) AS ones, count(*) FILTER (WHERE lo <> hi) AS misses FROM m")
def agg_filtered_hits(spark, d):
    df = assign_pairs(line_users(spark, d, "l_linestatus"), "user_id", "pub")
    m = reports(df, "user_id", ["l_linestatus"], 1, None, "pub", "noise").groupBy("bucket", "idx").agg(F.count("*").alias("c"), F.min("report").alias("lo"), F.max("report").alias("hi")).where("c = 2")
    return m.agg(F.count_if((F.col("lo") == F.col("hi")) & (F.col("lo") == 0)).alias("zeros"), F.count_if((F.col("lo") == F.col("hi")) & (F.col("lo") == 1)).alias("ones"), F.count_if(F.col("lo") != F.col("hi")).alias("misses"))


@query("entropy_cube", f"SELECT g::INT AS g, {tidy(h())} AS h FROM (SELECT grouping_id(l_returnflag, l_linestatus, l_linenumber) AS g, CAST(count(*) AS DOUBLE) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus, l_linenumber)) GROUP BY g")
def entropy_cube(spark, d):
    """Entropies of every subset of three attributes."""
    c = load(spark, d, "lineitem", "l_returnflag", "l_linestatus", "l_linenumber").cube("l_returnflag", "l_linestatus", "l_linenumber").agg(F.grouping_id().cast("int").alias("g"), F.count("*").cast("double").alias("n"))
    return c.groupBy("g").agg(tidy_col(M.h_of()).alias("h"))


@query("gini_rollup", f"SELECT g::INT AS level, n_regionkey, n_nationkey, {tidy('1 - ' + p2())} AS gini FROM (SELECT grouping_id(n_regionkey, n_nationkey) AS g, n_regionkey, n_nationkey, c_mktsegment, CAST(count(*) AS DOUBLE) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY c_mktsegment, ROLLUP (n_regionkey, n_nationkey)) GROUP BY ALL")
def gini_rollup(spark, d):
    c = load(spark, d, "customer", "c_nationkey", "c_mktsegment").join(F.broadcast(load(spark, d, "nation", "n_nationkey", "n_regionkey")), F.col("c_nationkey") == F.col("n_nationkey"))
    fine = M.histogram(c, ["n_regionkey", "n_nationkey", "c_mktsegment"])
    fine.createOrReplaceTempView("segment_histogram")
    r = spark.sql("SELECT CAST(grouping_id(c_mktsegment, n_regionkey, n_nationkey) AS INT) AS level, n_regionkey, n_nationkey, c_mktsegment, sum(n) AS n FROM segment_histogram GROUP BY c_mktsegment, n_regionkey, n_nationkey GROUPING SETS ((c_mktsegment), (c_mktsegment, n_regionkey), (c_mktsegment, n_regionkey, n_nationkey))")
    return r.groupBy("level", "n_regionkey", "n_nationkey").agg(tidy_col(1 - M.p2_of()).alias("gini"))


@query("pivot_reports", "SELECT l_returnflag, count(*) FILTER (WHERE l_linestatus = 'F') AS F, count(*) FILTER (WHERE l_linestatus = 'O') AS O FROM lineitem GROUP BY 1")
def pivot_reports(spark, d):
    return load(spark, d, "lineitem", "l_returnflag", "l_linestatus").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count().na.fill(0)


@query("error_quantiles", f"SELECT {tidy('quantile_cont(u, 0.5)')} AS median, {tidy('quantile_cont(u, 0.9)')} AS p90, {tidy('avg(CAST(u < 0.25 AS INT))')} AS success FROM (SELECT abs({coin('pub', 'e', 'o_orderkey')} - 0.5) AS u FROM orders)")
def error_quantiles(spark, d):
    u = load(spark, d, "orders", "o_orderkey").select(F.abs(uniform("pub", "e", F.col("o_orderkey")) - 0.5).alias("u"))
    return u.agg(tidy_col(F.percentile("u", 0.5)).alias("median"), tidy_col(F.percentile("u", 0.9)).alias("p90"), tidy_col(F.avg((F.col("u") < 0.25).cast("int"))).alias("success"))


@query("error_moments", f"SELECT {tidy('avg(u)')} AS mean, {tidy('stddev_samp(u)')} AS sd, {tidy('var_pop(u)')} AS var, {tidy('corr(u, v)')} AS corr FROM (SELECT {coin('pub', 'e', 'o_orderkey')} AS u, {coin('pub', 'e', 'o_orderkey')} + {coin('pub', 'f', 'o_orderkey')} AS v FROM orders)")
def error_moments(spark, d):
    u = load(spark, d, "orders", "o_orderkey").select(uniform("pub", "e", F.col("o_orderkey")).alias("u"), (uniform("pub", "e", F.col("o_orderkey")) + uniform("pub", "f", F.col("o_orderkey"))).alias("v"))
    return u.agg(tidy_col(F.avg("u")).alias("mean"), tidy_col(F.stddev_samp("u")).alias("sd"), tidy_col(F.var_pop("u")).alias("var"), tidy_col(F.corr("u", "v")).alias("corr"))


# Windows


@query("win_pairing", f"WITH {pairs_sql('SELECT o_orderkey FROM orders', 'o_orderkey')} SELECT o_orderkey, bucket, idx FROM p")
def win_pairing(spark, d):
    return assign_pairs(load(spark, d, "orders", "o_orderkey"), "o_orderkey", "pub")


_EDGES = """e AS (SELECT a.n_nationkey AS i, b.n_nationkey AS j, round(a.n * b.n / 1000.0::DOUBLE, 6) AS mi FROM c AS a JOIN c AS b ON a.n_nationkey < b.n_nationkey)"""
_C = "c AS (SELECT c_nationkey AS n_nationkey, CAST(count(*) AS DOUBLE) AS n FROM customer GROUP BY 1)"


def edges(spark, d):
    c = load(spark, d, "customer", "c_nationkey").groupBy("c_nationkey").agg(F.count("*").cast("double").alias("n"))
    a, b = c.select(F.col("c_nationkey").alias("i"), F.col("n").alias("na")), c.select(F.col("c_nationkey").alias("j"), F.col("n").alias("nb"))
    return a.join(b, F.col("i") < F.col("j")).select("i", "j", F.round(F.col("na") * F.col("nb") / 1000, 6).alias("mi"))


@query("win_rank_edges", f"WITH {_C}, {_EDGES} SELECT i, j, mi, row_number() OVER w AS rn, rank() OVER (ORDER BY mi DESC) AS rk, dense_rank() OVER (ORDER BY mi DESC) AS dr, {tidy('percent_rank() OVER (ORDER BY mi DESC)')} AS pr, ntile(4) OVER w AS tile FROM e WINDOW w AS (ORDER BY mi DESC, i, j)")
def win_rank_edges(spark, d):
    w, m = Window.orderBy(F.desc("mi"), "i", "j"), Window.orderBy(F.desc("mi"))
    return edges(spark, d).select("i", "j", "mi", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(m).cast("long").alias("rk"), F.dense_rank().over(m).cast("long").alias("dr"), tidy_col(F.percent_rank().over(m)).alias("pr"), F.ntile(4).over(w).cast("long").alias("tile"))


@query("win_cdf", f"SELECT l_discount, {tidy('sum(n) OVER (ORDER BY l_discount) / sum(n) OVER ()')} AS cdf, {tidy('cume_dist() OVER (ORDER BY l_discount)')} AS cd FROM ({counts('lineitem', 'l_discount')})")
def win_cdf(spark, d):
    n = M.histogram(load(spark, d, "lineitem", "l_discount"), ["l_discount"])
    w = Window.orderBy("l_discount")
    return n.select("l_discount", tidy_col(F.sum("n").over(w) / F.sum("n").over(Window.partitionBy(F.lit(0)))).alias("cdf"), tidy_col(F.cume_dist().over(w)).alias("cd"))


@query("win_chain_adjacent", "SELECT n_nationkey AS v, lag(n_nationkey) OVER w AS before, lead(n_nationkey) OVER w AS after FROM nation WINDOW w AS (PARTITION BY n_regionkey ORDER BY n_name)")
def win_chain_adjacent(spark, d):
    w = Window.partitionBy("n_regionkey").orderBy("n_name")
    return load(spark, d, "nation").select(F.col("n_nationkey").alias("v"), F.lag("n_nationkey").over(w).alias("before"), F.lead("n_nationkey").over(w).alias("after"))


@query("win_chain_ends", "SELECT n_nationkey AS v, first(n_nationkey) OVER w AS head, last(n_nationkey) OVER w AS tail, nth_value(n_nationkey, 2) OVER w AS second FROM nation WINDOW w AS (PARTITION BY n_regionkey ORDER BY n_name ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_chain_ends(spark, d):
    w = Window.partitionBy("n_regionkey").orderBy("n_name").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return load(spark, d, "nation").select(F.col("n_nationkey").alias("v"), F.first("n_nationkey").over(w).alias("head"), F.last("n_nationkey").over(w).alias("tail"), F.nth_value("n_nationkey", 2).over(w).alias("second"))


_M = f"{_PR}, m AS (SELECT bucket, idx, CAST(min(report) = max(report) AS INT) AS hit FROM r GROUP BY 1, 2 HAVING count(*) = 2)"


def pair_hits(spark, d):
    df = assign_pairs(line_users(spark, d, "l_linestatus"), "user_id", "pub")
    m = reports(df, "user_id", ["l_linestatus"], 1, None, "pub", "noise").groupBy("bucket", "idx").agg(F.count("*").alias("c"), (F.min("report") == F.max("report")).cast("int").alias("hit"))
    return m.where("c = 2").drop("c")


@query("win_running_estimate", f"{_M} SELECT bucket, idx, {tidy('2 * avg(hit) OVER (PARTITION BY bucket ORDER BY idx ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) - 1')} AS p2 FROM m")
def win_running_estimate(spark, d):
    """The estimate as pairs come in, per bucket."""
    w = Window.partitionBy("bucket").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
    return pair_hits(spark, d).select("bucket", "idx", tidy_col(2 * F.avg("hit").over(w) - 1).alias("p2"))


@query("win_sliding_estimate", f"{_M} SELECT bucket, idx, {tidy('2 * avg(hit) OVER (PARTITION BY bucket ORDER BY idx ROWS BETWEEN 99 PRECEDING AND CURRENT ROW) - 1')} AS p2 FROM m")
def win_sliding_estimate(spark, d):
    w = Window.partitionBy("bucket").orderBy("idx").rowsBetween(-99, 0)
    return pair_hits(spark, d).select("bucket", "idx", tidy_col(2 * F.avg("hit").over(w) - 1).alias("p2"))


@query("win_range_entropy", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY t RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS hour_events, count(*) FILTER (WHERE event_type = 'click') OVER (PARTITION BY user_id ORDER BY t RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS clicks FROM (SELECT *, floor(epoch(ts))::BIGINT AS t FROM events)")
def win_range_entropy(spark, d):
    """Trailing hour of each user's events, by time range."""
    w = Window.partitionBy("user_id").orderBy("t").rangeBetween(-3600, 0)
    e = load(spark, d, "events", "event_id", "user_id", "event_type", "ts").withColumn("t", F.unix_timestamp(F.col("ts").cast("timestamp_ltz")))
    return e.select("event_id", F.count("*").over(w).alias("hour_events"), F.coalesce(F.sum(F.when(F.col("event_type") == "click", 1)).over(w), F.lit(0)).alias("clicks"))


# Sorts, limits, sets


@query("sort_edges", f"WITH {_C}, {_EDGES} SELECT i, j, mi FROM e ORDER BY mi DESC, i, j")
def sort_edges(spark, d):
    return edges(spark, d).orderBy(F.desc("mi"), "i", "j")


@query("topk_neighbors", f"WITH {_C}, {_EDGES} SELECT i, j, mi FROM e ORDER BY mi DESC, i, j LIMIT 5 OFFSET 1")
def topk_neighbors(spark, d):
    return edges(spark, d).orderBy(F.desc("mi"), "i", "j").offset(1).limit(5)


@query("topk_per_group", f"WITH {_C}, {_EDGES} SELECT i, j, mi FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY mi DESC, j) AS rn FROM e) WHERE rn <= 2")
def topk_per_group(spark, d):
    w = Window.partitionBy("i").orderBy(F.desc("mi"), "j")
    return edges(spark, d).withColumn("rn", F.row_number().over(w)).where("rn <= 2").drop("rn")


@query("strongest_partner", f"WITH {_C}, {_EDGES}, t AS (SELECT i AS v, j AS w, mi FROM e UNION ALL SELECT j, i, mi FROM e) SELECT v, w AS partner, mi FROM (SELECT *, row_number() OVER (PARTITION BY v ORDER BY mi DESC, w) AS rn FROM t) WHERE rn = 1")
def strongest_partner(spark, d):
    return T.strongest_partner(edges(spark, d))


@query("set_union_rounds", "SELECT round, count(*) AS n FROM (SELECT 1 AS round FROM orders WHERE o_orderstatus = 'F' UNION ALL SELECT 2 FROM orders WHERE o_orderpriority LIKE '1%') GROUP BY 1")
def set_union_rounds(spark, d):
    o = load(spark, d, "orders", "o_orderstatus", "o_orderpriority")
    u = o.where("o_orderstatus = 'F'").select(F.lit(1).alias("round")).unionByName(o.where("o_orderpriority LIKE '1%'").select(F.lit(2).alias("round")))
    return u.groupBy("round").agg(F.count("*").alias("n"))


_TA, _TB = [(0, 1), (1, 2), (2, 3), (2, 3)], [(2, 3), (2, 3), (1, 2), (4, 5)]
_SETS = f"WITH a(i, j) AS (VALUES {', '.join(map(str, _TA))}), b(i, j) AS (VALUES {', '.join(map(str, _TB))})"


def _sets(spark):
    return spark.createDataFrame(_TA, "i int, j int"), spark.createDataFrame(_TB, "i int, j int")


@query("set_intersect_edges", f"{_SETS} SELECT i, j FROM a INTERSECT ALL SELECT i, j FROM b")
def set_intersect_edges(spark, d):
    a, b = _sets(spark)
    return a.intersectAll(b)


@query("set_except_edges", f"{_SETS} SELECT i, j FROM a EXCEPT ALL SELECT i, j FROM b")
def set_except_edges(spark, d):
    a, b = _sets(spark)
    return a.exceptAll(b)


_ASKED = f"SELECT hour(ts)::INT AS i, 24 + CAST(json_extract_string(props, '$.k') AS INT) AS j, {coin('pub', 'round', 'event_id')} < 0.5 AS first FROM events"


@query("distinct_requests", f"WITH r AS ({_ASKED}) SELECT DISTINCT i, j FROM (SELECT i, j FROM r WHERE first UNION ALL SELECT i, j FROM r WHERE NOT first)")
def distinct_requests(spark, d):
    """Pairs that the events of two rounds ask for, each once: the variables tell an hour (0 to 23) and a property (from 24)."""
    k = F.from_json("props", "k int")["k"]
    r = load(spark, d, "events", "event_id", "ts", "props").select(F.hour("ts").alias("i"), (24 + k).alias("j"), (uniform("pub", "round", F.col("event_id")) < 0.5).alias("first"))
    return r.where("first").select("i", "j").union(r.where("NOT first").select("i", "j")).dropDuplicates(["i", "j"])
