"""Scalar functions that the methods lean on."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import scalars as S
from ..functions.coins import hash_bits as hash_col
from ..functions.coins import uniform
from ..registry import query
from ..sources.tables import line_users, load
from .sqltext import KEY, coin, hash_bits, tidy


@query("fn_hash_bits", f"SELECT {hash_bits('pub', 3, 'o_orderkey', 'o_orderstatus')}::INT AS v, count(*) AS n FROM orders GROUP BY 1")
def fn_hash_bits(spark, d):
    return load(spark, d, "orders", "o_orderkey", "o_orderstatus").groupBy(hash_col("pub", 3, F.col("o_orderkey"), F.col("o_orderstatus")).alias("v")).agg(F.count("*").alias("n"))


@query("fn_hadamard_sign", f"SELECT r::INT AS r, x, (1 - 2 * (bit_count(r & x::BIGINT) % 2))::INT AS s, count(*) AS n FROM (SELECT CAST(floor({coin('pub', 'row', KEY)} * 8) AS BIGINT) AS r, l_linenumber AS x FROM lineitem) GROUP BY ALL")
def fn_hadamard_sign(spark, d):
    """Sign of every line's number in a public row of its own."""
    users = line_users(spark, d, "l_linenumber").select(F.floor(uniform("pub", "row", F.col("user_id")) * 8).cast("int").alias("r"), F.col("l_linenumber").alias("x"))
    return users.groupBy("r", "x", S.hadamard_sign(F.col("r"), F.col("x")).alias("s")).agg(F.count("*").alias("n"))


@query("fn_width_bucket", "SELECT (CASE WHEN l_quantity < 0 THEN 0 WHEN l_quantity >= 50 THEN 6 ELSE floor(l_quantity / 10) + 1 END)::BIGINT AS b, count(*) AS n FROM lineitem GROUP BY 1")
def fn_width_bucket(spark, d):
    return load(spark, d, "lineitem", "l_quantity").groupBy(F.width_bucket("l_quantity", F.lit(0.0), F.lit(50.0), F.lit(5)).cast("long").alias("b")).agg(F.count("*").alias("n"))


@query("fn_lambda", f"SELECT b, alpha, {tidy('(exp(alpha) - 1) / (pow(2::DOUBLE, b) + exp(alpha) - 1)')} AS lambda, count(*) AS n FROM (SELECT l_linenumber AS b, l_quantity / 10 AS alpha FROM lineitem) GROUP BY b, alpha")
def fn_lambda(spark, d):
    """Keep rates of lines that send as many bits as their number, each under a privacy of its own."""
    users = load(spark, d, "lineitem", F.col("l_linenumber").alias("b"), (F.col("l_quantity") / 10).alias("alpha"))
    return users.groupBy("b", "alpha", S.tidy(S.keep_rate_of(F.col("alpha"), F.col("b"))).alias("lambda")).agg(F.count("*").alias("n"))


@query("fn_heavy_tail_z", f"SELECT least(floor(1 / greatest({coin('pub', 'z', 'o_orderkey')}, 1e-9)), 20)::BIGINT AS z, count(*) AS n FROM orders GROUP BY 1")
def fn_heavy_tail_z(spark, d):
    """Budgets with Pr[Z >= z] = 1/z."""
    u = F.greatest(uniform("pub", "z", F.col("o_orderkey")), F.lit(1e-9))
    return load(spark, d, "orders", "o_orderkey").groupBy(F.least(F.floor(1 / u), F.lit(20)).cast("long").alias("z")).agg(F.count("*").alias("n"))


@query("fn_salted_encoding", "SELECT o_orderkey, concat_ws('|', 'salt', length(o_orderstatus || '|') || ':' || o_orderstatus || '|', length(o_orderpriority) || ':' || o_orderpriority) AS word FROM orders")
def fn_salted_encoding(spark, d):
    """Length prefixes keep values apart that hold the delimiter."""
    v = F.concat("o_orderstatus", F.lit("|"))
    part = lambda c: F.concat(F.length(c).cast("string"), F.lit(":"), c)
    return load(spark, d, "orders", "o_orderkey", "o_orderstatus", "o_orderpriority").select("o_orderkey", F.concat_ws("|", F.lit("salt"), part(v), part(F.col("o_orderpriority"))).alias("word"))


@query("fn_url_parts", r"SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, len(string_split(regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1), '/'))::INT AS depth FROM pages")
def fn_url_parts(spark, d):
    path = F.regexp_extract("url", r"^[a-z]+://[^/?#]+([^?#]*)", 1)
    return load(spark, d, "pages", "page_id", "url").select("page_id", F.regexp_extract("url", r"^([a-z]+)://", 1).alias("scheme"), F.regexp_extract("url", r"^[a-z]+://([^/?#]+)", 1).alias("host"), F.size(F.split(path, "/")).alias("depth"))


@query("fn_qgrams", "SELECT substr(p_name, i, 3) AS q, count(*) AS n FROM (SELECT p_name, unnest(range(1, length(p_name) - 1)) AS i FROM part) GROUP BY 1")
def fn_qgrams(spark, d):
    q = F.explode(F.expr("transform(sequence(1, length(p_name) - 2), i -> substring(p_name, i, 3))"))
    return load(spark, d, "part", "p_name").where("length(p_name) >= 3").select(q.alias("q")).groupBy("q").agg(F.count("*").alias("n"))


@query("fn_calendar_parts", "SELECT year(o_orderdate)::INT AS y, quarter(o_orderdate)::INT AS q, month(o_orderdate)::INT AS m, count(*) AS n, min(date_diff('day', DATE '1992-01-01', o_orderdate::DATE))::INT AS first_day FROM orders GROUP BY 1, 2, 3")
def fn_calendar_parts(spark, d):
    c = F.col("o_orderdate")
    return load(spark, d, "orders", "o_orderdate").groupBy(F.year(c).alias("y"), F.quarter(c).alias("q"), F.month(c).alias("m")).agg(F.count("*").alias("n"), F.min(F.datediff(F.to_date(c), F.to_date(F.lit("1992-01-01")))).alias("first_day"))


@query("fn_sign_bits", "SELECT vec_id, list_sum(list_transform(embedding, lambda x: CAST(x > 0 AS INT)))::INT AS ones, (embedding[1] > 0) AS first FROM embeddings")
def fn_sign_bits(spark, d):
    x = F.transform("embedding", lambda v: F.when(v > 0, 1).otherwise(0))
    return load(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", F.aggregate(x, F.lit(0), lambda a, b: a + b).alias("ones"), (F.get("embedding", F.lit(0)) > 0).alias("first"))


@query("fn_hist_map", "SELECT l_returnflag, max(n) FILTER (WHERE l_linestatus = 'F') AS f, count(*)::INT AS kinds FROM (SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY 1, 2) GROUP BY 1")
def fn_hist_map(spark, d):
    """A histogram as a map."""
    n = load(spark, d, "lineitem", "l_returnflag", "l_linestatus").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))
    m = n.groupBy("l_returnflag").agg(F.map_from_entries(F.collect_list(F.struct("l_linestatus", "n"))).alias("m"))
    return m.select("l_returnflag", F.try_element_at("m", F.lit("F")).alias("f"), F.size(F.map_keys("m")).alias("kinds"))


@query("fn_struct_report", f"SELECT o_orderkey, 1 AS round, {hash_bits('pub', 1, 'o_orderkey')}::INT AS report, 1 AS bits FROM orders")
def fn_struct_report(spark, d):
    r = F.struct(F.lit(1).alias("round"), hash_col("pub", 1, F.col("o_orderkey")).alias("report"), F.lit(1).alias("bits"))
    return load(spark, d, "orders", "o_orderkey").select("o_orderkey", r.alias("r")).select("o_orderkey", "r.*")


@query("fn_props_json", "SELECT CAST(json_extract_string(props, '$.k') AS INT) AS k, count(*) AS n FROM events GROUP BY 1")
def fn_props_json(spark, d):
    e = load(spark, d, "events", "props").select(F.from_json("props", "k int").alias("p"))
    return e.groupBy(F.col("p.k").alias("k")).agg(F.count("*").alias("n"))


@query("fn_null_symbol", "SELECT coalesce(nullif(l_returnflag, 'R'), '∅') AS s, count(*) AS n FROM lineitem GROUP BY 1")
def fn_null_symbol(spark, d):
    from ..functions.coins import symbol

    return load(spark, d, "lineitem", "l_returnflag").groupBy(symbol(F.nullif("l_returnflag", F.lit("R"))).alias("s")).agg(F.count("*").alias("n"))


@query("fn_cast_bins", "SELECT CAST(floor(o_totalprice / 50000) AS INT) AS bin, CAST(floor(epoch(o_orderdate) / 31536000) AS INT) AS yr, count(*) AS n FROM orders GROUP BY 1, 2")
def fn_cast_bins(spark, d):
    o = load(spark, d, "orders", "o_totalprice", "o_orderdate")
    return o.groupBy(F.floor(F.col("o_totalprice") / 50000).cast("int").alias("bin"), F.floor(F.unix_timestamp(F.col("o_orderdate").cast("timestamp_ltz")) / 31536000).cast("int").alias("yr")).agg(F.count("*").alias("n"))


@query("fn_safe_arithmetic", "SELECT n_nationkey, CASE WHEN n_regionkey = 0 THEN NULL ELSE round(n_nationkey::DOUBLE / n_regionkey, 6) END AS q FROM nation")
def fn_safe_arithmetic(spark, d):
    return load(spark, d, "nation").select("n_nationkey", F.round(F.try_divide(F.col("n_nationkey").cast("double"), F.col("n_regionkey")), 6).alias("q"))
