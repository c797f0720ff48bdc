"""The experiment workloads on the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.coins import uniform
from ..functions.scalars import keep_rate, tidy as tidy_col
from ..operators import collision as C
from ..operators import measures as M
from ..operators.workloads import exponential
from ..registry import query
from ..sources.tables import line_users, load
from .measures import exponential_truth
from .sqltext import KEY, coin, counts, h, p2, tidy

# Error against bits: repetitions as disjoint groups of users

TRUTH = exponential_truth()[2]


def error_rows(spark, d, alphas=(None, 4.0, 2.0, 1.0), groups=20, noise="noise"):
    """Mean relative error of collision entropy, in per cent, over disjoint groups of users."""
    users = line_users(spark, d).select("user_id", exponential(uniform("pub", "exp", F.col("user_id"))).alias("x"))
    users = users.withColumn("rep", F.floor(uniform("pub", "rep", F.col("user_id")) * F.lit(groups)).cast("int"))
    out = None
    for alpha in alphas:
        e = C.collision_sketch(users, "user_id", ["x"], 1, alpha, by=["rep"], private=noise)
        one = e.agg(F.avg("n_pairs").alias("pairs"), F.avg(F.abs(F.col("collision") - TRUTH) / TRUTH * 100).alias("error_percent"))
        one = one.select(F.lit("hash" if alpha is None else f"hash alpha={alpha:g}").alias("series"), tidy_col(2 * F.col("pairs")).alias("mean_bits"), tidy_col(F.col("error_percent")).alias("error_percent"))
        out = one if out is None else out.unionByName(one)
    raw = C.assign_pairs(users, "user_id", "pub", ["rep"])
    raw = C.match(raw.select("rep", "bucket", "idx", F.col("x").alias("report")), ["rep"])
    q = F.greatest(F.col("hits") / F.col("n_pairs"), 1 / F.col("n_pairs"))
    one = raw.agg(F.avg("n_pairs").alias("pairs"), F.avg(F.abs(-F.ln(q) - TRUTH) / TRUTH * 100).alias("e")).select(F.lit("raw").alias("series"), tidy_col(20 * F.col("pairs")).alias("mean_bits"), tidy_col(F.col("e")).alias("error_percent"))
    return out.unionByName(one)


BUDGETS = (1000, 2000, 5000, 10000, 20000, 50000)
ALPHAS = (None, 4.0, 3.0, 2.0, 1.0, 0.5)
#: Bits of a raw sample of 1000 symbols.
RAW_BITS = 10
#: Pairs that are added up before groups are formed; divides the pairs of every group.
UNIT = 50

#: (series, bits of a sample, squared keep rate).
SERIES = [("hash" if a is None else f"hash alpha={a:g}", 1, keep_rate(a, 1) ** 2) for a in ALPHAS] + [("raw", RAW_BITS, None)]
#: (k, series, bits, units of a group, squared keep rate).
GRID = [(k, name, bits, bits // each // 2 // UNIT, lam2) for k, (name, each, lam2) in enumerate(SERIES) for bits in BUDGETS]


def budget_rows(spark, users, grid=GRID, unit=UNIT):
    """(series, bits, groups, error_percent): mean relative error of collision entropy at fixed budgets of bits.

    Pairs are numbered through all buckets; a group is as many pairs in a row as the budget
    pays for. Groups are as many as whole ones fit; the error is null where none does.
    """
    paired = C.assign_pairs(users.select("user_id", "x"), "user_id", "pub")
    told = [C.report_of("user_id", ["x"], 1, a, "pub", "noise").alias(f"r{k}") for k, a in enumerate(ALPHAS)] + [F.col("x").alias(f"r{len(ALPHAS)}")]
    equal = [(F.min(f"r{k}") == F.max(f"r{k}")).cast("long").alias(f"h{k}") for k in range(len(SERIES))]
    pairs = paired.select("bucket", "idx", *told).groupBy("bucket", "idx").agg(F.count("*").alias("m"), *equal).where("m = 2")
    # A number a bucket of about a thousand users comes to the driver.
    sizes = paired.groupBy("bucket").agg(F.floor(F.count("*") / 2).cast("long").alias("n")).orderBy("bucket").collect()
    starts, at = [], 0
    for r in sizes:
        starts.append((r["bucket"], at))
        at += r["n"]
    starts = spark.createDataFrame(starts, "bucket long, start long")
    place = F.floor((F.col("start") + F.col("idx")) / unit).cast("long")
    units = pairs.join(starts, "bucket").groupBy(place.alias("unit")).agg(F.count("*").alias("n"), F.array(*[F.sum(f"h{k}") for k in range(len(SERIES))]).alias("hits")).where(F.col("n") == unit)
    table = F.broadcast(spark.createDataFrame(grid, "k int, series string, bits int, units int, lam2 double"))
    groups = units.crossJoin(table).groupBy("k", "series", "bits", "units", "lam2", F.floor(F.col("unit") / F.col("units")).alias("g")).agg(F.count("*").alias("c"), F.sum(F.get("hits", F.col("k"))).alias("hits")).where("c = units")
    n = F.col("units") * F.lit(float(unit))
    rate = F.col("hits") / n
    p2 = F.least(F.greatest(F.coalesce((2 * rate - 1) / F.col("lam2"), rate), 1 / n), F.lit(1.0))
    each = groups.groupBy("k", "bits").agg(F.count("*").alias("groups"), F.avg(F.abs(-F.ln(p2) - TRUTH) / TRUTH * 100).alias("e"))
    return table.join(each, ["k", "bits"], "left").select("series", "bits", F.coalesce("groups", F.lit(0)).alias("groups"), tidy_col(F.col("e")).alias("error_percent"))


def _error_sql() -> str:
    from .collision import pairs_sql, symbols
    from .sqltext import hash_bits

    users = f"SELECT {KEY} AS user_id, CAST(least(1000, ceil(-ln(1 - {coin('pub', 'exp', KEY)}))) AS INT) AS x FROM lineitem"
    hb = hash_bits("pub", 1, "concat_ws(':', bucket, idx)", symbols("x"))
    told = [hb if a is None else f"CASE WHEN {coin('noise', 'keep', 'user_id')} < {keep_rate(a, 1)!r}::DOUBLE THEN {hb} ELSE CAST(floor({coin('noise', 'draw', 'user_id')} * 2) AS BIGINT) END" for a in ALPHAS] + ["x"]
    ks = range(len(SERIES))
    grid = ", ".join(f"({k}, '{name}', {bits}, {units * UNIT}, {'NULL' if lam2 is None else repr(lam2)}::DOUBLE)" for k, name, bits, units, lam2 in GRID)
    hits = " ".join(f"WHEN {k} THEN h{k}" for k in ks)
    p2 = "least(greatest(coalesce((2 * (hits::DOUBLE / size) - 1) / lam2, hits::DOUBLE / size), 1.0::DOUBLE / size), 1.0::DOUBLE)"
    return f"""WITH {pairs_sql(users, 'user_id')},
      m AS (SELECT bucket, idx, {', '.join(f'CAST(min(r{k}) = max(r{k}) AS INT) AS h{k}' for k in ks)} FROM (SELECT bucket, idx, {', '.join(f'{t} AS r{k}' for k, t in enumerate(told))} FROM p) GROUP BY 1, 2 HAVING count(*) = 2),
      o AS (SELECT *, row_number() OVER (ORDER BY bucket, idx) - 1 AS pair FROM m),
      t(k, series, bits, size, lam2) AS (VALUES {grid}),
      s AS (SELECT k, bits, size, lam2, pair // size AS g, sum(CASE k {hits} END) AS hits FROM o CROSS JOIN t GROUP BY ALL HAVING count(*) = size),
      e AS (SELECT k, bits, count(*) AS groups, avg(abs(-ln({p2}) - {TRUTH!r}::DOUBLE) / {TRUTH!r}::DOUBLE * 100) AS e FROM s GROUP BY k, bits)
      SELECT series, bits, coalesce(groups, 0) AS groups, {tidy('e')} AS error_percent FROM t LEFT JOIN e USING (k, bits)"""


@query("error_curve", _error_sql())
def error_curve(spark, d):
    """Error against bits: a row for every series and budget, over as many groups as the rows allow."""
    return budget_rows(spark, line_users(spark, d).select("user_id", exponential(uniform("pub", "exp", F.col("user_id"))).alias("x")))


def _support_sql() -> str:
    from .collision import sketch_sql, symbols

    arms = [f"SELECT {k}::INT AS k, {tidy(f'abs(gini - {1 - 1 / k!r}::DOUBLE)')} AS gini_error, stderr, {tidy(f'abs(collision - ln({k}::DOUBLE))')} AS collision_error, clamped FROM ({sketch_sql(f'SELECT {KEY} AS user_id, l_partkey % {k} AS x FROM lineitem', 'user_id', symbols('x'), 1, None)})" for k in (2, 10, 100, 2000)]
    return " UNION ALL ".join(arms)


def _bits_sql() -> str:
    from .collision import _EXP, sketch_sql, symbols

    return " UNION ALL ".join(f"SELECT {b}::INT AS b, gini, stderr FROM ({sketch_sql(_EXP, 'user_id', symbols('x'), b, 1.0)})" for b in (1, 2, 3, 4))


@query("gini_by_support", _support_sql())
def gini_by_support(spark, d):
    """Error of Gini and collision estimates on uniform symbols of growing alphabets."""
    users = line_users(spark, d, "l_partkey")
    out = None
    for k in (2, 10, 100, 2000):
        e = C.collision_sketch(users.withColumn("x", F.col("l_partkey") % k), "user_id", ["x"], 1, None)
        e = e.select(F.lit(k).alias("k"), tidy_col(F.abs(F.col("gini") - (1 - 1 / k))).alias("gini_error"), "stderr", tidy_col(F.abs(F.col("collision") - F.ln(F.lit(float(k))))).alias("collision_error"), "clamped")
        out = e if out is None else out.unionByName(e)
    return out


@query("error_by_bits", _bits_sql())
def error_by_bits(spark, d):
    """Hash widths under privacy: one bit is best."""
    users = line_users(spark, d).select("user_id", exponential(uniform("pub", "exp", F.col("user_id"))).alias("x"))
    out = None
    for b in (1, 2, 3, 4):
        e = C.collision_sketch(users, "user_id", ["x"], b, 1.0).select(F.lit(b).alias("b"), "gini", "stderr")
        out = e if out is None else out.unionByName(e)
    return out


# Identifiability, splits, diversity, generators, reads

_FP = "SELECT event_type, CAST(hour(ts) AS INT) AS hour, json_extract_string(props, '$.k') AS k FROM events"


@query("fingerprint_events", f"SELECT {tidy(h())} AS h, max(n)::BIGINT AS largest, count(*) AS kinds FROM ({counts(f'({_FP})', 'event_type', 'hour', 'k')})")
def fingerprint_events(spark, d):
    """Joint entropy of attributes that could identify a user."""
    e = load(spark, d, "events", "event_type", "ts", "props").select("event_type", F.hour("ts").alias("hour"), F.get_json_object("props", "$.k").alias("k"))
    n = M.histogram(e, ["event_type", "hour", "k"])
    return n.agg(tidy_col(M.h_of()).alias("h"), F.max("n").cast("long").alias("largest"), F.count("*").alias("kinds"))


_HOST = r"regexp_extract(url, '^[a-z]+://([^/?#]+)', 1)"
_PG = rf"SELECT {_HOST} AS host, regexp_extract(url, '^[a-z]+://[^/]+/([a-z][a-z])/', 1) AS lang, contains(url, '?') AS q, contains(url, '#') AS f FROM pages"


@query("fingerprint_pages", f"SELECT {tidy(h())} AS h FROM ({counts(f'({_PG})', 'host', 'lang', 'q', 'f')})")
def fingerprint_pages(spark, d):
    p = load(spark, d, "pages", "url").select(F.regexp_extract("url", r"^[a-z]+://([^/?#]+)", 1).alias("host"), F.regexp_extract("url", r"^[a-z]+://[^/]+/([a-z][a-z])/", 1).alias("lang"), F.contains("url", F.lit("?")).alias("q"), F.contains("url", F.lit("#")).alias("f"))
    return M.shannon(p, ["host", "lang", "q", "f"])


_BAND = "CASE WHEN n_chars < 200 THEN 0 WHEN n_chars < 1000 THEN 1 ELSE 2 END"


def _band():
    return F.when(F.col("n_chars") < 200, 0).when(F.col("n_chars") < 1000, 1).otherwise(2)


@query("fingerprint_documents", f"SELECT {tidy(h())} AS h FROM ({counts(f'(SELECT lang, source, {_BAND} AS band FROM documents)', 'lang', 'source', 'band')})")
def fingerprint_documents(spark, d):
    return M.shannon(load(spark, d, "documents", "lang", "source", "n_chars").select("lang", "source", _band().alias("band")), ["lang", "source", "band"])


_SPLIT = " UNION ALL ".join(f"SELECT '{name}' AS split, CAST({expr} AS VARCHAR) AS side, quality FROM j" for name, expr in (("lang", "lang"), ("source", "source"), ("band", _BAND)))


@query("split_scoring", f"""WITH j AS (SELECT d.*, quality FROM documents AS d JOIN labels AS l ON d.doc_id = l.doc_id), s AS ({_SPLIT}),
    c AS (SELECT split, side, quality, CAST(count(*) AS DOUBLE) AS n FROM s GROUP BY ALL),
    g AS (SELECT split, side, sum(n) AS t, 1 - sum(n * n) / (sum(n) * sum(n)) AS g FROM c GROUP BY ALL)
    SELECT split, {tidy('sum(t * g) / sum(t)')} AS weighted_gini FROM g GROUP BY split""")
def split_scoring(spark, d):
    """Weighted Gini impurity of quality after candidate splits; texts are not read."""
    j = load(spark, d, "documents", "doc_id", "lang", "source", "n_chars").join(load(spark, d, "labels", "doc_id", "quality"), "doc_id")
    sides = F.array(*[F.struct(F.lit(n).alias("split"), c.cast("string").alias("side")) for n, c in (("lang", F.col("lang")), ("source", F.col("source")), ("band", _band()))])
    exact = M.histogram(j.select(F.inline(sides), "quality"), ["quality"], by=["split", "side"]).groupBy("split", "side").agg((1 - M.p2_of()).alias("g"), F.sum("n").alias("t"))
    return exact.groupBy("split").agg(tidy_col(F.sum(F.col("t") * F.col("g")) / F.sum("t")).alias("weighted_gini"))


@query("diversity_sources", f"SELECT lang, {tidy('1 - ' + p2())} AS g FROM ({counts('documents', 'lang', 'source')}) GROUP BY lang")
def diversity_sources(spark, d):
    return M.gini(load(spark, d, "documents", "lang", "source"), ["source"], by=["lang"])


@query("diversity_parts", f"SELECT p_brand, {tidy('1 - ' + p2())} AS g FROM ({counts('part', 'p_brand', 'p_type')}) GROUP BY p_brand")
def diversity_parts(spark, d):
    return M.gini(load(spark, d, "part", "p_brand", "p_type"), ["p_type"], by=["p_brand"])


@query("party_size", f"SELECT n_regionkey, {tidy('1 / ' + p2())} AS effective, {tidy(p2())} AS concentration FROM (SELECT n_regionkey, c_mktsegment, CAST(count(*) AS DOUBLE) AS n FROM customer JOIN nation ON n_nationkey = c_nationkey GROUP BY 1, 2) GROUP BY 1")
def party_size(spark, d):
    c = load(spark, d, "customer", "c_nationkey", "c_mktsegment").join(F.broadcast(load(spark, d, "nation", "n_nationkey", "n_regionkey")), F.col("c_nationkey") == F.col("n_nationkey"))
    return M.effective_number(c, ["c_mktsegment"], by=["n_regionkey"])


_GEN = " UNION ALL ".join(f"SELECT {b} AS b, CAST(floor({coin('gen', 'bits', 'o_orderkey')} * {1 << b}) AS INT) AS x FROM orders" for b in (1, 2, 4, 8))


@query("generator_quality", f"SELECT CAST(b AS INT) AS b, {tidy('-ln(' + p2() + ')')} AS c FROM ({counts(f'({_GEN})', 'b', 'x')}) GROUP BY b")
def generator_quality(spark, d):
    """Collision entropy of the top bits of the coins: b ln 2 for a good generator."""
    u = load(spark, d, "orders", "o_orderkey").select(uniform("gen", "bits", F.col("o_orderkey")).alias("u"))
    long = u.select(F.inline(F.array(*[F.struct(F.lit(b).alias("b"), F.floor(F.col("u") * (1 << b)).cast("int").alias("x")) for b in (1, 2, 4, 8)])))
    return M.histogram(long, ["x"], by=["b"]).groupBy("b").agg(tidy_col(-F.ln(M.p2_of())).alias("c"))


@query("qgram_collision", "SELECT lang, " + tidy("-ln(" + p2() + ")") + " AS c FROM (SELECT lang, substr(text, i, 2) AS q, CAST(count(*) AS DOUBLE) AS n FROM (SELECT lang, text, unnest(range(1, length(text))) AS i FROM documents) GROUP BY 1, 2) GROUP BY lang")
def qgram_collision(spark, d):
    """Collision entropy of two-character reads of whole texts, by language."""
    t = load(spark, d, "documents", "lang", "text").where(F.length("text") >= 2)
    q = t.select("lang", F.split("text", "").alias("c")).select("lang", F.explode(F.zip_with("c", F.slice("c", 2, F.size("c")), lambda a, b: F.when(b.isNotNull(), F.concat(a, b)))).alias("q")).where("q is not null")
    return M.histogram(q, ["q"], by=["lang"]).groupBy("lang").agg(tidy_col(-F.ln(M.p2_of())).alias("c"))


@query("mechanism_ablation")
def mechanism_ablation(spark, d):
    """Errors of private histograms of three symbols, by mechanism, at the same users."""
    from ..functions.scalars import project
    from ..operators import small_support as P
    from .protocol import coded

    df = coded(spark, d)
    truth = {r["x"]: r["count"] for r in df.groupBy("x").count().collect()}
    n = sum(truth.values())
    rows = []
    for alpha in (0.5, 1.0, 2.0):
        from ..operators.baselines import private_histogram

        for how in ("rr", "unary"):
            p = private_histogram(df, "user_id", "x", 3, alpha, how)
            rows.append((how, alpha, sum(abs(p[k] - truth.get(k, 0) / n) for k in range(3))))
        row, bit = P.hadamard_encode(F.col("x"), 3, alpha, "pub", "noise", F.col("user_id"))
        got = df.select(row.alias("r"), bit.alias("b")).groupBy("r").agg(F.sum("b").alias("s")).collect()
        p = project(P.hadamard_debias({r["r"]: float(r["s"]) for r in got}, float(n), 3, alpha))
        rows.append(("hadamard", alpha, sum(abs(p[k] - truth.get(k, 0) / n) for k in range(3))))
    return spark.createDataFrame(rows, "mechanism string, alpha double, l1_error double")
