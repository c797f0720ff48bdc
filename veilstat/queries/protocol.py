"""Coins, slots, ledgers and private small-alphabet estimators."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..functions import scalars as S
from ..functions.coins import uniform
from ..operators import small_support as P
from ..operators import workloads as W
from ..operators.protocol import UserPool, contacted_twice, criteria, slot
from ..registry import query
from ..sources.tables import line_users, load
from .sqltext import KEY, coin, tidy


@query("coin_uniform", f"SELECT o_orderkey, {tidy(coin('pub', 'u', 'o_orderkey'))} AS u FROM orders")
def coin_uniform(spark, d):
    return load(spark, d, "orders", "o_orderkey").select("o_orderkey", S.tidy(uniform("pub", "u", F.col("o_orderkey"))).alias("u"))


_SLOT = f"CAST(floor({coin('pub', 'slot', 'o_orderkey')} * 1000) AS BIGINT)"


@query("slot_allotment", f"SELECT CAST(floor(({_SLOT} - 100) / 50) AS INT) AS query_id, count(*) AS users FROM orders WHERE {_SLOT} BETWEEN 100 AND 399 GROUP BY 1")
def slot_allotment(spark, d):
    """Six questions with fifty slots each, after a hundred slots used before."""
    users = load(spark, d, "orders", "o_orderkey").select("o_orderkey", slot("o_orderkey", "pub", 1000).alias("slot"))
    _, rows = UserPool(users, 1000, 100).allot(list(range(6)), 50)
    return rows.groupBy("query_id").agg(F.count("*").alias("users"))


def _asked(spark, d):
    """A pool after a run of the mechanisms: four marginals, three pairs, four triples, forty slots each."""
    o = load(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderstatus", "o_orderpriority")
    bits = [F.col("o_orderstatus") == "O", F.col("o_orderpriority") < "3", F.col("o_custkey") % 2 == 0, F.col("o_custkey") % 3 == 0]
    users = o.select(F.col("o_orderkey").alias("user_id"), slot("o_orderkey", "pub", 1000).alias("slot"), F.array(*[b.cast("int") for b in bits]).alias("x"))
    pool = UserPool(users, 1000)
    source = P.PrivateSource(pool, 2, 1.0, 40)
    source.marginals([0, 1, 2, 3])
    source.mi([(0, 1), (0, 2), (1, 3)])
    source.cmi([(0, 1, 2), (0, 1, 3), (0, 2, 3), (1, 2, 3)])
    return pool


_TAKEN = f"asked AS (SELECT o_orderkey, CASE WHEN {_SLOT} < 160 THEN 1 WHEN {_SLOT} < 280 THEN 2 ELSE 3 END AS arity, {_SLOT} // 40 AS question FROM orders WHERE {_SLOT} < 440)"


@query("ledger_contact_once", f"WITH {_TAKEN}, t AS (SELECT o_orderkey, count(*) AS times FROM asked GROUP BY 1) SELECT CAST(sum(times) AS BIGINT) AS contacted, count(*) FILTER (WHERE times > 1) AS twice FROM t")
def ledger_contact_once(spark, d):
    ledger = _asked(spark, d).ledger()
    return ledger.agg(F.count("*").alias("contacted")).crossJoin(contacted_twice(ledger).agg(F.count("*").alias("twice")))


#: A report over 2^arity cells by randomised response takes as many bits as coordinates.
_CRIT = f"WITH {_TAKEN} SELECT count(*) AS samples, count(DISTINCT arity) AS rounds, count(DISTINCT question) AS queries, CAST(max(arity) AS BIGINT) AS max_bits, CAST(sum(arity) AS BIGINT) AS total_bits, CAST(max(arity) AS BIGINT) AS max_width, 1.0::DOUBLE AS alpha FROM asked"


@query("criteria_report", _CRIT)
def criteria_report(spark, d):
    """Every measure of a run, from what the mechanisms entered in the ledger."""
    return criteria(_asked(spark, d).ledger())


_ROUNDS = f"WITH {_TAKEN} SELECT CAST(arity AS INT) AS round, count(*) AS users, count(DISTINCT question) AS queries, CAST(arity AS INT) AS bits, CAST(arity AS INT) AS width FROM asked GROUP BY arity"


def _by_round(spark, d):
    return _asked(spark, d).ledger().groupBy("round").agg(F.count("*").alias("users"), F.countDistinct("query_id").alias("queries"), F.max("bits").alias("bits"), F.max("width").alias("width"))


for _name, _cols in (("cost_samples", ["round", "users"]), ("cost_bits", ["round", "users", "bits"]), ("cost_rounds", ["round", "queries"]), ("cost_width", ["round", "width"])):

    def _one(spark, d, cols=tuple(_cols)):
        return _by_round(spark, d).select(*cols)

    query(_name, f"SELECT {', '.join(_cols)} FROM ({_ROUNDS})")(_one)

# Small alphabets: l_returnflag as codes A, N, R

_CODE = "CAST(CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END AS INT)"
ALPHA = 1.0


def coded(spark, d):
    return line_users(spark, d, "l_returnflag").select("user_id", F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2).alias("x"))


def rr_sql(c: int, alpha: float, x: str, id_: str = "user_id") -> str:
    other = f"CAST(floor({coin('noise', 'other', id_)} * {c - 1}) AS INT)"
    return f"CASE WHEN {coin('noise', 'keep', id_)} < {P.rr_keep(c, alpha)!r}::DOUBLE THEN {x} WHEN {other} >= {x} THEN {other} + 1 ELSE {other} END"


def _debias(c: int, alpha: float) -> str:
    p = P.rr_keep(c, alpha)
    q = (1 - p) / (c - 1)
    return f"(n / sum(n) OVER () - {q!r}::DOUBLE) / {p - q!r}::DOUBLE"


_USERS = f"u AS (SELECT {KEY} AS user_id, {_CODE} AS x FROM lineitem)"


@query("ldp_rr_histogram", f"WITH {_USERS}, r AS (SELECT {rr_sql(3, ALPHA, 'x')} AS report, CAST(count(*) AS DOUBLE) AS n FROM u GROUP BY 1) SELECT CAST(report AS INT) AS report, CAST(n AS BIGINT) AS n, {tidy(_debias(3, ALPHA))} AS frequency FROM r")
def ldp_rr_histogram(spark, d):
    r = coded(spark, d).select(P.rr_encode(F.col("x"), 3, ALPHA, "noise", F.col("user_id")).alias("report")).groupBy("report").agg(F.count("*").alias("n"))
    p = P.rr_keep(3, ALPHA)
    q = (1 - p) / 2
    total = F.sum("n").over(_all())
    return r.select("report", "n", S.tidy((F.col("n").cast("double") / total - q) / (p - q)).alias("frequency"))


def _all():
    from pyspark.sql import Window

    return Window.partitionBy(F.lit(0))


_ROW = f"CAST(floor({coin('pub', 'row', 'user_id')} * 4) AS INT)"
_SIGN = f"(1 - 2 * (bit_count({_ROW} & (x + 1)) % 2))"
_BIT = f"CASE WHEN {coin('noise', 'flip', 'user_id')} < {1 / (1 + math.exp(ALPHA))!r}::DOUBLE THEN -{_SIGN} ELSE {_SIGN} END"


@query("ldp_hadamard_histogram", f"WITH {_USERS} SELECT {_ROW} AS row, CAST(sum({_BIT}) AS BIGINT) AS s, count(*) AS n FROM u GROUP BY 1")
def ldp_hadamard_histogram(spark, d):
    row, bit = P.hadamard_encode(F.col("x"), 3, ALPHA, "pub", "noise", F.col("user_id"))
    return coded(spark, d).select(row.alias("row"), bit.alias("bit")).groupBy("row").agg(F.sum("bit").alias("s"), F.count("*").alias("n"))


_F = 1 / (1 + math.exp(ALPHA / 2))
_ONE = " UNION ALL ".join(f"SELECT {s} AS symbol, CASE WHEN {coin('noise', f'bit{s}', 'user_id')} < {_F!r}::DOUBLE THEN CAST(x <> {s} AS INT) ELSE CAST(x = {s} AS INT) END AS b FROM u" for s in range(3))


@query("ldp_unary_histogram", f"WITH {_USERS}, b AS ({_ONE}) SELECT CAST(symbol AS INT) AS symbol, CAST(sum(b) AS BIGINT) AS ones, {tidy(f'(avg(b) - {_F!r}::DOUBLE) / {1 - 2 * _F!r}::DOUBLE')} AS frequency FROM b GROUP BY 1")
def ldp_unary_histogram(spark, d):
    bits = coded(spark, d).select(P.unary_encode(F.col("x"), 3, ALPHA, "noise", F.col("user_id")).alias("u"))
    long = bits.select(F.posexplode("u").alias("symbol", "b"))
    return long.groupBy("symbol").agg(F.sum("b").alias("ones"), F.avg("b").alias("m")).select("symbol", "ones", S.tidy((F.col("m") - _F) / (1 - 2 * _F)).alias("frequency"))


_V = "SELECT o_orderpriority AS k, [" + ", ".join(f"{coin('pub', f's{i}', 'o_orderpriority')} - 0.3" for i in range(4)) + "] AS v FROM (SELECT DISTINCT o_orderpriority FROM orders)"


@query(
    "simplex_projection",
    f"""WITH v AS ({_V}), s AS (SELECT k, v, list_reverse_sort(v) AS down FROM v),
    t AS (SELECT k, v, list_max([(list_sum(down[1:i]) - 1) / i FOR i IN range(1, 5)]) AS theta FROM s)
    SELECT k, {tidy('greatest(v[1] - theta, 0)')} AS p0, {tidy('greatest(v[2] - theta, 0)')} AS p1, {tidy('greatest(v[3] - theta, 0)')} AS p2, {tidy('greatest(v[4] - theta, 0)')} AS p3,
           {tidy('greatest(v[1], 0) / (greatest(v[1], 0) + greatest(v[2], 0) + greatest(v[3], 0) + greatest(v[4], 0))')} AS clipped0 FROM t""",
)
def simplex_projection(spark, d):
    v = load(spark, d, "orders", "o_orderpriority").distinct().select(F.col("o_orderpriority").alias("k"), F.array(*[uniform("pub", f"s{i}", F.col("o_orderpriority")) - 0.3 for i in range(4)]).alias("v"))
    p = v.select("k", S.project_simplex(F.col("v")).alias("p"), S.clip_norm(F.col("v")).alias("q"))
    return p.select("k", *[S.tidy(F.get("p", F.lit(i))).alias(f"p{i}") for i in range(4)], S.tidy(F.get("q", F.lit(0))).alias("clipped0"))


def _project_sql(cells: int, freq: str) -> str:
    """Projected frequencies p of cells 0..cells-1 from a table ``freq`` (report, f)."""
    return f"""g AS (SELECT c.report, coalesce(f, 0) AS f FROM (SELECT unnest(range({cells})) AS report) AS c LEFT JOIN {freq} AS x ON x.report = c.report),
      k AS (SELECT report, f, sum(f) OVER w AS total, row_number() OVER w AS n FROM g WINDOW w AS (ORDER BY f DESC, report)),
      th AS (SELECT max((total - 1) / n) AS theta FROM k), pr AS (SELECT report, greatest(f - theta, 0) AS p FROM g, th)"""


def _h(expr: str, group: str) -> str:
    return f"(SELECT -sum(CASE WHEN q > 0 THEN q * ln(q) ELSE 0 END) FROM (SELECT sum(p) AS q FROM pr GROUP BY {group}))"


def _private_sql(model, cells: int, cell: str, out: str) -> str:
    from .structure import vectors_sql

    p = P.rr_keep(cells, 1.0)
    q = (1 - p) / (cells - 1)
    return f"""WITH {vectors_sql(model)}, u AS (SELECT user_id, {cell} AS x FROM v),
      r AS (SELECT {rr_sql(cells, 1.0, 'x')} AS report, CAST(count(*) AS DOUBLE) AS n FROM u GROUP BY 1),
      fr AS (SELECT report, (n / sum(n) OVER () - {q!r}::DOUBLE) / {p - q!r}::DOUBLE AS f FROM r), {_project_sql(cells, 'fr')} SELECT {tidy(out)} AS estimate"""


def _vector_pool(spark, d):
    from .structure import D, order_vectors

    x = W.packed(order_vectors(spark, d, W.TREE6), D)
    return UserPool(x.withColumn("slot", F.lit(0).cast("long")), 1)


@query("ldp_marginal_entropy", _private_sql(W.TREE6, 2, "v3", _h("", "report")))
def ldp_marginal_entropy(spark, d):
    """Every user answers one question: a marginal entropy under alpha = 1."""
    h = P.PrivateSource(_vector_pool(spark, d), 2, 1.0, 1).marginals([3])[3]
    return spark.createDataFrame([(round(h, 6),)], "estimate double")


@query("ldp_pair_mi", _private_sql(W.TREE6, 4, "v0 * 2 + v1", f"{_h('', 'report // 2')} + {_h('', 'report % 2')} - {_h('', 'report')}"))
def ldp_pair_mi(spark, d):
    mi = P.PrivateSource(_vector_pool(spark, d), 2, 1.0, 1).mi([(0, 1)])[(0, 1)]
    return spark.createDataFrame([(round(mi, 6),)], "estimate double")


@query("ldp_triplet_cmi", _private_sql(W.TREE6, 8, "v0 * 4 + v1 * 2 + v3", f"greatest(0, {_h('', 'report // 2')} + {_h('', '(report % 2) + 2 * ((report // 2) % 2)')} - {_h('', 'report')} - {_h('', '(report // 2) % 2')})"))
def ldp_triplet_cmi(spark, d):
    """Information of variables 0 and 3 given 1, which lies between them."""
    got = P.PrivateSource(_vector_pool(spark, d), 2, 1.0, 1).cmi([(0, 1, 3)])[(0, 1, 3)][1]
    return spark.createDataFrame([(round(got, 6),)], "estimate double")
