"""Exact measures."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..functions import scalars as S
from ..operators import measures as M
from ..registry import query
from ..sources.tables import load
from .sqltext import counts, h, p2, tidy


@query("exact_shannon", f"SELECT {tidy(h())} AS h FROM ({counts('lineitem', 'l_discount')})")
def exact_shannon(spark, d):
    return M.shannon(load(spark, d, "lineitem", "l_discount"), ["l_discount"])


@query("exact_shannon_bits", f"SELECT {tidy(h() + ' / ln(2)')} AS h FROM ({counts('documents', 'lang', 'source')})")
def exact_shannon_bits(spark, d):
    return M.shannon(load(spark, d, "documents", "lang", "source"), ["lang", "source"], base=2)


@query("weighted_shannon", f"SELECT {tidy(h())} AS h FROM (SELECT c_mktsegment, sum(abs(c_acctbal)) AS n FROM customer GROUP BY 1)")
def weighted_shannon(spark, d):
    df = load(spark, d, "customer", "c_mktsegment", "c_acctbal").withColumn("w", F.abs("c_acctbal"))
    return M.shannon(df, ["c_mktsegment"], weight="w")


@query("exact_tsallis", f"SELECT {tidy('(1 - sum(pow(n, 3)) / pow(sum(n), 3)) / 2')} AS t FROM ({counts('lineitem', 'l_quantity')})")
def exact_tsallis(spark, d):
    return M.tsallis(load(spark, d, "lineitem", "l_quantity"), ["l_quantity"], 3)


@query("exact_renyi", f"SELECT {tidy('2 * ln(sum(pow(n, 0.5)) / pow(sum(n), 0.5))')} AS r FROM ({counts('orders', 'o_orderpriority', 'o_orderstatus')})")
def exact_renyi(spark, d):
    return M.renyi(load(spark, d, "orders", "o_orderpriority", "o_orderstatus"), ["o_orderpriority", "o_orderstatus"], 0.5)


@query("exact_gini", f"SELECT {tidy('1 - ' + p2())} AS g FROM ({counts('part', 'p_type')})")
def exact_gini(spark, d):
    return M.gini(load(spark, d, "part", "p_type"), ["p_type"])


@query("exact_collision", f"SELECT {tidy(p2())} AS p2, {tidy('-ln(' + p2() + ')')} AS c FROM ({counts('documents', 'lang')})")
def exact_collision(spark, d):
    return M.collision(load(spark, d, "documents", "lang"), ["lang"])


_U = "sum(n * (n - 1)) / (sum(n) * (sum(n) - 1))"


@query("exact_collision_ustat", f"SELECT {tidy(_U)} AS p2, {tidy(f'-ln({_U})')} AS c FROM ({counts('lineitem', 'l_partkey')})")
def exact_collision_ustat(spark, d):
    return M.collision(load(spark, d, "lineitem", "l_partkey"), ["l_partkey"], unbiased=True)


@query("joint_shannon", f"SELECT {tidy(h())} AS h FROM ({counts('lineitem', 'l_returnflag', 'l_linestatus', 'l_linenumber')})")
def joint_shannon(spark, d):
    cols = ["l_returnflag", "l_linestatus", "l_linenumber"]
    return M.shannon(load(spark, d, "lineitem", *cols), cols)


def _hsub(cols: str, src: str) -> str:
    return f"(SELECT {h()} FROM (SELECT {cols}, sum(n) AS n FROM {src} GROUP BY {cols}))"


@query("mi_pair", f"WITH f AS ({counts('nation', 'n_nationkey', 'n_regionkey')}) SELECT {tidy(_hsub('n_nationkey', 'f') + ' + ' + _hsub('n_regionkey', 'f') + ' - ' + _hsub('n_nationkey, n_regionkey', 'f'))} AS mi")
def mi_pair(spark, d):
    return M.mutual_information(load(spark, d, "nation", "n_nationkey", "n_regionkey"), "n_nationkey", "n_regionkey")


_A, _B, _C = "l_quantity_band", "l_price_band", "l_unit_band"
_BANDS = """SELECT CAST(floor(l_quantity / 10) AS INT) AS l_quantity_band, CAST(floor(l_extendedprice / 20000) AS INT) AS l_price_band,
    CAST(floor(l_extendedprice / l_quantity / 500) AS INT) AS l_unit_band FROM lineitem"""


def bands(spark, d):
    df = load(spark, d, "lineitem", "l_quantity", "l_extendedprice")
    return df.select(
        F.floor(F.col("l_quantity") / 10).cast("int").alias(_A), F.floor(F.col("l_extendedprice") / 20000).cast("int").alias(_B), F.floor(F.col("l_extendedprice") / F.col("l_quantity") / 500).cast("int").alias(_C)
    )


_CMI = _hsub(f"{_A}, {_C}", "f") + " + " + _hsub(f"{_B}, {_C}", "f") + " - " + _hsub(f"{_A}, {_B}, {_C}", "f") + " - " + _hsub(_C, "f")


@query("cmi_triplet", f"WITH b AS ({_BANDS}), f AS ({counts('b', _A, _B, _C)}) SELECT {tidy(_CMI)} AS cmi")
def cmi_triplet(spark, d):
    return M.conditional_mi(bands(spark, d), _A, _B, _C)


def mi_sql(source: str, variables: list[str]) -> str:
    """(i, j, mi) of all pairs of columns of ``source``."""
    arms = []
    for i in range(len(variables)):
        for j in range(i + 1, len(variables)):
            a, b = variables[i], variables[j]
            arms.append(f"SELECT {i} AS i, {j} AS j, {_hsub(a, f'f{i}_{j}')} + {_hsub(b, f'f{i}_{j}')} - {_hsub(f'{a}, {b}', f'f{i}_{j}')} AS mi")
    tables = ", ".join(f"f{i}_{j} AS ({counts(source, variables[i], variables[j])})" for i in range(len(variables)) for j in range(i + 1, len(variables)))
    return f"{tables}, edges AS ({' UNION ALL '.join(arms)})"


_MV = ["l_returnflag", "l_linestatus", "l_linenumber", "l_discount"]


@query("mi_matrix", f"WITH {mi_sql('lineitem', _MV)} SELECT CAST(i AS INT) AS i, CAST(j AS INT) AS j, {tidy('mi')} AS mi FROM edges")
def mi_matrix(spark, d):
    return M.mi_matrix(load(spark, d, "lineitem", *_MV), _MV).select("i", "j", S.tidy(F.col("mi")).alias("mi"))


@query("effective_number", f"SELECT l_returnflag, {tidy(p2())} AS concentration, {tidy('1 / ' + p2())} AS effective FROM ({counts('lineitem', 'l_returnflag', 'l_discount')}) GROUP BY 1")
def effective_number(spark, d):
    return M.effective_number(load(spark, d, "lineitem", "l_returnflag", "l_discount"), ["l_discount"], by=["l_returnflag"])


_SHARE = """SELECT n_name, l_suppkey, sum(l_extendedprice * (1 - l_discount)) AS n FROM lineitem
    JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey GROUP BY 1, 2"""


@query("market_concentration", f"SELECT n_name, {tidy(p2())} AS concentration, {tidy('1 / ' + p2())} AS effective FROM ({_SHARE}) GROUP BY 1")
def market_concentration(spark, d):
    """Revenue shares of suppliers within their nation; the lines are summed by supplier before any join."""
    sales = load(spark, d, "lineitem", "l_suppkey", "l_extendedprice", "l_discount").groupBy("l_suppkey").agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("w"))
    who = load(spark, d, "supplier", "s_suppkey", "s_nationkey").join(F.broadcast(load(spark, d, "nation", "n_nationkey", "n_name")), F.col("s_nationkey") == F.col("n_nationkey"))
    return M.effective_number(sales.join(who, sales.l_suppkey == who.s_suppkey), ["l_suppkey"], by=["n_name"], weight="w")


@query(
    "entropy_of_array",
    f"""WITH s AS (SELECT l_linenumber, sum(n) AS t, sum(n * ln(n)) AS l, sum(n * n) AS q, sum(pow(n, 3)) AS c FROM ({counts('lineitem', 'l_linenumber', 'l_returnflag')}) GROUP BY 1)
    SELECT l_linenumber, {tidy('ln(t) - l / t')} AS h, {tidy('1 - q / (t * t)')} AS g, {tidy('-ln(q / (t * t))')} AS c, {tidy('(1 - c / pow(t, 3)) / 2')} AS t3, {tidy('ln(c / pow(t, 3)) / -2')} AS r3 FROM s""",
)
def entropy_of_array(spark, d):
    """Entropies of a probability array per group, by higher-order functions."""
    n = M.histogram(load(spark, d, "lineitem", "l_linenumber", "l_returnflag"), ["l_returnflag"], by=["l_linenumber"])
    a = n.groupBy("l_linenumber").agg(F.collect_list("n").alias("v")).withColumn("v", F.transform("v", lambda x: x / S.array_sum(F.col("v"))))
    v = F.col("v")
    return a.select("l_linenumber", S.tidy(S.shannon_of(v)).alias("h"), S.tidy(S.gini_of(v)).alias("g"), S.tidy(S.collision_of(v)).alias("c"), S.tidy(S.tsallis_of(v, 3)).alias("t3"), S.tidy(S.renyi_of(v, 3)).alias("r3"))


_ID = f"""WITH f AS (SELECT c_nationkey, n_regionkey, c_mktsegment, CAST(count(*) AS DOUBLE) AS n FROM customer JOIN nation ON n_nationkey = c_nationkey GROUP BY 1, 2, 3)
    SELECT {tidy(' + '.join(_hsub(c, 'f') for c in ('c_nationkey', 'n_regionkey', 'c_mktsegment')))} AS marginals,
           {tidy(' + '.join(f"({_hsub(a, 'f')} + {_hsub(b, 'f')} - {_hsub(f'{a}, {b}', 'f')})" for a, b in (('c_nationkey', 'n_regionkey'), ('c_nationkey', 'c_mktsegment'))))} AS edges"""


@query("tree_identity_entropy", f"SELECT marginals, edges, {tidy('marginals - edges')} AS h FROM ({_ID})")
def tree_identity_entropy(spark, d):
    """Sum of marginal entropies less the information on a tree's edges."""
    nation = F.broadcast(load(spark, d, "nation", "n_nationkey", "n_regionkey"))
    df = load(spark, d, "customer", "c_nationkey", "c_mktsegment").join(nation, F.col("c_nationkey") == F.col("n_nationkey"))
    v = ["c_nationkey", "n_regionkey", "c_mktsegment"]
    total = M.marginal_entropies(df.select(*[F.col(x).cast("string").alias(x) for x in v]), v).agg(S.tidy(F.sum("h")).alias("marginals"))
    mi = M.mi_matrix(df.select(*[F.col(x).cast("string").alias(x) for x in v]), v)
    edges = F.broadcast(df.sparkSession.createDataFrame([(0, 1), (0, 2)], "i int, j int"))
    weight = mi.join(edges, ["i", "j"]).agg(S.tidy(F.sum("mi")).alias("edges"))
    return total.crossJoin(weight).withColumn("h", S.tidy(F.col("marginals") - F.col("edges")))


def exponential_truth(k: int = 1000) -> tuple[float, float, float, float]:
    """(collision probability, Gini, collision entropy, Shannon entropy) of p_i proportional to e^-i, i = 1..k."""
    p = [math.exp(-i) for i in range(1, k + 1)]
    p = [x / math.fsum(p) for x in p]
    q = math.fsum(x * x for x in p)
    return q, 1 - q, -math.log(q), S.entropy(p)
