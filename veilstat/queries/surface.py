"""The SQL, UDF, UDAF and UDTF surface."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import udf as U
from ..functions.scalars import tidy as tidy_col
from ..operators import measures as M
from ..operators import workloads as W
from ..registry import query
from ..sources.tables import load, register_views
from .sqltext import coin, counts, h, tidy
from .structure import STAR_SQL, V, base_sql, order_vectors, tree_sql


@query("sql_lambda", f"SELECT o_orderkey, {tidy(coin('pub', 'k', 'o_orderkey') + ' - (exp(1.0) - 1) / (2 + exp(1.0) - 1)')} AS over_rate FROM orders")
def sql_lambda(spark, d):
    """SQL functions that Catalyst inlines."""
    U.register_all(spark)
    register_views(spark, d, "orders")
    return spark.sql("SELECT o_orderkey, round(coin('pub', 'k', CAST(o_orderkey AS STRING)) - keep_rate(1D, 1), 6) + 0D AS over_rate FROM orders")


@query("udf_hadamard_inverse", "WITH c AS (SELECT " + ", ".join(f"count(*) FILTER (WHERE l_linenumber = {k})::DOUBLE AS n{k}" for k in range(1, 9)) + " FROM lineitem) SELECT " + ", ".join(f"n{k} AS n{k}" for k in range(1, 9)) + " FROM c")
def udf_hadamard_inverse(spark, d):
    """Transform of counts and back through the UDF."""
    n = load(spark, d, "lineitem", "l_linenumber").agg(*[F.count_if(F.col("l_linenumber") == k).cast("double").alias(f"n{k}") for k in range(1, 9)])
    sign = [[1 - 2 * (bin(r & x).count("1") % 2) for x in range(8)] for r in range(8)]
    sums = F.array(*[sum((F.col(f"n{x + 1}") * sign[r][x] for x in range(8)), F.lit(0.0)) for r in range(8)])
    back = n.select(U.hadamard_inverse_udf()(sums).alias("v"))
    return back.select(*[F.round(F.get("v", F.lit(k - 1)), 6).alias(f"n{k}") for k in range(1, 9)])


@query("udaf_entropy", f"SELECT l_returnflag, {tidy(h())} AS h FROM ({counts('lineitem', 'l_returnflag', 'l_linenumber')}) GROUP BY 1")
def udaf_entropy(spark, d):
    return load(spark, d, "lineitem", "l_returnflag", "l_linenumber").groupBy("l_returnflag").agg(tidy_col(U.entropy_udaf()("l_linenumber")).alias("h"))


@query("grouped_star_hub", f"{base_sql(W.STAR6)}, {STAR_SQL} SELECT 0 AS g, CAST((SELECT a FROM sums ORDER BY s DESC, a LIMIT 1) AS INT) AS hub")
def grouped_star_hub(spark, d):
    e = M.mi_matrix(order_vectors(spark, d, W.STAR6), V).withColumn("g", F.lit(0))
    return U.star_hub_per_group(e, "g")


@query("mi_matrix_blocks", f"{base_sql(W.TREE6)} SELECT CAST(i AS INT) AS i, CAST(j AS INT) AS j, {tidy('mi')} AS mi FROM edges")
def mi_matrix_blocks(spark, d):
    """All pairs by matrix products of one-hot blocks."""
    cells = U.pair_blocks(order_vectors(spark, d, W.TREE6), V, 2)
    return M.mi_from_cells(cells).select("i", "j", tidy_col(F.col("mi")).alias("mi"))


@query("udtf_random_tree")
def udtf_random_tree(spark, d):
    U.register_all(spark)
    return spark.sql("SELECT * FROM random_tree(12, '42')")


@query("udtf_spanning_tree", f"{base_sql(W.TREE6)}, {tree_sql()} SELECT CAST(i AS INT) AS i, CAST(j AS INT) AS j, {tidy('mi')} AS mi FROM tree")
def udtf_spanning_tree(spark, d):
    U.register_all(spark)
    M.mi_matrix(order_vectors(spark, d, W.TREE6), V).createOrReplaceTempView("tree_edges")
    return spark.sql("SELECT t.i, t.j, round(t.mi, 6) + 0D AS mi FROM (SELECT collect_list(struct(i, j, mi)) AS es FROM tree_edges) AS e, LATERAL spanning_tree(e.es) AS t")


@query("udtf_locate", "SELECT 1 AS place")
def udtf_locate(spark, d):
    U.register_all(spark)
    return spark.sql("SELECT place FROM locate_in_chain(array(1, 4, 6, 9, 12), 5)")
