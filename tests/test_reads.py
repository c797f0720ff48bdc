"""Queries that once made their data up, or read nothing, read every row of a given table in Spark's tasks."""

import json
import math

import pytest
from pyspark.sql import functions as F

from veilstat import queries as core
from veilstat.functions.scalars import keep_rate
from veilstat.operators import small_support as P
from veilstat.operators import structure as T
from veilstat.operators import workloads as W
from veilstat.queries import structure as Q

SF = "/root/testdata/sf0.001"


def rows_read(spark):
    """(highest stage, {stage: rows that its tasks read})."""
    sc = spark.sparkContext._jsc.sc()
    sc.listenerBus().waitUntilEmpty()
    new = spark._jvm.java.util.ArrayList
    stages = sc.statusStore().stageList(new(), False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), new())
    read = {stages.apply(k).stageId(): stages.apply(k).inputRecords() if stages.apply(k).inputBytes() else 0 for k in range(stages.size())}
    return max(read, default=-1), read


READS = {
    "bounds_hash": "lineitem",
    "bounds_table": "lineitem",
    "chain_call_count": "orders",
    "distinct_requests": "events",
    "fn_hadamard_sign": "lineitem",
    "hash_bias_table": "lineitem",
    "chain_variants": "orders",
    "fn_lambda": "lineitem",
    "hard_sequential": "lineitem",
    "cost_pairs_curve": "orders",
    "cost_slope": "orders",
}


@pytest.mark.parametrize("name", READS)
def test_tasks_read_the_table(spark, name):
    last, _ = rows_read(spark)
    core.queries()[name](spark, SF).collect()
    _, read = rows_read(spark)
    assert sum(n for stage, n in read.items() if stage > last) >= spark.read.parquet(f"{SF}/{READS[name]}.parquet").count()


def values(spark, table, column):
    return [r[0] for r in spark.read.parquet(f"{SF}/{table}.parquet").select(column).collect()]


def test_bounds_hash_of_columns(spark):
    got = core.queries()["bounds_hash"](spark, SF).collect()
    assert {(r["field"], r["b"]) for r in got} == {(c, b) for c in ("l_linestatus", "l_quantity", "l_suppkey") for b in (1, 2, 4)}
    for r in got:
        x = values(spark, "lineitem", r["field"])
        p2 = sum((x.count(v) / len(x)) ** 2 for v in set(x))
        assert (r["users"], r["k"]) == (len(x), len(set(x))) and r["p2"] == pytest.approx(p2, abs=1e-6)
        assert r["gini"] == pytest.approx(16 ** r["b"] * max(p2, 0.5 ** r["b"], 0.1) * math.log(10) / (0.5**4 * 0.01))
        assert r["collision"] == pytest.approx(16 ** r["b"] * len(set(x)) ** 2 * math.log(10) / (0.5**4 * 0.01))


def test_bounds_table_of_baskets(spark):
    got = core.queries()["bounds_table"](spark, SF).collect()
    assert {(r["field"], r["eps"]) for r in got} == {(c, e) for c in ("l_linenumber", "l_quantity", "l_suppkey") for e in (0.1, 0.5)}
    for r in got:
        n = len(set(values(spark, "lineitem", r["field"])))
        assert (r["users"], r["d"]) == (len(set(values(spark, "lineitem", "l_orderkey"))), n)
        assert r["chain"] == r["star"] == pytest.approx(n * math.log(n / 0.1) / (0.25 * r["eps"] ** 2), abs=0.01) and r["lower_fixed"] == n * n


def test_calls_on_sampled_chains(spark):
    """As many questions as on closed-form chains; the histogram of vectors answers as a pass over the rows does."""
    got = {r["d"]: (r["triples"], r["informations"]) for r in core.queries()["chain_call_count"](spark, SF).collect()}
    for n in (4, 6, 8, 10, 12):
        _, asked = T.chain_order(Q.ChainForm((0.5, *[0.02 + 0.08 * i / n for i in range(1, n)])), list(range(n)))
        assert got[n] == (asked, 3 * asked)
    users = W.chain_vectors(spark.read.parquet(f"{SF}/orders.parquet").select(F.col("o_orderkey").alias("user_id")), [0.0, 0.1, 0.2, 0.3], 3)
    every, once = P.ExactSource(users, 3), P.CountedSource(users, 3)
    assert once.cmi([(0, 1, 2), (1, 2, 3)]) == every.cmi([(0, 1, 2), (1, 2, 3)]) and once.mi([(0, 3)]) == every.mi([(0, 3)]) and once.marginals([2]) == every.marginals([2])
    assert P.CountedSource(users.limit(0), 3).mi([(0, 3)]) == {(0, 3): 0.0}


def test_requests_of_all_events(spark):
    events = spark.read.parquet(f"{SF}/events.parquet").select("ts", "props").collect()
    want = {(r["ts"].hour, 24 + json.loads(r["props"])["k"]) for r in events}
    got = [tuple(r) for r in core.queries()["distinct_requests"](spark, SF).collect()]
    assert len(got) == len(want) < len(events) and set(got) == want


def test_signs_of_all_lines(spark):
    got = core.queries()["fn_hadamard_sign"](spark, SF).collect()
    x = values(spark, "lineitem", "l_linenumber")
    assert sum(r["n"] for r in got) == len(x) and {r["x"] for r in got} == set(x) and {r["r"] for r in got} == set(range(8))
    assert all(r["s"] == (-1) ** bin(r["r"] & r["x"]).count("1") for r in got)


def test_hit_rates_of_columns(spark):
    got = core.queries()["hash_bias_table"](spark, SF).collect()
    assert len(got) == 27
    for r in got:
        x = values(spark, "lineitem", r["field"])
        p2, size, lam = sum((x.count(v) / len(x)) ** 2 for v in set(x)), 2 ** r["b"], keep_rate(r["alpha"], r["b"])
        assert r["lambda"] == pytest.approx(lam, abs=1e-6) and r["p2"] == pytest.approx(p2, abs=1e-6)
        assert r["hit_rate"] == pytest.approx(lam**2 * (p2 + (1 - p2) / size) + (1 - lam**2) / size, abs=1e-6)


def test_variants_follow_the_rows(spark, tmp_path):
    """Without rows nothing is recovered."""
    assert {r["variant"]: r["recovered"] for r in core.queries()["chain_variants"](spark, SF).collect()} == {"argmin": True, "threshold": True, "lookahead 2": True, "as printed": False}
    spark.read.parquet(f"{SF}/orders.parquet").limit(0).write.parquet(str(tmp_path / "orders.parquet"))
    assert not any(r["recovered"] for r in core.queries()["chain_variants"](spark, str(tmp_path)).collect())


def test_keep_rates_of_all_lines(spark):
    got = core.queries()["fn_lambda"](spark, SF).collect()
    assert sum(r["n"] for r in got) == len(values(spark, "lineitem", "l_quantity"))
    assert {r["alpha"] for r in got} == {q / 10 for q in values(spark, "lineitem", "l_quantity")} and {r["b"] for r in got} == set(values(spark, "lineitem", "l_linenumber"))
    assert all(r["lambda"] == pytest.approx(keep_rate(r["alpha"], r["b"]), abs=1e-6) for r in got)


def test_sequential_instances_on_lines(spark, tmp_path):
    """As many whole repetitions as there are lines for; none on a table that is too short."""
    lines = spark.read.parquet(f"{SF}/lineitem.parquet")
    got = core.queries()["hard_sequential"](spark, SF).collect()
    need = 2 * sum(r["pairs"] for r in got)
    assert len(got) == 18 and {r["reps"] for r in got} == {lines.count() // need}
    lines.limit(need - 1).write.parquet(str(tmp_path / "lineitem.parquet"))
    few = core.queries()["hard_sequential"](spark, str(tmp_path)).collect()
    assert len(few) == 18 and all(r["reps"] == 0 and r["told_apart"] is None for r in few)


def test_pair_counts_of_sampled_trees(spark):
    """Products of drawn bits, summed over tasks, are the counts of the same vectors."""
    users = spark.read.parquet(f"{SF}/orders.parquet").select(F.col("o_orderkey").alias("user_id"))
    tree = W.random_tree(70, "42")
    n, ones = W.pair_ones(users.repartition(3), tree)
    pairs = [(i, j) for i in range(70) for j in range(i, 70)]
    assert n == users.count() and (P.count_cells(W.sampled_vectors(users, tree), pairs, 2)[:, 3] == [ones[q] for q in pairs]).all()
    src, every = W.OnesSource(n, ones), P.ExactSource(W.sampled_vectors(users, tree), 2)
    some = [q for q in pairs if q[0] < q[1]]
    assert src.mi(some) == pytest.approx(every.mi(some), abs=1e-9) and src.marginals([0, 69]) == pytest.approx(every.marginals([0, 69]))
