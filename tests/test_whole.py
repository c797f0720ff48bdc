"""Queries that once worked on a part of their rows, sizes or variables work on all."""

import pytest

from veilstat import queries as core

SF = "/root/testdata/sf0.001"


def rows(spark, name):
    return core.queries()[name](spark, SF).collect()


def table(spark, name):
    return spark.read.parquet(f"{SF}/{name}.parquet")


def test_sql_lambda_all_orders(spark):
    assert {r["o_orderkey"] for r in rows(spark, "sql_lambda")} == {r[0] for r in table(spark, "orders").select("o_orderkey").collect()}


def test_edges_all_nations(spark):
    seen = {r[0] for r in table(spark, "customer").select("c_nationkey").distinct().collect()}
    n = len(seen)
    for name in ("sort_edges", "win_rank_edges"):
        got = {(r["i"], r["j"]) for r in rows(spark, name)}
        assert len(got) == n * (n - 1) // 2 and {x for e in got for x in e} == seen
    assert {r["v"] for r in rows(spark, "strongest_partner")} == seen
    assert {r["i"] for r in rows(spark, "topk_per_group")} == seen - {max(seen)}
    mi = {(r["i"], r["j"]): r["mi"] for r in rows(spark, "sort_edges")}
    assert [(r["i"], r["j"]) for r in rows(spark, "topk_neighbors")] == sorted(mi, key=lambda e: (-mi[e], e))[1:6]


def test_sign_bits_all_components(spark):
    import numpy as np

    vecs = {r["vec_id"]: np.array(r["embedding"]) > 0 for r in table(spark, "embeddings").collect()}
    x = np.array(list(vecs.values()))
    n, d = x.shape
    assert d == 64

    def h(*p):
        return -sum(v * np.log(v) for v in p if v > 0)

    mi = []
    for i in range(d):
        for j in range(i + 1, d):
            both = np.bincount(2 * x[:, i] + x[:, j], minlength=4) / n
            mi.append(h(*np.bincount(x[:, i], minlength=2) / n) + h(*np.bincount(x[:, j], minlength=2) / n) - h(*both))
    got = rows(spark, "natural_sign_bits")[0]
    assert abs(got["strongest"] - max(mi)) < 2e-6 and abs(got["total"] - sum(mi)) < 2e-6
    for r in rows(spark, "pack_bits"):
        assert r["word"] % (1 << 64) == sum(1 << i for i in range(64) if vecs[r["vec_id"]][i])


def test_pair_counts_are_run(spark):
    """Counts and slopes equal runs of the methods, one by one."""
    import numpy as np

    from veilstat.operators import structure as T
    from veilstat.operators import workloads as W
    from veilstat.operators.small_support import ExactSource
    from veilstat.queries import baselines as B

    class Asked:
        def __init__(self, n):
            src = ExactSource(W.sampled_vectors(users, W.random_tree(n, "42")), 2)
            self.known = src.mi([(i, j) for i in range(n) for j in range(i + 1, n)])
            self.h = src.marginals(list(range(n)))

        def mi(self, pairs):
            self.pairs += len(pairs)
            return {q: self.known[q] for q in pairs}

        def marginals(self, variables):
            return {i: self.h[i] for i in variables}

    def count(n, r):
        src[n].pairs = 0
        T.tree_entropy(src[n], n, 2, 0.5, 0.1, seed=f"rep{r}")
        return src[n].pairs  # questions that reached the source

    sizes, reps = (12, 30, 60), 3
    users = table(spark, "orders").selectExpr("o_orderkey AS user_id")
    src = {n: Asked(n) for n in sizes}
    want = {(n, r): count(n, r) for n in sizes for r in range(reps)}
    assert {(x["d"], x["rep"]): x["pairs"] for x in B.pair_counts(spark, B.order_sources(spark, SF, sizes), reps).collect()} == want
    got = B.slopes(spark, SF, sizes, reps).first()
    means = [sum(want[n, r] for r in range(reps)) / reps for n in sizes]
    assert abs(got["tree_slope"] - np.polyfit(np.log(sizes), np.log(means), 1)[0]) < 2e-6
    assert abs(got["all_slope"] - np.polyfit(np.log(sizes), np.log([n * (n - 1) / 2 for n in sizes]), 1)[0]) < 2e-6
    curve = {x["d"]: x["reps"] for x in rows(spark, "cost_pairs_curve")}
    assert curve == dict.fromkeys((10, 20, 50, 100, 200, 400), 100)


def test_error_curve_budgets(spark):
    """Every series at every budget; whole groups, as many as the rows allow."""
    got = {(r["series"], r["bits"]): r for r in rows(spark, "error_curve")}
    series = ["hash", *[f"hash alpha={a}" for a in ("4", "3", "2", "1", "0.5")], "raw"]
    assert set(got) == {(s, b) for s in series for b in (1000, 2000, 5000, 10000, 20000, 50000)}
    n = table(spark, "lineitem").count()
    for (s, bits), r in got.items():
        users = bits // (10 if s == "raw" else 1)
        assert n // users - (n // 1024 + 2) * 2 // users - 1 <= r["groups"] <= n // users
        assert (r["error_percent"] is None) == (r["groups"] == 0)
