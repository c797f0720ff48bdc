"""Algebra, bands and edge cases of the entropy methods."""

import math

import pytest
from pyspark.sql import functions as F

from veilstat.functions import scalars as S
from veilstat.operators import collision as C
from veilstat.operators import measures as M
from veilstat.operators import small_support as P
from veilstat.operators import structure as T
from veilstat.operators import workloads as W
from veilstat.operators.baselines import unobserved_clique
from veilstat.operators.protocol import PoolExhausted, UserPool, contacted_twice
from veilstat.plans import privacy
from veilstat.queries import structure as Q
from veilstat.queries.measures import exponential_truth

SF = "/root/testdata/sf0.01"


@pytest.mark.parametrize("alpha", [0.3, 1.0, 3.0])
def test_privacy_is_exactly_alpha(alpha):
    for b in (1, 2, 3):
        assert privacy.ratio(privacy.hash_reports(b, alpha)) == pytest.approx(alpha)
    for c in (2, 3, 8):
        assert privacy.ratio(privacy.rr_reports(c, alpha)) == pytest.approx(alpha)
        assert privacy.ratio(privacy.hadamard_reports(c, alpha)) == pytest.approx(alpha)
        assert privacy.ratio(privacy.unary_reports(c, alpha)) == pytest.approx(alpha)


@pytest.mark.parametrize("b", [1, 2, 3])
def test_collision_correction_by_enumeration(b):
    """Expected rate of equal reports over random hashes and noise, corrected, is the collision probability."""
    size, p, alpha = 1 << b, [0.5, 0.3, 0.2], 1.0
    lam = S.keep_rate(alpha, b)
    p2 = sum(x * x for x in p)
    same_hash = p2 + (1 - p2) / size
    rate = lam * lam * same_hash + (1 - lam * lam) / size
    assert (size * rate - 1) / (lam * lam * (size - 1)) == pytest.approx(p2)


def test_exponential_truth():
    q, g, c, h = exponential_truth()
    assert (q, g, c, h) == pytest.approx((0.462117, 0.537883, 0.771937, 1.040652), abs=1e-6)
    assert q == pytest.approx(math.tanh(0.5))


def test_hash_estimate_in_band_and_printed_form_out(spark):
    from veilstat.queries.collision import exponential_users

    users = exponential_users(spark, SF)
    good = C.collision_sketch(users, "user_id", ["x"]).first()
    assert abs(good["gini"] - 0.537883) < 0.02 and abs(good["collision"] / 0.771937 - 1) < 0.035
    printed = C.collision_sketch(users, "user_id", ["x"], as_printed=True).first()
    assert abs(printed["gini"] - 0.537883) > 0.05


def test_error_bands_of_figure(spark):
    from veilstat.queries.workloads import error_rows

    got = {r["series"]: r for r in error_rows(spark, SF, (None, 4.0, 1.0), groups=30).collect()}
    assert got["hash"]["mean_bits"] < got["raw"]["mean_bits"]
    assert got["hash"]["error_percent"] < got["hash alpha=4"]["error_percent"] * 1.3 < got["hash alpha=1"]["error_percent"]


def test_measures_limits(spark):
    df = spark.createDataFrame([(x % 5,) for x in range(50)], "x int")
    assert M.shannon(df, ["x"]).first()[0] == pytest.approx(math.log(5), abs=1e-6)
    assert M.tsallis(df, ["x"], 1).first()[0] == pytest.approx(math.log(5), abs=1e-6)
    assert M.renyi(df, ["x"], 1.0001).first()[0] == pytest.approx(math.log(5), abs=1e-3)
    assert M.gini(df.limit(0).union(spark.createDataFrame([(1,)] * 4, "x int")), ["x"]).first()[0] == 0.0
    with pytest.raises(ValueError):
        M.tsallis(df, ["x"], 0)
    one_null = spark.createDataFrame([(None,), (1,)], "x int")
    assert M.gini(one_null, ["x"]).first()[0] == 0.5


def test_continuity_inverse():
    for eps, c, want in ((0.1, 2, 0.0222), (0.1, 4, 0.0186), (0.1, 8, 0.0161)):
        assert M.l1_target(eps, c) == pytest.approx(want, abs=2e-4)
        assert M.continuity_bound(M.l1_target(eps, c), c) <= eps + 1e-9


def test_simplex_projection():
    p = S.project([0.6, 0.5, -0.2, 0.3])
    assert sum(p) == pytest.approx(1) and min(p) >= 0
    assert S.project([0.2, 0.3, 0.5]) == pytest.approx([0.2, 0.3, 0.5])


def test_hadamard_recovers_without_noise():
    c, alpha = 5, 50.0
    freq = [0.1, 0.2, 0.3, 0.25, 0.15]
    rows, n = P.hadamard_order(c), 1_000_000.0
    sums = {r: n / rows * sum(f * (1 - 2 * (bin(r & (x + 1)).count("1") % 2)) for x, f in enumerate(freq)) for r in range(rows)}
    assert P.hadamard_debias(sums, n, c, alpha) == pytest.approx(freq, abs=1e-6)


def test_isolated_nodes_and_paths_count_right():
    """Budgets are honoured on discovered nodes: isolated nodes are all components of their own."""

    class None_:
        def mi(self, pairs):
            return dict.fromkeys(pairs, 0.0)

    hits = T.component_indicators(T.EdgeCache(None_()), 40, [0.1], 200, 4.0, "a")
    assert 40 * sum(hits[0]) / 200 == 40

    class Path:
        def mi(self, pairs):
            return {(i, j): 1.0 if abs(i - j) == 1 else 0.0 for i, j in pairs}

    hits = T.component_indicators(T.EdgeCache(Path()), 40, [0.5], 400, 1000.0, "b")
    assert 40 * sum(hits[0]) / 400 < 4  # one component


def test_tree_method_within_eps_d_and_linear_cost():
    for d, cap in ((50, 1225), (100, 4950)):
        src = W.ClosedForm(W.random_tree(d, "42"))
        truth = T.all_pairs_entropy(W.ClosedForm(W.random_tree(d, "42")), d)
        e = T.tree_entropy(src, d, 2, 0.5, 0.1)
        assert abs(e.entropy - truth.entropy) <= 0.5 * d
        assert e.pairs < cap
    strong = T.tree_entropy(W.ClosedForm(W.random_tree(60, "3", strong=True)), 60, 2, 0.1, 0.1)
    truth = T.all_pairs_entropy(W.ClosedForm(W.random_tree(60, "3", strong=True)), 60)
    assert abs(strong.entropy - truth.entropy) <= 0.1 * 60 < truth.weight


def test_spanning_tree_against_enumeration():
    from itertools import combinations

    mi = {(i, j): ((i * 7 + j * 13) % 11) / 10 + (i + j) / 1000 for i, j in combinations(range(5), 2)}
    best = max(sum(mi[e] for e in es) for es in combinations(mi, 4) if len({x for e in es for x in e}) == 5 and T.true_components(5, {e: 1 for e in es}, 1) == 1)
    assert sum(mi[e] for e in T.kruskal(5, mi)) == pytest.approx(best)
    assert T.kruskal(5, mi) == T.prim(5, mi)


@pytest.mark.parametrize("d", [4, 7, 12])
@pytest.mark.parametrize("seed", ["a", "b", "c"])
def test_chain_recovered(d, seed):
    src = Q.ChainForm((0.5, *[0.02 + 0.08 * i / d for i in range(1, d)]))
    order, asked = T.chain_order(src, list(range(d)), seed)
    assert order == list(range(d))
    assert asked <= 1 + (d - 3) * (1 + math.ceil(math.log2(d)))


def test_star_hub_from_any_start(spark):
    mi = {(min(2, j), max(2, j)): 0.3 + j / 100 for j in (0, 1, 3, 4, 5)}

    class Star:
        def mi(self, pairs):
            return {p: mi.get(p, 0.01) for p in pairs}

    assert all(T.star_hub(Star(), 6, s)[0] == 2 for s in "abcdefgh")


def test_private_tree_beats_nothing(spark):
    pool = Q.pool(spark, SF, W.TREE6)
    e = T.all_pairs_entropy(P.PrivateSource(pool, 2, 4.0, pool.slots // 24), 6)
    exact = T.all_pairs_entropy(Q.source(spark, SF, W.TREE6), 6)
    assert abs(e.entropy - exact.entropy) < 0.35
    assert contacted_twice(pool.ledger()).isEmpty()


def test_pool_exhausted_and_disjoint(spark):
    users = spark.range(100).select(F.col("id").alias("user_id"), F.col("id").alias("slot"))
    pool = UserPool(users, 100)
    pool.allot([1, 2], 30)
    with pytest.raises(PoolExhausted):
        pool.allot([3, 4], 30)


def test_hash_edge_cases(spark):
    empty = spark.createDataFrame([], "user_id long, x string")
    r = C.collision_sketch(empty, "user_id", ["x"]).first()
    assert r["n_pairs"] == 0 and r["gini"] is not None
    one = C.collision_sketch(spark.createDataFrame([(1, "a")], "user_id long, x string"), "user_id", ["x"]).first()
    assert one["n_pairs"] == 0
    same = C.collision_sketch(spark.createDataFrame([(i, None) for i in range(101)], "user_id long, x string"), "user_id", ["x"]).first()
    assert same["n_pairs"] == 50 and same["gini"] == 0.0
    with pytest.raises(ValueError):
        C.collision_sketch(empty, "user_id", ["x"], b=0)
    with pytest.raises(ValueError):
        C.collision_sketch(empty, "user_id", ["x"], alpha=0.0)


def test_partitioning_does_not_change_reports(spark):
    df = spark.read.parquet(f"{SF}/orders.parquet").select(F.col("o_orderkey").alias("user_id"), "o_orderstatus")
    got = {C.collision_sketch(df.repartition(n), "user_id", ["o_orderstatus"], 1, 2.0).first() for n in (1, 7, 40)}
    assert len(got) == 1


def test_raw_value_does_not_cross_the_permuted_shuffle(spark):
    df = spark.range(1000).select(F.col("id").alias("user_id"), F.col("id").cast("string").alias("secret"))
    paired = C.assign_pairs(df, "user_id", "pub", pairing="permute", rows=1000)
    plan = C.match(C.reports(paired, "user_id", ["secret"], 1, 1.0, "pub", "noise"))._jdf.queryExecution().executedPlan().toString()
    above = plan[: plan.index("Exchange hashpartitioning(bucket")] if "Exchange hashpartitioning(bucket" in plan else plan.split("Exchange")[0]
    assert "secret" not in above


def test_unobserved_clique():
    pairs = [(i, j) for i in range(6) for j in range(6, 12)][:18]
    clique = unobserved_clique(12, pairs)
    assert len(clique) >= 6 and not any(set(p) <= set(clique) for p in pairs)
