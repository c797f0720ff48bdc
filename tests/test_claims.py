"""Claims on sampled data, variants, sample sizes, seeded pairing, and the guarantees of streams."""

import math

import pytest
from pyspark.sql import functions as F

from veilstat.operators import collision as C
from veilstat.operators import small_support as P
from veilstat.operators import structure as T
from veilstat.operators import workloads as W
from veilstat.operators.protocol import PoolExhausted, UserPool
from veilstat.queries import claims
from veilstat.queries import structure as Q
from veilstat.streaming import pairs as S

SF = "/root/testdata/sf0.01"


def test_sampled_trees_within_eps_d(spark):
    got = claims.sampled_curve(spark, SF, (10, 50)).collect()
    assert all(r["within"] for r in got)
    by = {(r["d"], r["method"]): r for r in got}
    assert by[50, "tree"]["pairs"] < by[50, "all pairs"]["pairs"] == 1225
    assert by[50, "all pairs"]["error_per_d"] < 0.005


def test_sampled_vectors_follow_the_tree(spark):
    tree = W.random_tree(30, "5")
    src = P.ExactSource(W.sampled_vectors(spark.range(40_000).select(F.col("id").alias("user_id")), tree), 2)
    closed = W.ClosedForm(tree)
    pairs = [(i, j) for i in range(30) for j in range(i + 1, 30)]
    seen, want = src.mi(pairs), closed.mi(pairs)
    assert max(abs(seen[p] - want[p]) for p in pairs) < 0.02
    some = [(0, 3), (4, 9)]  # question by question, and all pairs at once
    assert src.mi(some) == pytest.approx({p: seen[p] for p in some})


def test_good_estimates(spark):
    got = claims.good_estimates(spark, SF).collect()
    assert {r["method"] for r in got} == {"tree", "star"} and all(r["within"] and r["alpha"] < 1 for r in got)
    assert all(r["users_pair"] == P.users_needed(claims.GOOD_EPS / (2 if r["method"] == "tree" else 1) / 3, 4, r["alpha"], claims.DELTA / (16 if r["method"] == "tree" else 12)) for r in got)


def test_too_few_users_raise(spark):
    pool = UserPool.of(W.sampled_vectors(spark.range(1000).select(F.col("id").alias("user_id")), W.random_tree(4, "1")), "user_id", "p")
    with pytest.raises(PoolExhausted):
        P.tree_source(pool, 4, 2, 0.9, 0.5, 0.1).mi([(0, 1)])


def test_many_questions_are_a_table_not_a_plan(spark):
    """499 500 questions on 1000 variables: the plan has a join, not a literal for each."""
    questions = [(i, j) for i in range(1000) for j in range(i + 1, 1000)]
    users = spark.range(2000).select(F.col("id").alias("user_id"), (F.col("id") * 524).alias("slot"), F.array_repeat(F.lit(1), 1000).alias("x"))
    table = P.question_table(spark, questions)
    plan = UserPool(users).allot(questions, 2)[1].join(table, "query_id").select(P.cell_of(2, 2).alias("cell"))
    assert len(plan._jdf.queryExecution().optimizedPlan().toString()) < 20_000
    counts = P.count_cells(users, questions, 2)
    assert counts.shape == (499_500, 4) and (counts[:, 3] == 2000).all()
    assert P.PrivateSource(UserPool(users), 2, None, 2).mi(questions[:50])[(0, 1)] == 0.0


def test_split_batches_and_bias_correction(spark):
    users = W.sampled_vectors(spark.range(300_000).select(F.col("id").alias("user_id")), [{"node": 0, "parent": -1, "p": 0.5, "r": 0.0}, {"node": 1, "parent": 0, "p": 0.5, "r": 0.2}])
    truth = W.ClosedForm([{"node": 0, "parent": -1, "p": 0.5, "r": 0.0}, {"node": 1, "parent": 0, "p": 0.5, "r": 0.2}]).mi([(0, 1)])[(0, 1)]
    pool = UserPool.of(users, "user_id", "s")
    got = P.PrivateSource(pool, 2, None, pool.slots // 4, split_batches=True, bias_correction=True).mi([(0, 1)])[(0, 1)]
    assert abs(got - truth) < 0.02 and len(pool.batches) == 3
    assert P.corrected_entropy([0.5, 0.5, 0.0], 100) == pytest.approx(math.log(2) + 1 / 200)


@pytest.mark.parametrize("n", [1, 2, 3, 1000, 1024, 1025])
def test_seeded_permutation(spark, n):
    x = spark.range(n).select(F.col("id"), *[C.permuted(F.col("id"), n, s).alias(s) for s in ("pub", "other")]).toPandas()
    for s in ("pub", "other"):
        assert sorted(x[s].dropna().astype(int)) == list(range(n)) or n - x[s].count() <= 1
    if n >= 1000:
        assert (x["pub"] != x["other"]).mean() > 0.9


def test_permuted_pairs_on_periodic_rows(spark):
    df = spark.range(1000).select(F.col("id").alias("user_id"), (F.col("id") % 2).alias("v"))
    for seed in ("pub", "a", "b"):
        r = C.collision_sketch(df, "user_id", ["v"], 1, None, public=seed, pairing="permute").first()
        assert r["n_pairs"] >= 499 and abs(r["gini"] - 0.5) < 0.2
    with pytest.raises(Exception, match="0 to n - 1"):
        C.collision_sketch(df.withColumn("user_id", F.col("user_id") + 7), "user_id", ["v"], pairing="permute").first()


def test_tree_variants():
    tree = W.random_tree(40, "7", strong=True)
    run = lambda **how: T.tree_entropy(W.ClosedForm(tree), 40, 2, 0.25, 0.1, **how)
    base, anew, printed = run(), run(reuse=False), run(as_printed=True)
    assert anew.entropy == base.entropy and anew.pairs > 5 * base.pairs
    truth = T.all_pairs_entropy(W.ClosedForm(tree), 40).entropy
    assert abs(base.entropy - truth) <= 0.25 * 40 < abs(printed.entropy - truth)
    assert run(min_level=2).weight >= base.weight


def test_chain_variants():
    src = Q.ChainForm((0.5, *[0.02 + 0.008 * i for i in range(1, 10)]))
    plain, ahead = (T.TripleCache(src) for _ in range(2))
    a = T.chain_order(plain, list(range(10)))
    b = T.chain_order(ahead, list(range(10)), lookahead=2)
    assert a[0] == b[0] == list(range(10)) and ahead.jobs < plain.jobs and b[1] >= a[1]
    assert T.chain_order(src, list(range(10)), decision="threshold", eps=1e-9)[0] == a[0]
    assert T.chain_order(src, list(range(10)), decision="as_printed", eps=1e-9)[0] != a[0]
    with pytest.raises(ValueError, match="separated"):
        T.chain_order(src, list(range(10)), decision="threshold", eps=10.0)
    mi = src.mi([(i, j) for i in range(10) for j in range(i + 1, 10)])
    assert 0 < T.check_separation(mi, 10) < 0.2


def test_best_edge_rounds_equal_kruskal(spark):
    mi = {(i, j): ((i * 37 + j * 101) % 997) / 997 for i in range(40) for j in range(i + 1, 40)}
    got = T.boruvka(spark.createDataFrame([(i, j, w) for (i, j), w in mi.items()], "i int, j int, mi double")).collect()
    assert sorted((r["i"], r["j"]) for r in got) == T.kruskal(40, mi)


# Streams

EVENTS = "event_id long, ts timestamp, event_type string"


def run(spark, tmp, name, files, make, mode="append", checkpoint=None):
    """(rows, rows that came too late) of a stream of files of (id, minute, type), run to their end."""
    folder = tmp / f"{name}-in"
    folder.mkdir(exist_ok=True)
    for k, rows in enumerate(files):
        at = folder / f"f{len(list(folder.iterdir())):04d}"
        df = spark.createDataFrame([(i, m * 60, t) for i, m, t in rows], "event_id long, s long, event_type string")
        df.select("event_id", F.timestamp_seconds("s").alias("ts"), "event_type").coalesce(1).write.parquet(str(at))
    import os
    import time

    for k, x in enumerate(sorted(folder.iterdir())):  # files are taken by their time of change
        for f in x.iterdir():
            os.utime(f, (time.time() - 1000 + k, time.time() - 1000 + k))
    events = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", 1).parquet(str(folder / "f*"))
    out, at = str(tmp / f"{name}-out"), str(checkpoint or tmp / f"{name}-at")
    q = make(events).writeStream.format("parquet").option("path", out).option("checkpointLocation", at).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    late = sum(op["numRowsDroppedByWatermark"] for p in q.recentProgress for op in p["stateOperators"])
    rows = spark.read.parquet(out).collect()
    return rows, late


def counts(events):
    return S.windowed_counts(events, "event_type", "1 hour").select(F.unix_timestamp("w.start").alias("start"), "event_type", "n")


def test_rows_behind_the_watermark_are_counted_not_added(spark, tmp_path):
    files = [[(1, 5, "a"), (2, 10, "a")], [(3, 300, "a")], [(5, 310, "a")], [(4, 6, "a"), (7, 320, "a")], [(6, 900, "b")]]
    rows, late = run(spark, tmp_path, "late", files, counts)
    assert {(r["start"], r["n"]) for r in rows} == {(0, 2), (300 * 60, 3)} and late == 1


def test_restart_goes_on_from_the_checkpoint(spark, tmp_path):
    files = [[(1, 5, "a"), (2, 10, "b")], [(3, 70, "a"), (7, 20, "a")], [(4, 130, "a"), (5, 135, "a")], [(6, 900, "b")]]
    whole, _ = run(spark, tmp_path, "whole", files, counts)
    run(spark, tmp_path, "parts", files[:2], counts)
    parts, _ = run(spark, tmp_path, "parts", files[2:], counts)  # the same folders, source and checkpoint
    assert sorted(map(tuple, parts)) == sorted(map(tuple, whole)) and len(whole) >= 3


def test_order_of_arrival_does_not_change_pairs(spark, tmp_path):
    import random

    rows = [(i, 1 + i % 50, "ab"[i * 7 % 3 == 0]) for i in range(120)]
    seen = set()
    for k in range(2):
        random.Random(k).shuffle(rows)
        files = [rows[i : i + 40] for i in range(0, 120, 40)]
        got, _ = run(spark, tmp_path, f"order{k}", files, lambda e: S.match_with_state(S.pair_reports(e, "event_id", "event_type")))
        seen.add(tuple(sorted(map(tuple, got))))
    assert len(seen) == 1 and len(next(iter(seen))) == 60


def test_pairs_that_wait_too_long_are_dropped(spark, tmp_path):
    files = [[(0, 5, "a"), (2, 6, "a"), (3, 7, "a")], [(10, 5000, "a")], [(11, 5001, "a")], [(12, 5002, "a")]]
    rows, _ = run(spark, tmp_path, "wait", files, lambda e: S.match_with_state(S.pair_reports(e, "event_id", "event_type"), wait=3_600_000))
    assert sorted((r["pair"], r["hit"] >= 0) for r in rows) == [(0, False), (1, True), (5, True)]
