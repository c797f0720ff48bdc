"""Alphabet-bound baselines and cost and accuracy measures."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..functions.coins import draw
from ..functions.scalars import keep_rate, tidy as tidy_col
from ..operators import baselines as B
from ..operators import collision as C
from ..operators import measures as M
from ..operators import structure as T
from ..operators import workloads as W
from ..operators.small_support import rr_keep
from ..plans import bounds, privacy
from ..registry import query
from ..sources.tables import line_users, load
from .protocol import ALPHA, _USERS, _project_sql, coded, rr_sql
from .sqltext import coin, tidy


def _freq(c: int, alpha: float) -> str:
    p = rr_keep(c, alpha)
    q = (1 - p) / (c - 1)
    return f"r AS (SELECT {rr_sql(c, alpha, 'x')} AS report, CAST(count(*) AS DOUBLE) AS n FROM u GROUP BY 1), fr AS (SELECT report, (n / sum(n) OVER () - {q!r}::DOUBLE) / {p - q!r}::DOUBLE AS f FROM r)"


@query("plugin_gini_ldp", f"WITH {_USERS}, {_freq(3, ALPHA)}, {_project_sql(3, 'fr')} SELECT {tidy('1 - sum(p * p)')} AS gini FROM pr")
def plugin_gini_ldp(spark, d):
    """Private histogram, then plug-in: the cost grows with the alphabet."""
    return spark.createDataFrame([(round(B.plugin_gini(coded(spark, d), "user_id", "x", 3, ALPHA), 6),)], "gini double")


_F = 1 / (1 + math.exp(ALPHA / 2))
_K = math.exp(ALPHA) / (1 + math.exp(ALPHA))
_HALF = f"{coin('pub', 'half', 'user_id')} < 0.5"
_BITS = " UNION ALL ".join(f"SELECT {s} AS report, (avg(CASE WHEN {coin('noise', f'bit{s}', 'user_id')} < {_F!r}::DOUBLE THEN CAST(x <> {s} AS INT) ELSE CAST(x = {s} AS INT) END) - {_F!r}::DOUBLE) / {1 - 2 * _F!r}::DOUBLE AS f FROM u WHERE {_HALF}" for s in range(3))
_SENT = f"""a AS (SELECT {coin('noise', 'scale', 'user_id')} < least(p, 1) AS one, {coin('noise', 'answer', 'user_id')} < {_K!r}::DOUBLE AS kept FROM u JOIN pr ON pr.report = x WHERE NOT ({_HALF}))"""


@query("two_stage_gini", f"WITH {_USERS}, fr AS ({_BITS}), {_project_sql(3, 'fr')}, {_SENT} SELECT {tidy(f'1 - (avg(CASE WHEN kept = one THEN 1.0 ELSE 0.0 END) - {1 - _K!r}::DOUBLE) / {2 * _K - 1!r}::DOUBLE')} AS gini FROM a")
def two_stage_gini(spark, d):
    return spark.createDataFrame([(round(B.two_stage_gini(coded(spark, d), "user_id", "x", 3, ALPHA), 6),)], "gini double")


#: Repetitions of the tree method at every size.
REPS = 100


def order_sources(spark, d, sizes) -> dict:
    """Informations of random trees of these sizes, each sampled on every row of orders."""
    users = load(spark, d, "orders", F.col("o_orderkey").alias("user_id"))
    return {n: W.OnesSource(*W.pair_ones(users, W.random_tree(n, "42"))) for n in sizes}


def pair_counts(spark, sources: dict, reps: int = REPS):
    """(d, rep, pairs) of the tree method on sampled random trees; repetitions are dealt over tasks."""
    told = spark.sparkContext.broadcast(sources)

    def run(batches):
        for batch in batches:
            yield batch.assign(pairs=[T.tree_entropy(told.value[n], n, 2, 0.5, 0.1, seed=f"rep{r}").pairs for n, r in zip(batch["d"], batch["rep"], strict=True)])

    asked = [(n, r) for n in sources for r in range(reps)]
    tasks = spark.sparkContext.parallelize(sorted(asked, key=lambda x: (x[1] % 16, x)), 16)
    return spark.createDataFrame(tasks, "d int, rep int").mapInPandas(run, "d int, rep int, pairs long")


@query("cost_pairs_curve")
def cost_pairs_curve(spark, d):
    """Pair estimates by size, mean over repetitions, on random trees sampled on orders."""
    n = F.col("d").cast("double")
    mean = pair_counts(spark, order_sources(spark, d, (10, 20, 50, 100, 200, 400))).groupBy("d").agg(F.count("*").cast("int").alias("reps"), F.avg("pairs").alias("pairs_mean"))
    return mean.select("d", "reps", "pairs_mean", (n * n).alias("pairs_ordered"), (n * (n - 1) / 2).alias("pairs_distinct"))


def slopes(spark, d, sizes=(50, 100, 200, 400, 800), reps: int = REPS):
    sources = order_sources(spark, d, sizes)
    every = [(n, T.all_pairs_entropy(src, n).pairs) for n, src in sources.items()]
    t = pair_counts(spark, sources, reps).groupBy("d").agg(F.avg("pairs").alias("tree")).join(F.broadcast(spark.createDataFrame(every, "d int, every long")), "d")
    return t.agg(tidy_col(F.regr_slope(F.ln("tree"), F.ln("d"))).alias("tree_slope"), tidy_col(F.regr_slope(F.ln("every"), F.ln("d"))).alias("all_slope"))


@query("cost_slope")
def cost_slope(spark, d):
    """Log-log slopes of pair counts, of the tree method and of all pairs, as both run on random trees sampled on orders."""
    return slopes(spark, d)


@query("cost_space", "SELECT 'hash' AS method, 2::BIGINT AS live_rows UNION ALL SELECT 'histogram', count(DISTINCT l_quantity) FROM lineitem UNION ALL SELECT 'two_stage', count(DISTINCT l_quantity) FROM lineitem")
def cost_space(spark, d):
    """Server state: two counters for the hash method, a cell per symbol for its rivals."""
    users = line_users(spark, d, "l_quantity")
    state = C.match(C.reports(C.assign_pairs(users, "user_id", "pub"), "user_id", ["l_quantity"], 1, None, "pub", "noise"))
    counters = state.select(F.explode(F.array(*[F.col(c).cast("long") for c in state.columns]))).agg(F.count("*").alias("live_rows"))
    cells = users.groupBy("l_quantity").agg(F.count("*").alias("n"))  # a counter for each symbol that a report may name
    bits = users.groupBy("l_quantity").agg(F.sum(F.lit(1)).alias("ones"))  # a sum for each bit of the first half's noise
    kinds = (("hash", counters), ("histogram", cells.agg(F.count("*").alias("live_rows"))), ("two_stage", bits.agg(F.count("*").alias("live_rows"))))
    out = None
    for name, n in kinds:
        one = n.select(F.lit(name).alias("method"), "live_rows")
        out = one if out is None else out.unionByName(one)
    return out


_AUDIT = [(m, c, a) for m in ("hash", "rr", "hadamard", "unary") for c in (2, 4) for a in (0.5, 1.0, 2.0)]


@query("privacy_ratio_audit", f"SELECT method, CAST(size AS INT) AS size, alpha::DOUBLE AS alpha, round(alpha::DOUBLE, 6) + 0.0 AS spent FROM (VALUES {', '.join(str(x) for x in _AUDIT)}) AS t(method, size, alpha)")
def privacy_ratio_audit(spark, d):
    """Largest log ratio over all inputs and reports, by enumeration: exactly alpha."""
    table = {"hash": lambda c, a: privacy.hash_reports(c.bit_length() - 1, a), "rr": privacy.rr_reports, "hadamard": privacy.hadamard_reports, "unary": privacy.unary_reports}
    return spark.createDataFrame([(m, c, a, round(privacy.ratio(table[m](c, a)), 6)) for m, c, a in _AUDIT], "method string, size int, alpha double, spent double")


_BASKETS, _EPS = ("l_linenumber", "l_quantity", "l_suppkey"), (0.1, 0.5)
_HASH_COLUMNS, _HASH_BITS = ("l_linestatus", "l_quantity", "l_suppkey"), (1, 2, 4)
_LN10, _HASH_OVER, _SUPPORT_OVER = repr(math.log(1 / 0.1)), repr(0.5**4 * 0.1**2), repr(0.1 * 0.1 * 0.5 * 0.5)


@query(
    "bounds_table",
    f"""WITH v AS ({' UNION ALL '.join(f"SELECT '{x}' AS field, count(DISTINCT {x})::INT AS d FROM lineitem" for x in _BASKETS)}),
      s AS (SELECT field, (SELECT count(DISTINCT l_orderkey) FROM lineitem) AS users, d, eps, d * ln(d / 0.1::DOUBLE) / 0.25::DOUBLE AS base FROM v, (VALUES {', '.join(f'({e}::DOUBLE)' for e in _EPS)}) AS t(eps) WHERE d > 0)
      SELECT field, users, d, eps, round(base / pow(eps, 5), 2) AS tree, round(base / pow(eps, 5) * ln(2 / eps) * ln(10::DOUBLE), 2) AS tree_full, round(base / (eps * eps), 2) AS chain, round(base / (eps * eps), 2) AS star,
             d::DOUBLE * d AS lower_fixed, round(d / eps, 2) AS lower_adaptive, eps <= 0.5 AS in_theorem FROM s""",
)
def bounds_table(spark, d):
    """Users that the structural methods ask for at alpha 1/2 and delta 1/10, and the lower bounds in pairs, on baskets.

    An order is a user; a variable tells whether a value of the column is among its lines.
    """
    count = lambda c: load(spark, d, "lineitem", c).agg(F.count_distinct(c)).first()[0]
    users, rows = count("l_orderkey"), []
    for c in _BASKETS:
        n = count(c)
        for eps in _EPS if n else ():
            told = (bounds.tree(n, eps, 0.5, 0.1), bounds.tree(n, eps, 0.5, 0.1, True), bounds.chain(n, eps, 0.5, 0.1), bounds.star(n, eps, 0.5, 0.1), bounds.lower_pairs_noninteractive(n), bounds.lower_pairs_sequential(n, eps))
            rows.append((c, users, n, eps, *[round(x, 2) for x in told], bounds.in_theorem(0.5, eps)))
    return spark.createDataFrame(rows, "field string, users long, d int, eps double, tree double, tree_full double, chain double, star double, lower_fixed double, lower_adaptive double, in_theorem boolean")


@query(
    "bounds_hash",
    f"""WITH c AS ({' UNION ALL '.join(f"SELECT '{x}' AS field, CAST(count(*) AS DOUBLE) AS n FROM lineitem GROUP BY {x}" for x in _HASH_COLUMNS)}),
      g AS (SELECT field, sum(n) AS users, count(*) AS k, sum(n * n) / (sum(n) * sum(n)) AS p2 FROM c GROUP BY field),
      s AS (SELECT *, pow(2::DOUBLE, 4 * b) AS base FROM g, (VALUES {', '.join(f'({b}::INT)' for b in _HASH_BITS)}) AS t(b))
      SELECT field, CAST(users AS BIGINT) AS users, b, k, {tidy('p2')} AS p2, base * greatest(1 - (1 - p2), pow(2::DOUBLE, -b), 0.1::DOUBLE) * {_LN10}::DOUBLE / {_HASH_OVER}::DOUBLE AS gini,
             base * k * k * {_LN10}::DOUBLE / {_HASH_OVER}::DOUBLE AS collision, k::DOUBLE * k * {_LN10}::DOUBLE / {_SUPPORT_OVER}::DOUBLE AS small_support,
             {tidy('(exp(0.5::DOUBLE) - 1) / (pow(2::DOUBLE, b) + exp(0.5::DOUBLE) - 1)')} AS keep FROM s""",
)
def bounds_hash(spark, d):
    """Users that columns of lineitem ask of the hash method and of a private histogram, from their own support and Gini entropy, at alpha 1/2, eps and delta 1/10."""
    rows = []
    for c in _HASH_COLUMNS:
        r = M.histogram(load(spark, d, "lineitem", c), [c]).agg(F.coalesce(F.sum("n"), F.lit(0.0)).cast("long").alias("users"), F.count("*").alias("k"), M.p2_of().alias("p2")).first()
        if not r["k"]:
            continue
        for b in _HASH_BITS:
            told = (bounds.gini(b, 1 - r["p2"], 0.1, 0.5, 0.1), bounds.collision(b, r["k"], 0.1, 0.5, 0.1), float(bounds.small_support(r["k"], 0.1, 0.5, 0.1)))
            rows.append((c, r["users"], b, r["k"], round(r["p2"], 6), *told, round(keep_rate(0.5, b), 6)))
    return spark.createDataFrame(rows, "field string, users long, b int, k long, p2 double, gini double, collision double, small_support double, keep double")


@query("tree_quality")
def tree_quality(spark, d):
    """Error of the tree method and of the trivial estimator (no weight) on weak and strong trees."""
    rows = []
    for strong in (False, True):
        for eps in (0.5, 0.25):
            n = 50
            src = W.ClosedForm(W.random_tree(n, "7", strong=strong))
            truth = T.all_pairs_entropy(W.ClosedForm(W.random_tree(n, "7", strong=strong)), n)
            for how in ("floor", "midpoint"):
                e = T.tree_entropy(src, n, 2, eps, 0.1, seed=f"q{draw('q', 'x', n):.3f}", quantisation=how)
                rows.append(("strong" if strong else "weak", eps, how, truth.weight / n, abs(e.entropy - truth.entropy) / n, truth.weight / n, abs(e.entropy - truth.entropy) <= eps * n))
    return spark.createDataFrame(rows, "trees string, eps double, quantisation string, weight_per_d double, error_per_d double, trivial_error_per_d double, within boolean")
