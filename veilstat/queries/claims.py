"""The claims on the given tables: random trees sampled on rows, estimates sized by the bounds, hard instances, sizes and variants."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..functions.coins import draw
from ..functions.scalars import entropy, tidy as tidy_col
from ..operators import collision as C
from ..operators import structure as T
from ..operators import workloads as W
from ..operators.protocol import UserPool
from ..operators.small_support import CountedSource, ExactSource, star_source, tree_source
from ..registry import query
from ..sources.tables import line_users, load, ready_to_checkpoint
from .collision import sketch_sql, symbols
from .measures import mi_sql
from .sqltext import KEY, coin, counts, h, tidy
from .structure import _CHAIN, row, tree_sql, vectors_sql

# Random trees on lineitem rows

SIZE, SEED = 10, "42"
EPS, DELTA = 0.5, 0.1
LEVELS, REPS = math.ceil(2 * math.log(2) / EPS), math.ceil(math.log(1 / DELTA) / EPS**2)
_V = [f"v{i}" for i in range(SIZE)]


def _tree_sql() -> str:
    """Vectors of the random tree, drawn by coin for each row: parents before children."""
    tree = W.random_tree(SIZE, SEED)
    p = {t["node"]: t["p"] for t in tree}
    steps, last = [f"t_ AS (SELECT {KEY} AS user_id FROM lineitem)"], "t_"
    for t in tree:
        i, up = t["node"], t["parent"]
        zero, one = W.conditional(p[up], p[i], t["r"]) if up >= 0 else (p[i], p[i])
        chance = f"CASE WHEN v{up} = 1 THEN {one!r}::DOUBLE ELSE {zero!r}::DOUBLE END" if up >= 0 else f"{p[i]!r}::DOUBLE"
        steps.append(f"t{i} AS (SELECT *, CAST({coin('w1', f'x{i}', 'user_id')} < {chance} AS INT) AS v{i} FROM {last})")
        last = f"t{i}"
    marginals = " UNION ALL ".join(f"SELECT {i} AS i, (SELECT {h()} FROM ({counts('v', x)})) AS h" for i, x in enumerate(_V))
    return f"WITH RECURSIVE {', '.join(steps)}, v AS (SELECT * FROM {last}), {mi_sql('v', _V)}, marginals AS ({marginals})"


def _searches() -> str:
    z = coin("pub", "z", "m", "r")
    return f"""
      dir AS (SELECT i AS a, j AS b, mi FROM edges UNION ALL SELECT j, i, mi FROM edges),
      lv AS (SELECT unnest(range(1, {LEVELS + 1})) AS m),
      comp(m, a, b) AS (SELECT m, n, n FROM lv, (SELECT unnest(range({SIZE})) AS n) UNION SELECT c.m, c.a, e.b FROM comp AS c JOIN dir AS e ON e.a = c.b AND e.mi >= {EPS} * c.m),
      size AS (SELECT m, a, count(*) AS s FROM comp GROUP BY 1, 2),
      runs AS (SELECT m, floor(1 / {z}) AS z, CAST(floor({coin('pub', 'start', 'm', 'r')} * {SIZE}) AS INT) AS a FROM lv, (SELECT unnest(range(1, {REPS + 1})) AS r)),
      counted AS (SELECT runs.m, {SIZE} * avg(CASE WHEN s <= least(z, {2 / EPS}) THEN 1 ELSE 0 END) AS estimate FROM runs JOIN size ON size.m = runs.m AND size.a = runs.a GROUP BY runs.m)"""


def sampled(spark, d):
    return ExactSource(W.tree_vectors(line_users(spark, d), W.random_tree(SIZE, SEED)).select("x").cache(), 2)


@query("tree_sampled_allpairs", f"{_tree_sql()}, {tree_sql()} SELECT {tidy('(SELECT sum(h) FROM marginals)')} AS marginals, {tidy('(SELECT sum(mi) FROM tree)')} AS weight, {tidy('(SELECT sum(h) FROM marginals) - (SELECT sum(mi) FROM tree)')} AS entropy, {SIZE * (SIZE - 1) // 2}::BIGINT AS pairs")
def tree_sampled_allpairs(spark, d):
    """All pairs on a random tree of ten variables, one vector a lineitem row."""
    e = T.all_pairs_entropy(sampled(spark, d), SIZE)
    return spark.createDataFrame([(round(e.marginals, 6), round(e.weight, 6), round(e.entropy, 6), e.pairs)], "marginals double, weight double, entropy double, pairs long")


@query("tree_sampled_method", f"{_tree_sql()}, {_searches()} SELECT {tidy('s')} AS marginals, {tidy('w')} AS weight, {tidy('s - w')} AS entropy FROM (SELECT (SELECT sum(h) FROM marginals) AS s, (SELECT {EPS} * sum({SIZE} - estimate) FROM counted) AS w)")
def tree_sampled_method(spark, d):
    """The sub-linear method on the same vectors."""
    e = T.tree_entropy(sampled(spark, d), SIZE, 2, EPS, DELTA)
    return row(spark, marginals=round(e.marginals, 6), weight=round(e.weight, 6), entropy=round(e.entropy, 6))


def sampled_curve(spark, d, sizes=(10, 20, 50, 100), eps: float = EPS):
    rows = []
    ready_to_checkpoint(spark)
    for n in sizes:
        tree = W.random_tree(n, SEED)
        users = W.sampled_vectors(line_users(spark, d), tree).checkpoint()  # asked many times
        truth = T.all_pairs_entropy(W.ClosedForm(tree), n).entropy
        for how in ("tree", "all pairs"):
            src = ExactSource(users, 2)
            e = T.tree_entropy(src, n, 2, eps, DELTA) if how == "tree" else T.all_pairs_entropy(src, n)
            rows.append((n, how, e.pairs, n * n, e.entropy, truth, abs(e.entropy - truth) / n, abs(e.entropy - truth) <= eps * n, e.jobs))
    return spark.createDataFrame(rows, "d int, method string, pairs long, pairs_ordered long, entropy double, truth double, error_per_d double, within boolean, jobs long")


@query("tree_sampled_curve")
def tree_sampled_curve(spark, d):
    """Pairs asked for and errors of both methods on random trees of 10 to 100 variables sampled on lineitem rows."""
    return sampled_curve(spark, d)


# Estimates that are good: users from the bounds, privacy inside the theorems' range

GOOD_EPS, GOOD_ALPHA = 0.5, 0.9


def good_pool(spark, d, model, make, n: int, arities: dict[int, int]):
    """(pool, source) with as many virtual users per lineitem row as the questions of a run need, and a tenth more."""
    parents, chances = model
    need = sum(make(None).users(a) * k for a, k in arities.items())
    users = line_users(spark, d)
    copies = max(1, math.ceil(1.1 * need / max(1, users.count())))
    users = users.select(F.explode(F.sequence(F.lit(1), F.lit(copies))).alias("c"), "user_id").select(F.concat_ws("#", "user_id", "c").alias("user_id"))
    tree = [{"node": i, "parent": parents[i], "p": 0.5, "r": 0.0 if parents[i] < 0 else 0.25 - chances[i] / 2} for i in W.tree_order(parents)]
    pool = UserPool.of(W.sampled_vectors(users, tree), "user_id", "pool")
    return pool, make(pool), W.ClosedForm(tree)


@query("good_estimates")
def good_estimates(spark, d):
    """Private tree and star runs whose every answer has the users that its bound asks for; errors against eps * d."""
    n, rows = 4, []
    tree, star = ((-1, 0, 0, 1), (0.5, 0.05, 0.1, 0.15)), ((-1, 0, 0, 0), (0.5, 0.05, 0.12, 0.2))
    runs = (
        ("tree", tree, lambda p: tree_source(p, n, 2, GOOD_ALPHA, GOOD_EPS, DELTA), {1: n, 2: n * (n - 1) // 2}, lambda s: T.tree_entropy(s, n, 2, GOOD_EPS, DELTA)),
        ("star", star, lambda p: star_source(p, n, 2, GOOD_ALPHA, GOOD_EPS, DELTA), {1: n, 2: 2 * n - 3}, lambda s: T.star_entropy(s, n)),
    )
    for name, model, make, arities, run in runs:
        pool, source, closed = good_pool(spark, d, model, make, n, arities)
        truth = T.all_pairs_entropy(closed, n).entropy
        e = run(source)
        rows.append((name, n, GOOD_ALPHA, source.users(2), source.users(1), e.pairs, e.entropy, truth, abs(e.entropy - truth), GOOD_EPS * n, abs(e.entropy - truth) <= GOOD_EPS * n))
    return spark.createDataFrame(rows, "method string, d int, alpha double, users_pair long, users_single long, pairs long, entropy double, truth double, error double, allowed double, within boolean")


# Hard instances

HARD, HARD_FLIP = 8, 0.02
_SEEN = [(i, j) for i in range(HARD // 2) for j in range(HARD // 2, HARD)]


def _hard_sql() -> str:
    arms = []
    for case in ("equal", "independent"):
        own = [f"CAST({coin('hard', f'x{i}', 'o_orderkey')} < 0.5 AS INT)" for i in range(HARD)]
        if case == "equal":
            own[1 : HARD // 2] = [f"({own[0]} + CAST({coin('hard', f'x{i}', 'o_orderkey')} < {HARD_FLIP} AS INT)) % 2" for i in range(1, HARD // 2)]
        vectors = ", ".join(f"{c} AS v{i}" for i, c in enumerate(own))
        names = [f"v{i}" for i in range(HARD)]
        marginals = " UNION ALL ".join(f"SELECT (SELECT {h()} FROM ({counts('v', x)})) AS h" for x in names)
        seen = ", ".join(map(str, _SEEN))
        joint = h() + f" FROM ({counts('v', *names)})"
        arms.append(f"SELECT * FROM (WITH RECURSIVE v AS (SELECT {vectors} FROM orders), {mi_sql('v', names).replace('edges AS (', 'every AS (')}, edges AS (SELECT * FROM every WHERE (i, j) IN ({seen})), marginals AS ({marginals}), {tree_sql()} SELECT '{case}' AS instance, {len(_SEEN)}::BIGINT AS observed, {tidy('(SELECT sum(h) FROM marginals) - (SELECT sum(mi) FROM tree)')} AS estimate, {tidy(f'(SELECT {joint})')} AS joint)")
    return " UNION ALL ".join(arms)


@query("hard_clique", _hard_sql())
def hard_clique(spark, d):
    """A fixed plan that observes no pair inside half of the variables, run on two instances.

    In one that half follows a single coin (flipped at HARD_FLIP, so that no two pairs tie),
    in the other all are independent: the plan's estimates agree, the samples' entropies do not.
    """
    from ..functions.coins import uniform
    from ..operators import measures as M

    rows = []
    o = load(spark, d, "orders", "o_orderkey")
    for case in ("equal", "independent"):
        coins = [uniform("hard", f"x{i}", F.col("o_orderkey")) for i in range(HARD)]
        own = [(c < 0.5).cast("int") for c in coins]
        if case == "equal":
            own[1 : HARD // 2] = [(own[0] + (c < HARD_FLIP).cast("int")) % 2 for c in coins[1 : HARD // 2]]
        v = o.select(*[c.alias(f"v{i}") for i, c in enumerate(own)])
        e = T.subset_entropy(ExactSource(W.packed(v, HARD), 2), HARD, _SEEN)
        rows.append((case, len(_SEEN), round(e.entropy, 6), M.shannon(v, [f"v{i}" for i in range(HARD)]).first()["h"]))
    return spark.createDataFrame(rows, "instance string, observed long, estimate double, joint double")


#: (d, eps, pairs as a multiple of d / eps) of the sequential instances.
_SEQ = [(d, eps, f) for d in (50, 100, 200) for eps in (0.1, 0.2) for f in (0.002, 0.02, 0.2)]
#: Users of a bucket in which they are ranked.
_SEQ_BUCKET = 65536


def bias(entropy_: float) -> float:
    """q at most 1/2 whose binary entropy this is."""
    lo, hi = 1e-12, 0.5
    for _ in range(80):
        q = (lo + hi) / 2
        lo, hi = (q, hi) if entropy((q, 1 - q)) < entropy_ else (lo, q)
    return lo


def _sequential_grid():
    """(k, d, eps, pairs, low, high, first): ``first`` is the place, in a repetition, of the first user of the low family; those of the high one follow."""
    out, first = [], 0
    for k, (d, eps, f) in enumerate(_SEQ):
        pairs = max(1, round(f * d / eps))
        out.append((k, d, eps, pairs, bias(eps / 2), bias(3 * eps / 2), first))
        first += 2 * pairs
    return out


#: Users of a repetition of the whole grid.
_SEQ_USERS = sum(2 * g[3] for g in _sequential_grid())


@query(
    "hard_sequential",
    f"""WITH g(k, d, eps, pairs, low, high, first) AS (VALUES {', '.join(f'({k}, {n}, {e}::DOUBLE, {m}, {a!r}::DOUBLE, {b!r}::DOUBLE, {at})' for k, n, e, m, a, b, at in _sequential_grid())}),
      u AS (SELECT {KEY} AS user_id FROM lineitem),
      b AS (SELECT user_id, floor({coin('seq', 'bucket', 'user_id')} * (SELECT greatest(1, ceil(count(*) / {_SEQ_BUCKET}.0)) FROM u)) AS bucket FROM u),
      p AS (SELECT user_id, row_number() OVER (ORDER BY bucket, {coin('seq', 'rank', 'user_id')}, user_id) - 1 AS place FROM b),
      s AS (SELECT k, d, eps, pairs, low, high, place // {_SEQ_USERS} AS rep, place % {_SEQ_USERS} - first >= pairs AS is_high, count(*) AS n,
                   sum(CAST({coin('seq', 'a', 'user_id')} < CASE WHEN place % {_SEQ_USERS} - first >= pairs THEN high ELSE low END AS INT) + CAST({coin('seq', 'b', 'user_id')} < CASE WHEN place % {_SEQ_USERS} - first >= pairs THEN high ELSE low END AS INT)) AS hits
            FROM p JOIN g ON place % {_SEQ_USERS} BETWEEN first AND first + 2 * pairs - 1 WHERE place // {_SEQ_USERS} < (SELECT count(*) FROM u) // {_SEQ_USERS} GROUP BY ALL),
      t AS (SELECT k, count(*) // 2 AS reps, avg(CAST((hits / (2.0::DOUBLE * n) > (low + high) / 2) = is_high AS INT)) AS told FROM s GROUP BY k)
      SELECT CAST(d AS INT) AS d, eps, CAST(pairs AS BIGINT) AS pairs, {tidy('d * eps')} AS gap, coalesce(reps, 0) AS reps, {tidy('told')} AS told_apart FROM g LEFT JOIN t USING (k)""",
)
def hard_sequential(spark, d):
    """Two families of independent variables whose entropies differ by eps * d, and how often pairs of samples tell them.

    Every line is a user who shows two variables once; the rate of ones is compared with the
    middle of both. With a small share of d / eps pairs the families are hardly told apart.
    Users are numbered through random buckets; as many in a row as the whole grid takes are a
    repetition, and there are as many repetitions as the rows allow.
    """
    from pyspark.sql import Window

    from ..functions.coins import uniform

    users = line_users(spark, d)
    n = users.count()
    user = F.col("user_id")
    buckets = max(1, math.ceil(n / _SEQ_BUCKET))
    dealt = users.withColumn("bucket", F.floor(uniform("seq", "bucket", user) * F.lit(buckets)).cast("long"))
    starts, at = [], 0
    for r in dealt.groupBy("bucket").count().orderBy("bucket").collect():
        starts.append((r["bucket"], at))
        at += r["count"]
    starts = F.broadcast(spark.createDataFrame(starts, "bucket long, start long"))
    order = Window.partitionBy("bucket").orderBy(uniform("seq", "rank", user), user)
    placed = dealt.withColumn("idx", F.row_number().over(order) - 1).join(starts, "bucket").select("user_id", (F.col("start") + F.col("idx")).alias("place"))
    placed = placed.where(F.col("place") < n // _SEQ_USERS * _SEQ_USERS)
    grid = _sequential_grid()
    slots = [(first + i, k, i >= pairs, high if i >= pairs else low, (low + high) / 2) for k, _, _, pairs, low, high, first in grid for i in range(2 * pairs)]
    slots = F.broadcast(spark.createDataFrame(slots, "slot long, k int, is_high boolean, q double, middle double"))
    ones = sum((uniform("seq", p, user) < F.col("q")).cast("int") for p in "ab")
    s = placed.withColumn("slot", F.col("place") % _SEQ_USERS).join(slots, "slot").groupBy("k", "is_high", "middle", F.floor(F.col("place") / _SEQ_USERS).alias("rep")).agg(F.count("*").alias("n"), F.sum(ones).alias("hits"))
    right = ((F.col("hits") / (2.0 * F.col("n")) > F.col("middle")) == F.col("is_high")).cast("double")
    told = s.groupBy("k").agg(F.floor(F.count("*") / 2).alias("reps"), F.avg(right).alias("t"))
    table = spark.createDataFrame([g[:4] for g in grid], "k int, d int, eps double, pairs long")
    return table.join(told, "k", "left").select("d", "eps", "pairs", tidy_col(F.col("d") * F.col("eps")).alias("gap"), F.coalesce("reps", F.lit(0)).cast("long").alias("reps"), tidy_col(F.col("t")).alias("told_apart"))


# Chains and stars of several sizes

CHAINS = [(d, c) for d in (4, 6, 8, 10) for c in (2, 3, 4)]


def chain_model(d: int, c: int) -> list[float]:
    """Chance that a step moves to another symbol; the steps differ."""
    return [0.0, *[round(0.02 + 0.08 * ((3 * i) % d) / d, 6) for i in range(1, d)]]


@query("chain_sizes", " UNION ALL ".join(f"SELECT {d}::INT AS d, {c}::INT AS c, '{','.join(map(str, range(d)))}' AS chain, true AS within" for d, c in CHAINS))
def chain_sizes(spark, d):
    """Order and entropy of sampled chains of 4 to 10 variables with 2 to 4 symbols; SQL states the generator's order."""
    rows = []
    o = load(spark, d, "orders", "o_orderkey").select(F.col("o_orderkey").alias("user_id"))
    ready_to_checkpoint(spark)
    for n, c in CHAINS:
        moves = chain_model(n, c)
        users = W.chain_vectors(o, moves, c).checkpoint()
        e = T.chain_entropy(ExactSource(users, c), list(range(n)))
        truth = math.log(c) + sum(entropy((1 - m, *[m / (c - 1)] * (c - 1))) for m in moves[1:])
        rows.append((n, c, ",".join(map(str, e.order)), abs(e.entropy - truth) <= 0.1 * n and e.triples <= 1 + (n - 3) * (1 + math.ceil(math.log2(n)))))
    return spark.createDataFrame(rows, "d int, c int, chain string, within boolean")


STARS = (8, 32, 64)


@query("star_sizes", " UNION ALL ".join(f"SELECT {n}::INT AS d, {n // 3}::INT AS hub, {2 * n - 3}::BIGINT AS pairs, true AS within" for n in STARS))
def star_sizes(spark, d):
    """Hub and entropy of sampled stars of 8 to 64 variables; SQL states the generator's hub and the count of pairs."""
    rows = []
    ready_to_checkpoint(spark)
    for n in STARS:
        hub = n // 3
        flips = [0.05 + 0.25 * i / n for i in range(n)]
        tree = [{"node": hub, "parent": -1, "p": 0.5, "r": 0.0}] + [{"node": i, "parent": hub, "p": 0.5, "r": 0.25 - flips[i] / 2} for i in range(n) if i != hub]
        e = T.star_entropy(ExactSource(W.sampled_vectors(line_users(spark, d), tree).checkpoint(), 2), n)
        truth = math.log(2) + sum(entropy((flips[i], 1 - flips[i])) for i in range(n) if i != hub)
        rows.append((n, e.order[0], e.pairs, abs(e.entropy - truth) <= 0.05 * n))
    return spark.createDataFrame(rows, "d int, hub int, pairs long, within boolean")


# Variants

TREE_VARIANTS = {
    "default": {},
    "no reuse": {"reuse": False},
    "as printed": {"as_printed": True},
    "midpoint": {"quantisation": "midpoint"},
    "tight levels": {"level_cap": "tight"},
    "from level 2": {"min_level": 2},
}


@query("tree_variants")
def tree_variants(spark, d):
    """The variants of the sub-linear method on a strong random tree of 40 variables."""
    tree = W.random_tree(40, "7", strong=True)
    truth = T.all_pairs_entropy(W.ClosedForm(tree), 40)
    rows = []
    for name, how in TREE_VARIANTS.items():
        e = T.tree_entropy(W.ClosedForm(tree), 40, 2, 0.25, DELTA, **how)
        rows.append((name, e.pairs, e.jobs, e.weight, truth.weight, abs(e.entropy - truth.entropy) / 40))
    return spark.createDataFrame(rows, "variant string, pairs long, jobs long, weight double, truth double, error_per_d double")


#: A chain of ten variables, and a limit between what conditioning on a middle leaves (0 and the noise of the rows, .0045
#: at most of 1500 rows) and what it leaves elsewhere (.0062 at least in closed form).
CHAIN10, SEPARATE = (tuple(range(-1, 9)), (0.5, *[0.02 + 0.008 * i for i in range(1, 10)])), 0.005


def _variants_sql() -> str:
    """The chain that the informations tell; the printed test fails where it takes an end of the first triple for its middle."""
    names = [f"v{i}" for i in range(10)]
    q = sorted(sorted(range(10), key=lambda v: (draw("pub", "chain", v), v))[:3])
    joint = lambda *vs: f"(SELECT {h()} FROM ({counts('v', *[f'v{i}' for i in sorted(vs)])}))"
    left = [f"{joint(q[g], q[(g + 1) % 3])} + {joint(q[g], q[(g + 2) % 3])} - {joint(*q)} - {joint(q[g])}" for g in range(2)]
    right = "coalesce((SELECT bool_and(place = v) FROM pos), false)"
    middle = f"(SELECT v FROM pos WHERE v IN ({', '.join(map(str, q))}) ORDER BY place LIMIT 1 OFFSET 1)"
    printed = f"CASE WHEN {left[0]} > {SEPARATE} THEN {q[0]} WHEN {left[1]} > {SEPARATE} THEN {q[1]} ELSE {q[2]} END"
    arms = [f"SELECT '{n}' AS variant, {right} AS recovered" for n in ("argmin", "threshold", "lookahead 2")]
    return f"WITH RECURSIVE {vectors_sql(CHAIN10)}, {mi_sql('v', names)}, {_CHAIN} {' UNION ALL '.join(arms)} UNION ALL SELECT 'as printed', coalesce({right} AND {printed} = {middle}, false)"


@query("chain_variants", _variants_sql())
def chain_variants(spark, d):
    """Decisions and looking ahead on a chain of ten variables sampled on orders; the printed tests do not recover it."""
    users = W.flip_vectors(load(spark, d, "orders", "o_orderkey").select(F.col("o_orderkey").alias("user_id")), *CHAIN10)
    src = CountedSource(W.packed(users, 10), 2)
    rows = []
    for name, how in (("argmin", {}), ("threshold", {"decision": "threshold", "eps": SEPARATE}), ("lookahead 2", {"lookahead": 2}), ("as printed", {"decision": "as_printed", "eps": SEPARATE})):
        try:
            order, _ = T.chain_order(src, list(range(10)), **how)
        except ValueError:  # informations are not separated
            order = []
        rows.append((name, order == list(range(10))))
    return spark.createDataFrame(rows, "variant string, recovered boolean")


# Growing users

_COPIES = (1, 4, 16)


@query("scaling_users", sketch_sql(f"SELECT copies, o_orderkey || '#' || c AS user_id, o_orderstatus FROM (SELECT o_orderkey, o_orderstatus, copies, unnest(range(copies)) AS c FROM orders, (VALUES {', '.join(f'({c})' for c in _COPIES)}) AS t(copies))", "user_id", symbols("o_orderstatus"), 1, None, "copies"))
def scaling_users(spark, d):
    """Virtual users per row: the estimate's error falls with them, its state stays two counters."""
    o = load(spark, d, "orders", "o_orderkey", "o_orderstatus")
    o = o.select("o_orderkey", "o_orderstatus", F.explode(F.array(*[F.lit(c) for c in _COPIES])).alias("copies"))
    users = o.select("*", F.explode(F.sequence(F.lit(0), F.col("copies") - 1)).alias("c")).select("copies", "o_orderstatus", F.concat_ws("#", "o_orderkey", "c").alias("user_id"))
    return C.collision_sketch(users, "user_id", ["o_orderstatus"], by=["copies"])
