"""The hash method and its raw-sample rival."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.coins import uniform
from ..functions.scalars import keep_rate, tidy as tidy_col
from ..operators import collision as C
from ..operators import measures as M
from ..operators.workloads import exponential
from ..registry import query
from ..sources.tables import line_users, load
from .sqltext import KEY, coin, counts, hash_bits, p2, tidy


def symbols(*cols: str) -> str:
    parts = [f"(length(coalesce(CAST({c} AS VARCHAR), '∅')) || ':' || coalesce(CAST({c} AS VARCHAR), '∅'))" for c in cols]
    return parts[0] if len(parts) == 1 else f"concat_ws('|', {', '.join(parts)})"


def pairs_sql(users: str, id_: str, by: str = "", public: str = "pub") -> str:
    """users with bucket and idx."""
    g = f"{by}, " if by else ""
    return f"""
      u AS ({users}),
      b AS (SELECT *, CAST(floor({coin(public, 'bucket', id_)} * (SELECT greatest(1, ceil(count(*) / 1024.0)) FROM u)) AS BIGINT) AS bucket FROM u),
      p AS (SELECT *, CAST(floor((row_number() OVER (PARTITION BY {g}bucket ORDER BY {coin(public, 'rank', id_)}, {id_}) - 1) / 2) AS BIGINT) AS idx FROM b)"""


def sketch_sql(users: str, id_: str, value: str, b: int, alpha: float | None, by: str = "", tail: str = "", pairing: str = "") -> str:
    size, lam = 1 << b, keep_rate(alpha, b)
    h = hash_bits("pub", b, "concat_ws(':', bucket, idx)", value)
    if alpha is not None:
        h = f"CASE WHEN {coin('noise', 'keep', id_)} < {lam!r}::DOUBLE THEN {h} ELSE CAST(floor({coin('noise', 'draw', id_)} * {size}) AS BIGINT) END"
    g = f"{by}, " if by else ""
    raw = f"(({size} * (hits::DOUBLE / n_pairs) - 1) / {lam * lam * (size - 1)!r}::DOUBLE)"
    p2 = f"least(greatest({raw}, 1.0::DOUBLE / greatest(n_pairs, 1)), 1.0::DOUBLE)"
    err = f"({size / (lam * lam * (size - 1))!r}::DOUBLE * sqrt(hits::DOUBLE / n_pairs * (1 - hits::DOUBLE / n_pairs) / n_pairs))"
    return f"""WITH {pairing or pairs_sql(users, id_, by)},
      r AS (SELECT {g}bucket, idx, {h} AS report FROM p),
      m AS (SELECT {g}bucket, idx, min(report) AS lo, max(report) AS hi FROM r GROUP BY {g}bucket, idx HAVING count(*) = 2),
      c AS (SELECT {g}count(*) AS n_pairs, CAST(sum(CASE WHEN lo = hi THEN 1 ELSE 0 END) AS BIGINT) AS hits FROM m {f'GROUP BY {by}' if by else ''})
      SELECT {g}n_pairs, hits, {tidy(raw)} AS p2_raw, {tidy(f'1 - {p2}')} AS gini, {tidy(f'-ln({p2})')} AS collision, {tidy(err)} AS stderr,
             {raw} < 1.0::DOUBLE / greatest(n_pairs, 1) AS clamped FROM c{tail}"""


_LINES = f"SELECT {KEY} AS user_id, * FROM lineitem"


def _register(name, cols, b, alpha, by=None):
    sql = sketch_sql(_LINES, "user_id", symbols(*cols), b, alpha, by or "")

    @query(name, sql)
    def run(spark, d):
        need = dict.fromkeys([*([by] if by else []), *cols])
        return C.collision_sketch(line_users(spark, d, *need), "user_id", list(cols), b, alpha, by=[by] if by else [])

    return run


_register("hash_gini_b1", ["l_returnflag"], 1, None)
_register("hash_gini_b4", ["l_quantity"], 4, None)
_register("hash_collision_ldp", ["l_linestatus"], 1, 2.0)
_register("hash_gini_grouped", ["l_linestatus"], 1, None, "l_returnflag")
_register("hash_gini_multicol", ["l_returnflag", "l_linestatus"], 2, 3.0)

_EXP = f"SELECT {KEY} AS user_id, CAST(least(1000, ceil(-ln(1 - {coin('pub', 'exp', KEY)}))) AS INT) AS x FROM lineitem"


def exponential_users(spark, d, seed: str = "pub"):
    df = line_users(spark, d)
    return df.select("user_id", exponential(uniform(seed, "exp", F.col("user_id"))).alias("x"))


@query("hash_collision_b1", sketch_sql(_EXP, "user_id", symbols("x"), 1, None))
def hash_collision_b1(spark, d):
    """One-bit reports on the exponential distribution."""
    return C.collision_sketch(exponential_users(spark, d), "user_id", ["x"])


def _raw_sql(users: str, value: str, bits: int) -> str:
    q = "(hits::DOUBLE / n_pairs)"
    return f"""WITH {pairs_sql(users, 'user_id')},
      m AS (SELECT bucket, idx, min({value}) AS lo, max({value}) AS hi FROM p GROUP BY bucket, idx HAVING count(*) = 2),
      c AS (SELECT count(*) AS n_pairs, CAST(sum(CASE WHEN lo = hi THEN 1 ELSE 0 END) AS BIGINT) AS hits FROM m)
      SELECT n_pairs, hits, {tidy(q)} AS p2, {tidy(f'1 - {q}')} AS gini, {tidy(f'-ln({q})')} AS collision, n_pairs * {2 * bits} AS total_bits FROM c"""


@query("raw_collision_pairs", _raw_sql(_EXP, symbols("x"), 10))
def raw_collision_pairs(spark, d):
    """The rival on the same draws, ten bits a sample."""
    return C.raw_pairs(exponential_users(spark, d), "user_id", ["x"], bits=10)


_BIAS = ("l_linestatus", "l_returnflag", "l_quantity")


@query(
    "hash_bias_table",
    f"""WITH p AS ({' UNION ALL '.join(f"SELECT '{x}' AS field, {p2()} AS p2 FROM ({counts('lineitem', x)})" for x in _BIAS)}),
      g AS (SELECT field, p2, b, alpha, (exp(alpha) - 1) / (pow(2::DOUBLE, b) + exp(alpha) - 1) AS lam FROM p, (VALUES (1::INT), (2), (4)) AS t(b), (VALUES (0.5::DOUBLE), (1.0), (2.0)) AS s(alpha))
      SELECT field, b, alpha, {tidy('lam')} AS lambda, {tidy('p2')} AS p2, {tidy('(1 + lam * lam * p2 * (pow(2::DOUBLE, b) - 1)) / pow(2::DOUBLE, b)')} AS hit_rate FROM g""",
)
def hash_bias_table(spark, d):
    """Keep rate and expected rate of equal reports at the collision probabilities of columns of lineitem."""
    p = None
    for x in _BIAS:
        one = M.histogram(load(spark, d, "lineitem", x), [x]).agg(M.p2_of().alias("p2")).select(F.lit(x).alias("field"), "p2")
        p = one if p is None else p.unionByName(one)
    grid = p.select("*", F.explode(F.array(*[F.lit(b) for b in (1, 2, 4)])).alias("b")).select("*", F.explode(F.array(*[F.lit(a) for a in (0.5, 1.0, 2.0)])).alias("alpha"))
    size = F.pow(F.lit(2.0), F.col("b"))
    lam = (F.exp("alpha") - 1) / (size + F.exp("alpha") - 1)
    return grid.select("field", "b", "alpha", tidy_col(lam).alias("lambda"), tidy_col(F.col("p2")).alias("p2"), tidy_col((1 + lam * lam * F.col("p2") * (size - 1)) / size).alias("hit_rate"))


@query("pair_within_task")
def pair_within_task(spark, d):
    return C.pairs_within_task(line_users(spark, d, "l_returnflag"), "user_id", ["l_returnflag"])


def permuted_sql(users: str, id_: str) -> str:
    """users with bucket and idx of the keyed permutation of ids 0..n-1."""
    steps, last = [f"u0 AS (SELECT *, (SELECT count(*) FROM ({users})) AS n, CAST({id_} AS BIGINT) AS place FROM ({users}))", "s0 AS (SELECT *, CAST(ceil(sqrt(n)) AS BIGINT) AS a, CAST(ceil(n / ceil(sqrt(n))) AS BIGINT) AS b FROM u0)"], "s0"
    for walk in range(C.WALKS):
        steps.append(f"w{walk} AS (SELECT *, place // b AS y, place % b AS x FROM {last})")
        last = f"w{walk}"
        for r in range(0, C.ROUNDS, 2):
            steps.append(f"y{walk}_{r} AS (SELECT * REPLACE ((y + CAST(floor({coin('pub', f'row{r}', 'x')} * a) AS BIGINT)) % a AS y) FROM {last})")
            steps.append(f"x{walk}_{r} AS (SELECT * REPLACE ((x + CAST(floor({coin('pub', f'column{r}', 'y')} * b) AS BIGINT)) % b AS x) FROM y{walk}_{r})")
            last = f"x{walk}_{r}"
        moved = "y * b + x" if not walk else "CASE WHEN place >= n THEN y * b + x ELSE place END"
        steps.append(f"s{walk + 1} AS (SELECT * EXCLUDE (y, x) REPLACE ({moved} AS place) FROM {last})")
        last = f"s{walk + 1}"
    return ", ".join(steps) + f", p AS (SELECT *, 0::BIGINT AS bucket, place // 2 AS idx FROM {last} WHERE place < n)"


@query("hash_gini_permuted", sketch_sql("SELECT event_id, event_type FROM events", "event_id", symbols("event_type"), 1, None, pairing=permuted_sql("SELECT event_id, event_type FROM events", "event_id")))
def hash_gini_permuted(spark, d):
    """Pairs by a keyed permutation of dense ids: only (pair, report) is shuffled."""
    df = load(spark, d, "events", "event_id", "event_type")
    return C.collision_sketch(df, "event_id", ["event_type"], pairing="permute")


_BATCHED = f"SELECT *, CAST(floor({coin('pub', 'batch', 'user_id')} * 5) AS INT) AS batch FROM ({_LINES})"


@query("hash_gini_boosted", f"SELECT CAST(sum(n_pairs) AS BIGINT) AS n_pairs, {tidy('quantile_cont(gini, 0.5)')} AS gini FROM ({sketch_sql(_BATCHED, 'user_id', symbols('l_linestatus'), 1, None, 'batch')})")
def hash_gini_boosted(spark, d):
    return C.boosted(line_users(spark, d, "l_linestatus"), "user_id", ["l_linestatus"], 5)


_PRINTED = sketch_sql(_EXP, "user_id", symbols("x"), 1, None)


@query("hash_gini_as_printed", f"SELECT n_pairs, hits, p2_raw, {tidy('(2 * (hits::DOUBLE / n_pairs) - 1)')} AS gini, {tidy('-ln(1 - (2 * (hits::DOUBLE / n_pairs) - 1))')} AS collision, stderr, clamped FROM ({_PRINTED})")
def hash_gini_as_printed(spark, d):
    """The uncorrected form, for ablation: it estimates the collision probability, not the Gini entropy."""
    return C.collision_sketch(exponential_users(spark, d), "user_id", ["x"], as_printed=True)
