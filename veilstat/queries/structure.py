"""Tree, chain and star estimators on vectors that are drawn per row, and natural vectors."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..functions.scalars import tidy as tidy_col
from ..operators import measures as M
from ..operators import structure as T
from ..operators import workloads as W
from ..operators.protocol import UserPool
from ..operators.small_support import CountedSource, ExactSource, PrivateSource
from ..registry import query
from ..sources.tables import line_users, load
from ..udf import pair_blocks
from .measures import mi_sql
from .sqltext import coin, counts, h, tidy

D = 6
V = [f"v{i}" for i in range(D)]


def order_vectors(spark, d, model):
    """user_id and v0..v5 drawn for every order."""
    return W.flip_vectors(load(spark, d, "orders", "o_orderkey").select(F.col("o_orderkey").alias("user_id")), *model)


def source(spark, d, model):
    return ExactSource(W.packed(order_vectors(spark, d, model), D).cache(), 2)


def vectors_sql(model) -> str:
    parents, chances = model
    cols = []
    for i in W.tree_order(parents):
        c = f"CAST({coin('vec', f'x{i}', 'user_id')} < {chances[i]!r} AS INT)"
        cols.append(f"{c} AS v{i}" if parents[i] < 0 else f"({c} + v{parents[i]}) % 2 AS v{i}")
    return f"v AS (SELECT user_id, {', '.join(cols)} FROM (SELECT o_orderkey AS user_id FROM orders))"


def base_sql(model) -> str:
    """Recursive WITH of vectors, edges (i, j, mi) and marginal entropies (i, h)."""
    marginals = " UNION ALL ".join(f"SELECT {i} AS i, (SELECT {h()} FROM ({counts('v', x)})) AS h" for i, x in enumerate(V))
    return f"WITH RECURSIVE {vectors_sql(model)}, {mi_sql('v', V)}, marginals AS ({marginals})"


def tree_sql() -> str:
    """Edges whose ends no heavier edges connect: the heaviest spanning tree."""
    return """
      dir AS (SELECT i AS a, j AS b, mi FROM edges UNION ALL SELECT j, i, mi FROM edges),
      reach(i, j, w, a) AS (
        SELECT i, j, mi, i FROM edges
        UNION SELECT r.i, r.j, r.w, b.b FROM reach AS r JOIN dir AS b ON b.a = r.a AND b.mi > r.w),
      tree AS (SELECT i, j, mi FROM edges AS e WHERE NOT EXISTS (SELECT 1 FROM reach AS r WHERE r.i = e.i AND r.j = e.j AND r.a = e.j))"""


EPS, DELTA = 0.25, 0.1
LEVELS, REPS = math.ceil(2 * math.log(2) / EPS), math.ceil(math.log(1 / DELTA) / EPS**2)


def searches_sql() -> str:
    z = coin("pub", "z", "m", "r")
    return f"""
      dir AS (SELECT i AS a, j AS b, mi FROM edges UNION ALL SELECT j, i, mi FROM edges),
      lv AS (SELECT unnest(range(1, {LEVELS + 1})) AS m),
      comp(m, a, b) AS (
        SELECT m, n, n FROM lv, (SELECT unnest(range({D})) AS n)
        UNION SELECT c.m, c.a, e.b FROM comp AS c JOIN dir AS e ON e.a = c.b AND e.mi >= {EPS} * c.m),
      size AS (SELECT m, a, count(*) AS s, min(b) AS low FROM comp GROUP BY 1, 2),
      runs AS (SELECT m, r, floor(1 / {z}) AS z, CAST(floor({coin('pub', 'start', 'm', 'r')} * {D}) AS INT) AS a FROM lv, (SELECT unnest(range(1, {REPS + 1})) AS r)),
      gamma AS (SELECT runs.m, r, CASE WHEN s <= least(z, {2 / EPS}) THEN 1 ELSE 0 END AS g FROM runs JOIN size ON size.m = runs.m AND size.a = runs.a),
      counted AS (SELECT m, {D} * avg(g) AS estimate FROM gamma GROUP BY m),
      truth AS (SELECT m, count(DISTINCT low) AS components FROM size GROUP BY m)"""


def row(spark, **values):
    return spark.createDataFrame([values])


@query("tree_entropy_exact_mi", f"{base_sql(W.TREE6)}, {searches_sql()} SELECT {tidy('s')} AS marginals, {tidy('w')} AS weight, {tidy('s - w')} AS entropy FROM (SELECT (SELECT sum(h) FROM marginals) AS s, (SELECT {EPS} * sum({D} - estimate) FROM counted) AS w)")
def tree_entropy_exact_mi(spark, d):
    e = T.tree_entropy(source(spark, d, W.TREE6), D, 2, EPS, DELTA)
    return row(spark, marginals=round(e.marginals, 6), weight=round(e.weight, 6), entropy=round(e.entropy, 6))


@query("tree_component_counts", f"{base_sql(W.TREE6)}, {searches_sql()} SELECT CAST(m AS INT) AS m, {tidy('estimate')} AS estimate, components FROM counted JOIN truth USING (m)")
def tree_component_counts(spark, d):
    src = source(spark, d, W.TREE6)
    cache = T.EdgeCache(src)
    hits = T.component_indicators(cache, D, [EPS * m for m in range(1, LEVELS + 1)], REPS, 2 / EPS, "pub")
    every = src.mi([(i, j) for i in range(D) for j in range(i + 1, D)])
    rows = [(m, round(D * sum(g) / REPS, 6), T.true_components(D, every, EPS * m)) for m, g in enumerate(hits, 1)]
    return spark.createDataFrame(rows, "m int, estimate double, components long")


@query("tree_weight_levels", f"{base_sql(W.TREE6)}, {tree_sql()}, lv AS (SELECT unnest(range(1, {LEVELS + 1})) AS m), n AS (SELECT m, (SELECT count(*) FROM tree WHERE mi >= {EPS} * m) AS kept FROM lv) SELECT {tidy(f'{EPS} * (SELECT sum(kept) FROM n)')} AS by_levels, {tidy('(SELECT sum(mi) FROM tree)')} AS weight")
def tree_weight_levels(spark, d):
    """Levels count the heaviest spanning tree's edges: eps * sum (d - components) against its weight."""
    mi = source(spark, d, W.TREE6).mi([(i, j) for i in range(D) for j in range(i + 1, D)])
    levels = EPS * sum(D - T.true_components(D, mi, EPS * m) for m in range(1, LEVELS + 1))
    return row(spark, by_levels=round(levels, 6), weight=round(sum(mi[e] for e in T.kruskal(D, mi)), 6))


@query("tree_pair_cost")
def tree_pair_cost(spark, d):
    """Pairs asked for by the sub-linear method on random trees, by size, against all pairs."""
    rows = []
    for n in (20, 50, 100):
        src = W.ClosedForm(W.random_tree(n, "42"))
        e = T.tree_entropy(src, n, 2, 0.5, 0.1, seed=f"cost{n}")
        rows.append((n, e.pairs, n * (n - 1) // 2, n * n, e.jobs))
    return spark.createDataFrame(rows, "d int, pairs long, pairs_distinct long, pairs_ordered long, jobs long")


def pool(spark, d, model=None, rows=None, size=D, copies=1):
    users = line_users(spark, d)
    if copies > 1:
        users = users.select(F.explode(F.sequence(F.lit(1), F.lit(copies))).alias("c"), "user_id").select(F.concat_ws("#", "user_id", "c").alias("user_id"))
    x = W.packed(W.flip_vectors(users, *model), size) if model else W.tree_vectors(users, rows)
    return UserPool.of(x, "user_id", "pool")


@query("tree_entropy_ldp")
def tree_entropy_ldp(spark, d):
    p = pool(spark, d, W.TREE6)
    e = T.tree_entropy(PrivateSource(p, 2, 3.0, p.slots // 24), D, 2, EPS, DELTA, reps=12)
    return row(spark, marginals=e.marginals, weight=e.weight, entropy=e.entropy, pairs=e.pairs, jobs=e.jobs)


@query("chain_entropy_ldp")
def chain_entropy_ldp(spark, d):
    p = pool(spark, d, W.CHAIN6)
    e = T.chain_entropy(PrivateSource(p, 2, 4.0, p.slots // 30), list(range(D)))
    return row(spark, entropy=e.entropy, triples=e.triples, chain=",".join(map(str, e.order)))


@query("star_entropy_ldp")
def star_entropy_ldp(spark, d):
    p = pool(spark, d, W.STAR6)
    e = T.star_entropy(PrivateSource(p, 2, 3.0, p.slots // 24), D)
    return row(spark, entropy=e.entropy, pairs=e.pairs, hub=e.order[0])


_CHAIN = """
  far AS (SELECT i, j FROM edges ORDER BY mi, i, j LIMIT 1),
  pos AS (
    SELECT v, row_number() OVER (ORDER BY m DESC) - 1 AS place FROM (
      SELECT far.i AS v, 1e9::DOUBLE AS m FROM far
      UNION ALL SELECT CASE WHEN e.i = far.i THEN e.j ELSE e.i END, mi FROM edges AS e, far WHERE far.i IN (e.i, e.j)))"""


@query("chain_order_exact", f"{base_sql(W.CHAIN6)}, {_CHAIN} SELECT CAST(place AS INT) AS place, CAST(v AS INT) AS v FROM pos")
def chain_order_exact(spark, d):
    order, _ = T.chain_order(source(spark, d, W.CHAIN6), list(range(D)))
    return spark.createDataFrame(list(enumerate(order)), "place int, v int")


@query("chain_entropy_exact", f"{base_sql(W.CHAIN6)}, {_CHAIN}, w AS (SELECT sum(mi) AS w FROM pos AS a JOIN pos AS b ON b.place = a.place + 1 JOIN edges AS e ON e.i = least(a.v, b.v) AND e.j = greatest(a.v, b.v)) SELECT {tidy('(SELECT sum(h) FROM marginals) - w')} AS entropy FROM w")
def chain_entropy_exact(spark, d):
    return row(spark, entropy=round(T.chain_entropy(source(spark, d, W.CHAIN6), list(range(D))).entropy, 6))


CALL_SIZES = (4, 6, 8, 10, 12)


@query("chain_call_count")
def chain_call_count(spark, d):
    """Triple questions of the insertion order, by length, on chains sampled on orders."""
    rows = []
    users = load(spark, d, "orders", "o_orderkey").select(F.col("o_orderkey").alias("user_id"))
    for n in CALL_SIZES:
        moves = [0.0, *[0.02 + 0.08 * i / n for i in range(1, n)]]
        src = CountedSource(W.chain_vectors(users, moves, 2), 2)
        _, asked = T.chain_order(src, list(range(n)))
        rows.append((n, asked, 3 * asked))
    return spark.createDataFrame(rows, "d int, triples long, informations long")


class ChainForm:
    """Closed-form triple informations of a chain of flips."""

    def __init__(self, flips):
        self.flips = flips

    def _flip(self, a: int, b: int) -> float:
        f = 1.0
        for i in range(a + 1, b + 1):
            f *= 1 - 2 * self.flips[i]
        return (1 - f) / 2

    def mi(self, pairs):
        def one(a, b):
            f = self._flip(min(a, b), max(a, b))
            return math.log(2) + f * math.log(f) + (1 - f) * math.log(1 - f)

        return {q: one(*q) for q in pairs}

    def cmi(self, triples):
        out = {}
        for i, j, k in triples:  # sorted along the chain: j is between
            near = self.mi([(i, j), (j, k), (i, k)])
            out[(i, j, k)] = [near[(j, k)] - near[(i, k)], 0.0, near[(i, j)] - near[(i, k)]]
        return out


@query("chain_locate", f"{base_sql(W.CHAIN6)}, {_CHAIN} SELECT CAST(v AS INT) AS new, CAST(place - 1 AS INT) AS left_place FROM pos WHERE place BETWEEN 1 AND {D - 2}")
def chain_locate(spark, d):
    """Place of every inner variable in the chain of the others."""
    src = source(spark, d, W.CHAIN6)
    order, _ = T.chain_order(src, list(range(D)))
    rows = []
    for new in order[1:-1]:
        rest = [v for v in order if v != new]
        rows.append((new, T.locate_in_chain(src, rest, 0, len(rest) - 1, new)[0]))
    return spark.createDataFrame(rows, "new int, left_place int")


STAR_SQL = f"""
  dir AS (SELECT i AS a, j AS b, mi FROM edges UNION ALL SELECT j, i, mi FROM edges),
  first AS (SELECT CAST(floor({coin('pub', 'star')} * {D}) AS INT) AS a),
  partner AS (SELECT b AS a FROM dir JOIN first USING (a) ORDER BY mi DESC, b LIMIT 1),
  sums AS (SELECT a, sum(mi) AS s FROM dir GROUP BY a),
  hub AS (SELECT CASE WHEN x.s > y.s THEN x.a ELSE y.a END AS hub FROM first JOIN sums AS x USING (a), partner JOIN sums AS y USING (a))"""


@query("star_hub_exact", f"{base_sql(W.STAR6)}, {STAR_SQL} SELECT CAST(hub AS INT) AS hub FROM hub")
def star_hub_exact(spark, d):
    return spark.createDataFrame([(T.star_hub(source(spark, d, W.STAR6), D)[0],)], "hub int")


@query("star_entropy_exact", f"{base_sql(W.STAR6)}, {STAR_SQL} SELECT {tidy('(SELECT sum(h) FROM marginals) - (SELECT s FROM sums JOIN hub ON a = hub)')} AS entropy FROM (SELECT 1)")
def star_entropy_exact(spark, d):
    return row(spark, entropy=round(T.star_entropy(source(spark, d, W.STAR6), D).entropy, 6))


@query("allpairs_tree_exact", f"{base_sql(W.TREE6)}, {tree_sql()} SELECT {tidy('(SELECT sum(h) FROM marginals)')} AS marginals, {tidy('(SELECT sum(mi) FROM tree)')} AS weight, {tidy('(SELECT sum(h) FROM marginals) - (SELECT sum(mi) FROM tree)')} AS entropy")
def allpairs_tree_exact(spark, d):
    e = T.all_pairs_entropy(source(spark, d, W.TREE6), D)
    return row(spark, marginals=round(e.marginals, 6), weight=round(e.weight, 6), entropy=round(e.entropy, 6))


@query("allpairs_edges", f"{base_sql(W.TREE6)}, {tree_sql()} SELECT CAST(i AS INT) AS i, CAST(j AS INT) AS j, {tidy('mi')} AS mi FROM tree")
def allpairs_edges(spark, d):
    mi = source(spark, d, W.TREE6).mi([(i, j) for i in range(D) for j in range(i + 1, D)])
    return spark.createDataFrame([(i, j, round(mi[(i, j)], 6)) for i, j in T.kruskal(D, mi)], "i int, j int, mi double")


@query("mst_boruvka", f"{base_sql(W.TREE6)}, {tree_sql()} SELECT CAST(i AS INT) AS i, CAST(j AS INT) AS j, {tidy('mi')} AS mi FROM tree")
def mst_boruvka(spark, d):
    """The same tree, by rounds of best edges over a table of edges."""
    edges = M.mi_matrix(order_vectors(spark, d, W.TREE6), V)
    return T.boruvka(edges).select("i", "j", tidy_col(F.col("mi")).alias("mi"))


@query("mst_prim", f"{base_sql(W.TREE6)}, {tree_sql()} SELECT CAST(i AS INT) AS i, CAST(j AS INT) AS j FROM tree")
def mst_prim(spark, d):
    mi = source(spark, d, W.TREE6).mi([(i, j) for i in range(D) for j in range(i + 1, D)])
    return spark.createDataFrame(T.prim(D, mi), "i int, j int")


@query("allpairs_tree_ldp")
def allpairs_tree_ldp(spark, d):
    """All pairs in one round: users are dealt to pairs by slot arithmetic, one aggregation."""
    p = pool(spark, d, W.TREE6)
    e = T.all_pairs_entropy(PrivateSource(p, 2, 3.0, p.slots // 24), D)
    return row(spark, marginals=e.marginals, weight=e.weight, entropy=e.entropy, pairs=e.pairs)


_SUB = [(0, 1), (1, 2), (2, 3), (3, 4), (4, 5)]


@query("subset_tree_gap", f"{base_sql(W.TREE6)}, {tree_sql()}, sub AS (SELECT sum(mi) AS w FROM edges WHERE (i, j) IN ({', '.join(map(str, _SUB))})) SELECT {tidy('(SELECT sum(mi) FROM tree)')} AS tree_weight, {tidy('w')} AS subset_weight, {tidy('(SELECT sum(mi) FROM tree) - w')} AS gap FROM sub")
def subset_tree_gap(spark, d):
    """A plan fixed to d - 1 pairs misses the weight that it does not observe."""
    src = source(spark, d, W.TREE6)
    full, part = T.all_pairs_entropy(src, D), T.subset_entropy(src, D, _SUB)
    return row(spark, tree_weight=round(full.weight, 6), subset_weight=round(part.weight, 6), gap=round(full.weight - part.weight, 6))


_TRUE_TREE = sorted(T.pair(i, p) for i, p in enumerate(W.TREE6[0]) if p >= 0)


@query("edge_recovery", f"{base_sql(W.TREE6)}, {tree_sql()}, t(i, j) AS (VALUES {', '.join(map(str, _TRUE_TREE))}) SELECT (SELECT count(*) FROM (SELECT i, j FROM tree INTERSECT SELECT i, j FROM t)) AS recovered, (SELECT count(*) FROM (SELECT i, j FROM t EXCEPT SELECT i, j FROM tree)) AS missed, (SELECT count(*) FROM (SELECT i, j FROM tree EXCEPT SELECT i, j FROM t)) AS extra")
def edge_recovery(spark, d):
    mi = source(spark, d, W.TREE6).mi([(i, j) for i in range(D) for j in range(i + 1, D)])
    got = spark.createDataFrame(T.kruskal(D, mi), "i int, j int")
    true = spark.createDataFrame(_TRUE_TREE, "i int, j int")
    parts = [x.agg(F.count("*").alias(n)) for n, x in (("recovered", got.intersect(true)), ("missed", true.exceptAll(got)), ("extra", got.exceptAll(true)))]
    return parts[0].crossJoin(parts[1]).crossJoin(parts[2])


_SIGN_BITS = f"""WITH s AS (SELECT vec_id, unnest(range(len(embedding))) AS k, unnest(list_transform(embedding, lambda v: CAST(v > 0 AS INT))) AS x FROM embeddings),
    c AS (SELECT s.k AS i, t.k AS j, s.x AS a, t.x AS b, CAST(count(*) AS DOUBLE) AS n FROM s JOIN s AS t ON s.vec_id = t.vec_id AND s.k < t.k GROUP BY ALL),
    f AS (SELECT i, j, {h()} AS hab FROM c GROUP BY i, j),
    fa AS (SELECT i, j, {h()} AS ha FROM (SELECT i, j, a, sum(n) AS n FROM c GROUP BY ALL) GROUP BY i, j),
    fb AS (SELECT i, j, {h()} AS hb FROM (SELECT i, j, b, sum(n) AS n FROM c GROUP BY ALL) GROUP BY i, j)
    SELECT {tidy('max(ha + hb - hab)')} AS strongest, {tidy('sum(ha + hb - hab)')} AS total FROM f JOIN fa USING (i, j) JOIN fb USING (i, j)"""


@query("natural_sign_bits", _SIGN_BITS)
def natural_sign_bits(spark, d):
    """Sign bits of all components of embeddings: nearly independent."""
    e = load(spark, d, "embeddings", "embedding")
    bits = [f"v{i}" for i in range(e.agg(F.max(F.size("embedding"))).first()[0] or 0)]
    df = e.select(*[F.when(F.get("embedding", F.lit(i)) > 0, 1).otherwise(0).alias(v) for i, v in enumerate(bits)])
    return M.mi_from_cells(pair_blocks(df, bits, 2)).agg(tidy_col(F.max("mi")).alias("strongest"), tidy_col(F.sum("mi")).alias("total"))


_CAL = "SELECT CAST(month(l_shipdate) AS INT) AS m, CAST(quarter(l_shipdate) AS INT) AS q, l_linestatus AS s FROM lineitem"


@query("natural_calendar", f"WITH c AS ({_CAL}), {mi_sql('c', ['m', 'q', 's'])} SELECT CAST(i AS INT) AS i, CAST(j AS INT) AS j, {tidy('mi')} AS mi FROM edges")
def natural_calendar(spark, d):
    """Month tells the quarter: a natural tree edge."""
    df = load(spark, d, "lineitem", "l_shipdate", "l_linestatus").select(F.month("l_shipdate").alias("m"), F.quarter("l_shipdate").alias("q"), F.col("l_linestatus").alias("s"))
    return M.mi_matrix(df, ["m", "q", "s"]).select("i", "j", tidy_col(F.col("mi")).alias("mi"))


from .measures import _BANDS, bands  # noqa: E402

_BV = ["l_quantity_band", "l_price_band", "l_unit_band"]


@query("non_tree_control", f"WITH RECURSIVE b AS ({_BANDS}), {mi_sql('b', _BV)}, marginals AS ({' UNION ALL '.join(f'SELECT (SELECT {h()} FROM ({counts('b', x)})) AS h' for x in _BV)}), {tree_sql()}, j AS (SELECT {h()} AS h FROM ({counts('b', *_BV)})) SELECT {tidy('(SELECT sum(h) FROM marginals) - (SELECT sum(mi) FROM tree)')} AS identity_value, {tidy('(SELECT h FROM j)')} AS joint_entropy, (SELECT sum(h) FROM marginals) - (SELECT sum(mi) FROM tree) > (SELECT h FROM j) + 1e-9 AS upper_bound_only")
def non_tree_control(spark, d):
    """A collider: the identity's value is above the joint entropy."""
    df = bands(spark, d)
    mi = {(r["i"], r["j"]): r["mi"] for r in M.mi_matrix(df, _BV).collect()}
    total = sum(r["h"] for r in M.marginal_entropies(df, _BV).collect())
    joint = M.shannon(df, _BV).first()["h"]
    return row(spark, identity_value=round(total - sum(mi[e] for e in T.kruskal(3, mi)), 6), joint_entropy=joint, upper_bound_only=T.above_truth(mi, 3, joint, total, 1e-6))
