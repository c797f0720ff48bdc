"""Shannon entropy of vectors whose dependence graph is a tree, a chain or a star.

All three use the identity: joint entropy = sum of marginal entropies - information on the
edges of the heaviest spanning tree. They differ in how few informations they ask for. A
source (private, sampled or exact) answers batches of questions, one job for each batch.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.coins import draw
from ..sources.tables import ready_to_checkpoint


@dataclass
class Estimate:
    entropy: float
    marginals: float
    weight: float
    pairs: int = 0
    triples: int = 0
    jobs: int = 0
    order: list = field(default_factory=list)
    levels: list = field(default_factory=list)


def pair(i: int, j: int) -> tuple[int, int]:
    return (i, j) if i < j else (j, i)


# Trees


class EdgeCache:
    """Informations by unordered pair, each asked for once over a whole run; without ``reuse``, anew for each search."""

    def __init__(self, source, reuse: bool = True):
        self.source, self.reuse, self.known, self.jobs, self.asked = source, reuse, {}, 0, 0

    def need(self, pairs) -> None:
        """``pairs`` of (search, i, j)."""
        wanted = {(None if self.reuse else s, *pair(i, j)) for s, i, j in pairs}
        fresh = sorted(wanted - self.known.keys(), key=lambda k: (k[1:], str(k[0])))
        rounds: list[dict] = []
        for key in fresh:  # a job asks for a pair once
            for asked in rounds:
                if key[1:] not in asked:
                    asked[key[1:]] = key
                    break
            else:
                rounds.append({key[1:]: key})
        for asked in rounds:
            self.jobs += 1
            self.asked += len(asked)
            self.known |= {asked[p]: w for p, w in self.source.mi(list(asked)).items()}

    def of(self, search, i: int, j: int) -> float:
        return self.known[(None if self.reuse else search, *pair(i, j))]


def budgets(d: int, m: int, r: int, seed: str) -> tuple[int, int]:
    """(component budget, start variable) of a search: Pr[budget >= z] = 1/z."""
    u = draw(seed, "z", m, r)
    return (int(1 / u) if u > 0 else 1 << 30), int(draw(seed, "start", m, r) * d)


@dataclass
class Search:
    level: float
    limit: float
    found: list
    done: int = 0
    state: str = "open"


def component_indicators(cache: EdgeCache, d: int, thresholds: list[float], reps: int, cap: float, seed: str, as_printed: bool = False) -> list[list[int]]:
    """For each threshold and repetition, 1 where the start's component is no larger than its budget.

    All searches step together, so one batch of questions a step serves them all. A node is
    counted when it is discovered, not when it is expanded. ``as_printed`` compares the nodes
    that wait with the budget, and strictly, which miscounts isolated nodes and paths.
    """
    searches = []
    for m, level in enumerate(thresholds, 1):
        for r in range(1, reps + 1):
            z, start = budgets(d, m, r, seed)
            searches.append(Search(level, min(cap, z), [start]))
    while open_ := [(k, s) for k, s in enumerate(searches) if s.state == "open"]:
        cache.need((k, s.found[s.done], j) for k, s in open_ for j in range(d) if j not in s.found)
        for k, s in open_:
            at = s.found[s.done]
            s.done += 1
            s.found += [j for j in range(d) if j not in s.found and cache.of(k, at, j) >= s.level]
            waiting = len(s.found) - s.done
            if waiting + 1 >= s.limit if as_printed else len(s.found) > s.limit:
                s.state = "large"
            elif not waiting:
                s.state = "small"
    hits = [int(s.state == "small") for s in searches]
    return [hits[k : k + reps] for k in range(0, len(hits), reps)]


def tree_entropy(source, d: int, c: int, eps: float, delta: float, seed: str = "pub", level_cap: str = "paper", quantisation: str = "floor", reps: int | None = None, reuse: bool = True, as_printed: bool = False, min_level: int = 1) -> Estimate:
    """Entropy through the weight of the heaviest spanning tree, without finding the tree.

    Over thresholds eps * m the weight is eps times the sum of (d - number of components);
    component numbers are estimated from searches that stop early at heavy-tailed budgets.
    ``level_cap``: ``paper`` has 2 log(c) / eps levels, ``tight`` leaves out empty ones;
    ``quantisation``: ``floor`` or ``midpoint`` (thresholds half a level lower);
    ``reuse=False``: every search asks for its pairs anew; ``as_printed``: the strict test on
    waiting nodes; ``min_level``: levels below it are not searched and count as connected.
    """
    levels = math.ceil((2 if level_cap == "paper" else 1) * math.log(c) / eps) + (level_cap == "tight")
    reps = reps or math.ceil(math.log(1 / delta) / eps**2)
    shift = 0.5 if quantisation == "midpoint" else 0.0
    cache = EdgeCache(source, reuse)
    searched = range(min_level, levels + 1)
    hits = component_indicators(cache, d, [eps * (m - shift) for m in searched], reps, 2 / eps, seed, as_printed)
    counts = [d * sum(h) / reps for h in hits]
    weight = eps * (sum(d - k for k in counts) + (min_level - 1) * (d - 1))
    total = math.fsum(source.marginals(list(range(d))).values())
    return Estimate(total - weight, total, weight, cache.asked, 0, cache.jobs + 1, [], counts)


def true_components(d: int, mi: dict, level: float) -> int:
    group = list(range(d))

    def top(i):
        while group[i] != i:
            i = group[i]
        return i

    for (i, j), w in mi.items():
        if w >= level:
            group[top(i)] = top(j)
    return len({top(i) for i in range(d)})


def kruskal(d: int, mi: dict) -> list[tuple[int, int]]:
    """Edges of the heaviest spanning tree; ties go to the smaller pair."""
    group = list(range(d))

    def top(i):
        while group[i] != i:
            group[i] = group[group[i]]
            i = group[i]
        return i

    out = []
    for (i, j), _ in sorted(mi.items(), key=lambda kv: (-kv[1], kv[0])):
        a, b = top(i), top(j)
        if a != b:
            group[a] = b
            out.append((i, j))
    return sorted(out)


def prim(d: int, mi: dict) -> list[tuple[int, int]]:
    seen, out = {0}, []
    while len(seen) < d:
        _, e = max(((w, (-i, -j)), (i, j)) for (i, j), w in mi.items() if (i in seen) != (j in seen))
        out.append(e)
        seen |= set(e)
    return sorted(out)


def boruvka(edges: DataFrame, rounds: int = 40) -> DataFrame:
    """(i, j, mi) of the heaviest spanning forest: in each round every component takes its best edge.

    Components merge through the roots that their best edges point at: the lesser end of a
    mutual choice is a root, and others follow their pointers by doubling. A round is a few
    aggregations and joins; there are at most log2(variables) of them. Tables of a round are
    checkpointed, nothing but row counts comes to the driver.
    """
    ready_to_checkpoint(edges.sparkSession)
    edges = edges.select("i", "j", "mi").checkpoint()
    nodes = edges.select(F.col("i").alias("v")).union(edges.select(F.col("j").alias("v"))).distinct()
    label = nodes.select("v", F.col("v").alias("g")).checkpoint()
    chosen = None
    for _ in range(rounds):
        a, b = label.select(F.col("v").alias("i"), F.col("g").alias("gi")), label.select(F.col("v").alias("j"), F.col("g").alias("gj"))
        cross = edges.join(a, "i").join(b, "j").where("gi <> gj")
        both = cross.select("i", "j", "mi", F.col("gi").alias("g"), F.col("gj").alias("h")).union(cross.select("i", "j", "mi", F.col("gj").alias("g"), F.col("gi").alias("h")))
        best = both.groupBy("g").agg(F.max_by(F.struct("i", "j", "mi", "h"), F.struct("mi", -F.col("i"), -F.col("j"))).alias("e")).select("g", "e.*").checkpoint()
        if best.isEmpty():
            break
        picked = best.select("i", "j", "mi").distinct()
        chosen = picked if chosen is None else chosen.unionByName(picked).distinct()
        back = best.select(F.col("g").alias("h"), F.col("h").alias("hh"))
        root = best.join(back, "h").select("g", F.when((F.col("hh") == F.col("g")) & (F.col("g") < F.col("h")), F.col("g")).otherwise(F.col("h")).alias("r"))
        while True:  # follow pointers until all point at roots
            on = root.select(F.col("g").alias("r"), F.col("r").alias("rr"))
            root = root.join(on, "r").select("g", F.col("rr").alias("r"), (F.col("rr") != F.col("r")).alias("moved")).checkpoint()
            if root.where("moved").isEmpty():
                break
            root = root.drop("moved")
        label = label.join(root.select("g", "r"), "g", "left").select("v", F.coalesce("r", "g").alias("g")).checkpoint()
    return chosen if chosen is not None else edges.limit(0)


def identity(source, d: int, edges: list[tuple[int, int]], mi: dict | None = None) -> Estimate:
    """Marginal entropies less the information on given edges; ``mi`` reuses what was asked before."""
    total = math.fsum(source.marginals(list(range(d))).values())
    if mi is None:
        mi = source.mi([pair(*e) for e in edges])
    weight = math.fsum(mi[pair(*e)] for e in edges)
    return Estimate(total - weight, total, weight)


def all_pairs_entropy(source, d: int) -> Estimate:
    """The baseline: informations of all pairs, heaviest spanning tree, identity."""
    every = [(i, j) for i in range(d) for j in range(i + 1, d)]
    mi = source.mi(every)
    out = identity(source, d, kruskal(d, mi), mi)
    out.pairs, out.jobs, out.order = len(every), 2, kruskal(d, mi)
    return out


def subset_entropy(source, d: int, pairs: list[tuple[int, int]]) -> Estimate:
    """A plan fixed in advance over some pairs only: what it never observes, it cannot subtract."""
    mi = source.mi(pairs)
    out = identity(source, d, kruskal(d, mi), mi)
    out.pairs = len(pairs)
    return out


# Chains


class TripleCache:
    """Conditional informations by triple, in jobs of several triples."""

    def __init__(self, source):
        self.source, self.known, self.jobs = source, {}, 0

    def need(self, triples) -> None:
        fresh = sorted({tuple(sorted(t)) for t in triples} - self.known.keys())
        if fresh:
            self.jobs += 1
            self.known |= self.source.cmi(fresh)

    def __getitem__(self, triple) -> list[float]:
        self.need([triple])
        return self.known[tuple(sorted(triple))]


def middle(cache: TripleCache, i: int, j: int, k: int, decision: str = "argmin", eps: float = 0.0) -> int:
    """Which of three variables lies between the others.

    ``argmin``: conditioning on it leaves least information. ``threshold``: the one whose
    conditioning leaves less than ``eps``, where it is the only one; with separated
    informations it is. ``as_printed``: one whose conditioning leaves more than ``eps``.
    """
    key = tuple(sorted((i, j, k)))
    left = cache[key]
    if decision == "as_printed":
        return next((key[g] for g in range(3) if left[g] > eps), key[2])
    below = [g for g in range(3) if left[g] < eps]
    if decision == "threshold" and len(below) != 1:
        raise ValueError(f"{len(below)} of the triple {key} lie below {eps}: informations are not separated")
    return key[below[0] if decision == "threshold" else min(range(3), key=lambda g: (left[g], g))]


def locate_in_chain(source, order: list[int], lo: int, hi: int, new: int, decision: str = "argmin", eps: float = 0.0, lookahead: int = 1) -> tuple[int, int]:
    """(left neighbour's position, questions): bisection between positions lo < hi that enclose ``new``.

    With ``lookahead`` n, one job asks for the triples of the next n steps, whichever way they go.
    """
    cache = source if isinstance(source, TripleCache) else TripleCache(source)
    before = len(cache.known)
    while hi - lo > 1:
        ahead = [(lo, hi)]
        wanted = []
        for _ in range(lookahead):
            mids = [(a, (a + b + 1) // 2, b) for a, b in ahead if b - a > 1]
            wanted += [(order[a], order[m], new) for a, m, _ in mids]
            ahead = [x for a, m, b in mids for x in ((a, m), (m, b))]
        cache.need(wanted)
        for _ in range(lookahead):
            if hi - lo <= 1:
                break
            mid = (lo + hi + 1) // 2
            # new lies left of mid when it is between the left end and mid.
            if middle(cache, order[lo], order[mid], new, decision, eps) == new:
                hi = mid
            else:
                lo = mid
    return lo, len(cache.known) - before


def chain_order(source, variables: list[int], seed: str = "pub", decision: str = "argmin", eps: float = 0.0, lookahead: int = 1) -> tuple[list[int], int]:
    """(order along the chain, triple questions) by insertion; a chain is told up to direction."""
    cache = source if isinstance(source, TripleCache) else TripleCache(source)
    queue = sorted(variables, key=lambda v: (draw(seed, "chain", v), v))
    if len(queue) < 3:
        return sorted(queue), 0
    i, j, k = queue[:3]
    m = middle(cache, i, j, k, decision, eps)
    ends = [v for v in (i, j, k) if v != m]
    order = [ends[0], m, ends[1]]
    for new in queue[3:]:
        m = middle(cache, order[0], order[-1], new, decision, eps)
        if m == order[0]:
            order.insert(0, new)
        elif m == order[-1]:
            order.append(new)
        else:
            at, _ = locate_in_chain(cache, order, 0, len(order) - 1, new, decision, eps, lookahead)
            order.insert(at + 1, new)
    return (order if order[0] < order[-1] else order[::-1]), len(cache.known)


def chain_entropy(source, variables: list[int], seed: str = "pub", decision: str = "argmin", eps: float = 0.0, lookahead: int = 1) -> Estimate:
    cache = TripleCache(source)
    order, asked = chain_order(cache, variables, seed, decision, eps, lookahead)
    out = identity(source, len(variables), [pair(a, b) for a, b in zip(order, order[1:], strict=False)])
    out.order, out.triples, out.jobs = order, asked, cache.jobs + 2
    return out


def above_truth(mi: dict, d: int, joint: float, marginals: float, slack: float = 1e-9) -> bool:
    """Whether the identity's value is only an upper bound: the vector is no tree."""
    return marginals - math.fsum(mi[e] for e in kruskal(d, mi)) > joint + slack


def check_separation(mi: dict, d: int) -> float:
    """Least gap of the informations of a variable with two others; chain and star want it above eps."""
    gaps = [abs(mi[pair(i, j)] - mi[pair(j, k)]) for j in range(d) for i in range(d) for k in range(i + 1, d) if len({i, j, k}) == 3]
    return min(gaps) if gaps else math.inf


# Stars


def star_hub(source, d: int, seed: str = "pub") -> tuple[int, dict]:
    """(hub, informations): a random variable's strongest partner, then the larger sum of the two."""
    i = int(draw(seed, "star") * d)
    mi = source.mi([pair(i, j) for j in range(d) if j != i])
    k = max((j for j in range(d) if j != i), key=lambda j: (mi[pair(i, j)], -j))
    mi |= source.mi([pair(k, j) for j in range(d) if j not in (i, k)])
    rows = {v: math.fsum(mi[pair(v, j)] for j in range(d) if j != v) for v in (i, k)}
    return (i if rows[i] > rows[k] else k), mi


def star_entropy(source, d: int, seed: str = "pub", reuse: bool = True) -> Estimate:
    hub, mi = star_hub(source, d, seed)
    edges = [pair(hub, j) for j in range(d) if j != hub]
    out = identity(source, d, edges, mi if reuse else None)
    out.order, out.pairs = [hub], len(mi) + (0 if reuse else len(edges))
    return out


def strongest_partner(edges: DataFrame) -> DataFrame:
    """(v, partner, mi) of every variable by one aggregation."""
    both = edges.select(F.col("i").alias("v"), F.col("j").alias("w"), "mi").union(edges.select(F.col("j").alias("v"), F.col("i").alias("w"), "mi"))
    return both.groupBy("v").agg(F.max_by("w", F.struct("mi", -F.col("w"))).alias("partner"), F.max("mi").alias("mi"))


def ranked_edges(edges: DataFrame) -> DataFrame:
    return edges.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("mi"), "i", "j")))
