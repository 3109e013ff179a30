"""Whole-graph estimators: push-walk in its variants, Monte Carlo, and exact power iteration."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pushwave.functions.formulas import PprParams, push_threshold
from pushwave.operators import kernels
from pushwave.operators.graph import Graph
from pushwave.operators.index import WalkIndex, index_walks
from pushwave.operators.push import Pushed, forward_push
from pushwave.operators.walks import run_walks
from pushwave.plans.durable import cut


@dataclass(frozen=True)
class Estimate:
    """scores: query_id, v, score. The rest is work: rounds, arcs touched, residue left, walks, hops."""

    scores: DataFrame
    rounds: int = 0
    edge_touches: int = 0
    residue: float = 0.0
    walks: int = 0
    hops: int = 0


def allocate_walks(state: DataFrame, c: float, alpha: float, pruned: bool) -> DataFrame:
    """(query_id, start, n_walks, weight) for what residues are left; pruned: of walks that move."""
    share = (1 - alpha) if pruned else 1.0
    left = state.filter(F.col("r") > 0)
    if pruned:
        left = left.filter("deg > 0")
    n = F.ceil(F.lit(share * c) * F.col("r")).cast("long")
    return left.select("query_id", F.col("v").alias("start"), n.alias("n_walks"), (F.lit(share) * F.col("r") / n).alias("weight"))


def base_scores(state: DataFrame, alpha: float, pruned: bool) -> DataFrame:
    """Reserves; pruned: with the walks that would stop at once, and all of a dead end's residue."""
    own = F.col("p") + (F.when(F.col("deg") == 0, F.col("r")).otherwise(alpha * F.col("r")) if pruned else F.lit(0.0))
    return state.select("query_id", "v", own.alias("score")).filter("score > 0")


def combine(base: DataFrame, ends: DataFrame) -> DataFrame:
    """(query_id, v, score, n, hops): reserves plus what walks bring, and the walks themselves."""
    zero = F.lit(0).cast("long")
    both = base.select("query_id", "v", "score", zero.alias("n"), zero.alias("hops")).unionByName(ends.select("query_id", "v", F.col("weight").alias("score"), "n", "hops"))
    return both.groupBy("query_id", "v").agg(F.sum("score").alias("score"), F.sum("n").alias("n"), F.sum("hops").alias("hops"))


def finish(g: Graph, pushed: Pushed, p: PprParams, c: float, pruned: bool, index: WalkIndex | None = None, engine: str = "auto") -> Estimate:
    """Walks from the residues on top of the reserves."""
    alloc = allocate_walks(pushed.state, c, p.alpha, pruned)
    ends = index_walks(g, index, alloc) if index is not None else run_walks(g, alloc, p, pruned, engine)
    found = cut(combine(base_scores(pushed.state, p.alpha, pruned), ends), "scores")
    n, hops = found.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum("hops"), F.lit(0))).first()
    return Estimate(found.select("query_id", "v", "score"), pushed.rounds, pushed.edge_touches, pushed.residue, int(n), int(hops))


def _in_kernel(g: Graph, p: PprParams, index: WalkIndex | None, engine: str):
    """(whether the query runs in one task, the broadcast index or None)."""
    if not g.in_kernel(engine):
        return False, None
    if index is None:
        return True, None
    stored = index.local(g)
    return stored is not None, stored


def _estimate(found: DataFrame) -> Estimate:
    """Of a written kernel result, whose rows repeat what a query cost."""
    work = found.groupBy("query_id").agg(*(F.first(c).alias(c) for c in ("rounds", "touched", "residue", "walks", "hops")))
    rounds, touched, residue, walks, hops = work.agg(F.max("rounds"), *(F.sum(c) for c in ("touched", "residue", "walks", "hops"))).first()
    return Estimate(found.select("query_id", "v", "score"), rounds or 0, touched or 0, residue or 0.0, walks or 0, hops or 0)


def push_walk(g: Graph, state: DataFrame, p: PprParams, rho: float | None = None, rho_mult: float = 1.0, pruned: bool = False, index: WalkIndex | None = None, engine: str = "auto") -> Estimate:
    """Push to rho (default: rho_mult times the balancing threshold), then walks.

    state: of push.starts or push.from_distribution. pruned False: the basic method; True: zero-hop
    walks are added up at once and the rest take a forced first hop. index: read walks instead.
    """
    p = p.resolve(g.n)
    c = p.walks
    rho = rho if rho is not None else rho_mult * push_threshold(g.m, c)[0]
    here, stored = _in_kernel(g, p, index, engine)
    if here:
        alpha = p.alpha
        return _estimate(cut(kernels.estimated(state, g.adjacency(), stored, p, c, pruned, lambda s: s.run(rho, alpha)), "scores"))
    return finish(g, forward_push(g, state, rho, p.alpha, engine=engine), p, c, pruned, index, engine)


@dataclass(frozen=True)
class Prices:
    """Cost of a touched arc, of a hop (or an index row), and of a round of jobs."""

    arc: float = 1.0
    hop: float = 1.0
    round: float = 0.0


def push_walk_balanced(g: Graph, state: DataFrame, p: PprParams, prices: Prices | None = None, index: WalkIndex | None = None, engine: str = "auto") -> Estimate:
    """The tuned method: push down a ladder of thresholds while that has cost less than the walks
    predicted from the residue; then pruned walks. Prices are in work units unless calibrated. In kernels
    every query decides for itself; the join engine pushes the batch together, so there the sums over
    the queries decide, and a round has a price."""
    p = p.resolve(g.n)
    prices = prices or Prices()
    c = p.walks
    per_walk = prices.hop * (1.0 if index is not None else 1 / p.alpha)
    floor = push_threshold(g.m, c)[0] / 64
    here, stored = _in_kernel(g, p, index, engine)
    if here:
        alpha, arc, ahead = p.alpha, prices.arc, per_walk * (1 - p.alpha)
        return _estimate(cut(kernels.estimated(state, g.adjacency(), stored, p, c, True, lambda s: kernels.balanced(s, alpha, c, floor, arc, ahead)), "scores"))
    sources = max(1, state.select("query_id").distinct().count())
    top = state.agg(F.max(F.col("r") / F.greatest(F.col("deg"), F.lit(1)))).first()[0] or 0.0
    rho = max(floor, top / 2)
    rounds = 0
    while True:  # one round at a time: a whole rung may cost far more than it saves
        pushed = forward_push(g, state, rho, p.alpha, max_rounds=1, chain=1, engine=engine)
        state, rounds = pushed.state, rounds + pushed.rounds
        spent = prices.arc * pushed.edge_touches + prices.round * rounds * sources
        ahead = per_walk * (1 - p.alpha) * pushed.residue * c
        if spent + prices.round >= ahead or (not pushed.rounds and rho <= floor):
            return finish(g, Pushed(state, rounds, pushed.residue, pushed.edge_touches), p, c, True, index, engine)
        if not pushed.rounds:
            rho /= 4


def calibrate(g: Graph, p: PprParams, walks: int = 20_000) -> Prices:
    """Seconds of a hop, an arc and a round on this cluster, from short probes."""
    from time import perf_counter

    p = p.resolve(g.n)
    some = g.nodes.orderBy(F.xxhash64("v")).limit(20).select(F.lit(0).cast("long").alias("query_id"), F.col("v").alias("start"), F.lit(walks // 20).cast("long").alias("n_walks"), F.lit(1.0).alias("weight"))
    some = cut(some, "probe")
    t = perf_counter()
    hops = run_walks(g, some, p).agg(F.sum("hops")).first()[0] or 1
    hop = (perf_counter() - t) / hops
    from pushwave.operators.push import from_distribution

    sigma = g.nodes.select(F.lit(0).cast("long").alias("query_id"), "v", F.lit(1.0 / g.n).alias("mass"))
    state = from_distribution(g, sigma)
    t = perf_counter()
    pushed = forward_push(g, state, 0.0, p.alpha, max_rounds=1, engine="join")
    took = perf_counter() - t
    return Prices(took / max(1, pushed.edge_touches), hop, took / 2)


def monte_carlo(g: Graph, state: DataFrame, p: PprParams, engine: str = "auto", walks: int | None = None) -> Estimate:
    """Frequencies of walk ends from the start distribution itself."""
    p = p.resolve(g.n)
    c = walks or p.walks
    return finish(g, Pushed(state, 0, float(state.agg(F.sum("r")).first()[0] or 0.0), 0), p, c, False, None, engine)


def monte_carlo_visits(g: Graph, state: DataFrame, p: PprParams, walks: int | None = None, engine: str = "auto") -> Estimate:
    """Monte Carlo that counts every node a walk visits, not its end alone: a visit is worth alpha, and
    1 at a node without out-arcs, where the walk must end. The same mean with less variance a walk."""
    p = p.resolve(g.n)
    alloc = allocate_walks(state, walks or p.walks, p.alpha, False)
    found = cut(run_walks(g, alloc, p, False, engine, visits=True), "scores")
    n, hops = found.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum("hops"), F.lit(0))).first()
    return Estimate(found.select("query_id", "v", F.col("weight").alias("score")), residue=float(state.agg(F.sum("r")).first()[0] or 0.0), walks=int(n), hops=int(hops))


def power(g: Graph, state: DataFrame, rounds: int = 100, alpha: float = 0.2, chain: int = 2, engine: str = "auto") -> Estimate:
    """Exact up to (1-alpha)^rounds: everything is pushed every round; what is left counts where it lies."""
    from pushwave.operators.push import _round

    if g.in_kernel(engine):
        state = cut(kernels.pushed(state, g.adjacency(), 0.0, alpha, 0.0, rounds), "power")
        return Estimate(state.filter("p > 0").select("query_id", "v", F.col("p").alias("score")), rounds)
    steps = g.steps()
    for i in range(0, rounds, chain):
        for _ in range(min(chain, rounds - i)):
            state = _round(state, steps, alpha, 0.0, 0.0)
        state = cut(state, "power")
    return Estimate(state.filter("p > 0").select("query_id", "v", F.col("p").alias("score")), rounds)
