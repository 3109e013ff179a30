"""Methods to compare with: bidirectional (one target, all targets, hub-indexed), filter-refine
top-k, tuned push alone, and the shell approximation (reconstructed from published work)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pushwave.functions.formulas import PprParams, push_threshold, reverse_threshold
from pushwave.operators.estimators import Estimate, finish, monte_carlo, power
from pushwave.operators.graph import Graph
from pushwave.operators.push import Pushed, forward_push, from_distribution, push_only, reverse_push, starts
from pushwave.operators.topk import TopK, _answer, rank
from pushwave.operators.walks import run_walks
from pushwave.plans.durable import cut


#: The coarse walks of filter-refine are this part of a whole estimate's: they only have to rule nodes out.
COARSE = 16


def _histogram(g: Graph, sources: DataFrame, walks: int, p: PprParams, engine: str = "auto") -> DataFrame:
    """(query_id, src, x, share): where walks from each source end."""
    alloc = sources.select("query_id", F.col("src").alias("start"), F.lit(walks).cast("long").alias("n_walks"), F.lit(1.0 / walks).alias("weight"))
    ends = run_walks(g, alloc, p, engine=engine)
    return cut(ends.join(sources, "query_id").select("query_id", "src", F.col("v").alias("x"), F.col("weight").alias("share")), "histogram")


def _meet(ends: DataFrame, reverse: DataFrame) -> DataFrame:
    """(query_id, v, score): reserve at the source plus the mean residue where walks end."""
    mean = ends.join(reverse.filter("r > 0").select("target", F.col("v").alias("x"), "r"), "x").groupBy("query_id", "target").agg(F.sum(F.col("share") * F.col("r")).alias("score"))
    sources = ends.select("query_id", "src").distinct()
    own = sources.join(reverse.filter("p > 0").select("target", F.col("v").alias("src"), "p"), "src").select("query_id", "target", F.col("p").alias("score"))
    return mean.unionByName(own).groupBy("query_id", F.col("target").alias("v")).agg(F.sum("score").alias("score"))


def _forward_walks(rho_b: float, p: PprParams) -> int:
    from math import ceil

    return max(1, ceil(p.walks * min(1.0, rho_b)))


def bidirectional_pair(g: Graph, sources: DataFrame, targets: DataFrame, p: PprParams, rho_b: float | None = None, balanced: bool = False) -> DataFrame:
    """Scores of (source, target) pairs: reverse push from the targets, walks from the sources.

    balanced: reverse rounds go on while they have cost less than the walks still foreseen.
    """
    p = p.resolve(g.n)
    if balanced:
        steps, state, cost = None if g.in_kernel("auto") else g.backward(), None, 0.0
        bound = 1.0
        while True:
            state = reverse_push(g, targets, bound / 2, p.alpha, steps=steps)
            bound = float(state.state.agg(F.max("r")).first()[0] or 0.0)
            cost = cost + state.rounds * g.m / g.n
            if cost >= _forward_walks(bound, p) / p.alpha or bound < 1e-12:
                break
        rho_b = bound
    else:
        rho_b = rho_b or reverse_threshold(g.n, g.m, p, shared=False)
        state = reverse_push(g, targets, rho_b, p.alpha)
    return _meet(_histogram(g, sources, _forward_walks(rho_b, p), p), state.state)


def bidirectional_all(g: Graph, sources: DataFrame, p: PprParams, share_forward: bool = True, rho_b: float | None = None, hubs: HubIndex | None = None) -> Estimate:
    """All targets. share_forward: one batch of walks serves every target, at a larger threshold;
    without it each target has the walks of its own pair query."""
    p = p.resolve(g.n)
    rho_b = rho_b or reverse_threshold(g.n, g.m, p, shared=share_forward)
    walks = _forward_walks(rho_b, p)
    targets = g.nodes.select(F.col("v").alias("target"))
    if hubs is not None:
        targets = targets.join(hubs.reverse.select("target").distinct(), "target", "left_anti")
    state = reverse_push(g, targets, rho_b, p.alpha).state
    if hubs is not None:
        state = state.unionByName(hubs.reverse)
    ends = hubs.histogram(g, sources, walks, p) if hubs is not None else _histogram(g, sources, walks, p)
    return Estimate(cut(_meet(ends, state), "scores"), 0, 0, 0.0, walks)


@dataclass(frozen=True)
class HubIndex:
    """Precomputed results of the nodes with most in-arcs: walk ends and reverse states."""

    forward: DataFrame
    reverse: DataFrame
    rho_b: float
    walks: int

    def histogram(self, g: Graph, sources: DataFrame, walks: int, p: PprParams) -> DataFrame:
        """Walk ends of the sources: stored ones for hubs (as many as are stored), live ones for others."""
        known = sources.join(self.forward.withColumnRenamed("hub", "src"), "src").select("query_id", "src", "x", "share")
        rest = sources.join(self.forward.select(F.col("hub").alias("src")).distinct(), "src", "left_anti")
        return cut(known.unionByName(_histogram(g, rest, walks, p)), "histogram")


def build_hub_index(g: Graph, p: PprParams, budget_rows: int, hubs: int = 32) -> HubIndex:
    """Hubs by in-degree, as many as fit a budget of rows (at most hubs)."""
    p = p.resolve(g.n)
    rho_b = reverse_threshold(g.n, g.m, p, shared=True)
    walks = _forward_walks(rho_b, p)
    count = max(1, min(hubs, budget_rows // max(1, g.m // g.n)))
    best = g.nodes.orderBy(F.desc("in_deg"), "v").limit(count).select(F.col("v").alias("hub"))
    reverse = cut(reverse_push(g, best.select(F.col("hub").alias("target")), rho_b, p.alpha).state, "hub-reverse")
    sources = best.select(F.col("hub").alias("query_id"), F.col("hub").alias("src"))
    forward = cut(_histogram(g, sources, walks, p).select(F.col("src").alias("hub"), "x", "share"), "hub-forward")
    return HubIndex(forward, reverse, rho_b, walks)


def ranked(found: Estimate, k: int, n: int) -> TopK:
    """Top-k of a whole-graph estimate."""
    return TopK(_answer(found.scores, k, 1 / n, False), 1, found.walks, found.edge_touches)


def hub_top_k(g: Graph, sources: DataFrame, k: int, p: PprParams, hubs: HubIndex) -> TopK:
    """Hub-indexed top-k: stored results of hubs in place of their walks and reverse pushes, then ranked."""
    return ranked(bidirectional_all(g, sources, p, hubs=hubs), max(1, min(k, g.n)), g.n)


def pair_top_k(g: Graph, sources: DataFrame, k: int, p: PprParams) -> TopK:
    """A pair query for every node as the target, with walks of its own threshold each, then ranked."""
    targets = g.nodes.select(F.col("v").alias("target"))
    scores = cut(bidirectional_pair(g, sources, targets, p).filter("score > 0"), "scores")
    return TopK(_answer(scores, max(1, min(k, g.n)), 1 / g.n, False), 1, 0, 0)


def filter_refine_top_k(g: Graph, sources: DataFrame, k: int, p: PprParams, precision: float = 0.99) -> TopK:
    """Push and coarse walks give bounds; nodes whose upper bound is below the k-th lower bound go;
    reverse pushes from the rest tighten the bounds until precision * k of the answer are certain."""
    from math import log

    p, k = p.resolve(g.n), max(1, min(k, g.n))
    c = p.walks / COARSE
    pushed = forward_push(g, starts(g, sources), push_threshold(g.m, c)[0], p.alpha)
    found = finish(g, pushed, p, c, False)
    rate = log(2 / p.p_fail) / c
    slack = F.sqrt(2 * rate * F.greatest("score", F.lit(rate))) + 2.0 / 3.0 * rate
    own = found.scores.join(pushed.state.select("query_id", "v", "p"), ["query_id", "v"], "left")
    bounds = cut(own.select("query_id", "v", "score", F.greatest(F.coalesce("p", F.lit(0.0)), F.col("score") - slack).alias("lb"), (F.col("score") + slack).alias("ub")), "bounds")
    rho_b, rounds, walks, steps = 2 * rate, 0, found.walks, None if g.in_kernel("auto") else g.backward()
    while True:
        kth = rank(bounds.select("query_id", "v", F.col("lb").alias("score")), k).groupBy("query_id").agg(F.min("score").alias("kth"))
        alive = cut(bounds.join(kth, "query_id").filter(F.col("ub") >= F.col("kth")), "alive")
        sure = alive.groupBy("query_id").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > k / precision)
        open_ = sure.count()
        if not open_ or rho_b < p.eps * p.delta / 2:  # all certain, or every bound within eps of any score above delta
            break
        targets = alive.select(F.col("v").alias("target")).distinct()
        back = reverse_push(g, targets, rho_b, p.alpha, chain=4, steps=steps).state
        at = back.join(sources, F.col("v") == F.col("src")).select("query_id", F.col("target").alias("v"), F.col("p").alias("low"))
        tight = alive.select("query_id", "v", "score", "lb", "ub").join(at, ["query_id", "v"], "left")
        low = F.greatest("lb", F.coalesce("low", F.lit(0.0)))
        high = F.least("ub", F.coalesce("low", F.lit(0.0)) + rho_b)
        bounds = cut(tight.select("query_id", "v", F.least(F.greatest("score", low), high).alias("score"), low.alias("lb"), high.alias("ub")), "bounds")
        rho_b, rounds = rho_b / 4, rounds + 1
    return TopK(_answer(alive.select("query_id", "v", "score"), k, 1 / g.n, not open_), rounds + 1, walks, pushed.edge_touches)


def tune_push_only(g: Graph, sources: DataFrame, truth: DataFrame, k: int, target: float, alpha: float = 0.2, tries: int = 8) -> tuple[float, DataFrame]:
    """The largest rho of a bisection on its logarithm whose top-k reaches a precision; its scores."""
    from pushwave.operators.metrics import precision_at_k

    low, high, best = 1e-9, 1e-1, None
    for _ in range(tries):
        rho = (low * high) ** 0.5
        scores = push_only(g, sources, rho, alpha)
        got = precision_at_k(rank(scores, k), truth, k).agg(F.avg("precision")).first()[0] or 0.0
        if got >= target:
            low, best = rho, (rho, scores)
        else:
            high = rho
    return best or (low, push_only(g, sources, low, alpha))


def shell_approximation(g: Graph, sources: DataFrame, near: int = 3, far: int = 8, alpha: float = 0.2, pagerank: DataFrame | None = None) -> Estimate:
    """Exact mass of the first near rounds, a scaled copy of the last of them for the rounds up to
    far, and global scores for the remainder. No guarantee; reconstructed, not the authors' code."""
    state = starts(g, sources)
    one = forward_push(g, state, 0.0, alpha, max_rounds=near - 1, chain=max(1, near - 1)).state if near > 1 else state
    two = forward_push(g, one, 0.0, alpha, max_rounds=1, chain=1).state
    last = two.select("query_id", "v", F.col("p").alias("p2")).join(one.select("query_id", "v", F.col("p").alias("p1")), ["query_id", "v"], "left").select("query_id", "v", (F.col("p2") - F.coalesce("p1", F.lit(0.0))).alias("gain"))
    scale = sum((1 - alpha) ** i for i in range(1, far - near + 1))
    if pagerank is None:
        pagerank = global_pagerank(g, PprParams(alpha), "power", rounds=30).scores
    rest = (1 - alpha) ** far
    parts = two.select("query_id", "v", F.col("p").alias("score")).unionByName(last.select("query_id", "v", (scale * F.col("gain")).alias("score")))
    queries = sources.select("query_id").distinct()
    # A row a query and node comes out; they are made where the node is, and only what queries have near by is moved.
    near_by = parts.groupBy("query_id", "v").agg(F.sum("score").alias("score")).groupBy("v").agg(F.map_from_entries(F.collect_list(F.struct("query_id", "score"))).alias("own"))
    wide = pagerank.select("v", (rest * F.col("score")).alias("all")).join(near_by, "v", "full").crossJoin(F.broadcast(queries))
    score = F.coalesce(F.col("own")[F.col("query_id")], F.lit(0.0)) + F.coalesce("all", F.lit(0.0))
    return Estimate(cut(wide.select("query_id", "v", score.alias("score")).filter("score > 0"), "scores"), near)


def global_pagerank(g: Graph, p: PprParams, method: str = "push_walk", rounds: int = 100) -> Estimate:
    """Scores from the uniform distribution: push_walk, monte_carlo or power."""
    from pushwave.operators.estimators import push_walk

    sigma = g.nodes.select(F.lit(0).cast("long").alias("query_id"), "v", F.lit(1.0 / g.n).alias("mass"))
    state = from_distribution(g, sigma)
    if method == "power":
        return power(g, state, rounds, p.alpha)
    if method == "monte_carlo":
        return monte_carlo(g, state, p)
    return push_walk(g, state, p, pruned=True)


__all__ = ["Pushed", "HubIndex", "bidirectional_all", "bidirectional_pair", "build_hub_index", "filter_refine_top_k", "global_pagerank", "hub_top_k", "pair_top_k", "ranked", "shell_approximation", "tune_push_only"]
