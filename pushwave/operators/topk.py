"""Top-k queries: threshold halving, bound refinement, and the baselines that rank an estimate."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pushwave.functions.formulas import PprParams, cap_aware_rho, ladder
from pushwave.operators import kernels
from pushwave.operators.estimators import Estimate, Prices, _in_kernel, finish, push_walk, push_walk_balanced
from pushwave.operators.graph import Graph
from pushwave.operators.index import WalkIndex
from pushwave.operators.push import Pushed, forward_push
from pushwave.plans.durable import cut


def rank(scores: DataFrame, k: int) -> DataFrame:
    """(query_id, rk, v, score): best k of each query, ties by node. Spark limits groups before it sorts."""
    w = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "v")
    return scores.withColumn("rk", F.row_number().over(w)).filter(F.col("rk") <= k).select("query_id", F.col("rk").cast("int").alias("rk"), "v", "score")


@dataclass(frozen=True)
class TopK:
    """answer: query_id, rk, v, score, delta_end, guaranteed."""

    answer: DataFrame
    rungs: int
    walks: int
    edge_touches: int


def _answer(scores: DataFrame, k: int, delta: float, guaranteed: bool) -> DataFrame:
    return rank(scores, k).withColumns({"delta_end": F.lit(delta), "guaranteed": F.lit(guaranteed)})


def top_k_halving(g: Graph, state: DataFrame, k: int, p: PprParams, index: WalkIndex | None = None, pruned: bool = True, use_push: bool = True, rho_mult: float = 1.0, engine: str = "auto") -> TopK:
    """Estimates with eps/2 at thresholds 1/k, 1/2k, ... until the k-th score is (1+eps) times the threshold.

    The push of a rung goes on from the rung before. Queries that pass leave; the rest go on to 1/n,
    where the answer is given with guaranteed = false. use_push=False: Monte Carlo top-k.
    """
    k = max(1, min(k, g.n))
    rungs, walks, touches = ladder(g.n, g.m, k, p), 0, 0
    here, stored = _in_kernel(g, p, index, engine)
    if here and use_push:  # without pushes all work is walks, which are spread evenly below
        found = cut(kernels.halving(state, g.adjacency(), stored, index.per_degree if index is not None else None, k, p, rungs, g.m, pruned, use_push, rho_mult), "answer")
        most, walked, touched = found.filter("rk = 1").agg(F.max("rungs"), F.sum("walks"), F.sum("touched")).first()
        return TopK(found.select("query_id", "rk", "v", "score", "delta_end", "guaranteed"), most or 0, walked or 0, touched or 0)
    done: DataFrame | None = None
    for i, rung in enumerate(rungs):
        q = PprParams(p.alpha, rung.eps, rung.delta, rung.p_fail, p.seed, p.dangling, p.rng, p.shared_walks)
        rho = rho_mult * rung.rho if index is None else min(rho_mult * rung.rho, cap_aware_rho(index.per_degree, rung.c, g.m))
        if use_push:
            pushed = forward_push(g, state, rho, p.alpha, engine=engine)
        else:
            pushed = Pushed(state, 0, float(state.agg(F.sum("r")).first()[0] or 0.0), 0)
        found = finish(g, pushed, q, rung.c, pruned and use_push, index, engine)
        state, walks, touches = pushed.state, walks + found.walks, touches + pushed.edge_touches
        kth = rank(found.scores, k).groupBy("query_id").agg(F.min("score").alias("kth"), F.count(F.lit(1)).alias("n"))
        passed = [r[0] for r in kth.filter((F.col("kth") >= (1 + p.eps) * rung.delta) & (F.col("n") == k)).select("query_id").collect()]  # one row a query
        last = i == len(rungs) - 1
        ready = found.scores if last else found.scores.filter(F.col("query_id").isin(passed))
        if passed or last:
            part = _answer(ready, k, rung.delta, True)
            if last:
                part = part.withColumn("guaranteed", F.col("query_id").isin(passed) if passed else F.lit(False))
            part = cut(part, "answer")
            done = part if done is None else done.unionByName(part)
        if last:
            break
        if passed:
            state = cut(state.filter(~F.col("query_id").isin(passed)), "state")
        if not state.limit(1).count():
            break
    return TopK(done, i + 1, walks, touches)


def refine_bounds(scores: DataFrame, state: DataFrame, before: DataFrame | None, c: float, p_fail: float, pruned: bool, alpha: float) -> DataFrame:
    """(query_id, v, score, lb, ub): bounds of a rung, no looser than those before.

    With R the residue and w = R*C walks: a relative error from the larger of reserve and last
    lower bound, and an absolute one from the last upper bound. Nodes that were never touched are
    no rows; their upper bound is the absolute error at an upper bound of one.
    """
    from math import log

    share = (1 - alpha) if pruned else 1.0
    big = log(2 / p_fail)
    total = state.groupBy("query_id").agg((F.sum("r") * share).alias("res"))
    if before is not None:  # a node that no walk of this rung reached keeps its bounds, at an estimate of 0
        scores = scores.join(before.select("query_id", "v", F.col("lb").alias("lb0"), F.col("ub").alias("ub0")), ["query_id", "v"], "full").withColumn("score", F.coalesce("score", F.lit(0.0)))
    else:
        scores = scores.withColumns({"lb0": F.lit(0.0), "ub0": F.lit(1.0)})
    own = scores.join(state.select("query_id", "v", "p"), ["query_id", "v"], "left").join(total, "query_id")
    lb0, ub0, p = F.coalesce("lb0", F.lit(0.0)), F.coalesce("ub0", F.lit(1.0)), F.coalesce("p", F.lit(0.0))
    sure = F.greatest(p, lb0)
    rate = F.lit(big / c)  # R*L / w
    rel = F.when((sure > 0) & (F.col("res") > 0), F.sqrt(3 * rate / sure)).when(F.col("res") <= 0, F.lit(0.0)).otherwise(F.lit(float("inf")))
    half = 2.0 / 3.0 * rate
    absolute = F.when(F.col("res") <= 0, F.lit(0.0)).otherwise((half + F.sqrt(half * half + 8 * rate * ub0)) / 2)
    ub = F.least(F.lit(1.0), ub0, F.col("score") + absolute, F.when(rel < 1, F.col("score") / (1 - rel)).otherwise(F.lit(1.0)))
    lb = F.greatest(F.lit(0.0), lb0, p, F.col("score") - absolute, F.col("score") / (1 + rel))
    return own.select("query_id", "v", "score", F.least(lb, ub).alias("lb"), ub.alias("ub"))


def bounds_pass(bounds: DataFrame, k: int, eps: float, delta: float) -> DataFrame:
    """(query_id) of the queries whose k best lower bounds are tight, above delta, and unrivalled."""
    w = Window.partitionBy("query_id").orderBy(F.col("lb").desc(), "v")
    best = bounds.withColumn("rk", F.row_number().over(w)).filter(F.col("rk") <= k)
    inside = best.groupBy("query_id").agg(F.min("lb").alias("least"), F.max((F.col("ub") >= (1 + eps) * F.col("lb")).cast("int")).alias("loose"), F.count(F.lit(1)).alias("n"))
    outside = bounds.join(best.select("query_id", "v"), ["query_id", "v"], "left_anti").join(inside.select("query_id", "least"), "query_id")
    rivals = outside.filter((F.col("ub") > (1 + eps) * F.col("least")) & (F.col("ub") < (1 + eps) * F.col("lb") / (1 - eps))).select("query_id").distinct()
    return inside.filter((F.col("loose") == 0) & (F.col("least") >= delta) & (F.col("n") == k)).select("query_id").join(rivals, "query_id", "left_anti")


def top_k_bounds(g: Graph, state: DataFrame, k: int, p: PprParams, index: WalkIndex | None = None, pruned: bool = False, engine: str = "auto") -> TopK:
    """The same ladder with bounds of every node kept from rung to rung; stops on their three tests."""
    k = max(1, min(k, g.n))
    rungs, walks, touches = ladder(g.n, g.m, k, p, halve_eps=False), 0, 0
    bounds: DataFrame | None = None
    done: DataFrame | None = None
    for i, rung in enumerate(rungs):
        q = PprParams(p.alpha, rung.eps, rung.delta, rung.p_fail, p.seed, p.dangling, p.rng, p.shared_walks)
        rho = rung.rho if index is None else cap_aware_rho(index.per_degree, rung.c, g.m)
        pushed = forward_push(g, state, rho, p.alpha, engine=engine)
        found = finish(g, pushed, q, rung.c, pruned, index, engine)
        state, walks, touches = pushed.state, walks + found.walks, touches + pushed.edge_touches
        bounds = cut(refine_bounds(found.scores, state, bounds, rung.c, rung.p_fail, pruned, p.alpha), "bounds")
        passed = [r[0] for r in bounds_pass(bounds, k, p.eps, rung.delta).collect()]  # one row a query
        last = i == len(rungs) - 1
        if passed or last:
            ready = bounds if last else bounds.filter(F.col("query_id").isin(passed))
            part = cut(_answer(ready.select("query_id", "v", "score"), k, rung.delta, True).withColumn("guaranteed", F.col("query_id").isin(passed) if passed else F.lit(False)), "answer")
            done = part if done is None else done.unionByName(part)
        if last:
            break
        if passed:
            state = cut(state.filter(~F.col("query_id").isin(passed)), "state")
            bounds = bounds.filter(~F.col("query_id").isin(passed))
        if not state.limit(1).count():
            break
    return TopK(done, i + 1, walks, touches)


def top_k_full_sort(g: Graph, state: DataFrame, k: int, p: PprParams, index: WalkIndex | None = None, tuned: bool = False) -> TopK:
    """The whole-graph estimate at delta = 1/n, then ranked."""
    found: Estimate = push_walk_balanced(g, state, p, Prices(), index) if tuned else push_walk(g, state, p, index=index)
    return TopK(_answer(found.scores, k, 1 / g.n, True), 1, found.walks, found.edge_touches)


def recommend(answer: DataFrame, g: Graph, sources: DataFrame, k: int) -> DataFrame:
    """Best k of an answer that the source has no arc to yet, itself left out."""
    linked = g.arcs.select("src", F.col("dst").alias("v")).join(F.broadcast(sources), "src").select("query_id", "v")
    selves = sources.select("query_id", F.col("src").alias("v"))
    return rank(answer.select("query_id", "v", "score").join(linked.unionByName(selves), ["query_id", "v"], "left_anti"), k)
