"""Residue pushing, forward and backward, from any start distribution, for many queries at once.

A round is one join and one aggregation: eligible rows meet their arcs, stored in buckets by node so
that arcs are not shuffled, and what they send is added to what all rows keep. A written table cuts the
plan every few rounds, and one aggregate tells whether anything is left. Only touched nodes are rows.
Any order of pushes keeps reserve + residue-weighted score constant, so all eligible nodes push
together. On graphs of a checked size a query's push runs in one task instead (see kernels).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pushwave.operators import kernels
from pushwave.operators.graph import Graph
from pushwave.plans.durable import cut

#: Rounds in one plan.
CHAIN = 2
#: Frontier nodes whose ids are sent into the arc scan as a filter at most.
PRUNE = 2000


@dataclass(frozen=True)
class Pushed:
    """state: query_id, v, deg, p, r, touched (arcs touched by pushes of v)."""

    state: DataFrame
    rounds: int
    residue: float
    edge_touches: int


def starts(g: Graph, sources: DataFrame) -> DataFrame:
    """State of one-point distributions: sources (query_id, src); unknown sources are an error."""
    first = sources.select(F.col("query_id").cast("long").alias("query_id"), F.col("src").cast("long").alias("v"), F.lit(1.0).alias("mass"))
    return from_distribution(g, first)


def from_distribution(g: Graph, sigma: DataFrame) -> DataFrame:
    """State of distributions (query_id, v, mass); each query's mass must sum to 1 over known nodes."""
    known = sigma.groupBy("query_id", "v").agg(F.sum("mass").alias("mass")).join(g.nodes.select("v", F.col("out_deg").alias("deg")), "v", "left")
    state = cut(known.select(F.col("query_id").cast("long").alias("query_id"), F.col("v").cast("long").alias("v"), "deg", F.lit(0.0).alias("p"), F.col("mass").cast("double").alias("r"), F.lit(0).cast("long").alias("touched")), "state")
    worst = state.groupBy("query_id").agg(F.sum(F.when(F.col("deg").isNull(), 0.0).otherwise(F.col("r"))).alias("s")).agg(F.max(F.abs(F.col("s") - 1))).first()[0]
    if worst is not None and worst > 1e-9:
        raise ValueError("a source is unknown, or a distribution does not sum to 1")
    return state


def _eligible(rho: float, tol: float):
    return F.col("r") > F.greatest(F.lit(rho) * F.greatest(F.col("deg"), F.lit(1)), F.lit(tol))


def _round(state: DataFrame, steps: DataFrame, alpha: float, rho: float, tol: float) -> DataFrame:
    """One round: eligible rows alone meet arcs; all rows give what they keep, and one aggregation adds both.

    So a round moves the frontier's arcs and not those of every touched node. The state occurs twice in
    the plan; its exchange is computed once and reused.
    """
    hot = _eligible(rho, tol)
    gain = F.when(F.col("deg") == 0, F.col("r")).otherwise(alpha * F.col("r"))
    stay = state.select(
        "query_id", "v", "deg", (F.col("p") + F.when(hot, gain).otherwise(0.0)).alias("p"), F.when(hot, 0.0).otherwise(F.col("r")).alias("r"), (F.col("touched") + F.when(hot, F.col("deg")).otherwise(0)).alias("touched")
    )
    send = state.filter(hot & (F.col("deg") > 0)).select("query_id", F.col("v").alias("src"), ((1 - alpha) * F.col("r") / F.col("deg")).alias("r"))
    moved = send.join(steps, "src").select("query_id", F.col("dst").alias("v"), F.col("dst_deg").alias("deg"), F.lit(0.0).alias("p"), "r", F.lit(0).cast("long").alias("touched"))
    return stay.unionByName(moved).groupBy("query_id", "v").agg(F.max("deg").alias("deg"), F.sum("p").alias("p"), F.sum("r").alias("r"), F.sum("touched").alias("touched"))


def forward_push(g: Graph, state: DataFrame, rho: float, alpha: float = 0.2, tol: float = 0.0, max_rounds: int | None = None, chain: int = CHAIN, engine: str = "auto") -> Pushed:
    """Push while a residue exceeds rho times its node's degree (and tol). A state of an earlier push
    with a larger rho may be given: it goes on from there. With max_rounds it may stop early; the
    invariant holds anyway. engine: kernel (a query a task, for graphs that are broadcast), join
    (rounds of joins), or auto: the kernel where the graph is small enough."""
    if g.in_kernel(engine):
        state = cut(kernels.pushed(state, g.adjacency(), rho, alpha, tol, max_rounds), "state")
        rounds, residue, touches = state.agg(F.coalesce(F.max("rounds"), F.lit(0)), F.coalesce(F.sum("r"), F.lit(0.0)), F.coalesce(F.sum("touched"), F.lit(0))).first()
        return Pushed(state.drop("rounds"), int(rounds), float(residue), int(touches))
    steps, rounds = g.steps(), 0
    while True:
        hot = _eligible(rho, tol)
        eligible, residue, touches = state.agg(F.count_if(hot), F.coalesce(F.sum("r"), F.lit(0.0)), F.coalesce(F.sum("touched"), F.lit(0))).first()
        if not eligible or (max_rounds is not None and rounds >= max_rounds):
            return Pushed(state, rounds, float(residue), int(touches))
        todo = chain if max_rounds is None else min(chain, max_rounds - rounds)
        near = steps
        if todo == 1 and eligible <= PRUNE:  # a small frontier goes into the scan of the arcs
            near = steps.filter(F.col("src").isin([r[0] for r in state.filter(hot).select("v").distinct().collect()]))
        now = state
        for _ in range(todo):
            now = _round(now, near, alpha, rho, tol)
        state, rounds = cut(now, "state"), rounds + todo


def push_only(g: Graph, sources: DataFrame, rho: float, alpha: float = 0.2) -> DataFrame:
    """Reserves as estimates, without a guarantee: (query_id, v, score)."""
    return forward_push(g, starts(g, sources), rho, alpha).state.filter("p > 0").select("query_id", "v", F.col("p").alias("score"))


@dataclass(frozen=True)
class ReversePushed:
    """state: query_id (of the target), target, v, p, r."""

    state: DataFrame
    rounds: int


def _back_round(state: DataFrame, steps: DataFrame, alpha: float, rho: float) -> DataFrame:
    hot = F.col("r") > rho
    met = state.select("target", F.col("v").alias("src"), F.col("deg"), "p", "r", hot.alias("hot")).join(steps, "src").filter("own or hot")
    # A node without out-arcs absorbs: a unit of residue there is reserve as a whole.
    gain = F.when(F.col("deg") == 0, F.col("r")).otherwise(alpha * F.col("r"))
    p = F.when(F.col("own"), F.col("p") + F.when(F.col("hot"), gain).otherwise(0.0)).otherwise(0.0)
    sent = F.when(F.col("deg") == 0, F.col("r") / alpha).otherwise(F.col("r"))
    r = F.when(F.col("own"), F.when(F.col("hot"), 0.0).otherwise(F.col("r"))).otherwise((1 - alpha) * F.col("share") * sent)
    moved = met.select("target", F.col("dst").alias("v"), F.col("dst_deg").alias("deg"), p.alias("p"), r.alias("r"))
    return moved.groupBy("target", "v").agg(F.max("deg").alias("deg"), F.sum("p").alias("p"), F.sum("r").alias("r"))


def reverse_push(g: Graph, targets: DataFrame, rho: float, alpha: float = 0.2, max_rounds: int | None = None, chain: int = 2, steps: DataFrame | None = None, engine: str = "auto") -> ReversePushed:
    """From targets (target), against the arcs, until no residue exceeds rho.

    score(s, t) = p(s) + sum over x of score(s, x) * r(x), for a state started with r(t) = 1.
    """
    if steps is None and g.in_kernel(engine):
        few = targets.select(F.col("target").cast("long").alias("target")).join(g.nodes.select(F.col("v").alias("target")), "target").repartition(4 * g.spark.sparkContext.defaultParallelism, "target")
        state = cut(few.mapInArrow(kernels.pushed_back(g.reverse_adjacency(), rho, alpha, max_rounds), kernels.BACK), "reverse")
        return ReversePushed(state.select("target", "v", "p", "r"), int(state.agg(F.coalesce(F.max("rounds"), F.lit(0))).first()[0]))
    steps = g.backward() if steps is None else steps
    state = targets.select("target", F.col("target").alias("v")).join(g.nodes.select("v", F.col("out_deg").alias("deg")), "v").select("target", "v", "deg", F.lit(0.0).alias("p"), F.lit(1.0).alias("r"))
    state, rounds = cut(state, "reverse"), 0
    while state.filter(F.col("r") > rho).limit(1).count() and (max_rounds is None or rounds < max_rounds):
        todo = chain if max_rounds is None else min(chain, max_rounds - rounds)
        for _ in range(todo):
            state = _back_round(state, steps, alpha, rho)
        state, rounds = cut(state, "reverse"), rounds + todo
    return ReversePushed(state.select("target", "v", "p", "r"), rounds)
