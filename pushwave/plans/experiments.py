"""The paper's experiments on the derived graphs, as tables of runs.

Each function returns rows (workload, graph, method, k, rho_mult, seconds, precision, ndcg,
max_error, walks, edge_touches, rows). Times are of this machine; the other columns don't depend on it.
"""

from __future__ import annotations

from collections.abc import Callable
from time import perf_counter

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pushwave.functions.formulas import PprParams, expected_costs, push_threshold
from pushwave.operators import baselines as B
from pushwave.operators import estimators as E
from pushwave.operators import metrics as M
from pushwave.operators import topk as T
from pushwave.operators.graph import Graph, build_graph
from pushwave.operators.index import build_walk_index
from pushwave.operators.push import from_distribution, push_only, starts
from pushwave.plans.durable import cut, drop
from pushwave.sources.graphs import rmat
from pushwave.workloads import graph, hashed_sources, register, uniform

#: Sources of a batch and answer sizes of the experiments (clamped to half of a smaller graph), the graphs,
#: and the most nodes of a graph on which whole-graph methods push back from every node.
SOURCES, KS, GRAPHS, TARGETS = 50, (100, 200, 300, 400, 500), ("event_user", "supp_next", "part_next"), 300
SCHEMA = "workload string, graph string, method string, k int, rho_mult double, seconds double, precision double, ndcg double, max_error double, walks long, edge_touches long, rows long"
P = PprParams()


class Bench:
    """One graph with its sources, start state and exact scores."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str, count: int = SOURCES, rounds: int = 100, g: Graph | None = None):
        self.spark, self.name, self.rows = spark, name, []
        self.g: Graph = g or graph(spark, sf_dir, name)
        self.sources = hashed_sources(self.g, count)
        self.state = starts(self.g, self.sources)
        self.truth = cut(E.power(self.g, self.state, rounds).scores, "truth")
        self.rho = push_threshold(self.g.m, P.resolve(self.g.n).walks)[0]
        self.best, self.known = None, 0  # the highest exact scores of each query, as many as were asked for

    def _row(self, workload, method, seconds, k=None, mult=None, precision=None, ndcg=None, error=None, walks=None, touches=None, rows=None):
        self.rows.append((workload, self.name, method, k, None if mult is None else float(mult), seconds, precision, ndcg, error, walks, touches, rows))

    def whole(self, workload: str, method: str, run: Callable[[], E.Estimate], mult: float | None = None) -> None:
        t = perf_counter()
        found = run()
        seconds = perf_counter() - t
        error = M.relative_error(found.scores, self.truth, 1 / self.g.n).agg(F.max("max_error")).first()[0]
        drop(found.scores)
        self._row(workload, method, seconds, mult=mult, error=error, walks=found.walks, touches=found.edge_touches)

    def top(self, workload: str, method: str, k: int, run: Callable[[], T.TopK], mult: float | None = None) -> float:
        t = perf_counter()
        found = run()
        answer = cut(found.answer, "answer")
        seconds = perf_counter() - t
        if self.best is None or self.known < k:
            self.best, self.known = cut(T.rank(self.truth, k).select("query_id", "v", "score"), "best"), k
        precision = M.precision_at_k(answer, self.best, k).agg(F.avg("precision")).first()[0]
        ndcg = M.ndcg_at_k(answer, self.truth, k, self.best).agg(F.avg("ndcg")).first()[0]
        drop(found.answer, answer)
        self._row(workload, method, seconds, k, mult, precision, ndcg, walks=found.walks, touches=found.edge_touches)
        return precision or 0.0

    def timed(self, workload: str, method: str, run: Callable, size: Callable):
        """run's result, with its time and the rows that it keeps."""
        t = perf_counter()
        made = run()
        self._row(workload, method, perf_counter() - t, rows=size(made))
        return made

    def index(self, workload: str, mult: float, pruned: bool, held: bool = True):
        t = perf_counter()
        made = build_walk_index(self.g, P, mult * self.rho, pruned, held=held)
        rows = made.rows.count()
        self._row(workload, "index pruned" if pruned else "index", perf_counter() - t, mult=mult, rows=rows)
        return made

    def table(self) -> DataFrame:
        """The rows; the exact scores go, as the last thing that is compared with them is."""
        drop(self.truth)
        return self.spark.createDataFrame(self.rows, SCHEMA)


def whole_graph(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = GRAPHS, count: int = SOURCES, targets: bool = True) -> DataFrame:
    """Whole-graph methods and their ablation, with preprocessing and index sizes.

    targets: also the methods that push back from every node; their state grows with the square of the
    nodes, so they run on graphs of up to TARGETS nodes.
    """
    rows = None
    for name in names:
        b = Bench(spark, sf_dir, name, count)
        plain, wide = b.index("preprocessing", 1, False), b.index("preprocessing", 2, True)
        b.whole("whole-graph", "monte carlo", lambda: E.monte_carlo(b.g, b.state, P))
        b.whole("whole-graph", "monte carlo, visits", lambda: E.monte_carlo_visits(b.g, b.state, P))
        b.whole("whole-graph", "push-walk basic", lambda: E.push_walk(b.g, b.state, P))
        b.whole("whole-graph", "push-walk pruned", lambda: E.push_walk(b.g, b.state, P, pruned=True))
        b.whole("whole-graph", "push-walk tuned", lambda: E.push_walk_balanced(b.g, b.state, P))
        b.whole("whole-graph", "push-walk basic indexed", lambda: E.push_walk(b.g, b.state, P, index=plain))
        b.whole("whole-graph", "push-walk tuned indexed", lambda: E.push_walk(b.g, b.state, P, rho_mult=2, pruned=True, index=wide))
        b.whole("whole-graph", "shell approximation", lambda: B.shell_approximation(b.g, b.sources))
        if targets and b.g.n <= TARGETS:
            b.whole("whole-graph", "bidirectional", lambda: B.bidirectional_all(b.g, b.sources, P))
            hubs = b.timed("preprocessing", "hub index", lambda: B.build_hub_index(b.g, P, plain.rows.count()), lambda h: h.forward.count() + h.reverse.count())
            b.whole("whole-graph", "hub-indexed bidirectional", lambda: B.bidirectional_all(b.g, b.sources, P, hubs=hubs))
        plain.drop()
        wide.drop()
        rows = b.table() if rows is None else rows.unionByName(b.table())
    return rows


def top_k(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("event_user", "part_next"), ks: tuple[int, ...] = KS, count: int = SOURCES, slow: bool = True) -> DataFrame:
    """Top-k methods over k: time, precision and NDCG. Push alone is tuned, by graph, to the precision of the
    halving method. slow: the methods without an index, and those of many jobs or of state that grows with the
    square of the nodes, run too (at the greatest k), on graphs of any size."""
    rows = None
    for name in names:
        b = Bench(spark, sf_dir, name, count)
        plain, index = b.index("preprocessing", 1, False), b.index("preprocessing", 1, True)
        some = sorted({min(k, b.g.n // 2) for k in ks})
        tuned = None
        for k in reversed(some):
            want = b.top("top-k", "halving indexed", k, lambda k=k: T.top_k_halving(b.g, b.state, k, P, index=index))
            b.top("top-k", "full sort indexed", k, lambda k=k: T.top_k_full_sort(b.g, b.state, k, P, index=plain))
            if tuned is None:
                tuned = B.tune_push_only(b.g, b.sources, b.truth, k, want, tries=5)[0]
            b.top("top-k", "push only, tuned", k, lambda k=k: T.TopK(T.rank(push_only(b.g, b.sources, tuned), k), 1, 0, 0))
        b.top("top-k", "shell approximation", some[-1], lambda k=some[-1]: B.ranked(B.shell_approximation(b.g, b.sources), k, b.g.n))
        if slow:
            k = some[-1]
            b.top("ablation", "halving", k, lambda: T.top_k_halving(b.g, b.state, k, P))
            b.top("ablation", "halving indexed", k, lambda: T.top_k_halving(b.g, b.state, k, P, index=index))
            b.top("ablation", "bounds", k, lambda: T.top_k_bounds(b.g, b.state, k, P))
            b.top("ablation", "bounds indexed", k, lambda: T.top_k_bounds(b.g, b.state, k, P, index=plain))
            b.top("top-k", "monte carlo", k, lambda: T.top_k_halving(b.g, b.state, k, P, use_push=False))
            b.top("top-k", "filter-refine", k, lambda: B.filter_refine_top_k(b.g, b.sources, k, P))
            b.top("top-k", "hub-indexed", k, lambda: B.hub_top_k(b.g, b.sources, k, P, B.build_hub_index(b.g, P, plain.rows.count())))
        rows = b.table() if rows is None else rows.unionByName(b.table())
    return rows


def rho_tuning(spark: SparkSession, sf_dir: str, name: str = "part_next", mults: tuple[int, ...] = (1, 2, 3, 4, 5, 6, 7)) -> DataFrame:
    """Whole-graph queries over multiples of the threshold: pushes fall and walks rise with it."""
    b = Bench(spark, sf_dir, name)
    for m in mults:
        index = b.index("rho tuning", m, True)
        b.whole("rho tuning", "push-walk tuned indexed", lambda m=m, i=index: E.push_walk(b.g, b.state, P, rho_mult=m, pruned=True, index=i), m)
        index.drop()
    return b.table()


def rho_tuning_top_k(spark: SparkSession, sf_dir: str, name: str = "part_next", k: int = 100, mults: tuple[int, ...] = (1, 2, 3, 4, 5, 6, 7)) -> DataFrame:
    """Top-k queries over multiples of the threshold, each with an index for it."""
    b = Bench(spark, sf_dir, name)
    for m in mults:
        index = b.index("rho tuning top-k", m, True)
        b.top("rho tuning top-k", "halving indexed", k, lambda m=m, i=index: T.top_k_halving(b.g, b.state, k, P, index=i, rho_mult=m), m)
        index.drop()
    return b.table()


def scalability(spark: SparkSession, sf_dir: str, scales: tuple[int, ...] = (10, 12), k: int = 500, count: int = 10) -> DataFrame:
    """Recursive-matrix graphs of growing size: the indexed halving method against a full sort."""
    rows = None
    for scale in scales:
        b = Bench(spark, sf_dir, f"rmat_{scale}", count, g=build_graph(rmat(spark, scale)))
        index = b.index("preprocessing", 1, True)
        b.top("scalability", "halving indexed", k, lambda: T.top_k_halving(b.g, b.state, k, P, index=index))
        b.top("scalability", "full sort", k, lambda: T.top_k_full_sort(b.g, b.state, k, P, index=index))
        rows = b.table() if rows is None else rows.unionByName(b.table())
    return rows


def networks(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("emb_knn", "part_part")) -> DataFrame:
    """Two further networks, of another kind: the four whole-graph methods of the ablation."""
    return whole_graph(spark, sf_dir, names, targets=False)


def space(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = GRAPHS) -> DataFrame:
    """Rows, files and bytes of what every method keeps: the graph, its reverse copy, the indexes."""
    rows = None
    for name in names:
        b = Bench(spark, sf_dir, name, 1, rounds=1)
        tables = {"graph": b.g.arcs, "reverse graph": b.g.backward(), "index": b.index("space", 1, False, held=False).rows, "index pruned": b.index("space", 1, True, held=False).rows, "index pruned, 2 rho": b.index("space", 2, True, held=False).rows}
        one = M.table_cost(tables).select(F.lit(name).alias("graph"), "*")
        rows = one if rows is None else rows.unionByName(one)
    return rows


def balance(spark: SparkSession, sf_dir: str, name: str = "part_next") -> DataFrame:
    """(method, push_cost, walk_cost): arcs touched against hops walked when a query stops, whole batch."""
    b = Bench(spark, sf_dir, name, rounds=1)
    runs = {"push-walk basic": lambda: E.push_walk(b.g, b.state, P), "push-walk pruned": lambda: E.push_walk(b.g, b.state, P, pruned=True), "push-walk tuned": lambda: E.push_walk_balanced(b.g, b.state, P)}
    rows = []
    for method, run in runs.items():
        found = run()
        drop(found.scores)  # its work alone counts here
        rows.append((method, found.edge_touches, found.hops))
    return spark.createDataFrame(rows, "method string, push_cost long, walk_cost long")


def ratios(spark: SparkSession, sf_dir: str, name: str = "event_user") -> DataFrame:
    """(graph, method, seconds, ratio): every whole-graph method's time over the tuned indexed one's."""
    runs = whole_graph(spark, sf_dir, (name,)).filter("workload = 'whole-graph'").select("graph", "method", "seconds")
    return M.ratio_table(runs, "push-walk tuned indexed")


def failures(spark: SparkSession, sf_dir: str, name: str = "event_user", seeds: int = 10) -> DataFrame:
    """(failure_rate): share of queries that break the whole-graph contract, over seeds."""
    b = Bench(spark, sf_dir, name, 5)
    checks = None
    for seed in range(seeds):
        p = PprParams(seed=seed)
        one = M.check_whole_graph(E.push_walk(b.g, b.state, p, pruned=True).scores, b.truth, p.eps, 1 / b.g.n)
        checks = one if checks is None else checks.unionByName(one)
    return M.failure_rate(checks)


def pagerank(spark: SparkSession, sf_dir: str, name: str = "page_link") -> DataFrame:
    """Global scores by push-walk and Monte Carlo against power iteration, and their best by halving."""
    b = Bench(spark, sf_dir, name, 1)
    b.truth = cut(B.global_pagerank(b.g, P, "power").scores, "truth")
    b.whole("pagerank", "push-walk", lambda: B.global_pagerank(b.g, P))
    b.whole("pagerank", "monte carlo", lambda: B.global_pagerank(b.g, P, "monte_carlo"))
    b.top("pagerank", "halving", 50, lambda: T.top_k_halving(b.g, from_distribution(b.g, uniform(b.g)), 50, P))
    return b.table()


def cost_model(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("event_user", "part_next", "cust_supp")) -> DataFrame:
    """Expected work of every method by formula."""
    rows = [(n, m, c) for n in names for g in [graph(spark, sf_dir, n)] for m, c in expected_costs(g.n, g.m, P, 10 / g.n).items()]
    return spark.createDataFrame(rows, "graph string, method string, cost double")


for _name, _run in {
    "w_whole_graph": whole_graph, "w_rho_tuning": rho_tuning, "w_rho_tuning_top_k": rho_tuning_top_k, "w_scalability": scalability, "w_networks": networks, "w_space": space, "w_balance": balance, "w_ratios": ratios, "w_failures": failures, "w_pagerank": pagerank,
}.items():
    register(_name)(_run)
register("w_top_k")(lambda spark, d: top_k(spark, d, ("event_user",)))
register("w_top_k_large")(lambda spark, d: top_k(spark, d, ("part_next",), slow=False))
