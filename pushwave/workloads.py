"""Registered queries of the engine: each method, variant, baseline, measure and surrounding
operator on the given tables, with its DuckDB twin where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pushwave.functions.formulas import PprParams, ladder, push_threshold
from pushwave.operators import baselines as B
from pushwave.operators import estimators as E
from pushwave.operators import metrics as M
from pushwave.operators import topk as T
from pushwave.operators.graph import Graph, build_graph, degree_distribution, power_law_fit
from pushwave.operators.index import build_walk_index, capacities
from pushwave.operators.push import forward_push, from_distribution, push_only, reverse_push, starts
from pushwave.operators.walks import run_walks
from pushwave.plans import oracles as O
from pushwave.plans.durable import cut, ship
from pushwave.sources import graphs as S

Query = Callable[[SparkSession, str], DataFrame]
#: A threshold that no residue of the test graphs hits exactly.
RHO = 0.000123457
_graphs: dict[tuple[str, str, str], Graph] = {}


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """The tables of a derived graph, built once a session."""
    ship(spark)
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _graphs:
        _graphs[key] = build_graph(S.GRAPHS[name](spark, sf_dir))
    return _graphs[key]


def first_sources(g: Graph, count: int) -> DataFrame:
    """The least node ids as sources 0 .. count-1."""
    few = g.nodes.orderBy("v").limit(count).select("v")
    return cut(few.select((F.row_number().over(Window.orderBy("v")) - 1).cast("long").alias("query_id"), F.col("v").alias("src")), "sources")


def hashed_sources(g: Graph, count: int, seed: int = 42) -> DataFrame:
    """count nodes in hash order: a uniform sample without replacement."""
    few = g.nodes.orderBy(F.xxhash64(F.lit(seed).cast("long"), "v"), "v").limit(count).select("v")
    return cut(few.select((F.row_number().over(Window.orderBy(F.xxhash64(F.lit(seed).cast("long"), "v"))) - 1).cast("long").alias("query_id"), F.col("v").alias("src")), "sources")


def uniform(g: Graph) -> DataFrame:
    return g.nodes.select(F.lit(0).cast("long").alias("query_id"), "v", F.lit(1.0 / g.n).alias("mass"))


def _r(column: str, digits: int = 9):
    return F.round(F.col(column), digits).alias(column)


def _scores(df: DataFrame) -> DataFrame:
    return df.select("query_id", "v", _r("score"))


_SCORES = "SELECT query_id, v, round(score, 9) AS score FROM"
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


# --- graphs -----------------------------------------------------------------------------------

for _name, _load in S.GRAPHS.items():
    register(f"q_graph_{_name}", S.GRAPH_SQL.get(_name))(lambda spark, d, f=_load: (ship(spark), f(spark, d))[1])


SQL["q_graph_emb_knn"] = """WITH e AS (SELECT * FROM embeddings), k AS (SELECT a.{id} AS src, b.{id} AS dst, row_number() OVER (PARTITION BY a.{id} ORDER BY round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) DESC, b.{id}) AS rk
FROM e a JOIN e b ON a.{id} <> b.{id}) SELECT src::BIGINT AS src, dst::BIGINT AS dst FROM k WHERE rk <= 10""".replace("{id}", "vec_id")


@register("q_graph_stats", "SELECT * FROM (" + " UNION ALL ".join(O.query(f"SELECT '{n}' AS graph, (SELECT count(*) FROM nodes) AS n, count(*) AS m, sum((SELECT count(*) FROM nodes WHERE d = 0))::BIGINT // count(*) AS dangling FROM arcs", O.graph_cte(n)).join(["SELECT * FROM (", ")"]) for n in ("trade_nation", "event_user", "part_next", "page_link")) + ")")
def q_graph_stats(spark, d):
    rows = None
    for n in ("trade_nation", "event_user", "part_next", "page_link"):
        g = graph(spark, d, n)
        one = g.nodes.agg(F.lit(n).alias("graph"), F.count(F.lit(1)).alias("n"), F.sum("out_deg").alias("m"), F.sum((F.col("out_deg") == 0).cast("long")).alias("dangling"))
        rows = one if rows is None else rows.unionByName(one)
    return rows


@register("q_degree_dist", O.query("SELECT d AS out_deg, count(*) AS n FROM nodes GROUP BY d", O.graph_cte("cust_supp")))
def q_degree_dist(spark, d):
    return degree_distribution(graph(spark, d, "cust_supp"))


@register("q_power_law", O.query("SELECT round(regr_slope(y, x), 6) AS slope, round(regr_intercept(y, x), 6) AS intercept, round(corr(y, x), 6) AS corr FROM (SELECT ln(i) AS x, ln(count(*)) AS y FROM nodes WHERE i > 0 GROUP BY i)", O.graph_cte("page_link")))
def q_power_law(spark, d):
    return power_law_fit(graph(spark, d, "page_link")).select(_r("slope", 6), _r("intercept", 6), _r("corr", 6))


@register("q_adjacency_pos", O.query("SELECT src, pos, dst FROM pos", O.graph_cte("event_user")))
def q_adjacency_pos(spark, d):
    return graph(spark, d, "event_user").arcs.select("src", "pos", "dst")


@register("q_dangling", O.query("SELECT v, i AS in_deg FROM nodes WHERE d = 0", O.graph_cte("page_link")))
def q_dangling(spark, d):
    return graph(spark, d, "page_link").nodes.filter("out_deg = 0").select("v", "in_deg")


# --- scalars ----------------------------------------------------------------------------------

_PARAM_GRAPHS = ("trade_nation", "event_user", "part_next", "supp_next")
_C_SQL = "(2 + 2 * 0.5 / 3) * ln(2.0 * n) / (0.25 / n)"


@register("q_params", " UNION ALL ".join(f"SELECT * FROM ({O.query(f'SELECT {chr(39)}{n}{chr(39)} AS graph, round(c, 3) AS c, round(CASE WHEN m <= c THEN 1 / sqrt(m * c) ELSE 1 / c END, 12) AS rho, CASE WHEN m <= c THEN 1 ELSE 2 END AS threshold_case FROM (SELECT m, {_C_SQL} AS c FROM (SELECT (SELECT count(*) FROM nodes) AS n, count(*) AS m FROM arcs))', O.graph_cte(n))})" for n in _PARAM_GRAPHS))
def q_params(spark, d):
    rows = []
    for n in _PARAM_GRAPHS:
        g = graph(spark, d, n)
        c = PprParams().resolve(g.n).walks
        rho, case = push_threshold(g.m, c)
        rows.append((n, round(c, 3), round(rho, 12), case))
    return spark.createDataFrame(rows, "graph string, c double, rho double, threshold_case int")


def _capacity_sql(share: str, pruned: bool) -> str:
    dead = "CASE WHEN d = 0 THEN 0 ELSE " if pruned else ""
    end = " END" if pruned else ""
    return O.query(f"SELECT v, ({dead}ceil({share} / sqrt(m * c) * c * greatest(d, 1)){end})::BIGINT AS cap FROM nodes, (SELECT m, {_C_SQL} AS c FROM (SELECT (SELECT count(*) FROM nodes) AS n, count(*) AS m FROM arcs))", O.graph_cte("part_next"))


@register("q_index_capacity", _capacity_sql("1.0", False))
def q_index_capacity(spark, d):
    g = graph(spark, d, "part_next")
    p = PprParams().resolve(g.n)
    return capacities(g, push_threshold(g.m, p.walks)[0], p.walks, p.alpha, False)


@register("q_index_capacity_pruned", _capacity_sql("0.8", True))
def q_index_capacity_pruned(spark, d):
    g = graph(spark, d, "part_next")
    p = PprParams().resolve(g.n)
    return capacities(g, push_threshold(g.m, p.walks)[0], p.walks, p.alpha, True)


_L, _N, _M = "ln(2.0 * n)", "n::DOUBLE", "m::DOUBLE"
_COSTS = {
    "monte_carlo": "c", "push_walk": "least(sqrt(m * c), c)", "bidirectional": f"sqrt(m * n * {_L} * n) / 0.5", "bidirectional_shared": f"sqrt(m * {_L} * n) / 0.5",
    "push_only": "CASE WHEN m <= c THEN sqrt(m * c) ELSE c END", "power": "m * ln(n / 0.5) / -ln(0.8)", "mc_top_k": f"{_L} / (10.0 / n * 0.25)",
    "top_k_halving": f"least(sqrt(m * {_L} / (10.0 / n)) / 0.5, {_L} / (10.0 / n * 0.25))", "filter_refine_top_k": "(m + n * ln(n)) / sqrt(10.0 / n)",
}


def _costs_sql(name: str) -> str:
    each = " UNION ALL ".join(f"SELECT '{name}' AS graph, '{method}' AS method, {cost} AS cost FROM size" for method, cost in _COSTS.items())
    return "SELECT * FROM (" + O.query(each, O.graph_cte(name), f"size AS (SELECT n::DOUBLE AS n, m::DOUBLE AS m, {_C_SQL} AS c FROM (SELECT (SELECT count(*) FROM nodes) AS n, count(*) AS m FROM arcs))") + ")"


def _digits(column: str) -> str:
    return f"round({column} / pow(10, floor(log10({column}))), 6)"


@register("q_cost_model", f"SELECT graph, method, {_digits('cost')} AS cost, floor(log10(cost))::INT AS power FROM (" + " UNION ALL ".join(_costs_sql(n) for n in _PARAM_GRAPHS) + ")")
def q_cost_model(spark, d):
    from pushwave.functions.formulas import expected_costs

    rows = [(n, method, float(cost)) for n in _PARAM_GRAPHS for g in [graph(spark, d, n)] for method, cost in expected_costs(g.n, g.m, PprParams(), 10 / g.n).items()]
    cost = F.col("cost")
    return spark.createDataFrame(rows, "graph string, method string, cost double").select("graph", "method", F.round(cost / F.pow(F.lit(10.0), F.floor(F.log10(cost))), 6).alias("cost"), F.floor(F.log10(cost)).cast("int").alias("power"))


_LADDER = """SELECT (row_number() OVER (ORDER BY delta DESC) - 1)::INT AS rung, round(delta, 12) AS delta, round(c, 3) AS c, round(CASE WHEN m <= c THEN 1 / sqrt(m * c) ELSE 1 / c END, 15) AS rho FROM (
SELECT *, (2 + 0.5 / 3) * ln(2 / (1 / (n * n * greatest(1, log2(n / 20))))) / (0.0625 * delta) AS c FROM (SELECT n, m, 1 / (20.0 * pow(2, i)) AS delta FROM size, range(60) t(i) WHERE 1 / (20.0 * pow(2, i)) > 1 / n * (1 + 1e-12) UNION ALL SELECT n, m, 1 / n FROM size))"""


@register("q_topk_ladder", O.query(_LADDER, O.graph_cte("part_next"), "size AS (SELECT (SELECT count(*) FROM nodes)::DOUBLE AS n, count(*)::DOUBLE AS m FROM arcs)"))
def q_topk_ladder(spark, d):
    g = graph(spark, d, "part_next")
    return spark.createDataFrame([(i, r.delta, r.c, r.rho) for i, r in enumerate(ladder(g.n, g.m, 20, PprParams()))], "rung int, delta double, c double, rho double").select("rung", _r("delta", 12), _r("c", 3), _r("rho", 15))


# --- exact ------------------------------------------------------------------------------------

ROUNDS = 100


def _power_sql(name: str, sigma: str, sources: int = 2) -> str:
    return O.query(f"{_SCORES} (SELECT query_id, v, p AS score FROM push WHERE p > 0)", O.graph_cte(name), O.sources_cte(sources), O.push_cte(sigma, "0.0", ROUNDS))


def _truth(g: Graph, count: int = 2, rounds: int = ROUNDS) -> DataFrame:
    key = (g.spark.sparkContext.applicationId, f"truth{count}.{rounds}", str(id(g)))
    if key not in _graphs:
        _graphs[key] = cut(E.power(g, starts(g, first_sources(g, count)), rounds).scores, "truth")
    return _graphs[key]


for _name in ("trade_nation", "event_user", "part_next", "page_link"):
    register(f"q_power_ppr_{_name}", _power_sql(_name, O.POINT))(lambda spark, d, n=_name: _scores(_truth(graph(spark, d, n))))


@register("q_power_pagerank", _power_sql("page_link", O.UNIFORM))
def q_power_pagerank(spark, d):
    return _scores(B.global_pagerank(graph(spark, d, "page_link"), PprParams(), "power", ROUNDS).scores)


_RANKED = "(SELECT query_id, v, p AS score, row_number() OVER (PARTITION BY query_id ORDER BY p DESC, v) AS rk FROM push)"


@register("q_exact_topk", O.query(f"SELECT query_id, rk::INT AS rk, v, round(score, 9) AS score FROM {_RANKED} WHERE rk <= 10", O.graph_cte("event_user"), O.sources_cte(2), O.push_cte(O.POINT, "0.0", ROUNDS)))
def q_exact_topk(spark, d):
    return T.rank(_truth(graph(spark, d, "event_user")), 10).select("query_id", "rk", "v", _r("score"))


@register("q_pagerank_topk", O.query(f"SELECT query_id, rk::INT AS rk, v, round(score, 9) AS score FROM {_RANKED} WHERE rk <= 10", O.graph_cte("event_user"), O.push_cte(O.UNIFORM, "0.0", ROUNDS)))
def q_pagerank_topk(spark, d):
    return T.rank(B.global_pagerank(graph(spark, d, "event_user"), PprParams(), "power", ROUNDS).scores, 10).select("query_id", "rk", "v", _r("score"))


_SEGMENT_SQL = "SELECT 0::BIGINT AS query_id, v, 1.0::DOUBLE / count(*) OVER () AS mass FROM (SELECT c_custkey * 2 AS v FROM customer WHERE c_mktsegment = 'BUILDING') JOIN nodes USING (v)"


def _segment(spark, d, g: Graph) -> DataFrame:
    """Customers of one market segment as a source distribution."""
    who = S.read(spark, d, "customer", "c_custkey", "c_mktsegment").filter("c_mktsegment = 'BUILDING'").select((F.col("c_custkey") * 2).alias("v")).join(g.nodes.select("v"), "v")
    total = who.count()
    return who.select(F.lit(0).cast("long").alias("query_id"), "v", F.lit(1.0 / max(1, total)).alias("mass"))


@register("q_sigma_ppr", O.query(f"{_SCORES} (SELECT query_id, v, p AS score FROM push WHERE p > 0)", O.graph_cte("cust_supp"), O.push_cte(_SEGMENT_SQL, "0.0", ROUNDS)))
def q_sigma_ppr(spark, d):
    g = graph(spark, d, "cust_supp")
    return _scores(E.power(g, from_distribution(g, _segment(spark, d, g)), ROUNDS).scores)


# --- pushes -----------------------------------------------------------------------------------


def _push_sql(name: str, sigma: str = O.POINT, rho: float = RHO, rounds: int = 40, sources: int = 2) -> str:
    return O.query("SELECT query_id, v, round(p, 9) AS p, round(r, 9) AS r FROM push", O.graph_cte(name), O.sources_cte(sources), O.push_cte(sigma, str(rho), rounds))


def _pushed(spark, d, name, sources: int = 2, rho: float = RHO):
    g = graph(spark, d, name)
    return g, forward_push(g, starts(g, first_sources(g, sources)), rho)


for _name in ("event_user", "part_next", "cust_supp", "page_link"):
    register(f"q_push_{_name}", _push_sql(_name))(lambda spark, d, n=_name: _pushed(spark, d, n)[1].state.select("query_id", "v", _r("p"), _r("r")))


@register("q_push_sigma", _push_sql("cust_supp", _SEGMENT_SQL, RHO / 10))
def q_push_sigma(spark, d):
    g = graph(spark, d, "cust_supp")
    return forward_push(g, from_distribution(g, _segment(spark, d, g)), RHO / 10).state.select("query_id", "v", _r("p"), _r("r"))


@register("q_push_only", O.query(f"{_SCORES} (SELECT query_id, v, p AS score FROM push WHERE p > 0)", O.graph_cte("part_next"), O.sources_cte(2), O.push_cte(O.POINT, str(RHO), 40)))
def q_push_only(spark, d):
    g = graph(spark, d, "part_next")
    return _scores(push_only(g, first_sources(g, 2), RHO))


@register("q_reverse_push", O.query("SELECT target, v, round(p, 9) AS p, round(r, 9) AS r FROM back", O.graph_cte("event_user"), O.reverse_cte("SELECT v FROM nodes ORDER BY v LIMIT 3", 0.00512345, 30)))
def q_reverse_push(spark, d):
    g = graph(spark, d, "event_user")
    return reverse_push(g, g.nodes.orderBy("v").limit(3).select(F.col("v").alias("target")), 0.00512345).state.select("target", "v", _r("p"), _r("r"))


# --- walks, by md5 so that SQL draws the same -----------------------------------------------------

MD5 = PprParams(rng="md5")
#: The walk constant, as it follows from the graph.
C = f"(SELECT {_C_SQL} FROM (SELECT count(*) AS n FROM nodes))"
_PART = (O.graph_cte("event_user"), O.sources_cte(2))


def _c(g: Graph) -> float:
    return MD5.resolve(g.n).walks


_BASIC = f"SELECT query_id, v AS start, ceil(r * {C})::BIGINT AS n_walks, r / ceil(r * {C}) AS weight FROM push WHERE r > 0"
_PRUNED = f"SELECT query_id, v AS start, ceil(0.8 * {C} * r)::BIGINT AS n_walks, 0.8 * r / ceil(0.8 * {C} * r) AS weight FROM push JOIN nodes USING (v) WHERE r > 0 AND d > 0"
_SUM = "(SELECT query_id, v, sum(score) AS score FROM (SELECT query_id, v, {own} AS score FROM push JOIN nodes USING (v) UNION ALL SELECT query_id, endpoint, weight FROM ends) GROUP BY query_id, v HAVING sum(score) > 0)"


@register("q_alloc_basic", O.query(f"SELECT query_id, start, n_walks, round(weight, 9) AS weight FROM ({_BASIC})", *_PART, O.push_cte(O.POINT, str(RHO * 20), 20)))
def q_alloc_basic(spark, d):
    g, pushed = _pushed(spark, d, "event_user", rho=RHO * 20)
    return E.allocate_walks(pushed.state, _c(g), 0.2, False).select("query_id", "start", "n_walks", _r("weight"))


@register("q_alloc_pruned", O.query(f"SELECT query_id, start, n_walks, round(weight, 9) AS weight FROM ({_PRUNED})", *_PART, O.push_cte(O.POINT, str(RHO * 20), 20)))
def q_alloc_pruned(spark, d):
    g, pushed = _pushed(spark, d, "event_user", rho=RHO * 20)
    return E.allocate_walks(pushed.state, _c(g), 0.2, True).select("query_id", "start", "n_walks", _r("weight"))


_MC = f"SELECT query_id, src AS start, ceil({C})::BIGINT AS n_walks, 1.0::DOUBLE / ceil({C}) AS weight FROM sources"


@register("q_monte_carlo", O.query(f"{_SCORES} (SELECT query_id, endpoint AS v, sum(weight) AS score FROM ends GROUP BY 1, 2)", *_PART, O.walks_cte(_MC, False)))
def q_monte_carlo(spark, d):
    g = graph(spark, d, "event_user")
    return _scores(E.monte_carlo(g, starts(g, first_sources(g, 2)), MD5).scores)


def _push_walk_sql(pruned: bool) -> str:
    own = "p + CASE WHEN d = 0 THEN r ELSE 0.2 * r END" if pruned else "p"
    return O.query(f"{_SCORES} {_SUM.format(own=own)}", *_PART, O.push_cte(O.POINT, str(RHO * 20), 20), O.walks_cte(_PRUNED if pruned else _BASIC, pruned))


def _push_walk(spark, d, pruned: bool) -> DataFrame:
    g, pushed = _pushed(spark, d, "event_user", rho=RHO * 20)
    return _scores(E.finish(g, pushed, MD5.resolve(g.n), _c(g), pruned).scores)


register("q_push_walk_basic", _push_walk_sql(False))(lambda spark, d: _push_walk(spark, d, False))
register("q_push_walk_pruned", _push_walk_sql(True))(lambda spark, d: _push_walk(spark, d, True))


@register("q_walk_index", O.query("SELECT start, walk_no, endpoint FROM ends", O.graph_cte("event_user"), O.walks_cte("SELECT 0 AS query_id, v AS start, ceil(0.2 * d)::BIGINT AS n_walks, 1.0 AS weight FROM nodes", False)))
def q_walk_index(spark, d):
    g = graph(spark, d, "event_user")
    c = MD5.resolve(g.n).walks
    return build_walk_index(g, MD5, 0.2 / c).rows.select("start", "walk_no", "endpoint")


_FEW = _MC.replace(f"ceil({C})", f"ceil({C} * 0.00512345)")


@register("q_bidirectional_pair", O.query(f"{_SCORES} (SELECT query_id, target AS v, sum(score) AS score FROM (SELECT e.query_id, b.target, e.weight * b.r AS score FROM ends e JOIN back b ON b.v = e.endpoint UNION ALL SELECT s.query_id, b.target, b.p FROM sources s JOIN back b ON b.v = s.src) GROUP BY 1, 2 HAVING sum(score) > 0)", *_PART, O.reverse_cte("SELECT v FROM nodes ORDER BY v LIMIT 3", 0.00512345, 30), O.walks_cte(_FEW, False)))
def q_bidirectional_pair(spark, d):
    g = graph(spark, d, "event_user")
    targets = g.nodes.orderBy("v").limit(3).select(F.col("v").alias("target"))
    return _scores(B.bidirectional_pair(g, first_sources(g, 2), targets, MD5, 0.00512345).filter("score > 0"))


#: The balancing threshold, times a multiple, as it follows from the graph.
_RHO = f"(SELECT {{mult}} * CASE WHEN m <= c THEN 1 / sqrt(m * c) ELSE 1 / c END FROM (SELECT (SELECT count(*) FROM arcs) AS m, {C} AS c))"
_BASIC_OWN, _PRUNED_OWN = "p", "p + CASE WHEN d = 0 THEN r ELSE 0.2 * r END"


def _own_sql(sigma: str, mult: float, pruned: bool, select: str | None = None) -> str:
    """Push to a multiple of the balancing threshold, then md5 walks: a stored walk is the same walk."""
    found = _SUM.format(own=_PRUNED_OWN if pruned else _BASIC_OWN)
    return O.query((select or f"{_SCORES} {{found}}").format(found=found), *_PART, "level AS MATERIALIZED (SELECT " + _RHO.format(mult=mult) + " AS rho)", O.push_cte(sigma, "(SELECT rho FROM level)", 40), O.walks_cte(_PRUNED if pruned else _BASIC, pruned))


def _md5_setting(spark, d):
    g = graph(spark, d, "event_user")
    return g, starts(g, first_sources(g, 2))


def _md5_index(g: Graph, mult: float, pruned: bool):
    return build_walk_index(g, MD5, mult * push_threshold(g.m, _c(g))[0], pruned)


_TOP = "SELECT query_id, rk::INT AS rk, v, round(score, 9) AS score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, v) AS rk FROM {found}) WHERE rk <= 10"


@register("q_push_walk_own", _own_sql(O.POINT, 1, False))
def q_push_walk_own(spark, d):
    g, state = _md5_setting(spark, d)
    return _scores(E.push_walk(g, state, MD5).scores)


@register("q_push_walk_indexed", _own_sql(O.POINT, 1, False))
def q_push_walk_indexed(spark, d):
    g, state = _md5_setting(spark, d)
    return _scores(E.push_walk(g, state, MD5, index=_md5_index(g, 1, False)).scores)


@register("q_push_walk_tuned_indexed", _own_sql(O.POINT, 2, True))
def q_push_walk_tuned_indexed(spark, d):
    g, state = _md5_setting(spark, d)
    return _scores(E.push_walk(g, state, MD5, rho_mult=2, pruned=True, index=_md5_index(g, 2, True)).scores)


for _mult in range(1, 8):
    register(f"q_push_walk_rho_{_mult}", _own_sql(O.POINT, _mult, True))(lambda spark, d, m=_mult: _scores(E.push_walk(*_md5_setting(spark, d), MD5, rho_mult=m, pruned=True).scores))


@register("q_pagerank_push_walk", _own_sql(O.UNIFORM, 1, True))
def q_pagerank_push_walk(spark, d):
    return _scores(B.global_pagerank(graph(spark, d, "event_user"), MD5).scores)


@register("q_pagerank_push_walk_topk", _own_sql(O.UNIFORM, 1, True, _TOP))
def q_pagerank_push_walk_topk(spark, d):
    return T.rank(B.global_pagerank(graph(spark, d, "event_user"), MD5).scores, 10).select("query_id", "rk", "v", _r("score"))


@register("q_topk_full_sort", _own_sql(O.POINT, 1, False, _TOP))
def q_topk_full_sort(spark, d):
    g, state = _md5_setting(spark, d)
    return T.top_k_full_sort(g, state, 10, MD5).answer.select("query_id", "rk", "v", _r("score"))


@register("q_topk_push_only", O.query(_TOP.format(found="(SELECT query_id, v, p AS score FROM push WHERE p > 0)"), *_PART, O.push_cte(O.POINT, str(RHO), 40)))
def q_topk_push_only(spark, d):
    g = graph(spark, d, "event_user")
    return T.rank(push_only(g, first_sources(g, 2), RHO), 10).select("query_id", "rk", "v", _r("score"))


@register("q_table_function_topk", O.query(_TOP.format(found="(SELECT query_id, v, p AS score FROM push WHERE p > 0)"), *_PART, O.push_cte(O.POINT, str(RHO), 40)))
def q_table_function_topk(spark, d):
    """The same by a table function over a partitioned, ordered table argument."""
    from pushwave.functions.udx import register_sql

    register_sql(spark)
    g = graph(spark, d, "event_user")
    push_only(g, first_sources(g, 2), RHO).createOrReplaceTempView("pushwave_scores")
    return spark.sql("SELECT query_id, rk, v, round(score, 9) AS score FROM top_rows(row => TABLE(pushwave_scores) PARTITION BY query_id ORDER BY (score DESC, v), k => 10)")


@register("q_sink_bucketed", O.query("SELECT src, count(*) AS n, sum(dst)::BIGINT AS dst FROM arcs GROUP BY src", O.graph_cte("cust_supp")))
def q_sink_bucketed(spark, d):
    """Arcs written in buckets by src, aggregated without an exchange."""
    return graph(spark, d, "cust_supp").steps().groupBy("src").agg(F.count(F.lit(1)).alias("n"), F.sum("dst").alias("dst"))


# --- methods at their own settings: rows, held against exact scores in tests -----------------------


def _setting(spark, d, name: str = "part_next", count: int = 3):
    g = graph(spark, d, name)
    sources = first_sources(g, count)
    return g, sources, starts(g, sources)


def _method(name: str, run):
    register(name)(lambda spark, d, run=run: run(*_setting(spark, d)))


_P = PprParams()


def _index(g: Graph, pruned: bool, mult: float):
    key = (g.spark.sparkContext.applicationId, f"index{pruned}{mult}", str(id(g)))
    if key not in _graphs:
        _graphs[key] = build_walk_index(g, _P, mult * push_threshold(g.m, _P.resolve(g.n).walks)[0], pruned)
    return _graphs[key]


_method("m_monte_carlo", lambda g, q, s: _scores(E.monte_carlo(g, s, _P).scores))
_method("m_push_walk", lambda g, q, s: _scores(E.push_walk(g, s, _P).scores))
_method("m_push_walk_pruned", lambda g, q, s: _scores(E.push_walk(g, s, _P, pruned=True).scores))
_method("m_push_walk_tuned", lambda g, q, s: _scores(E.push_walk_balanced(g, s, _P).scores))
_method("m_monte_carlo_visits", lambda g, q, s: _scores(E.monte_carlo_visits(g, s, _P).scores))
_method("m_topk_hub", lambda g, q, s: B.hub_top_k(g, q, 20, _P, B.build_hub_index(g, _P, g.m)).answer)
_method("m_topk_bounds_indexed", lambda g, q, s: T.top_k_bounds(g, s, 20, _P, index=_index(g, False, 1)).answer)
_method("m_topk_pagerank", lambda g, q, s: T.top_k_halving(g, from_distribution(g, uniform(g)), 20, _P).answer)
register("m_topk_pairs")(lambda spark, d: (lambda g, q, s: B.pair_top_k(g, q, 10, _P).answer)(*_setting(spark, d, "event_user")))
_method("m_push_walk_indexed", lambda g, q, s: _scores(E.push_walk(g, s, _P, index=_index(g, False, 1)).scores))
_method("m_push_walk_tuned_indexed", lambda g, q, s: _scores(E.push_walk(g, s, _P, rho_mult=2, pruned=True, index=_index(g, True, 2)).scores))
_method("m_bidirectional_all", lambda g, q, s: _scores(B.bidirectional_all(g, q, _P).scores))
_method("m_hub_bidirectional", lambda g, q, s: _scores(B.bidirectional_all(g, q, _P, hubs=B.build_hub_index(g, _P, g.m)).scores))
_method("m_shell_approximation", lambda g, q, s: _scores(B.shell_approximation(g, q).scores))
_method("m_global_pagerank", lambda g, q, s: _scores(B.global_pagerank(g, _P).scores))
_method("m_topk_halving", lambda g, q, s: T.top_k_halving(g, s, 20, _P).answer)
_method("m_topk_halving_indexed", lambda g, q, s: T.top_k_halving(g, s, 20, _P, index=_index(g, True, 1)).answer)
_method("m_topk_bounds", lambda g, q, s: T.top_k_bounds(g, s, 20, _P).answer)
_method("m_topk_monte_carlo", lambda g, q, s: T.top_k_halving(g, s, 20, _P, use_push=False).answer)
_method("m_topk_full_sort", lambda g, q, s: T.top_k_full_sort(g, s, 20, _P).answer)
_method("m_topk_filter_refine", lambda g, q, s: B.filter_refine_top_k(g, q, 20, _P).answer)
_method("m_topk_bidirectional", lambda g, q, s: B.ranked(B.bidirectional_all(g, q, _P), 20, g.n).answer)


# --- measures -----------------------------------------------------------------------------------

_BOTH = (O.graph_cte("event_user"), O.sources_cte(2), O.push_cte(O.POINT, "0.0", ROUNDS), O.push_cte(O.POINT, str(RHO * 8), 40).replace("st AS (", "lst AS (").replace("FROM st ", "FROM lst ").replace("push AS MATERIALIZED", "low AS MATERIALIZED").replace("FROM st WHERE", "FROM lst WHERE"))
_TRUE = "(SELECT query_id, v, p AS score, row_number() OVER (PARTITION BY query_id ORDER BY p DESC, v) AS rk FROM push)"
_LOW = "(SELECT query_id, v, p AS score, row_number() OVER (PARTITION BY query_id ORDER BY p DESC, v) AS rk FROM low WHERE p > 0)"


def _low(spark, d):
    g = graph(spark, d, "event_user")
    return g, push_only(g, first_sources(g, 2), RHO * 8), _truth(g)


@register("q_precision", O.query(f"SELECT a.query_id, round(count(b.v) / 20.0, 6)::DOUBLE AS precision FROM {_TRUE} a LEFT JOIN {_LOW} b ON a.query_id = b.query_id AND a.v = b.v AND b.rk <= 20 WHERE a.rk <= 20 GROUP BY 1", *_BOTH))
def q_precision(spark, d):
    _, low, truth = _low(spark, d)
    return M.precision_at_k(T.rank(low, 20), truth, 20).select("query_id", _r("precision", 6))


@register("q_ndcg", O.query(f"SELECT i.query_id, round(g.got / i.ideal, 9) AS ndcg FROM (SELECT query_id, sum((pow(2.0, score) - 1) / log2(rk + 1)) AS ideal FROM {_TRUE} WHERE rk <= 20 GROUP BY 1) i JOIN (SELECT b.query_id, sum((pow(2.0, coalesce(t.score, 0)) - 1) / log2(b.rk + 1)) AS got FROM {_LOW} b LEFT JOIN {_TRUE} t ON t.query_id = b.query_id AND t.v = b.v WHERE b.rk <= 20 GROUP BY 1) g USING (query_id)", *_BOTH))
def q_ndcg(spark, d):
    _, low, truth = _low(spark, d)
    return M.ndcg_at_k(T.rank(low, 20), truth, 20).select("query_id", _r("ndcg"))


@register("q_relative_error", O.query(f"SELECT t.query_id, round(max(abs(coalesce(b.score, 0) - t.score) / t.score), 9) AS max_error, round(avg(abs(coalesce(b.score, 0) - t.score) / t.score), 9) AS mean_error FROM {_TRUE} t LEFT JOIN {_LOW} b ON t.query_id = b.query_id AND t.v = b.v WHERE t.score > 1.0 / (SELECT count(*) FROM nodes) GROUP BY 1", *_BOTH))
def q_relative_error(spark, d):
    g, low, truth = _low(spark, d)
    return M.relative_error(low, truth, 1 / g.n).select("query_id", _r("max_error"), _r("mean_error"))


@register("q_check_topk")
def q_check_topk(spark, d):
    g, sources, state = _setting(spark, d)
    return M.check_top_k(T.top_k_halving(g, state, 20, _P).answer, _truth(g, 3, 60), 20, _P.eps, 1 / g.n)


def _tails_sql(e: str, score: str, residue: str = "0.5", walks: str = "10000") -> str:
    relative = f"least(1, 2 * exp(greatest(-745.0, -{e} * {e} * {walks} * {score} / ({residue} * (2 + 2 * {e} / 3)))))"
    absolute = f"least(1, 2 * exp(greatest(-745.0, -({e} / 100) * ({e} / 100) * {walks} / ({residue} * (2 * {score} + 2 * ({e} / 100) / 3)))))"
    return f"round({relative}, 12) AS relative, round({absolute}, 12) AS absolute"


@register("q_tail_bounds", f"SELECT s_nationkey, eps, {_tails_sql('eps', 'score')} FROM (SELECT s_nationkey::BIGINT AS s_nationkey, count(*)::DOUBLE / (SELECT count(*) FROM supplier) AS score FROM supplier GROUP BY 1), (SELECT unnest([0.1::DOUBLE, 0.3::DOUBLE, 0.5::DOUBLE]) AS eps)")
def q_tail_bounds(spark, d):
    """Both bounds for what 10,000 walks over half the mass say of each nation's share of the suppliers."""
    from pushwave.functions.formulas import tail_bound_absolute, tail_bound_relative

    ship(spark)
    each = S.read(spark, d, "supplier", "s_nationkey").groupBy(F.col("s_nationkey").cast("long").alias("s_nationkey")).agg(F.count(F.lit(1)).alias("n"))
    score = each.select("s_nationkey", (F.col("n") / F.sum("n").over(Window.partitionBy())).alias("score"))  # one row a nation
    bound = {f: F.udf(lambda e, s, f=f, by=by: f(e / by, 10_000, 0.5, s), "double") for f, by in ((tail_bound_relative, 1), (tail_bound_absolute, 100))}
    rows = score.withColumn("eps", F.explode(F.array(*(F.lit(e) for e in (0.1, 0.3, 0.5)))))
    return rows.select("s_nationkey", "eps", *(F.round(b(F.col("eps"), F.col("score")), 12).alias(n) for b, n in zip(bound.values(), ("relative", "absolute"), strict=True)))


@register("q_recommend_parts", O.query(f"SELECT query_id, rk::INT AS rk, v, round(score, 9) AS score FROM (SELECT t.query_id, t.v, t.score, row_number() OVER (PARTITION BY t.query_id ORDER BY t.score DESC, t.v) AS rk FROM {_TRUE} t JOIN sources s USING (query_id) WHERE t.v <> s.src AND NOT EXISTS (SELECT 1 FROM arcs a WHERE a.src = s.src AND a.dst = t.v)) WHERE rk <= 10", O.graph_cte("part_next"), O.sources_cte(2), O.push_cte(O.POINT, "0.0", ROUNDS)))
def q_recommend_parts(spark, d):
    g = graph(spark, d, "part_next")
    return T.recommend(_truth(g), g, first_sources(g, 2), 10).select("query_id", "rk", "v", _r("score"))

