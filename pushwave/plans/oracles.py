"""DuckDB SQL of the graph methods: recursive queries over the derived arcs."""

from __future__ import annotations

from pushwave.functions.rng import md5_sql, stop_limit
from pushwave.sources.graphs import GRAPH_SQL

ALPHA = 0.2


def graph_cte(name: str) -> str:
    """arcs, nodes (v, d, i), steps (src, dst, own) and pos (src, pos, dst) of a graph."""
    return f"""arcs AS MATERIALIZED (SELECT src::BIGINT AS src, dst::BIGINT AS dst FROM ({GRAPH_SQL[name]}) WHERE src IS NOT NULL AND dst IS NOT NULL),
od AS (SELECT src AS v, count(*) AS d FROM arcs GROUP BY 1), ind AS (SELECT dst AS v, count(*) AS i FROM arcs GROUP BY 1),
nodes AS MATERIALIZED (SELECT v, coalesce(d, 0) AS d, coalesce(i, 0) AS i FROM (SELECT src AS v FROM arcs UNION SELECT dst FROM arcs) LEFT JOIN od USING (v) LEFT JOIN ind USING (v)),
steps AS MATERIALIZED (SELECT src, dst, false AS own FROM arcs UNION ALL SELECT v, v, true FROM nodes),
pos AS MATERIALIZED (SELECT src, row_number() OVER (PARTITION BY src ORDER BY dst % 16, dst) - 1 AS pos, dst FROM arcs)"""


#: Sources of the oracle queries: the least node ids.
def sources_cte(count: int) -> str:
    return f"sources AS (SELECT row_number() OVER (ORDER BY v) - 1 AS query_id, v AS src FROM nodes ORDER BY v LIMIT {count})"


POINT = "SELECT query_id, src AS v, 1.0::DOUBLE AS mass FROM sources"
UNIFORM = "SELECT 0::BIGINT AS query_id, v, 1.0::DOUBLE / (SELECT count(*) FROM nodes) AS mass FROM nodes"


def push_cte(sigma: str, rho: str, rounds: int, alpha: float = ALPHA) -> str:
    """push(query_id, v, p, r): the state after the last of a number of rounds."""
    hot = f"(s.r > {rho} * greatest(n.d, 1))"
    return f"""st AS (SELECT 0 AS round, query_id, v, 0.0::DOUBLE AS p, mass AS r FROM ({sigma})
 UNION ALL SELECT round + 1, query_id, dst, sum(p), sum(r) FROM (
  SELECT s.round, s.query_id, t.dst, CASE WHEN t.own THEN s.p + CASE WHEN {hot} THEN CASE WHEN n.d = 0 THEN s.r ELSE {alpha} * s.r END ELSE 0.0 END ELSE 0.0 END AS p,
   CASE WHEN t.own THEN CASE WHEN {hot} THEN 0.0 ELSE s.r END ELSE (1 - {alpha}) * s.r / n.d END AS r
  FROM st s JOIN nodes n ON n.v = s.v JOIN steps t ON t.src = s.v WHERE s.round < {rounds} AND (t.own OR {hot})) GROUP BY round, query_id, dst),
push AS MATERIALIZED (SELECT query_id, v, p, r FROM st WHERE round = {rounds})"""


def reverse_cte(targets: str, rho: float, rounds: int, alpha: float = ALPHA) -> str:
    """back(target, v, p, r) for graphs without dead ends."""
    return f"""bst AS (SELECT 0 AS round, v AS target, v, 0.0::DOUBLE AS p, 1.0::DOUBLE AS r FROM ({targets})
 UNION ALL SELECT round + 1, target, v, sum(p), sum(r) FROM (
  SELECT s.round, s.target, t.src AS v, CASE WHEN t.own THEN s.p + CASE WHEN s.r > {rho} THEN {alpha} * s.r ELSE 0.0 END ELSE 0.0 END AS p,
   CASE WHEN t.own THEN CASE WHEN s.r > {rho} THEN 0.0 ELSE s.r END ELSE (1 - {alpha}) * s.r / n.d END AS r
  FROM bst s JOIN steps t ON t.dst = s.v JOIN nodes n ON n.v = t.src WHERE s.round < {rounds} AND (t.own OR s.r > {rho})) GROUP BY round, target, v),
back AS MATERIALIZED (SELECT target, v, p, r FROM bst WHERE round = {rounds})"""


def walks_cte(alloc: str, forced: bool, alpha: float = ALPHA, seed: int = 42) -> str:
    """ends(query_id, start, walk_no, endpoint, weight) of md5 walks; alloc: query_id, start, n_walks, weight."""
    stop, choice = md5_sql(seed, "0", "start", "walk_no", "hop", 1), md5_sql(seed, "0", "start", "walk_no", "hop", 9)
    free = "hop = 0" if forced else "false"
    return f"""walk AS (SELECT query_id, start, unnest(range(0, n_walks::BIGINT)) AS walk_no, weight, start AS cur, 0 AS hop, false AS done FROM ({alloc})
 UNION ALL SELECT query_id, start, walk_no, weight, CASE WHEN stop THEN cur ELSE a.dst END, hop + 1, stop FROM (
  SELECT w.*, (n.d = 0 OR (NOT ({free}) AND {stop} < {stop_limit(alpha)})) AS stop, CASE WHEN n.d = 0 THEN 0 ELSE {choice} % n.d END AS pick FROM walk w JOIN nodes n ON n.v = w.cur WHERE NOT w.done) x
  LEFT JOIN pos a ON a.src = x.cur AND a.pos = x.pick AND NOT x.stop),
ends AS MATERIALIZED (SELECT query_id, start, walk_no, cur AS endpoint, weight FROM walk WHERE done)"""


def query(select: str, *ctes: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(ctes) + "\n" + select
