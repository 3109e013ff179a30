"""User-defined surfaces where built-in functions can't say it: table functions for SQL users and
a kernel for graphs that tasks map."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf
from pyspark.sql.types import DoubleType

from pushwave.functions.formulas import expected_costs, push_threshold, walk_constant


@udtf(returnType="walk_constant: double, rho: double, threshold_case: int, push_walk: double, monte_carlo: double")
class PprPlan:
    """ppr_plan(n, m, eps, delta, p_fail): one row of the numbers a query would run with."""

    def eval(self, n: int, m: int, eps: float, delta: float, p_fail: float):
        from pushwave.functions.formulas import PprParams

        c = walk_constant(eps, delta, p_fail)
        rho, case = push_threshold(m, c)
        costs = expected_costs(n, m, PprParams(eps=eps, delta=delta, p_fail=p_fail))
        yield c, rho, case, costs["push_walk"], costs["monte_carlo"]


@udtf(returnType="query_id: bigint, rk: int, v: bigint, score: double")
class TopRows:
    """top_rows(TABLE(scores) PARTITION BY query_id ORDER BY (score DESC, v), k): the first k rows of each partition."""

    def __init__(self):
        self.rank = 0

    def eval(self, row, k: int):
        self.rank += 1
        if self.rank <= k:
            yield row["query_id"], self.rank, row["v"], row["score"]


def register_sql(spark: SparkSession) -> None:
    spark.udtf.register("ppr_plan", PprPlan)
    spark.udtf.register("top_rows", TopRows)


def small_graph_push(arcs: DataFrame, sources: DataFrame, rho: float, alpha: float = 0.2) -> DataFrame:
    """One query a group: every group maps the arcs (src, dst) of a graph that kernels take;
    (query_id, v, score) of a push to rho."""
    from pushwave.operators.graph import build_graph
    from pushwave.operators.kernels import Local, Push

    adjacency = build_graph(arcs).adjacency()

    def push(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        g = Local(*adjacency.value)
        s = Push(g, np.searchsorted(g.v, pdf["src"].to_numpy()[:1]), np.ones(1))
        s.run(rho, alpha)
        keep = np.flatnonzero(s.p > 0)
        return pd.DataFrame({"query_id": key[0], "v": g.v[keep], "score": s.p[keep]})

    return sources.groupBy("query_id").applyInPandas(push, "query_id long, v long, score double")


@F.pandas_udf(DoubleType())
def ndcg_of(true: pd.Series, place: pd.Series, ideal: pd.Series) -> float:
    """Grouped measure over rows of an answer: true scores, ranks, and the ideal scores in the same order."""
    discount = np.log2(place + 1)
    return float(((2**true - 1) / discount).sum() / ((2**ideal - 1) / discount).sum())
