"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

"""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def session():
    from pyspark.sql import SparkSession

    s = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    s.sparkContext.setLogLevel("ERROR")
    return s


def main() -> None:
    from pushwave import workloads as w
    from pushwave.operators import baselines as B
    from pushwave.operators import estimators as E
    from pushwave.operators import metrics as M
    from pushwave.operators import topk as T
    from pushwave.operators.index import build_walk_index
    from pushwave.operators.push import starts
    from pushwave.plans.durable import ship

    spark = session()
    ship(spark)
    p, queries, quality, batch = w.PprParams(), {}, {}, int(os.environ.get("BENCH_SOURCES", "10"))

    def timed(name, f):
        t = time.perf_counter()
        out = f()
        queries[name] = round(time.perf_counter() - t, 3)
        print(name, queries[name], file=sys.stderr, flush=True)
        return out

    for name in ("part_next",) if not os.environ.get("BENCH_TABLES") else ("part_next", "cust_part", "order_part"):
        g = timed(f"{name}.build_graph", lambda name=name: w.graph(spark, SF, name))
        sources = w.hashed_sources(g, batch)
        state = starts(g, sources)
        rho = w.push_threshold(g.m, p.resolve(g.n).walks)[0]
        g.adjacency()
        index = timed(f"{name}.build_index_topk", lambda: build_walk_index(g, p, rho, True))
        wide = timed(f"{name}.build_index_whole", lambda: build_walk_index(g, p, 2 * rho, True))
        timed(f"{name}.load_indexes", lambda index=index, wide=wide, g=g: (index.local(g), wide.local(g)))
        runs = {
            "push_walk": lambda: E.push_walk(g, state, p),
            "push_walk_pruned": lambda: E.push_walk(g, state, p, pruned=True),
            "push_walk_tuned_indexed": lambda: E.push_walk(g, state, p, rho_mult=2, pruned=True, index=wide),
            "monte_carlo": lambda: E.monte_carlo(g, state, p),
            "push_walk_balanced": lambda: E.push_walk_balanced(g, state, p),
            "power_100": lambda: E.power(g, state, 100),
            "topk_halving": lambda: T.top_k_halving(g, state, 500, p),
            "topk_halving_indexed": lambda: T.top_k_halving(g, state, 500, p, index=index),
            "topk_monte_carlo": lambda: T.top_k_halving(g, state, 500, p, use_push=False),
        }
        if os.environ.get("BENCH_TABLES"):
            runs |= {
                "topk_bounds": lambda: T.top_k_bounds(g, state, 500, p),
                "topk_filter_refine": lambda: B.filter_refine_top_k(g, sources, 500, p),
                "pagerank": lambda: B.global_pagerank(g, p),
            }
        answers = {}
        for method, f in runs.items():
            answers[method] = timed(f"{name}.{method}", f)
        for method in ("topk_halving", "topk_halving_indexed", "topk_monte_carlo"):
            truth, answer = answers["power_100"].scores, answers[method].answer
            quality[f"{name}.{method}"] = [round(m(answer, truth, 500).agg({c: "avg"}).first()[0], 6) for m, c in ((M.precision_at_k, "precision"), (M.ndcg_at_k, "ndcg"))]
    print(json.dumps({"metric": "graph queries, total", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "sf": os.path.basename(SF.rstrip("/")), "sources": batch, "precision_ndcg_at_500": quality}))


if __name__ == "__main__":
    main()
