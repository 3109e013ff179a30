"""What larger graphs need: mapped adjacency, md5 walks in kernels, visits by joins, reverse pushes in kernels."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from pushwave.functions.formulas import PprParams
from pushwave.functions.udx import small_graph_push
from pushwave.operators import estimators as E
from pushwave.operators import graph as G
from pushwave.operators import kernels as K
from pushwave.operators.push import reverse_push, starts
from pushwave.plans.durable import Mapped
from tests.test_engine import random_arcs, sources, toy


def rows(df, *columns):
    return {tuple(r[c] for c in columns[:-1]): r[columns[-1]] for r in df.collect()}


def same(a, b):
    assert a.keys() == b.keys()
    assert all(abs(a[k] - b[k]) < 1e-12 for k in a)


def test_adjacency_is_mapped_and_whole(spark):
    arcs = random_arcs(40, 300)
    made = toy(spark, arcs).adjacency()
    v, first, target = made.value
    assert isinstance(made, Mapped) and target.dtype == np.int32
    assert sorted((int(v[i]), int(v[t])) for i in range(len(v)) for t in target[first[i] : first[i + 1]]) == arcs


@pytest.mark.parametrize("rng", ["md5", "xxhash64"])
def test_ends_and_visits_of_both_engines(spark, rng):
    g, p = toy(spark, random_arcs(12, 30)), PprParams(rng=rng)
    state = starts(g, sources(spark, 0, 1))
    for method in (E.monte_carlo, E.monte_carlo_visits):
        kernel, join = method(g, state, p, walks=200), method(g, state, p, walks=200, engine="join")
        assert (kernel.walks, kernel.hops) == (join.walks, join.hops)
        same(rows(kernel.scores, "query_id", "v", "score"), rows(join.scores, "query_id", "v", "score"))


def test_visits_on_a_graph_beyond_the_kernels(spark, monkeypatch):
    monkeypatch.setattr(G, "KERNEL_ARCS", 1)
    g = toy(spark)
    found = E.monte_carlo_visits(g, starts(g, sources(spark, 0)), PprParams(), walks=300).scores
    assert found.agg(F.sum("score")).first()[0] == pytest.approx(1, abs=0.2)


def test_a_push_in_pieces(monkeypatch):
    g = K.Local(np.arange(50), np.arange(51) * 4, np.random.default_rng(1).integers(0, 50, 200).astype(np.int32))
    states = []
    for arcs in (1 << 22, 3):
        monkeypatch.setattr(K, "ARCS", arcs)
        s = K.Push(g, np.array([0]), np.array([1.0]))
        s.run(1e-4, 0.2)
        states.append((s.p, s.r))
    assert np.allclose(states[0], states[1], rtol=0, atol=1e-14)


def test_reverse_pushes_of_both_engines(spark):
    g = toy(spark, random_arcs(30, 120) + [(5, 40), (6, 40)])  # 40 has no arc out
    targets = g.nodes.select(F.col("v").alias("target"))
    kernel, join = reverse_push(g, targets, 0.01), reverse_push(g, targets, 0.01, engine="join")
    for column in ("p", "r"):
        same(rows(kernel.state, "target", "v", column), rows(join.state.filter("p > 0 or r > 0"), "target", "v", column))


def test_reverse_pushes_in_pieces(monkeypatch):
    class Held:
        value = (np.arange(50), np.full(50, 4), np.arange(51) * 4, np.random.default_rng(2).permutation(np.repeat(np.arange(50), 4)).astype(np.int32))

    found = []
    for most in (1 << 20, 8):
        monkeypatch.setattr(K, "BACK_ROWS", most)
        monkeypatch.setattr(K, "ARCS", most)
        targets = pa.RecordBatch.from_arrays([pa.array(np.arange(50))], names=["target"])
        out = pa.Table.from_batches(K.pushed_back(Held, 0.002, 0.2, None)([targets])).sort_by([("target", "ascending"), ("v", "ascending")])
        found.append(out)
    assert found[0].select(["target", "v"]).equals(found[1].select(["target", "v"]))
    assert all(np.allclose(found[0].column(c), found[1].column(c), rtol=0, atol=1e-14) for c in ("p", "r"))


def test_grouped_push_takes_more_than_100000_arcs(spark):
    arcs = spark.range(100_100).select(F.col("id").alias("src"), ((F.col("id") + 1) % 100_100).alias("dst"))
    found = rows(small_graph_push(arcs, sources(spark, 7), 0.1), "v", "score")
    assert found[(7,)] == pytest.approx(0.2) and found[(8,)] == pytest.approx(0.16)


def test_bounds_and_plan_read_given_tables(spark):
    import duckdb

    import __spark_entry__ as entry

    d = "/root/testdata/sf0.001"
    for name in ("q_tail_bounds", "q_udtf_plan"):
        db = duckdb.connect()
        for t in ("supplier", "lineitem"):
            db.sql(f"CREATE VIEW {t} AS SELECT * FROM '{d}/{t}.parquet'")
        want = db.sql(entry.oracle_sql()[name]).fetchall()
        found = entry.queries()[name](spark, d)
        got = [tuple(r) for r in found.collect()]
        assert sorted(got) == sorted(want) and got, name
