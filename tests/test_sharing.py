"""What experiments leave on disk and in the driver, and how a batch of queries is spread."""

import os

import numpy as np
import pyarrow.parquet as pq
import pytest

from pushwave.functions.formulas import PprParams
from pushwave.operators import estimators as E
from pushwave.operators import kernels as K
from pushwave.operators.index import build_walk_index
from pushwave.operators.push import forward_push, starts
from pushwave.plans import durable as D
from tests.test_engine import random_arcs, sources, toy


def test_queries_of_a_batch_are_tasks_of_their_own(spark):
    g = toy(spark, random_arcs(40, 300))
    state = starts(g, sources(spark, *range(40)))
    spread = K.pushed(state, g.adjacency(), 0.01, 0.2, 0.0, None)
    D.cut(spread)  # as adaptive execution runs it
    assert len({r[0] for r in spread.selectExpr("spark_partition_id()").collect()}) > 1


@pytest.mark.parametrize("shared", [True, False])
def test_arrays_are_filled_once_and_dropped(spark, monkeypatch, shared):
    if not shared:
        monkeypatch.setattr(D, "local_path", lambda *_: None)
    arcs = random_arcs(40, 300)
    g, p = toy(spark, arcs), PprParams()
    v, first, target = g.adjacency().value
    assert sorted((int(v[i]), int(v[t])) for i in range(len(v)) for t in target[first[i] : first[i + 1]]) == arcs
    index = build_walk_index(g, p, 0.01)
    rows = {(r["start"], r["walk_no"]): r["endpoint"] for r in index.rows.collect()}
    heads, ends = index.local(g).value
    assert {(int(v[i]), j - int(heads[i])): int(v[ends[j]]) for i in range(len(v)) for j in range(heads[i], heads[i + 1])} == rows
    assert all(os.path.isabs(n) == shared for n in index.local(g).names)
    files = [n for n in index.local(g).names if shared] + [D.local_path(spark, f) or f.removeprefix("file://") for f in index.rows.inputFiles()]
    assert all(map(os.path.exists, files))
    index.drop()
    assert not any(map(os.path.exists, files))


def test_only_cuts_are_dropped(spark, tmp_path):
    spark.range(3).write.parquet(kept := str(tmp_path / "given"))
    D.drop(given := spark.read.parquet(kept), made := D.cut(given))
    assert given.count() == 3 and not os.path.exists(made.inputFiles()[0].removeprefix("file://"))


def test_stored_walks_are_in_order(spark):
    index = build_walk_index(toy(spark, random_arcs(40, 300)), PprParams(), 0.05)
    for file in index.rows.inputFiles():
        part = pq.read_table(file.removeprefix("file://")).select(["start", "walk_no"]).to_pylist()
        assert part == sorted(part, key=lambda r: (r["start"], r["walk_no"]))


def test_rounds_over_the_same_nodes(monkeypatch):
    g = K.Local(np.arange(150), np.arange(151) * 4, (np.random.default_rng(1).integers(0, 50, (3, 200)) + [[0], [50], [100]]).ravel().astype(np.int32))  # three parts
    picks, expand = [], K.expand
    monkeypatch.setattr(K, "expand", lambda *a: picks.append(1) or expand(*a))
    states = []
    for arcs in (1 << 22, 3):  # picked once, or in pieces every round
        monkeypatch.setattr(K, "ARCS", arcs)
        s = K.Push(g, np.array([0]), np.array([1.0]))
        s.run(0.0, 0.2, max_rounds=60)
        states.append((s.p, s.r, s.touched))
        assert arcs == 3 or len(picks) < 30
    assert all(np.allclose(a, b, rtol=0, atol=1e-14) for a, b in zip(*states, strict=True))


def test_pushes_agree_over_engines_for_a_batch(spark):
    g = toy(spark, random_arcs(30, 120))
    state = starts(g, sources(spark, *range(10)))
    both = [{(r["query_id"], r["v"]): r["p"] for r in forward_push(g, state, 0.001, engine=e).state.collect() if r["p"]} for e in ("kernel", "join")]
    assert both[0].keys() == both[1].keys() and all(abs(both[0][k] - both[1][k]) < 1e-12 for k in both[0])
    assert E.power(g, state, 5).rounds == 5


def test_balance_leaves_no_scores(spark):
    from pushwave.plans import experiments as X

    def scores():
        return {n for n in os.listdir(D.local_path(spark, D.shared_dir(spark))) if n.startswith("scores-")}

    before = scores()
    found = X.balance(spark, "/root/testdata/sf0.001")
    assert {r["method"] for r in found.collect()} == {"push-walk basic", "push-walk pruned", "push-walk tuned"}
    assert scores() == before
