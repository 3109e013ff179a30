"""Arcs are numbered and walks stored in one pass, which fills the files that kernels map as well."""

import numpy as np
import pyarrow as pa
import pytest

from pushwave.functions.formulas import PprParams
from pushwave.operators import baselines as B
from pushwave.operators import graph as G
from pushwave.operators import index as I
from pushwave.operators import kernels as K
from pushwave.operators import walks as W
from pushwave.operators.push import forward_push, starts
from tests.test_engine import random_arcs, sources, toy


def unread(*_):
    raise AssertionError("a stored table is read again to fill an array")


def test_arcs_are_numbered_in_one_pass(spark, monkeypatch):
    arcs = random_arcs(60, 900) + [(7, 100 + i) for i in range(300)]
    monkeypatch.setattr(G, "fill", unread)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "32")  # sources that go on over batches
    try:
        one = toy(spark, arcs)
        found = [tuple(r) for r in one.arcs.collect()]
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    v, first, target = one.adjacency().value
    assert {(s, p): d for s, p, d, *_ in found} == {(int(v[i]), j - int(first[i])): int(v[target[j]]) for i in range(len(v)) for j in range(first[i], first[i + 1])}
    monkeypatch.setattr(G, "KERNEL_ARCS", 1)  # numbered by windows
    other = toy(spark, arcs)
    assert sorted(found) == sorted(tuple(r) for r in other.arcs.collect()) and one.arcs.schema == other.arcs.schema
    assert sorted(map(tuple, one.nodes.collect())) == sorted(map(tuple, other.nodes.collect()))


@pytest.mark.parametrize("pruned", [False, True])
def test_stored_walks_are_mapped_as_they_are_walked(spark, monkeypatch, pruned):
    g, p = toy(spark, random_arcs(40, 300) + [(3, 99)]), PprParams()
    monkeypatch.setattr(I, "fill", unread)
    index = I.build_walk_index(g, p, 0.02, pruned, held=True)
    rows = {(r["start"], r["walk_no"]): r["endpoint"] for r in index.rows.collect()}
    v = g.adjacency().value[0]
    heads, ends = index.local(g).value
    assert {(int(v[i]), j - int(heads[i])): int(v[ends[j]]) for i in range(len(v)) for j in range(heads[i], heads[i + 1])} == rows


@pytest.mark.parametrize("rng", ["xxhash64", "md5"])
def test_walks_in_steps(monkeypatch, rng):
    g = K.Local(np.arange(50) * 3, np.arange(51) * 4, np.random.default_rng(1).integers(0, 50, 200).astype(np.int32))
    found = []
    for step in (1 << 14, 7):
        monkeypatch.setattr(K, "STEP", step)
        for lane in (0, np.arange(300) % 3):
            seen = []
            at, hops = K.walk(g, PprParams(rng=rng), True, lane, np.arange(300) % 50, np.arange(300), lambda live, now: seen.append((live, now)))
            found.append([at, hops, *(np.concatenate(x) for x in zip(*seen, strict=True))])
    assert all(np.array_equal(a, b) for a, b in zip(found[0] + found[1], found[2] + found[3], strict=True))


def test_visits_of_a_query_are_summed_before_they_are_handed_on(monkeypatch):
    n = 100_000
    rng = np.random.default_rng(3)

    class Held:
        value = (np.arange(n), np.arange(n + 1) * 8, rng.integers(0, n, 8 * n).astype(np.int32))

    monkeypatch.setattr(W, "GROUP", 4 * W.BATCH)  # a span a group, for visits
    spans = 12
    columns = {"query_id": np.arange(spans) // 6, "start": np.full(spans, 5), "lo": np.arange(spans) % 6 * W.BATCH, "hi": (np.arange(spans) % 6 + 1) * W.BATCH, "weight": np.full(spans, 1.0 / W.BATCH)}
    batch = pa.RecordBatch.from_arrays([pa.array(c) for c in columns.values()], names=list(columns))
    out = pa.Table.from_batches(W._kernel(Held, PprParams(), False, False, True)([batch])).to_pandas()
    assert not out.duplicated(["query_id", "v"]).any()
    assert out.groupby("query_id")["n"].sum().tolist() == [6 * W.BATCH] * 2 and out.groupby("query_id")["weight"].sum().tolist() == pytest.approx([6, 6], rel=0.02)


def test_shell_scores_are_made_where_the_node_is(spark, monkeypatch):
    g, some = toy(spark, random_arcs(40, 300) + [(3, 99)]), sources(spark, 0, 3)
    plans, alpha = [], 0.2
    cut = B.cut
    monkeypatch.setattr(B, "cut", lambda df, name: (plans.append(df._jdf.queryExecution().optimizedPlan().toString()), cut(df, name))[1])
    found = {(r["query_id"], r["v"]): r["score"] for r in B.shell_approximation(g, some).scores.collect()}
    above = plans[-1].split("Join Cross" if "Join Cross" in plans[-1] else "Join Inner")[0]
    assert "Join" in plans[-1] and "Aggregate" not in above and "Union" not in above  # no exchange of a row a query and node
    p1, p2 = ({(r["query_id"], r["v"]): r["p"] for r in forward_push(g, starts(g, some), 0.0, alpha, max_rounds=k).state.collect()} for k in (2, 3))
    wide = {r["v"]: r["score"] for r in B.global_pagerank(g, PprParams(alpha), "power", rounds=30).scores.collect()}
    scale = sum((1 - alpha) ** i for i in range(1, 6))
    for q in (0, 1):
        for v in wide:
            near = p2.get((q, v), 0.0)
            assert found[q, v] == pytest.approx(near + scale * (near - p1.get((q, v), 0.0)) + (1 - alpha) ** 8 * wide[v], abs=1e-12)
    assert len(found) == 2 * len(wide)
