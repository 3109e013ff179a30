"""The engine against dense solves, closed forms and its own variants."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from pushwave.functions import formulas as FM
from pushwave.functions.rng import hash_longs
from pushwave.operators import baselines as B
from pushwave.operators import estimators as E
from pushwave.operators import metrics as M
from pushwave.operators import topk as T
from pushwave.operators.graph import build_graph
from pushwave.operators.index import build_walk_index, index_walks
from pushwave.operators.push import forward_push, from_distribution, reverse_push, starts
from pushwave.operators.walks import run_walks

A = 0.2
TOY = [(0, 1), (0, 2), (1, 2), (2, 0), (3, 2)]


def toy(spark, arcs=TOY, **kw):
    return build_graph(spark.createDataFrame(arcs, "src long, dst long"), **kw)


def sources(spark, *nodes):
    return spark.createDataFrame(list(enumerate(nodes)), "query_id long, src long")


def dense(arcs, alpha=A):
    n = max(max(a) for a in arcs) + 1
    w = np.zeros((n, n))
    for s, d in set(arcs):
        w[s, d] = 1
    deg = w.sum(axis=1)
    w[deg > 0] /= deg[deg > 0, None]
    out = np.linalg.inv(np.eye(n) - (1 - alpha) * w) * alpha
    out[:, deg == 0] /= alpha  # a walk stops where it can't go on
    return out


def vector(df, n, query=0, column="score"):
    out = np.zeros(n)
    for r in df.filter(F.col("query_id") == query).collect():
        out[r["v"]] += r[column]
    return out


def random_arcs(n=30, m=120, seed=3):
    rng = np.random.default_rng(seed)
    return sorted({(int(a), int(b)) for a, b in rng.integers(0, n, (m, 2)) if a != b})


def test_toy_scores_and_first_rounds(spark):
    g = toy(spark)
    assert (g.n, g.m) == (4, 5)
    exact = vector(E.power(g, starts(g, sources(spark, 0)), 120).scores, 4)
    assert np.allclose(exact, [0.4716981, 0.1886792, 0.3396226, 0], atol=1e-7)
    state = forward_push(g, starts(g, sources(spark, 0)), 0.1, A, max_rounds=2, chain=1).state
    assert np.allclose(vector(state, 4, column="p"), [0.2, 0.08, 0.08, 0])
    assert np.allclose(vector(state, 4, column="r"), [0.32, 0, 0.32, 0])


@pytest.mark.parametrize("rounds", [1, 3, None])
def test_push_keeps_its_invariant(spark, rounds):
    arcs = random_arcs()
    g, exact = toy(spark, arcs), dense(arcs)
    n = len(exact)
    pushed = forward_push(g, starts(g, sources(spark, arcs[0][0])), 0.004, A, max_rounds=rounds)
    p, r = vector(pushed.state, n, column="p"), vector(pushed.state, n, column="r")
    assert abs(p.sum() + r.sum() - 1) < 1e-12
    assert np.allclose(p + r @ exact, exact[arcs[0][0]], atol=1e-10)
    if rounds is None:
        deg = np.bincount([a for a, _ in arcs], minlength=n)
        assert (r <= 0.004 * np.maximum(deg, 1) + 1e-15).all()
        assert pushed.edge_touches <= 1 / (A * 0.004)


def test_push_resumes_and_takes_distributions(spark):
    arcs = random_arcs()
    g, exact = toy(spark, arcs), dense(arcs)
    sigma = spark.createDataFrame([(0, arcs[0][0], 0.25), (0, arcs[5][0], 0.75)], "query_id long, v long, mass double")
    first = forward_push(g, from_distribution(g, sigma), 0.05, A)
    then = forward_push(g, first.state, 0.001, A)
    p, r = vector(then.state, len(exact), column="p"), vector(then.state, len(exact), column="r")
    assert np.allclose(p + r @ exact, 0.25 * exact[arcs[0][0]] + 0.75 * exact[arcs[5][0]], atol=1e-10)


def test_bad_input_is_refused(spark):
    g = toy(spark)
    with pytest.raises(ValueError):
        starts(g, sources(spark, 99))
    with pytest.raises(ValueError):
        from_distribution(g, spark.createDataFrame([(0, 0, 0.9)], "query_id long, v long, mass double"))
    for bad in ({"alpha": 0.0}, {"alpha": 1.0}, {"eps": 1.5}, {"dangling": "x"}, {"rng": "x"}):
        with pytest.raises(ValueError):
            FM.PprParams(**bad)
    with pytest.raises(ValueError):
        toy(spark, [*TOY, (2, 4)], dangling="reject")


def test_closed_forms(spark):
    pair = toy(spark, [(0, 1), (1, 0)])
    assert np.allclose(vector(E.power(pair, starts(pair, sources(spark, 0)), 120).scores, 2), [1 / 1.8, 0.8 / 1.8])
    star = toy(spark, [x for leaf in range(1, 6) for x in ((0, leaf), (leaf, 0))])
    assert np.allclose(vector(E.power(star, starts(star, sources(spark, 0)), 120).scores, 6), [1 / 1.8] + [0.8 / 1.8 / 5] * 5)
    ring = toy(spark, [(i, (i + 1) % 5) for i in range(5)])
    assert np.allclose(vector(E.power(ring, starts(ring, sources(spark, 0)), 120).scores, 5), [A * 0.8**j / (1 - 0.8**5) for j in range(5)])
    alone = build_graph(spark.createDataFrame([], "src long, dst long"), more_nodes=spark.createDataFrame([(7,)], "v long"))
    got = E.push_walk(alone, starts(alone, sources(spark, 7)), FM.PprParams(delta=0.5, p_fail=0.1)).scores.collect()
    assert [(r["v"], round(r["score"], 12)) for r in got] == [(7, 1.0)]


def test_dangling_nodes_absorb_or_loop(spark):
    arcs = [*TOY, (2, 4)]
    g = toy(spark, arcs)
    assert np.allclose(vector(E.power(g, starts(g, sources(spark, 0)), 150).scores, 5), dense(arcs)[0], atol=1e-9)
    looped = toy(spark, arcs, dangling="self_loop")
    assert np.allclose(vector(E.power(looped, starts(looped, sources(spark, 0)), 150).scores, 5), dense(arcs)[0], atol=1e-9)
    p = FM.PprParams(eps=0.3)
    for pruned in (False, True):
        got = vector(E.push_walk(g, starts(g, sources(spark, 0)), p, pruned=pruned).scores, 5)
        assert abs(got.sum() - 1) < 1e-9
        assert np.allclose(got, dense(arcs)[0], atol=0.05)


def test_reverse_push_identity(spark):
    arcs = random_arcs()
    arcs += [(v, 0) for v in range(30) if v not in {a for a, _ in arcs} and v]
    g, exact = toy(spark, arcs), dense(arcs)
    state = reverse_push(g, spark.createDataFrame([(3,)], "target long"), 0.05, A).state.collect()
    p, r = np.zeros(len(exact)), np.zeros(len(exact))
    for x in state:
        p[x["v"]], r[x["v"]] = x["p"], x["r"]
    assert r.max() <= 0.05
    assert np.allclose(p + exact @ r, exact[:, 3], atol=1e-10)


def test_hash_equals_sparks(spark):
    rows = spark.range(50).select("id", (F.col("id") * -7919).alias("x"), F.xxhash64(F.col("id"), F.col("id") * -7919).alias("h")).collect()
    got = hash_longs([r["id"] for r in rows], [r["x"] for r in rows]).view(np.int64)
    assert got.tolist() == [r["h"] for r in rows]


@pytest.mark.parametrize("rng", ["xxhash64", "md5"])
@pytest.mark.parametrize("forced", [False, True])
def test_walks_follow_the_law(spark, rng, forced):
    g = toy(spark)
    alloc = spark.createDataFrame([(0, 0, 3000, 1 / 3000)], "query_id long, start long, n_walks long, weight double")
    got = vector(run_walks(g, alloc, FM.PprParams(rng=rng), forced=forced), 4, column="weight")
    exact = dense(TOY)
    want = exact[0] if not forced else (exact[0] - A * np.eye(4)[0]) / (1 - A)
    assert abs(got.sum() - 1) < 1e-9
    assert np.abs(got - want).max() < 0.04


def test_kernel_and_joins_walk_alike(spark):
    g = toy(spark, random_arcs())
    alloc = spark.createDataFrame([(0, 1, 40, 1.0), (1, 5, 17, 0.5)], "query_id long, start long, n_walks long, weight double")
    for shared in (True, False):
        p = FM.PprParams(shared_walks=shared)
        for forced in (False, True):
            rows = [sorted(map(tuple, run_walks(g, alloc, p, forced, e).select("query_id", "v", "weight", "hops", "n").collect())) for e in ("kernel", "join")]
            assert rows[0] == rows[1]


def test_index_is_a_memo_and_tops_up(spark):
    g = toy(spark, random_arcs())
    p = FM.PprParams(eps=0.5, delta=0.05, p_fail=0.1)
    for pruned in (False, True):
        index = build_walk_index(g, p, 0.02, pruned)
        rows = [(0, 1, 3, 1.0), (0, 2, 500, 0.1)]  # the second start needs more than is stored
        alloc = spark.createDataFrame(rows, "query_id long, start long, n_walks long, weight double")
        a = {(r["query_id"], r["v"]): round(r["weight"], 9) for r in index_walks(g, index, alloc).collect()}
        b = {(r["query_id"], r["v"]): round(r["weight"], 9) for r in run_walks(g, alloc, p, pruned).collect()}
        assert a == b
    state = starts(g, sources(spark, 1))
    live, stored = (vector(E.push_walk(g, state, p, rho=0.02, pruned=True, index=i).scores, 30) for i in (None, index))
    assert np.allclose(live, stored)


def test_capacity_covers_need():
    for m, c in ((100, 1000.0), (5000, 1000.0)):
        rho, case = FM.push_threshold(m, c)
        assert case == (1 if m <= c else 2)
        assert all(FM.index_capacity(d, rho, c) >= np.ceil(d * rho * c) for d in (1, 5, 50))
        assert FM.index_capacity(10, rho, c, 0.2) <= FM.index_capacity(10, rho, c)


def test_estimators_hold_their_guarantee(spark):
    arcs = random_arcs(60, 400, 5)
    g, exact = toy(spark, arcs), dense(arcs)
    p = FM.PprParams()
    state = starts(g, sources(spark, 0, 1))
    truth = spark.createDataFrame([(q, v, float(exact[q, v])) for q in (0, 1) for v in range(60)], "query_id long, v long, score double")
    index = build_walk_index(g, p, 2 * FM.push_threshold(g.m, p.resolve(g.n).walks)[0], True)
    for found in (E.monte_carlo(g, state, p), E.push_walk(g, state, p), E.push_walk(g, state, p, pruned=True), E.push_walk(g, state, p, rho_mult=2, pruned=True, index=index), E.push_walk_balanced(g, state, p), B.bidirectional_all(g, sources(spark, 0, 1), p)):
        assert all(r["holds"] for r in M.check_whole_graph(found.scores, truth, p.eps, 1 / g.n).collect())
    a, b = E.push_walk(g, state, p), E.push_walk(g, state, p, pruned=True)
    assert 0.7 < b.walks / a.walks < 0.95  # about 1 - alpha


def test_top_k_methods(spark):
    arcs = random_arcs(60, 400, 5)
    g, exact = toy(spark, arcs), dense(arcs)
    p, k = FM.PprParams(), 5
    q = sources(spark, 0, 1)
    state = starts(g, q)
    truth = spark.createDataFrame([(s, v, float(exact[s, v])) for s in (0, 1) for v in range(60)], "query_id long, v long, score double")
    for found in (T.top_k_halving(g, state, k, p), T.top_k_halving(g, state, k, p, use_push=False), T.top_k_bounds(g, state, k, p), T.top_k_full_sort(g, state, k, p), B.filter_refine_top_k(g, q, k, p)):
        assert found.answer.groupBy("query_id").count().filter("count <> 5").count() == 0
        assert all(r["scores_hold"] and r["order_holds"] for r in M.check_top_k(found.answer, truth, k, p.eps, 1 / g.n).collect())
        assert M.ndcg_at_k(found.answer, truth, k).agg(F.min("ndcg")).first()[0] > 0.95
    assert T.top_k_halving(g, state, 500, p).answer.groupBy("query_id").count().agg(F.max("count")).first()[0] <= 60


def test_bounds_hold_in_every_rung(spark):
    arcs = random_arcs(40, 200, 9)
    g, exact = toy(spark, arcs), dense(arcs)
    state, bounds = starts(g, sources(spark, 0)), None
    for rung in FM.ladder(g.n, g.m, 4, FM.PprParams(), halve_eps=False):
        pushed = forward_push(g, state, rung.rho, A)
        q = FM.PprParams(eps=rung.eps, delta=rung.delta, p_fail=rung.p_fail)
        found = E.finish(g, pushed, q, rung.c, False)
        bounds = T.refine_bounds(found.scores, pushed.state, bounds, rung.c, rung.p_fail, False, A)
        for r in bounds.collect():
            assert r["lb"] - 1e-12 <= exact[0, r["v"]] <= r["ub"] + 1e-12
        state = pushed.state


def test_ladder_ends_at_one_over_n():
    for n, k in ((150, 100), (1000, 10), (16, 16), (7, 50)):
        rungs = FM.ladder(n, 10 * n, k, FM.PprParams())
        assert rungs[-1].delta == 1 / n
        assert all(a.delta > b.delta for a, b in zip(rungs, rungs[1:], strict=False))


def test_measures(spark):
    truth = spark.createDataFrame([(0, v, s) for v, s in enumerate((0.5, 0.3, 0.15, 0.05))], "query_id long, v long, score double")
    answer = spark.createDataFrame([(0, 1, 0, 0.5), (0, 2, 2, 0.2)], "query_id long, rk int, v long, score double")
    assert M.precision_at_k(answer, truth, 2).first()["precision"] == 0.5
    gain = lambda s, i: (2**s - 1) / np.log2(i + 1)
    want = (gain(0.5, 1) + gain(0.15, 2)) / (gain(0.5, 1) + gain(0.3, 2))
    assert abs(M.ndcg_at_k(answer, truth, 2).first()["ndcg"] - want) < 1e-12
    est = spark.createDataFrame([(0, 0, 0.4), (0, 1, 0.3)], "query_id long, v long, score double")
    r = M.relative_error(est, truth, 0.2).first()
    assert abs(r["max_error"] - 0.2) < 1e-12
    assert abs(r["mean_error"] - 0.1) < 1e-12


def test_pagerank_is_the_mean_of_all(spark):
    arcs = random_arcs()
    g, exact = toy(spark, arcs), dense(arcs)
    got = vector(B.global_pagerank(g, FM.PprParams(), "power", 120).scores, len(exact))
    nodes = sorted({x for a in arcs for x in a})
    assert np.allclose(got[nodes], exact[nodes][:, nodes].mean(axis=0), atol=1e-9)


def test_answers_do_not_depend_on_partitions(spark):
    arcs = random_arcs()
    p, seen = FM.PprParams(), []
    before = spark.conf.get("spark.sql.shuffle.partitions")
    for parts in ("1", "7"):
        spark.conf.set("spark.sql.shuffle.partitions", parts)
        g = toy(spark, arcs)
        seen.append(vector(E.push_walk(g, starts(g, sources(spark, 1)), p, pruned=True).scores, 30))
    spark.conf.set("spark.sql.shuffle.partitions", before)
    assert np.allclose(*seen, atol=1e-12)


def test_kernel_and_joins_push_and_rank_alike(spark):
    """A query in one task and by rounds of joins: the same state, estimates and answers."""
    from pushwave import workloads as w
    from pushwave.operators import estimators as E
    from pushwave.operators import topk as T
    from pushwave.operators.index import build_walk_index
    from pushwave.operators.push import forward_push, starts

    g = w.graph(spark, "/root/testdata/sf0.001", "event_user")
    p = w.PprParams(eps=0.9, delta=0.02, p_fail=0.05)
    state = starts(g, w.first_sources(g, 2))
    rows = lambda df, *c: {tuple(r[x] for x in c): r for r in df.collect()}
    one, two = (rows(forward_push(g, state, 0.001, engine=e).state, "query_id", "v") for e in ("kernel", "join"))
    for key in two.keys() | one.keys():
        for c in ("p", "r", "touched"):
            assert abs((one[key][c] if key in one else 0) - (two[key][c] if key in two else 0)) < 1e-9
    index = build_walk_index(g, p, w.push_threshold(g.m, p.walks)[0] / 2, True)
    for stored in (None, index):
        one, two = (rows(E.push_walk(g, state, p, pruned=True, index=stored, engine=e).scores, "query_id", "v") for e in ("kernel", "join"))
        assert one.keys() == two.keys() and all(abs(one[k]["score"] - two[k]["score"]) < 1e-9 for k in one)
    one, two = (rows(T.top_k_halving(g, state, 5, p, engine=e).answer, "query_id", "rk") for e in ("kernel", "join"))
    assert one.keys() == two.keys()
    assert all(one[k]["v"] == two[k]["v"] and one[k]["delta_end"] == two[k]["delta_end"] and one[k]["guaranteed"] == two[k]["guaranteed"] for k in one)
