"""Whole queries in one task, for graphs whose adjacency tasks map (a checked size).

A query's residues and reserves are arrays here, so a push round costs the degrees of its frontier and
a rung of a top-k ladder costs no job. Queries are the unit of work: a batch spreads over the cluster.
Rounds, walks and allocations are those of the distributed engine, which serves every larger graph.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pushwave.functions.formulas import PprParams, Rung, cap_aware_rho
from pushwave.functions.rng import drawer, stop_limit

#: Walks that are summed together, walks that move together, arcs pushed together; walks whose hop is drawn together.
BATCH, BLOCK, ARCS, STEP = 1 << 18, 1 << 18, 1 << 22, 1 << 14
STATE = "query_id long, v long, deg long, p double, r double, touched long"


@dataclass
class Local:
    """Node ids ascending, first arc of each (and the end), targets as places, degrees."""

    v: np.ndarray
    first: np.ndarray
    target: np.ndarray

    def __post_init__(self):
        self.deg = np.diff(self.first)


def expand(first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """first[i], first[i] + 1, ... of size[i] each, one after the other."""
    return np.repeat(first - np.cumsum(size) + size, size) + np.arange(int(size.sum()))


class Push:
    """The state of one query: reserves p, residues r, arcs touched by pushes of each node."""

    def __init__(self, g: Local, place: np.ndarray, r: np.ndarray, p: np.ndarray | None = None, touched: np.ndarray | None = None):
        n = len(g.v)
        self.g = g
        self.p, self.r, self.touched = np.zeros(n), np.zeros(n), np.zeros(n, np.int64)
        self.r[place] = r
        if p is not None:
            self.p[place], self.touched[place] = p, touched

    def run(self, rho: float, alpha: float, tol: float = 0.0, max_rounds: int | None = None) -> int:
        """Push all eligible nodes together until none is left; returns the rounds."""
        g, r = self.g, self.r
        floor = np.maximum(rho * np.maximum(g.deg, 1), tol)
        hot, rounds, before, to = np.flatnonzero(r > floor), 0, None, None
        while len(hot) and (max_rounds is None or rounds < max_rounds):
            amount, deg = r[hot], g.deg[hot]
            self.p[hot] += np.where(deg == 0, amount, alpha * amount)
            self.touched[hot] += deg
            r[hot] = 0.0
            each, border = (1 - alpha) * amount / np.maximum(deg, 1), np.cumsum(deg)
            if border[-1] <= min(ARCS, len(g.target) // 2) and np.array_equal(hot, before):  # the nodes of the last round: their arcs are picked once
                to = g.target[expand(g.first[hot], deg)].astype(np.intp) if to is None else to
                r += np.bincount(to, np.repeat(each, deg), len(r))
                hot = np.flatnonzero(r > floor)
                rounds += 1
                continue
            before, to = hot, None
            if border[-1] > len(g.target) // 2:  # most arcs: all are read as they lie, which costs less than picking
                sent = np.zeros(len(r))
                sent[hot] = each
                i = 0
                while i < len(sent):  # a bounded number of arcs at a time
                    j = max(i + 1, int(np.searchsorted(g.first, g.first[i] + ARCS, side="right")) - 1)
                    r += np.bincount(g.target[g.first[i] : g.first[j]], np.repeat(sent[i:j], g.deg[i:j]), len(r))
                    i = j
                hot = np.flatnonzero(r > floor)
            elif border[-1] > len(r) // 4:
                i = 0
                while i < len(hot):  # a bounded number of arcs at a time
                    j = max(i + 1, int(np.searchsorted(border, (border[i - 1] if i else 0) + ARCS, side="right")))
                    r += np.bincount(g.target[expand(g.first[hot[i:j]], deg[i:j])], np.repeat(each[i:j], deg[i:j]), len(r))
                    i = j
                hot = np.flatnonzero(r > floor)
            else:
                near, back = np.unique(g.target[expand(g.first[hot], deg)], return_inverse=True)
                r[near] += np.bincount(back, np.repeat(each, deg), len(near))
                hot = near[r[near] > floor[near]]
            rounds += 1
        return rounds


@dataclass
class LocalIndex:
    """Stored walk ends (places) by start, read from the front of each."""

    first: np.ndarray
    ends: np.ndarray


def walk(g: Local, p: PprParams, forced: bool, lane, start: np.ndarray, number: np.ndarray, visit: Callable | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(end, hops) of walks from places; a walk is a function of (seed, lane, start id, number). lane: one for
    all, or one each. visit is told the walks under way and where they are, hop by hop."""
    limit, at, hops = stop_limit(p.alpha), np.empty(len(start), np.int64), np.empty(len(start), np.int32)
    for low in range(0, len(start), BLOCK):
        part = slice(low, low + BLOCK)
        now = start[part].astype(np.int64)
        drawn = drawer(p.rng)(p.seed, lane[part] if np.ndim(lane) else lane, g.v[now], number[part])
        live, hop = np.arange(low, low + len(now)), 0
        while len(live):
            if visit is not None:
                visit(live.copy(), now.copy())
            left = 0
            for i in range(0, len(live), STEP):  # a hop's arrays stay in a core's cache; who goes on moves up
                some = slice(i, i + STEP)
                here, who = now[some], live[some]
                first = g.first.take(here)
                deg = g.first.take(here + 1) - first
                stop, choice = drawn.draw(hop, some)
                go = deg > 0
                if not (forced and hop == 0):
                    go &= stop >= limit
                over, on = np.flatnonzero(~go), np.flatnonzero(go)
                ended = who[over]
                at[ended], hops[ended] = here[over], hop
                up = slice(left, left + len(on))
                to = g.target.take(first[on] + choice[on] % deg[on].astype(np.uint32))
                drawn.move(some, on, up)
                live[up], now[up] = who[on], to
                left += len(on)
            drawn.keep(left)
            live, now = live[:left], now[:left]
            hop += 1
    return at, hops


@dataclass
class Found:
    scores: np.ndarray
    walks: int
    hops: int


def finish(s: Push, p: PprParams, c: float, pruned: bool, lane: int, index: LocalIndex | None) -> Found:
    """Walks from the residues on top of the reserves, stored ones first."""
    g, share = s.g, (1 - p.alpha) if pruned else 1.0
    scores = s.p + np.where(g.deg == 0, s.r, p.alpha * s.r) if pruned else s.p.copy()
    left = np.flatnonzero((s.r > 0) & (g.deg > 0)) if pruned else np.flatnonzero(s.r > 0)
    n = np.ceil(share * c * s.r[left]).astype(np.int64)
    weight = share * s.r[left] / np.maximum(n, 1)
    done = np.zeros(len(left), np.int64)
    if index is not None:
        have = np.diff(index.first)[left]
        done = np.minimum(n, have)
        rows = expand(index.first[left], done)
        scores += np.bincount(index.ends[rows], np.repeat(weight, done), len(scores))
    rest, hops = n - done, 0
    border = np.cumsum(rest)
    i = 0
    while i < len(left):  # a bounded number of walks at a time
        j = max(i + 1, int(np.searchsorted(border, (border[i - 1] if i else 0) + BATCH, side="right")))
        for low in range(0, max(1, int(rest[i])) if j == i + 1 else 1, BATCH):  # one start with very many
            size = np.minimum(rest[i:j] - low, BATCH) if j == i + 1 else rest[i:j]
            number = expand(done[i:j] + low, size)
            ends, steps = walk(g, p, pruned, lane, np.repeat(left[i:j], size), number)
            scores += np.bincount(ends, np.repeat(weight[i:j], size), len(scores))
            hops += int(steps.sum())
        i = j
    return Found(scores, int(n.sum()), hops)


def best(g: Local, scores: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best positive scores, ties by node."""
    some = np.flatnonzero(scores > 0)
    if len(some) > k:
        least = np.partition(scores[some], len(some) - k)[len(some) - k]
        some = some[scores[some] >= least]
    return some[np.lexsort((g.v[some], -scores[some]))][:k]


def per_query(state: DataFrame, adjacency, index, body: Callable, schema: str, params: PprParams) -> DataFrame:
    """body(push, lane, query_id, index) of every query in a task of its own; it yields record batches."""
    shared = params.shared_walks

    def run(t: pa.Table) -> pa.Table:
        g = Local(*adjacency.value)
        query = t.column("query_id")[0].as_py()
        place = np.searchsorted(g.v, t.column("v").to_numpy())
        s = Push(g, place, t.column("r").to_numpy(), t.column("p").to_numpy(), t.column("touched").to_numpy())
        stored = LocalIndex(*index.value) if index is not None else None
        return pa.Table.from_batches([body(s, 0 if shared else query + 1, query, stored)])

    rows = state.select("query_id", "v", "p", "r", F.col("touched").cast("long").alias("touched"))
    # A number of its own: a state of few rows would be coalesced into one task, and all queries with it.
    return rows.repartition(4 * state.sparkSession.sparkContext.defaultParallelism, "query_id").groupBy("query_id").applyInArrow(run, schema)


def batch(schema: str, n: int, **columns) -> pa.RecordBatch:
    """A batch of n rows; scalars are repeated."""
    kinds = {"long": pa.int64(), "double": pa.float64(), "int": pa.int32(), "boolean": pa.bool_()}
    out, names = [], []
    for part in schema.split(", "):
        name, kind = part.split()
        value = columns[name]
        value = value if isinstance(value, np.ndarray) else np.full(n, value)
        out.append(pa.array(value, kinds[kind]))
        names.append(name)
    return pa.RecordBatch.from_arrays(out, names=names)


def pushed(state: DataFrame, adjacency, rho: float, alpha: float, tol: float, max_rounds: int | None) -> DataFrame:
    """The state after a push, with its rounds."""
    schema = STATE + ", rounds int"

    def body(s: Push, lane: int, query: int, index) -> pa.RecordBatch:
        rounds = s.run(rho, alpha, tol, max_rounds)
        at = np.flatnonzero((s.p > 0) | (s.r > 0))
        return batch(schema, len(at), query_id=query, v=s.g.v[at], deg=s.g.deg[at], p=s.p[at], r=s.r[at], touched=s.touched[at], rounds=rounds)

    return per_query(state, adjacency, None, body, schema, PprParams())


#: Rows of the state of reverse pushes that go on together.
BACK_ROWS = 1 << 20
BACK = "target long, v long, p double, r double, rounds int"


def pushed_back(reverse, rho: float, alpha: float, max_rounds: int | None) -> Callable:
    """Of targets (target): the states of reverse pushes, for many targets at once; a state that grows is split
    by target."""

    def run(batches):
        v, deg, first, source = reverse.value
        n = len(v)

        def round_of(key, p, r):
            hot = np.flatnonzero(r > rho)
            node, amount = key[hot] % n, r[hot]
            p[hot] += np.where(deg[node] == 0, amount, alpha * amount)
            r[hot] = 0.0
            sent = (1 - alpha) * np.where(deg[node] == 0, amount / alpha, amount)
            size = first[node + 1] - first[node]
            border, i = np.cumsum(size), 0
            while i < len(hot):  # a bounded number of arcs at a time
                j = max(i + 1, int(np.searchsorted(border, (border[i - 1] if i else 0) + ARCS, side="right")))
                to = source[expand(first[node[i:j]], size[i:j])]
                near, back = np.unique(np.repeat(key[hot[i:j]] - node[i:j], size[i:j]) + to, return_inverse=True)
                gain = np.bincount(back, np.repeat(sent[i:j], size[i:j]) / deg[to], len(near))
                i = j
                yield near, gain

        def merged(key, p, r, near, gain):
            at = np.minimum(np.searchsorted(key, near), len(key) - 1)
            old = key[at] == near
            r[at[old]] += gain[old]
            if old.all():
                return key, p, r
            new = ~old
            order = np.argsort(both := np.concatenate([key, near[new]]), kind="stable")
            return both[order], np.concatenate([p, np.zeros(int(new.sum()))])[order], np.concatenate([r, gain[new]])[order]

        for b in batches:
            targets = b.column("target").to_numpy()
            place = np.searchsorted(v, targets)
            border, i = np.cumsum(first[place + 1] - first[place] + 1), 0
            while i < len(targets):
                j = max(i + 1, int(np.searchsorted(border, (border[i - 1] if i else 0) + BACK_ROWS // 4, side="right")))
                open_ = [(np.arange(i, j) * n + place[i:j], np.zeros(j - i), np.ones(j - i), 0)]
                i = j
                while open_:
                    key, p, r, rounds = open_.pop()
                    if (r > rho).any() and (max_rounds is None or rounds < max_rounds):
                        low, high = key[0] // n, key[-1] // n
                        if len(key) > BACK_ROWS and low < high:
                            cut = np.searchsorted(key, (low + high + 1) // 2 * n)
                            open_ += [(key[:cut], p[:cut], r[:cut], rounds), (key[cut:], p[cut:], r[cut:], rounds)]
                            continue
                        for near, gain in list(round_of(key, p, r)):
                            key, p, r = merged(key, p, r, near, gain)
                        open_.append((key, p, r, rounds + 1))
                    else:
                        yield batch(BACK, len(key), target=targets[key // n], v=v[key % n], p=p, r=r, rounds=rounds)

    return run


SCORES = "query_id long, v long, score double, rounds int, touched long, residue double, walks long, hops long"


def estimated(state: DataFrame, adjacency, index, p: PprParams, c: float, pruned: bool, push: Callable[[Push], int]) -> DataFrame:
    """Whole-graph scores after push (a function of the state that returns its rounds) and walks."""

    def body(s: Push, lane: int, query: int, stored) -> pa.RecordBatch:
        rounds = push(s)
        residue = float(s.r.sum())
        found = finish(s, p, c, pruned, lane, stored)
        at = np.flatnonzero(found.scores > 0)
        return batch(SCORES, len(at), query_id=query, v=s.g.v[at], score=found.scores[at], rounds=rounds, touched=int(s.touched.sum()), residue=residue, walks=found.walks, hops=found.hops)

    return per_query(state, adjacency, index, body, SCORES, p)


def balanced(s: Push, alpha: float, c: float, floor: float, arc: float, ahead: float) -> int:
    """Push down falling thresholds, a round at a time, while that has cost less than the walks foreseen.

    arc: price of a touched arc; ahead: price of all walks of a unit of residue. Each query decides for itself.
    """
    top = float((s.r / np.maximum(s.g.deg, 1)).max())
    rho, rounds = max(floor, top / 2), 0
    while arc * s.touched.sum() < ahead * c * s.r.sum():
        if s.run(rho, alpha, max_rounds=1):
            rounds += 1
        elif rho <= floor:
            break
        else:
            rho = max(floor, rho / 4)
    return rounds


ANSWER = "query_id long, rk int, v long, score double, delta_end double, guaranteed boolean, rungs int, walks long, touched long"


def halving(state: DataFrame, adjacency, index, per_degree: float | None, k: int, p: PprParams, rungs: list[Rung], m: int, pruned: bool, use_push: bool, rho_mult: float) -> DataFrame:
    """The ladder of threshold halving of each query, without a job a rung."""

    def body(s: Push, lane: int, query: int, stored) -> pa.RecordBatch:
        walks = 0
        for i, rung in enumerate(rungs):
            rho = rho_mult * rung.rho if per_degree is None else min(rho_mult * rung.rho, cap_aware_rho(per_degree, rung.c, m))
            if use_push:
                s.run(rho, p.alpha)
            found = finish(s, p, rung.c, pruned and use_push, lane, stored)
            walks += found.walks
            top = best(s.g, found.scores, k)
            passed = len(top) == k and found.scores[top[-1]] >= (1 + p.eps) * rung.delta
            if passed or i == len(rungs) - 1:
                return batch(ANSWER, len(top), query_id=query, rk=np.arange(1, len(top) + 1), v=s.g.v[top], score=found.scores[top], delta_end=rung.delta, guaranteed=bool(passed), rungs=i + 1, walks=walks, touched=int(s.touched.sum()))
        raise AssertionError("a ladder has a rung")

    return per_query(state, adjacency, index, body, ANSWER, p)
