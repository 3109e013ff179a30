"""Random walks with restart, many at once.

Two engines give the same walks. The kernel maps the adjacency of a graph of checked size and runs
whole walks of a batch in numpy, so no round costs a job. The join engine moves all live
walkers one hop a round by an equi-join on (node, position), several hops in one plan, and a written
table splits off walks that have stopped. No walk is cut short.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pushwave.functions.formulas import PprParams
from pushwave.functions.rng import draw_columns, stop_limit
from pushwave.operators.graph import Graph
from pushwave.operators.kernels import Local, walk
from pushwave.plans.durable import ArrayFile, Mapped, cut, put, runs_of

#: Walks in one kernel row; walks that a kernel sums together; hops in one plan of the join engine.
BATCH, GROUP, HOPS = 8192, 1 << 18, 8
#: Sums that a kernel task holds at most, over all nodes of its queries.
HELD = 1 << 21
ENDS = "query_id long, v long, weight double, hops long, n long"
SPANS = "query_id long, start long, lo long, hi long, weight double"


def _lane(p: PprParams, query):
    return query * 0 if p.shared_walks else query + 1


def _spans(alloc: DataFrame) -> DataFrame:
    """Walk numbers lo .. hi-1 of each start, at most BATCH in a row; alloc may carry first_walk."""
    first = F.col("first_walk") if "first_walk" in alloc.columns else F.lit(0).cast("long")
    have = alloc.filter(F.col("n_walks") > first)
    return have.select("query_id", "start", "weight", "n_walks", F.explode(F.sequence(first, F.col("n_walks") - 1, F.lit(BATCH).cast("long"))).alias("lo")).select(
        "query_id", "start", "lo", F.least(F.col("lo") + BATCH, "n_walks").alias("hi"), "weight"
    )


def _kernel(adjacency, p: PprParams, forced: bool, each: bool, visits: bool = False, into: tuple[Mapped, ArrayFile] | None = None):
    shared = p.shared_walks
    heads, file = (into[0], (into[1].path, into[1].begin, into[1].width)) if into is not None else (None, None)

    def run(batches):
        g = Local(*adjacency.value)
        n, held = len(g.v), {}
        group = GROUP // 4 if visits else GROUP  # a walk visits five nodes, about
        worth = np.where(g.deg == 0, 1.0, p.alpha) if visits else None
        front = heads.value[0] if heads is not None else None

        def rows(q, code, weight, hops, count):
            return pa.RecordBatch.from_arrays([pa.array(np.full(len(code), q)), pa.array(g.v[code]), pa.array(weight), pa.array(hops.astype(np.int64)), pa.array(count.astype(np.int64))], names=["query_id", "v", "weight", "hops", "n"])

        def flush():
            for q, (weight, hops, count) in held.items():
                code = np.flatnonzero(weight > 0)
                yield rows(q, code, weight[code], hops[code], count[code])
            held.clear()

        for b in batches:
            q, s, lo, hi, w = (b.column(c).to_numpy() for c in ("query_id", "start", "lo", "hi", "weight"))
            order = np.argsort(q, kind="stable")
            q, s, lo, hi, w = (x[order] for x in (q, s, lo, hi, w))
            place, size = np.searchsorted(g.v, s), hi - lo
            ends = np.cumsum(size)
            asked, begin = np.unique(q, return_index=True)
            many = dict(zip(asked.tolist(), (np.add.reduceat(size, begin) * 8 > n).tolist(), strict=True)) if len(q) else {}
            i = 0
            while i < len(q):  # a bounded number of walks at a time
                j = max(i + 1, int(np.searchsorted(ends, (ends[i - 1] if i else 0) + group, side="right")))
                own = size[i:j]
                row = np.repeat(np.arange(i, j), own)
                number = lo[row] + np.arange(len(row)) - np.repeat(np.cumsum(own) - own, own)
                seen = []
                at, hops = walk(g, p, forced, 0 if shared else q[row] + 1, place[row], number, (lambda live, now: seen.append((live, now))) if visits else None)
                if each:
                    if front is not None:
                        put(*file, runs_of(front[place[row]] + number, at.astype(np.int32)))
                    yield pa.RecordBatch.from_arrays([pa.array(s[row]), pa.array(number), pa.array(g.v[at])], names=["start", "walk_no", "endpoint"])
                    i = j
                    continue
                who, node = np.arange(len(row)), at
                if visits:
                    who, node = (np.concatenate(x) for x in zip(*seen, strict=True))
                    order = np.argsort(who, kind="stable") if q[i] != q[j - 1] else slice(None)
                    who, node = who[order], node[order]
                value = w[row[who]] if not visits else w[row[who]] * worth[node]
                one, first = np.unique(q[i:j], return_index=True)
                border = np.append((np.cumsum(own) - own)[first], len(row))
                for k, low, high in zip(one.tolist(), border[:-1].tolist(), border[1:].tolist(), strict=True):
                    a, z = (np.searchsorted(who, (low, high)) if len(one) > 1 else (0, len(who)))
                    if k in held or many[k]:
                        if k not in held:
                            if (len(held) + 1) * n > HELD:
                                yield from flush()
                            held[k] = np.zeros(n), np.zeros(n), np.zeros(n)
                        for total, to, part in zip(held[k], (node[a:z], at[low:high], at[low:high]), (value[a:z], hops[low:high], None), strict=True):
                            if len(to) * 16 > n:
                                total += np.bincount(to, part, n)
                            else:  # few: no array over all nodes for them
                                np.add.at(total, to, 1 if part is None else part)
                    else:
                        code, back = np.unique(node[a:z], return_inverse=True)
                        end = np.searchsorted(code, at[low:high])
                        yield rows(k, code, np.bincount(back, value[a:z], len(code)), np.bincount(end, hops[low:high], len(code)), np.bincount(end, minlength=len(code)))
                i = j
        yield from flush()

    return run


def _join_walks(g: Graph, alloc: DataFrame, p: PprParams, forced: bool, visits: bool = False) -> tuple[DataFrame, DataFrame | None]:
    """(query_id, start, walk_no, endpoint, weight, hops) by rounds of joins; visits: also (query_id, v, deg,
    weight) of every node that a walk comes to."""
    spans = _spans(alloc)
    none = [F.expr("cast(array() as array<struct<v: bigint, deg: bigint>>)").alias("seen")] if visits else []
    now = spans.select("query_id", "start", "weight", F.explode(F.sequence(F.col("lo"), F.col("hi") - 1)).alias("walk_no"))
    deg = g.nodes.select(F.col("v").alias("start"), F.col("out_deg").alias("deg"))
    now = now.join(deg, "start").select("query_id", "start", "walk_no", "weight", F.col("start").alias("cur"), "deg", F.lit(0).cast("long").alias("hop"), F.lit(False).alias("done"), *none)
    arcs = g.arcs.select(F.col("src").alias("a_src"), F.col("pos").alias("a_pos"), F.col("dst").alias("a_dst"), F.col("dst_deg").alias("a_deg"))
    ended, met_nodes = None, None
    while True:
        for _ in range(HOPS):
            stop, choice = draw_columns(p.rng, p.seed, _lane(p, F.col("query_id")), F.col("start"), F.col("walk_no"), F.col("hop"))
            stays = (stop < stop_limit(p.alpha)) & ~(F.lit(forced) & (F.col("hop") == 0))
            if visits:
                now = now.withColumn("seen", F.when(F.col("done"), F.col("seen")).otherwise(F.concat("seen", F.array(F.struct(F.col("cur").alias("v"), F.col("deg").cast("long").alias("deg"))))))
            drawn = now.withColumn("end", F.col("done") | (F.col("deg") == 0) | stays).withColumn("pick", F.when(F.col("end"), F.lit(None)).otherwise(choice % F.greatest(F.col("deg"), F.lit(1))))
            met = drawn.join(arcs, (F.col("cur") == F.col("a_src")) & (F.col("pick") == F.col("a_pos")), "left")
            now = met.select("query_id", "start", "walk_no", "weight", F.coalesce("a_dst", "cur").alias("cur"), F.coalesce("a_deg", "deg").alias("deg"), F.when(F.col("end"), F.col("hop")).otherwise(F.col("hop") + 1).alias("hop"), F.col("end").alias("done"), *["seen"] * visits)
        now = cut(now, "walkers")
        if visits:
            came = now.select("query_id", F.inline("seen"), "weight")
            met_nodes = came if met_nodes is None else met_nodes.unionByName(came)
            now = now.drop("seen").withColumns({"seen": F.expr("cast(array() as array<struct<v: bigint, deg: bigint>>)")})
        part = now.filter("done").select("query_id", "start", "walk_no", F.col("cur").alias("endpoint"), "weight", F.col("hop").alias("hops"))
        ended = part if ended is None else ended.unionByName(part)
        now = now.filter(~F.col("done"))
        if not now.limit(1).count():
            return ended, met_nodes


def run_walks(g: Graph, alloc: DataFrame, p: PprParams, forced: bool = False, engine: str = "auto", visits: bool = False) -> DataFrame:
    """Weights by endpoint: (query_id, v, weight, hops, n). alloc: query_id, start, n_walks, weight of a walk,
    and optionally first_walk. forced: the first hop is always taken (nodes without out-arcs stay). visits: every
    visited node has alpha of the weight, or all of it where the walk must end."""
    if g.in_kernel(engine):
        # A query's walks are in as few tasks as they fill, one after the other, so that each sums them before it hands on.
        spans = _spans(alloc).repartitionByRange(4 * g.spark.sparkContext.defaultParallelism, "query_id", "start", "lo").sortWithinPartitions("query_id", "start", "lo")
        ends = spans.mapInArrow(_kernel(g.adjacency(), p, forced, False, visits), ENDS)
        return ends.groupBy("query_id", "v").agg(F.sum("weight").alias("weight"), F.sum("hops").alias("hops"), F.sum("n").alias("n"))
    ended, came = _join_walks(g, alloc, p, forced, visits)
    own = F.lit(0.0) if visits else F.col("weight")
    each = ended.select("query_id", F.col("endpoint").alias("v"), own.alias("weight"), "hops", F.lit(1).cast("long").alias("n"))
    if came is not None:
        zero = F.lit(0).cast("long")
        each = each.unionByName(came.select("query_id", "v", F.when(F.col("deg") == 0, F.col("weight")).otherwise(p.alpha * F.col("weight")).alias("weight"), zero.alias("hops"), zero.alias("n")))
    return each.groupBy("query_id", "v").agg(F.sum("weight").alias("weight"), F.sum("hops").alias("hops"), F.sum("n").alias("n"))


def walk_ends(g: Graph, alloc: DataFrame, p: PprParams, forced: bool = False, engine: str = "auto", ordered: bool = False, into: tuple[Mapped, ArrayFile] | None = None) -> DataFrame:
    """Every walk's end: (start, walk_no, endpoint). ordered: in range partitions sorted by (start, walk_no); the
    kernel walks then in that order, so no end is shuffled and no walk walked twice for the ranges' sake.
    into: (first row of each node, a shared file), for the kernel: ends go into the file as places as well."""
    if g.in_kernel(engine):
        spans, tasks = _spans(alloc), g.spark.sparkContext.defaultParallelism
        spans = spans.repartitionByRange(2 * tasks, "start", "lo").sortWithinPartitions("start", "lo") if ordered else spans.repartition(tasks)
        return spans.mapInArrow(_kernel(g.adjacency(), p, forced, True, into=into), "start long, walk_no long, endpoint long")
    ends = _join_walks(g, alloc, p, forced)[0].select("start", "walk_no", "endpoint")
    return ends.repartitionByRange("start", "walk_no").sortWithinPartitions("start", "walk_no") if ordered else ends
