"""Walk index: stored endpoints of walks from every node, read from the front.

A walk is a pure function of (seed, start, number), so the index is a memo of it: indexed and live
answers agree. Rows are sorted by (start, walk_no) in files, so a few starts touch few row groups.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pushwave.functions.formulas import PprParams
from pushwave.operators.graph import Graph, placed
from pushwave.operators.walks import run_walks, walk_ends
from pushwave.plans.durable import ArrayFile, Mapped, drop, fill, local_path, mapped, new_folder, shared_dir


#: Stored walks that kernels map at most, in a file of 4 bytes each.
KERNEL_ROWS = 500_000_000


@dataclass
class WalkIndex:
    """rows: start, walk_no, endpoint; per_degree: walks stored for each out-arc, about."""

    rows: DataFrame
    path: str
    rho: float
    c: float
    pruned: bool
    params: PprParams
    _local: object = field(default=None, repr=False)

    def local(self, g: Graph) -> Mapped | None:
        """(first row of each node, ends as places), mapped by tasks, or None where the index is too large for it."""
        if self._local is None:
            total = self.rows.count()
            if total > KERNEL_ROWS:
                return None
            places, ends = _files(g, capacities(g, self.rho, self.c, self.params.alpha, self.pruned), total)
            arcs = self.rows.select(F.col("start").alias("src"), F.col("walk_no").alias("pos"), F.col("endpoint").alias("dst"))
            fill(arcs, placed(places), ends)
            self._local = _held(g, places, ends)
        return self._local

    def drop(self) -> None:
        """Delete the files; the index is of no use afterwards."""
        if self._local is not None:
            self._local.drop()
        drop(self.rows)

    @property
    def per_degree(self) -> float:
        return (1 - self.params.alpha if self.pruned else 1.0) * self.rho * self.c


def capacities(g: Graph, rho: float, c: float, alpha: float, pruned: bool) -> DataFrame:
    """(v, cap): enough walks for any residue up to rho times the degree."""
    share = (1 - alpha) if pruned else 1.0
    deg = F.greatest(F.col("out_deg"), F.lit(1))
    cap = F.ceil(F.lit(share * rho * c) * deg)
    return g.nodes.select("v", F.when(F.lit(pruned) & (F.col("out_deg") == 0), F.lit(0)).otherwise(cap).cast("long").alias("cap"))


def _files(g: Graph, size: DataFrame, total: int) -> tuple[Mapped, ArrayFile]:
    """(node ids and first row of each, a file for total ends) of capacities (v, cap)."""
    table = size.toArrow()
    v, cap = (table.column(c).to_numpy() for c in ("v", "cap"))
    order = np.argsort(v)
    heads = (v[order], np.append(0, np.cumsum(cap[order])).astype(np.int64))
    return mapped(g.spark, *heads), ArrayFile(g.spark, np.int32, total)


def _held(g: Graph, places: Mapped, ends: ArrayFile) -> Mapped:
    """(first row of each node, ends), once the ends are filled."""
    found = Mapped(places.names[1:] + mapped(g.spark, ends).names)
    Mapped(places.names[:1]).drop()
    return found


def build_walk_index(g: Graph, p: PprParams, rho: float, pruned: bool = False, path: str | None = None, engine: str = "auto", held: bool = False) -> WalkIndex:
    """held: the file that kernels map is filled as the walks are walked, where graph and index are small enough for it."""
    p = p.resolve(g.n)
    size = capacities(g, rho, p.walks, p.alpha, pruned)
    into = None
    if held and g.in_kernel(engine) and local_path(g.spark, shared_dir(g.spark)) is not None:
        total = size.agg(F.sum("cap")).first()[0] or 0
        if total <= KERNEL_ROWS:
            places, ends = _files(g, size, total)
            into = Mapped(places.names[1:]), ends
    alloc = size.select(F.lit(0).cast("long").alias("query_id"), F.col("v").alias("start"), F.col("cap").alias("n_walks"), F.lit(1.0).alias("weight"))
    path = path or new_folder(g.spark, "walk-index")
    walked = walk_ends(g, alloc.filter("n_walks > 0"), p, forced=pruned, engine=engine, ordered=True, into=into)
    walked.write.parquet(path)
    return WalkIndex(g.spark.read.schema(walked.schema).parquet(path), path, rho, p.walks, pruned, p, _held(g, places, ends) if into is not None else None)


def index_walks(g: Graph, index: WalkIndex, alloc: DataFrame) -> DataFrame:
    """As run_walks, from the index; a start that needs more walks than are stored walks the rest live."""
    cap = capacities(g, index.rho, index.c, index.params.alpha, index.pruned).withColumnRenamed("v", "start")
    need = alloc.join(cap, "start")
    stored = need.select("start", "query_id", "n_walks", "weight").join(index.rows, "start").filter(F.col("walk_no") < F.col("n_walks"))
    found = stored.groupBy("query_id", F.col("endpoint").alias("v")).agg(F.sum("weight").alias("weight"), F.lit(0).cast("long").alias("hops"), F.count(F.lit(1)).alias("n"))
    short = need.filter("n_walks > cap").select("query_id", "start", "n_walks", "weight", F.col("cap").alias("first_walk"))
    if not short.limit(1).count():
        return found
    live = run_walks(g, short, index.params, index.pruned)
    return found.unionByName(live).groupBy("query_id", "v").agg(F.sum("weight").alias("weight"), F.sum("hops").alias("hops"), F.sum("n").alias("n"))
