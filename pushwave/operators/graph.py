"""Graph tables: nodes and positioned arcs.

One row an arc, so a hub's adjacency is spread over tasks. Positions 0 .. d-1 of a node's arcs are
numbered inside (node, salt) groups and shifted by the groups' sizes, so no task orders a whole hub; where the graph
is small enough for kernels, tasks number the arcs of their range of nodes as they read them in order.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pushwave.plans.durable import ArrayFile, Mapped, bucketed, cut, fill, local_path, mapped, put, runs_of, shared_dir

#: Groups that the arcs of one node are dealt to when they are numbered.
SALTS = 16
#: Arcs and nodes of the largest graph whose adjacency is mapped by kernels: a file of 4 bytes an arc and 16 a
#: node on every executor's disk, and some arrays of 8 bytes a node in a task's memory.
KERNEL_ARCS, KERNEL_NODES = 200_000_000, 5_000_000


@dataclass
class Graph:
    """nodes (v, out_deg, in_deg); arcs (src, pos, dst, src_deg, dst_deg); n and m are driver scalars."""

    nodes: DataFrame
    arcs: DataFrame
    n: int
    m: int
    _adjacency: object = field(default=None, repr=False)
    _reverse: object = field(default=None, repr=False)
    _steps: DataFrame | None = field(default=None, repr=False)

    @property
    def spark(self):
        return self.arcs.sparkSession

    def in_kernel(self, engine: str) -> bool:
        """Whether an engine (auto, kernel or join) runs in tasks that hold the adjacency."""
        return engine == "kernel" or (engine == "auto" and self.m <= KERNEL_ARCS and self.n <= KERNEL_NODES)

    def steps(self) -> DataFrame:
        """Arcs for a push round: (src, dst, dst_deg), in buckets by src, so that a round shuffles its frontier only."""
        if self._steps is None:
            self._steps = bucketed(self.arcs.select("src", "dst", "dst_deg"), "src", "steps")
        return self._steps

    def backward(self) -> DataFrame:
        """Arcs against their direction for reverse push rounds: (src, dst, dst_deg, own, share): a unit of
        residue at src sends (1-alpha)*share to dst. The second copy of the graph."""
        back = self.arcs.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("src_deg").alias("dst_deg"), F.lit(False).alias("own"), (F.lit(1.0) / F.col("src_deg")).alias("share"))
        mine = self.nodes.select(F.col("v").alias("src"), F.col("v").alias("dst"), F.col("out_deg").alias("dst_deg"), F.lit(True).alias("own"), F.lit(0.0).alias("share"))
        return cut(back.unionByName(mine), "backward")

    def adjacency(self) -> Mapped:
        """(node ids, first arc of each, targets as places), mapped by tasks; only for graphs of a checked size."""
        if self._adjacency is None:
            if self.m > KERNEL_ARCS or self.n > KERNEL_NODES:
                raise ValueError("the graph is too large for a walk kernel; use engine='join'")
            places, target = _heads(self.nodes), ArrayFile(self.spark, np.int32, self.m)
            fill(self.arcs.select("src", "pos", "dst"), placed(places), target)
            self._adjacency = Mapped(places.names + mapped(self.spark, target).names)
        return self._adjacency


    def reverse_adjacency(self) -> Mapped:
        """(node ids, out-degrees, first in-arc of each, sources as places), mapped by tasks: 4 bytes an arc more."""
        if self._reverse is None:
            table = self.nodes.select("v", "out_deg", "in_deg").toArrow()
            v, deg, size = (table.column(c).to_numpy() for c in ("v", "out_deg", "in_deg"))
            order = np.argsort(v)
            heads = (v[order], deg[order], np.append(0, np.cumsum(size[order])).astype(np.int64))
            places, source = mapped(self.spark, *heads), ArrayFile(self.spark, np.int32, self.m)
            arcs = self.arcs.select("src", "dst").repartitionByRange("dst").sortWithinPartitions("dst")
            fill(arcs, _counted(places), source)
            self._reverse = Mapped(places.names + mapped(self.spark, source).names)
        return self._reverse


def _heads(nodes: DataFrame) -> Mapped:
    """(node ids, first arc of each)."""
    table = nodes.select("v", "out_deg").toArrow()
    v, deg = (table.column(c).to_numpy() for c in ("v", "out_deg"))
    order = np.argsort(v)
    return mapped(nodes.sparkSession, v[order], np.append(0, np.cumsum(deg[order])).astype(np.int64))


def _numbered(heads: Mapped, target: ArrayFile):
    """Arcs with positions and degrees, of arcs (src, dst) in the order of positions; a task has all arcs of its
    sources. Targets go into a shared file as places on the way."""
    path, begin, width = target.path, target.begin, target.width

    def run(batches):
        v, first = heads.value
        last, before = -1, 0
        for b in batches:
            if not b.num_rows:
                continue
            src, dst = (b.column(c).to_numpy() for c in ("src", "dst"))
            node, to = np.searchsorted(v, src), np.searchsorted(v, dst)
            begins = np.append(True, node[1:] != node[:-1])
            pos = np.arange(len(node)) - np.flatnonzero(begins)[np.cumsum(begins) - 1]
            if node[0] == last:  # the batch before ended inside this source
                pos[: int(np.searchsorted(node, last, side="right"))] += before
            last, before = node[-1], int(pos[-1]) + 1
            put(path, begin, width, runs_of(first[node] + pos, to.astype(np.int32)))
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (src, pos, dst, first[node + 1] - first[node], first[to + 1] - first[to])], names=["src", "pos", "dst", "src_deg", "dst_deg"])

    return run


def _counted(heads: Mapped):
    """Runs (at, run) of sources as places; a task has all arcs into its nodes, ordered by node."""

    def run(batches):
        v, _, first = heads.value
        last, before = -1, 0
        for b in batches:
            if not b.num_rows:
                continue
            src, dst = (b.column(c).to_numpy() for c in ("src", "dst"))
            node = np.searchsorted(v, dst)
            at = int(first[node[0]]) + (before if node[0] == last else 0)
            tail = len(node) - int(np.searchsorted(node, node[-1]))
            before = tail + (before if node[0] == last == node[-1] else 0)
            last = node[-1]
            yield pa.RecordBatch.from_arrays([pa.array([at], pa.int64()), pa.array([np.searchsorted(v, src).astype(np.int32).tobytes()], pa.binary())], names=["at", "run"])

    return run


def placed(heads: Mapped):
    """Runs (at, run) of targets as places: rows are read as they are stored, by (src, pos)."""

    def run(batches):
        v, first = heads.value
        for b in batches:
            src, pos, dst = (b.column(c).to_numpy() for c in ("src", "pos", "dst"))
            at = first[np.searchsorted(v, src)] + pos
            order = np.argsort(at, kind="stable")
            at, to = at[order], np.searchsorted(v, dst[order]).astype(np.int32)
            border = np.concatenate([[0], np.flatnonzero(np.diff(at) != 1) + 1, [len(at)]]) if len(at) else np.zeros(1, np.int64)
            runs = [to[lo:hi].tobytes() for lo, hi in zip(border[:-1], border[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(at[border[:-1]] if len(at) else at), pa.array(runs, pa.binary())], names=["at", "run"])

    return run


def build_graph(arcs: DataFrame, dangling: str = "absorb", more_nodes: DataFrame | None = None) -> Graph:
    """Tables of distinct arcs (src, dst); more_nodes (v) adds isolated nodes.

    Null ends and repeats are dropped. dangling: absorb leaves nodes without out-arcs as they are
    (a walk stops there), self_loop adds an arc to itself, reject raises.
    """
    arcs = arcs.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")).filter("src is not null and dst is not null").distinct()
    arcs = cut(arcs, "arcs")
    one, none = F.lit(1).cast("long"), F.lit(0).cast("long")
    ends = arcs.select(F.col("src").alias("v"), one.alias("o"), none.alias("i")).unionByName(arcs.select(F.col("dst").alias("v"), none.alias("o"), one.alias("i")))
    if more_nodes is not None:
        ends = ends.unionByName(more_nodes.select(F.col("v").cast("long").alias("v"), F.lit(0).cast("long").alias("o"), F.lit(0).cast("long").alias("i")))
    nodes = ends.groupBy("v").agg(F.sum("o").alias("out_deg"), F.sum("i").alias("in_deg"))
    if dangling != "absorb":
        stuck = nodes.filter("out_deg = 0").select(F.col("v").alias("src"), F.col("v").alias("dst"))
        if dangling == "reject":
            if stuck.limit(1).count():
                raise ValueError("the graph has nodes without out-arcs")
        else:
            return build_graph(arcs.unionByName(stuck), "absorb", more_nodes)
    nodes = cut(nodes, "nodes")
    n, m = nodes.agg(F.count(F.lit(1)), F.coalesce(F.sum("out_deg"), F.lit(0))).first()
    spark = arcs.sparkSession
    if 0 < m <= KERNEL_ARCS and n <= KERNEL_NODES and local_path(spark, shared_dir(spark)) is not None:
        heads, target = _heads(nodes), ArrayFile(spark, np.int32, m)
        ordered = arcs.repartitionByRange("src").sortWithinPartitions("src", F.pmod("dst", F.lit(SALTS)), "dst")
        out = cut(ordered.mapInArrow(_numbered(heads, target), "src long, pos long, dst long, src_deg long, dst_deg long"), "out-arcs")
        return Graph(nodes, out, n, m, Mapped(heads.names + mapped(spark, target).names))
    salted = arcs.withColumn("salt", F.pmod("dst", F.lit(SALTS)))
    sizes = salted.groupBy("src", "salt").agg(F.count(F.lit(1)).alias("size"))
    before = Window.partitionBy("src").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    shift = sizes.select("src", "salt", F.coalesce(F.sum("size").over(before), F.lit(0)).alias("shift"))
    inside = salted.withColumn("rn", F.row_number().over(Window.partitionBy("src", "salt").orderBy("dst")))
    placed = inside.join(shift, ["src", "salt"]).select("src", (F.col("shift") + F.col("rn") - 1).alias("pos"), "dst")
    deg = nodes.select("v", "out_deg")
    full = placed.join(deg.select(F.col("v").alias("src"), F.col("out_deg").alias("src_deg")), "src").join(deg.select(F.col("v").alias("dst"), F.col("out_deg").alias("dst_deg")), "dst")
    out = cut(full.select("src", "pos", "dst", "src_deg", "dst_deg").repartitionByRange("src").sortWithinPartitions("src", "pos"), "out-arcs")
    return Graph(nodes, out, n, m)


def degree_distribution(g: Graph) -> DataFrame:
    return g.nodes.groupBy("out_deg").agg(F.count(F.lit(1)).alias("n"))


def power_law_fit(g: Graph) -> DataFrame:
    """Slope of log count over log in-degree; minus the exponent of a scale-free graph."""
    d = g.nodes.filter("in_deg > 0").groupBy("in_deg").agg(F.count(F.lit(1)).alias("c"))
    x, y = F.log(F.col("in_deg").cast("double")), F.log(F.col("c").cast("double"))
    return d.agg(F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.corr(y, x).alias("corr"))
