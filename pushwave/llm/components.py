"""Connected components of a sparse link table, without a driver-side graph.

Alternates two star rewrites: every node points its larger neighbours, then its smaller ones, at
the least id it knows. Links only ever move towards smaller ids, and a few rounds turn each
component into a star around its least id. Each round is a written table in the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pushwave.plans.durable import cut


def _least(arcs: DataFrame) -> DataFrame:
    return arcs.groupBy("u").agg(F.min("v").alias("w")).select("u", F.least("u", "w").alias("m"))


def _rewrite(links: DataFrame, large: bool) -> DataFrame:
    both = links.select(F.col("a").alias("u"), F.col("b").alias("v"))
    if large:
        both = both.unionByName(links.select(F.col("b").alias("u"), F.col("a").alias("v")))
    else:  # b is always the larger end
        both = links.select(F.col("b").alias("u"), F.col("a").alias("v"))
    least = _least(both)
    met = both.join(least, "u")
    if large:
        out = met.filter(F.col("v") > F.col("u")).select(F.col("m").alias("a"), F.col("v").alias("b"))
    else:
        out = met.select(F.col("m").alias("a"), F.col("v").alias("b")).unionByName(least.select(F.col("m").alias("a"), F.col("u").alias("b")))
    return out.filter("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def components(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root) of every node that has a link; links: (a, b) longs, in any direction, repeated or
    self-links allowed, nulls ignored. root is the least node of the component. No links: no rows."""
    now = cut(links.filter("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "links")
    seen = None
    for _ in range(max_rounds):
        sign = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if sign == seen or not sign[0]:
            break
        seen = sign
        now = cut(_rewrite(_rewrite(now, True), False), "links")
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("b").alias("node"), F.col("a").alias("root")).unionByName(now.select(F.col("a").alias("node"), F.col("a").alias("root")).distinct())
