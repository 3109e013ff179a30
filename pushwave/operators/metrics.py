"""Accuracy measures and contract checks, as joins of answers with the truth."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pushwave.operators.topk import rank


def precision_at_k(answer: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(query_id, precision): share of the answer that is in the true top k (recall is the same)."""
    best = rank(truth, k).select("query_id", "v")
    hits = answer.filter(F.col("rk") <= k).join(best, ["query_id", "v"], "left_semi").groupBy("query_id").agg(F.count(F.lit(1)).alias("hits"))
    size = best.groupBy("query_id").agg(F.count(F.lit(1)).alias("size"))
    return size.join(hits, "query_id", "left").select("query_id", (F.coalesce("hits", F.lit(0)) / F.col("size")).alias("precision"))


def ndcg_at_k(answer: DataFrame, truth: DataFrame, k: int, best: DataFrame | None = None) -> DataFrame:
    """(query_id, ndcg): gains 2^score - 1 of true scores, discounted by log2(rank + 1), over the ideal. best: k rows
    of the truth or more a query, its highest, if they are known."""
    gain = (F.pow(F.lit(2.0), F.col("true")) - 1) / F.log2(F.col("rk") + 1)
    got = answer.filter(F.col("rk") <= k).select("query_id", "rk", "v").join(truth.select("query_id", "v", F.col("score").alias("true")), ["query_id", "v"], "left").withColumn("true", F.coalesce("true", F.lit(0.0))).groupBy("query_id").agg(F.sum(gain).alias("got"))
    ideal = rank(truth if best is None else best, k).withColumnRenamed("score", "true").groupBy("query_id").agg(F.sum(gain).alias("ideal"))
    return ideal.join(got, "query_id", "left").select("query_id", (F.coalesce("got", F.lit(0.0)) / F.col("ideal")).alias("ndcg"))


def relative_error(estimate: DataFrame, truth: DataFrame, delta: float) -> DataFrame:
    """(query_id, max_error, mean_error) over nodes whose true score is above delta."""
    both = truth.filter(F.col("score") > delta).join(estimate.select("query_id", "v", F.col("score").alias("got")), ["query_id", "v"], "left")
    err = F.abs(F.coalesce("got", F.lit(0.0)) - F.col("score")) / F.col("score")
    return both.groupBy("query_id").agg(F.max(err).alias("max_error"), F.avg(err).alias("mean_error"))


def check_whole_graph(estimate: DataFrame, truth: DataFrame, eps: float, delta: float) -> DataFrame:
    """(query_id, holds): every score above delta is within eps, relatively."""
    return relative_error(estimate, truth, delta).select("query_id", (F.col("max_error") <= eps).alias("holds"))


def check_top_k(answer: DataFrame, truth: DataFrame, k: int, eps: float, delta: float) -> DataFrame:
    """(query_id, scores_hold, order_holds): scores within eps of the node's own, and the i-th node's true
    score at least (1 - eps) of the i-th best, for ranks whose best score is above delta."""
    own = answer.filter(F.col("rk") <= k).join(truth.select("query_id", "v", F.col("score").alias("true")), ["query_id", "v"], "left").withColumn("true", F.coalesce("true", F.lit(0.0)))
    best = rank(truth, k).select("query_id", "rk", F.col("score").alias("best"))
    both = best.filter(F.col("best") > delta).join(own, ["query_id", "rk"], "left")
    score_ok = F.coalesce((F.abs(F.col("score") - F.col("true")) <= eps * F.col("true")), F.lit(False))
    order_ok = F.coalesce(F.col("true") >= (1 - eps) * F.col("best"), F.lit(False))
    return both.groupBy("query_id").agg(F.min(score_ok).alias("scores_hold"), F.min(order_ok).alias("order_holds"))


def failure_rate(checks: DataFrame, holds: str = "holds") -> DataFrame:
    """Share of failed checks, e.g. over seeds."""
    return checks.agg(F.avg((~F.col(holds)).cast("double")).alias("failure_rate"))


def ratio_table(runs: DataFrame, base: str) -> DataFrame:
    """runs (graph, method, seconds): each method's time as a multiple of a base method's, by graph."""
    w = Window.partitionBy("graph")
    own = F.max(F.when(F.col("method") == base, F.col("seconds"))).over(w)
    return runs.select("graph", "method", "seconds", (F.col("seconds") / own).alias("ratio"))


def space_report(graph_arcs: int, index_rows: int, width: int = 8) -> dict[str, float]:
    """Bytes of the graph once and twice (for reverse methods), of the index, and the index's ratio."""
    graph = graph_arcs * width
    return {"graph": graph, "graph_twice": 2 * graph, "index": index_rows * width, "ratio": index_rows / max(1, graph_arcs)}


def table_cost(tables: dict[str, DataFrame]) -> DataFrame:
    """(name, rows, files, bytes, columns) of written tables: what a method keeps on disk and a scan reads."""
    spark = next(iter(tables.values())).sparkSession
    path = spark._jvm.org.apache.hadoop.fs.Path
    conf = spark._jsc.hadoopConfiguration()
    rows = []
    for name, df in tables.items():
        files = df.inputFiles()
        size = 0
        for f in files:  # one look-up a file of a table
            at = path(f)
            size += at.getFileSystem(conf).getFileStatus(at).getLen()
        rows.append((name, df.count(), len(files), size, len(df.columns)))
    return spark.createDataFrame(rows, "name string, rows long, files long, bytes long, columns long")
