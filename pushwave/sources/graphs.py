"""Graphs derived from the given tables, a generator, and readers of edge files.

Each derivation is a pair: a DataFrame plan and the same in DuckDB's SQL for the oracle.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pushwave.schemas import ARCS, conform

Loader = Callable[[SparkSession, str], DataFrame]


def read(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def clean(arcs: DataFrame, keep_loops: bool = False) -> DataFrame:
    """Distinct arcs without nulls, and without loops unless asked for."""
    arcs = conform(arcs, ARCS).filter("src is not null and dst is not null")
    return (arcs if keep_loops else arcs.filter("src <> dst")).distinct()


def both_ways(edges: DataFrame) -> DataFrame:
    """An undirected edge becomes two opposite arcs."""
    return edges.select("src", "dst").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


def trade_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    line = read(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey")
    order = read(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    supplier = read(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey")
    customer = read(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    joined = line.join(order, F.col("l_orderkey") == F.col("o_orderkey")).join(supplier, F.col("l_suppkey") == F.col("s_suppkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    return clean(joined.select(F.col("s_nationkey").alias("src"), F.col("c_nationkey").alias("dst")), keep_loops=True)


def event_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    # A chain over all events has one order. Only (ts, event_id, user_id) is sorted: days are dealt
    # out and the borders between days joined, so no task orders the whole stream.
    e = read(spark, sf_dir, "events", "ts", "event_id", "user_id").withColumn("day", F.to_date("ts"))
    inside = Window.partitionBy("day").orderBy("ts", "event_id")
    chained = e.select("day", "user_id", F.lead("user_id").over(inside).alias("next_user"), F.row_number().over(inside).alias("rn"))
    heads = chained.filter("rn = 1").select("day", F.col("user_id").alias("head"))
    days = heads.select(F.lag("day").over(Window.orderBy("day")).alias("day"), "head")  # one row a day
    border = chained.filter("next_user is null").drop("next_user", "rn").join(F.broadcast(days), "day").select(F.col("user_id").alias("src"), F.col("head").alias("dst"))
    return clean(chained.filter("next_user is not null").select(F.col("user_id").alias("src"), F.col("next_user").alias("dst")).unionByName(border))


def _chain(spark: SparkSession, sf_dir: str, key: str) -> DataFrame:
    line = read(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    return clean(line.select(F.col(key).alias("src"), F.lead(key).over(w).alias("dst")))


def part_next(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _chain(spark, sf_dir, "l_partkey")


def supp_next(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _chain(spark, sf_dir, "l_suppkey")


def order_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    line = read(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey")
    return clean(both_ways(line.select((F.col("l_orderkey") * 2).alias("src"), (F.col("l_partkey") * 2 + 1).alias("dst"))))


def _customer_side(spark: SparkSession, sf_dir: str, key: str) -> DataFrame:
    line = read(spark, sf_dir, "lineitem", "l_orderkey", key)
    order = read(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    return line.join(order, F.col("l_orderkey") == F.col("o_orderkey")).select((F.col("o_custkey") * 2).alias("src"), (F.col(key) * 2 + 1).alias("dst")).distinct()


def cust_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return clean(both_ways(_customer_side(spark, sf_dir, "l_partkey")))


def cust_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return clean(both_ways(_customer_side(spark, sf_dir, "l_suppkey")))


def part_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    line = read(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey").distinct()
    other = line.select("l_orderkey", F.col("l_partkey").alias("dst"))
    return clean(line.join(other, "l_orderkey").select(F.col("l_partkey").alias("src"), "dst"))


HREF = 'href="([^"]+)"'


def page_link(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages and the paths they link to; ids by rank of the name (pages first)."""
    page = read(spark, sf_dir, "pages", "page_id", "html")
    hop = page.select("page_id", F.explode(F.expr(f"regexp_extract_all(html, '{HREF}', 1)")).alias("path")).distinct()
    paths = hop.select("path").distinct().withColumn("id", F.dense_rank().over(Window.orderBy("path")))  # as many rows as path names
    return clean(hop.join(paths, "path").select((F.col("page_id") * 2).alias("src"), (F.col("id") * 2 + 1).alias("dst")))


def page_coanchor(spark: SparkSession, sf_dir: str) -> DataFrame:
    page = read(spark, sf_dir, "pages", "page_id", "html")
    hop = page.select("page_id", F.explode(F.expr(f"regexp_extract_all(html, '{HREF}', 1)")).alias("path")).distinct()
    return clean(hop.join(hop.select(F.col("page_id").alias("dst"), "path"), "path").select(F.col("page_id").alias("src"), "dst"))


def doc_line(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that share a line of over 20 characters which 2 to 50 documents hold."""
    docs = read(spark, sf_dir, "documents", "doc_id", "text")
    line = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).filter(F.char_length("line") > 20).select("doc_id", F.md5("line").alias("h")).distinct()
    some = line.groupBy("h").agg(F.count(F.lit(1)).alias("n")).filter("n between 2 and 50")
    shared = line.join(some, "h").select("h", "doc_id")
    return clean(shared.join(shared.select("h", F.col("doc_id").alias("dst")), "h").select(F.col("doc_id").alias("src"), "dst"))


def emb_knn(spark: SparkSession, sf_dir: str, k: int = 10) -> DataFrame:
    """Each vector's k nearest by cosine, exact: vectors are compared in blocks, best k kept on the way."""
    import numpy as np
    import pandas as pd

    e = read(spark, sf_dir, "embeddings")
    key = e.columns[0]
    rows = e.select(F.col(key).cast("long").alias("id"), F.col("embedding").cast("array<double>").alias("x"))
    blocks = 8
    left = rows.withColumn("a", F.pmod("id", F.lit(blocks)))
    right = rows.select(F.col("id").alias("other"), F.col("x").alias("y"), F.pmod("id", F.lit(blocks)).alias("b"))
    pairs = left.withColumn("b", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).groupBy("a", "b").cogroup(right.withColumn("a", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).groupBy("a", "b"))

    def near(lhs: pd.DataFrame, rhs: pd.DataFrame) -> pd.DataFrame:
        if not len(lhs) or not len(rhs):
            return pd.DataFrame({"src": [], "dst": [], "cos": []})
        x, y = np.array(lhs["x"].tolist()), np.array(rhs["y"].tolist())
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        y /= np.linalg.norm(y, axis=1, keepdims=True)
        cos = np.where(lhs["id"].to_numpy()[:, None] == rhs["other"].to_numpy()[None, :], -2.0, x @ y.T)
        best = np.argsort(-cos, axis=1, kind="stable")[:, :k]
        out = pd.DataFrame({"src": np.repeat(lhs["id"].to_numpy(), best.shape[1]), "dst": rhs["other"].to_numpy()[best.ravel()], "cos": np.take_along_axis(cos, best, 1).ravel()})
        return out[out["cos"] > -2]

    found = pairs.applyInPandas(near, "src long, dst long, cos double")
    w = Window.partitionBy("src").orderBy(F.round("cos", 9).desc(), "dst")
    return clean(found.withColumn("rk", F.row_number().over(w)).filter(F.col("rk") <= k).select("src", "dst"))


GRAPHS: dict[str, Loader] = {f.__name__: f for f in (trade_nation, event_user, part_next, supp_next, order_part, cust_part, cust_supp, part_part, page_link, page_coanchor, doc_line, emb_knn)}


def _both(inner: str) -> str:
    return f"SELECT src, dst FROM ({inner}) UNION SELECT dst AS src, src AS dst FROM ({inner})"


def _chain_sql(key: str) -> str:
    return f"SELECT DISTINCT src, dst FROM (SELECT {key} AS src, lead({key}) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS dst FROM lineitem) WHERE dst IS NOT NULL AND src <> dst"


def _customer_sql(key: str) -> str:
    return f"SELECT DISTINCT o_custkey * 2 AS src, {key} * 2 + 1 AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey"


_HOP = f"SELECT DISTINCT page_id, unnest(regexp_extract_all(html, '{HREF}', 1)) AS path FROM pages"
_LINE = "SELECT DISTINCT doc_id, md5(line) AS h FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) > 20"
#: Arcs of each graph in DuckDB's SQL.
GRAPH_SQL: dict[str, str] = {
    "trade_nation": "SELECT DISTINCT s_nationkey::BIGINT AS src, c_nationkey::BIGINT AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey JOIN customer ON o_custkey = c_custkey",
    "event_user": "SELECT DISTINCT src, dst FROM (SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL AND src <> dst",
    "part_next": _chain_sql("l_partkey"),
    "supp_next": _chain_sql("l_suppkey"),
    "order_part": _both("SELECT l_orderkey * 2 AS src, l_partkey * 2 + 1 AS dst FROM lineitem"),
    "cust_part": _both(_customer_sql("l_partkey")),
    "cust_supp": _both(_customer_sql("l_suppkey")),
    "part_part": "SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey WHERE a.l_partkey <> b.l_partkey",
    "page_link": f"SELECT DISTINCT page_id * 2 AS src, id * 2 + 1 AS dst FROM ({_HOP}) h JOIN (SELECT path, dense_rank() OVER (ORDER BY path) AS id FROM (SELECT DISTINCT path FROM ({_HOP}))) p USING (path)",
    "page_coanchor": f"WITH h AS ({_HOP}) SELECT DISTINCT a.page_id AS src, b.page_id AS dst FROM h a JOIN h b USING (path) WHERE a.page_id <> b.page_id",
    "doc_line": f"WITH l AS ({_LINE}), s AS (SELECT h FROM l GROUP BY h HAVING count(*) BETWEEN 2 AND 50), x AS (SELECT h, doc_id FROM l SEMI JOIN s USING (h)) SELECT DISTINCT a.doc_id AS src, b.doc_id AS dst FROM x a JOIN x b USING (h) WHERE a.doc_id <> b.doc_id",
}


def rmat(spark: SparkSession, scale: int, edge_factor: int = 16, seed: int = 42, quadrants: tuple[float, float, float] = (0.57, 0.19, 0.19)) -> DataFrame:
    """Recursive-matrix graph: one hashed quadrant a bit and edge, nothing shuffled before distinct."""
    a, b, c = (int(x * 2**32) for x in (quadrants[0], quadrants[0] + quadrants[1], sum(quadrants)))
    e = spark.range(edge_factor << scale)
    src = dst = F.lit(0).cast("long")
    for bit in range(scale):
        u = F.xxhash64(F.lit(seed).cast("long"), F.col("id"), F.lit(bit).cast("long")).bitwiseAND(F.lit(0xFFFFFFFF).cast("long"))
        src = src + F.when(u >= b, F.lit(1 << bit)).otherwise(0).cast("long")
        dst = dst + F.when(((u >= a) & (u < b)) | (u >= c), F.lit(1 << bit)).otherwise(0).cast("long")
    return clean(e.select(src.alias("src"), dst.alias("dst")))


def read_edges(spark: SparkSession, path: str, fmt: str = "text", undirected: bool = False, keep_loops: bool = True) -> DataFrame:
    """Edges from text (two numbers a line, # and % start comments), csv, json, orc or parquet (src, dst)."""
    if fmt == "text":
        line = spark.read.text(path).filter(~F.col("value").rlike("^[#%]")).select(F.split(F.trim("value"), r"[\s,]+").alias("x"))
        e = line.filter(F.size("x") >= 2).select(F.col("x")[0].cast("long").alias("src"), F.col("x")[1].cast("long").alias("dst"))
    elif fmt == "csv":
        e = spark.read.schema(ARCS).option("header", True).csv(path)
    else:
        e = spark.read.schema(ARCS).format(fmt).load(path)
    return clean(both_ways(e) if undirected else e, keep_loops)


def node_ids(names: DataFrame, column: str) -> DataFrame:
    """(name, v): dense ids of names in sorted order, by range partitions and their offsets."""
    from pushwave.plans.durable import cut

    ordered = cut(names.select(F.col(column).alias("name")).filter("name is not null").distinct().repartitionByRange("name").sortWithinPartitions("name").withColumn("part", F.spark_partition_id()), "names")
    w = Window.partitionBy("part").orderBy("name")
    counts = ordered.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    before = counts.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))  # one row a partition
    return ordered.withColumn("rn", F.row_number().over(w)).join(F.broadcast(before), "part").select("name", (F.col("before") + F.col("rn") - 1).alias("v"))
