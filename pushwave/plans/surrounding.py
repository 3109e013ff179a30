"""Operators around the methods, on the given tables: each as a DataFrame plan with its SQL twin."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pushwave.plans import oracles as O
from pushwave.sources.graphs import both_ways, read
from pushwave.workloads import graph, register
from pushwave.workloads import _truth as truth

_ORDER_LINE = "lineitem JOIN orders ON l_orderkey = o_orderkey"


@register("q_scan_project_filter", f"SELECT DISTINCT o_custkey AS src, l_suppkey AS dst FROM {_ORDER_LINE} WHERE l_returnflag = 'R' AND l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1996-01-01'")
def q_scan_project_filter(spark: SparkSession, d: str) -> DataFrame:
    line = read(spark, d, "lineitem").filter("l_returnflag = 'R' and l_shipdate >= timestamp'1995-01-01' and l_shipdate < timestamp'1996-01-01'").select("l_orderkey", "l_suppkey")
    order = read(spark, d, "orders", "o_orderkey", "o_custkey")
    return line.join(order, F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_custkey").alias("src"), F.col("l_suppkey").alias("dst")).distinct()


_MULTI = f"SELECT o_custkey AS src, l_suppkey AS dst, count(*) AS n FROM {_ORDER_LINE} GROUP BY 1, 2"


def _joined(hint: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        line, order = read(spark, d, "lineitem", "l_orderkey", "l_suppkey"), read(spark, d, "orders", "o_orderkey", "o_custkey")
        joined = line.join(order.hint(hint), F.col("l_orderkey") == F.col("o_orderkey"))
        return joined.groupBy(F.col("o_custkey").alias("src"), F.col("l_suppkey").alias("dst")).agg(F.count(F.lit(1)).alias("n"))

    return run


for _name, _hint in (("q_join_sort_merge", "merge"), ("q_join_shuffle_hash", "shuffle_hash")):
    register(_name, _MULTI)(_joined(_hint))


@register("q_join_broadcast", "SELECT s_nationkey AS nation, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY 1")
def q_join_broadcast(spark, d):
    # nation has 25 rows at every scale; supplier may grow and is left to the planner.
    line, supplier, nation = read(spark, d, "lineitem", "l_suppkey"), read(spark, d, "supplier", "s_suppkey", "s_nationkey"), read(spark, d, "nation", "n_nationkey")
    return line.join(supplier, F.col("l_suppkey") == F.col("s_suppkey")).join(F.broadcast(nation), F.col("s_nationkey") == F.col("n_nationkey")).groupBy(F.col("s_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("n"))


@register("q_join_left", "SELECT c_custkey AS v, coalesce(n, 0) AS n FROM customer LEFT JOIN (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1) ON c_custkey = o_custkey")
def q_join_left(spark, d):
    n = read(spark, d, "orders", "o_custkey").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
    return read(spark, d, "customer", "c_custkey").join(n, F.col("c_custkey") == F.col("o_custkey"), "left").select(F.col("c_custkey").alias("v"), F.coalesce("n", F.lit(0)).alias("n"))


@register("q_join_full", "SELECT coalesce(a.k, b.k) AS k, coalesce(a.n, 0) AS suppliers, coalesce(b.n, 0) AS customers FROM (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY 1) a FULL JOIN (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY 1) b ON a.k = b.k")
def q_join_full(spark, d):
    a = read(spark, d, "supplier").groupBy(F.col("s_nationkey").alias("a")).agg(F.count(F.lit(1)).alias("m"))
    b = read(spark, d, "customer").groupBy(F.col("c_nationkey").alias("b")).agg(F.count(F.lit(1)).alias("n"))
    return a.join(b, F.col("a") == F.col("b"), "full").select(F.coalesce("a", "b").alias("k"), F.coalesce("m", F.lit(0)).alias("suppliers"), F.coalesce("n", F.lit(0)).alias("customers"))


@register("q_join_semi", "SELECT p_partkey AS v FROM part WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_returnflag = 'R')")
def q_join_semi(spark, d):
    returned = read(spark, d, "lineitem").filter("l_returnflag = 'R'").select("l_partkey")
    return read(spark, d, "part", "p_partkey").join(returned, F.col("p_partkey") == F.col("l_partkey"), "left_semi").select(F.col("p_partkey").alias("v"))


@register("q_join_anti", "SELECT c_custkey AS v FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")
def q_join_anti(spark, d):
    done = read(spark, d, "orders").filter("o_orderstatus = 'F'").select("o_custkey")
    return read(spark, d, "customer", "c_custkey").join(done, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select(F.col("c_custkey").alias("v"))


@register("q_join_asof", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, max(b.o_orderdate) AS latest FROM (SELECT DISTINCT l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate, o_custkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey) a LEFT JOIN orders b ON a.o_custkey = b.o_custkey AND b.o_orderdate <= a.l_shipdate GROUP BY 1, 2, 3, 4")
def q_join_asof(spark, d):
    """Latest order of the same customer at or before a line's ship date: one sorted pass over both, no range join."""
    order = read(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    line = read(spark, d, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate").join(order.select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).distinct()
    marks = order.select("o_custkey", F.col("o_orderdate").alias("t"), F.lit(0).alias("kind"), F.col("o_orderdate").alias("mark"))
    asks = line.select("o_custkey", F.col("l_shipdate").alias("t"), F.lit(1).alias("kind"), "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    w = Window.partitionBy("o_custkey").orderBy("t", "kind").rowsBetween(Window.unboundedPreceding, 0)
    both = marks.unionByName(asks, allowMissingColumns=True).withColumn("latest", F.last("mark", ignorenulls=True).over(w))
    return both.filter("kind = 1").groupBy("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").agg(F.max("latest").alias("latest"))


@register("q_join_interval", "SELECT a.o_orderkey AS src, b.o_orderkey AS dst FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND b.o_orderdate > a.o_orderdate AND b.o_orderdate <= a.o_orderdate + INTERVAL 7 DAY")
def q_join_interval(spark, d):
    """Orders of one customer within 7 days: equal week or the next, then the exact test."""
    o = read(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    week = F.floor(F.unix_timestamp("o_orderdate") / (7 * 86400))
    a = o.select(F.col("o_orderkey").alias("src"), F.col("o_custkey").alias("c"), F.col("o_orderdate").alias("t"), F.explode(F.array(week, week + 1)).alias("w"))
    b = o.select(F.col("o_orderkey").alias("dst"), F.col("o_custkey").alias("c"), F.col("o_orderdate").alias("u"), week.alias("w"))
    return a.join(b, ["c", "w"]).filter((F.col("u") > F.col("t")) & (F.col("u") <= F.col("t") + F.expr("interval 7 days"))).select("src", "dst")


@register("q_agg_distinct", f"SELECT o_custkey AS v, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM {_ORDER_LINE} GROUP BY 1")
def q_agg_distinct(spark, d):
    line, order = read(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_suppkey"), read(spark, d, "orders", "o_orderkey", "o_custkey")
    return line.join(order, F.col("l_orderkey") == F.col("o_orderkey")).groupBy(F.col("o_custkey").alias("v")).agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"))


@register("q_agg_filter", "SELECT l_suppkey AS v, count(*) FILTER (WHERE l_returnflag = 'R') AS returned, count(*) AS lines FROM lineitem GROUP BY 1")
def q_agg_filter(spark, d):
    return read(spark, d, "lineitem", "l_suppkey", "l_returnflag").groupBy(F.col("l_suppkey").alias("v")).agg(F.count_if(F.col("l_returnflag") == "R").alias("returned"), F.count(F.lit(1)).alias("lines"))


_LEVELS = "customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _levels(spark, d):
    c, n, r = read(spark, d, "customer", "c_nationkey", "c_mktsegment"), read(spark, d, "nation", "n_nationkey", "n_name", "n_regionkey"), read(spark, d, "region", "r_regionkey", "r_name")
    return c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))


@register("q_agg_rollup", f"SELECT r_name, n_name, count(*) AS n FROM {_LEVELS} GROUP BY ROLLUP (r_name, n_name)")
def q_agg_rollup(spark, d):
    return _levels(spark, d).rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"))


@register("q_agg_cube", f"SELECT r_name, c_mktsegment, count(*) AS n FROM {_LEVELS} GROUP BY CUBE (r_name, c_mktsegment)")
def q_agg_cube(spark, d):
    return _levels(spark, d).cube("r_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@register("q_agg_grouping_sets", f"SELECT r_name, c_mktsegment, count(*) AS n FROM {_LEVELS} GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())")
def q_agg_grouping_sets(spark, d):
    return _levels(spark, d).groupingSets([["r_name"], ["c_mktsegment"], []], "r_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@register("q_agg_quantiles", "SELECT round(quantile_cont(n, 0.5), 6) AS median, round(quantile_cont(n, 0.9), 6) AS high, round(stddev_samp(n), 6) AS spread FROM (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1)")
def q_agg_quantiles(spark, d):
    n = read(spark, d, "orders", "o_custkey").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
    return n.agg(F.round(F.expr("percentile(n, 0.5)"), 6).alias("median"), F.round(F.expr("percentile(n, 0.9)"), 6).alias("high"), F.round(F.stddev_samp("n"), 6).alias("spread"))


@register("q_agg_approx")
def q_agg_approx(spark, d):
    return read(spark, d, "lineitem", "l_suppkey", "l_partkey").groupBy("l_suppkey").agg(F.approx_count_distinct("l_partkey").alias("parts"))


@register("q_pivot", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'purchase') AS purchase FROM events GROUP BY 1")
def q_pivot(spark, d):
    wide = read(spark, d, "events", "user_id", "event_type").groupBy("user_id").pivot("event_type", ["click", "purchase"]).count()
    return wide.select("user_id", F.coalesce("click", F.lit(0)).alias("click"), F.coalesce("purchase", F.lit(0)).alias("purchase"))


_W = "OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey)"


@register("q_win_rank", f"SELECT c_custkey, row_number() {_W} AS rn, rank() {_W} AS rk, dense_rank() {_W} AS dr, ntile(4) {_W} AS nt, round(percent_rank() {_W}, 9) AS pr, round(cume_dist() {_W}, 9) AS cd FROM customer")
def q_win_rank(spark, d):
    w = Window.partitionBy("c_mktsegment").orderBy(F.col("c_acctbal").desc(), "c_custkey")
    c = read(spark, d, "customer", "c_custkey", "c_mktsegment", "c_acctbal")
    return c.select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"))


_A = "OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"


@register("q_win_analytic", f"SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS after, first_value(event_id) {_A} AS head, last_value(event_id) {_A} AS tail, nth_value(event_id, 2) {_A} AS second FROM events")
def q_win_analytic(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    full = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    e = read(spark, d, "events", "event_id", "user_id", "ts")
    return e.select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(full).alias("head"), F.last("event_id").over(full).alias("tail"), F.nth_value("event_id", 2).over(full).alias("second"))


@register("q_win_frames", "SELECT day, n, sum(n) OVER (ORDER BY day ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)::BIGINT AS running, sum(n) OVER (ORDER BY epoch(day)::BIGINT RANGE BETWEEN 518400 PRECEDING AND CURRENT ROW)::BIGINT AS week FROM (SELECT date_trunc('day', ts)::TIMESTAMP AS day, count(*) AS n FROM events GROUP BY 1)")
def q_win_frames(spark, d):
    day = read(spark, d, "events", "ts").groupBy(F.date_trunc("day", "ts").alias("day")).agg(F.count(F.lit(1)).alias("n"))
    # One row a day, so windows over all days stay small.
    running = Window.orderBy("day").rowsBetween(Window.unboundedPreceding, 0)
    week = Window.orderBy(F.unix_timestamp("day")).rangeBetween(-6 * 86400, 0)
    return day.select("day", "n", F.sum("n").over(running).alias("running"), F.sum("n").over(week).alias("week"))


@register("q_sort_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 50")
def q_sort_limit(spark, d):
    return read(spark, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(50)


@register("q_topk_per_group", "SELECT c_nationkey, c_custkey FROM (SELECT c_nationkey, c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS rn FROM customer) WHERE rn <= 3")
def q_topk_per_group(spark, d):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return read(spark, d, "customer", "c_nationkey", "c_custkey", "c_acctbal").withColumn("rn", F.row_number().over(w)).filter("rn <= 3").select("c_nationkey", "c_custkey")


_CS, _SS = "SELECT c_nationkey AS k FROM customer", "SELECT s_nationkey AS k FROM supplier"


@register("q_set_union", "SELECT src, dst FROM (SELECT l_partkey AS src, l_suppkey AS dst FROM lineitem) UNION SELECT l_suppkey, l_partkey FROM lineitem")
def q_set_union(spark, d):
    return both_ways(read(spark, d, "lineitem").select(F.col("l_partkey").alias("src"), F.col("l_suppkey").alias("dst"))).distinct()


@register("q_set_intersect", f"{_CS} INTERSECT {_SS}")
def q_set_intersect(spark, d):
    return read(spark, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(read(spark, d, "supplier").select(F.col("s_nationkey").alias("k")))


@register("q_set_except_all", f"{_CS} EXCEPT ALL {_SS}")
def q_set_except_all(spark, d):
    return read(spark, d, "customer").select(F.col("c_nationkey").alias("k")).exceptAll(read(spark, d, "supplier").select(F.col("s_nationkey").alias("k")))


@register("q_fn_string", "SELECT page_id, length(url) AS n, upper(left(url, 5)) AS head, regexp_extract(url, '^https?://([^/]+)', 1) AS host, array_length(string_split(url, '/'))::INT AS parts FROM pages")
def q_fn_string(spark, d):
    return read(spark, d, "pages", "page_id", "url").select("page_id", F.length("url").cast("long").alias("n"), F.upper(F.substring("url", 1, 5)).alias("head"), F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"), F.size(F.split("url", "/")).alias("parts"))


@register("q_fn_date", "SELECT year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, count(*) AS n, max(date_diff('day', DATE '1992-01-01', o_orderdate::DATE))::INT AS days FROM orders GROUP BY 1, 2")
def q_fn_date(spark, d):
    o = read(spark, d, "orders", "o_orderdate")
    return o.groupBy(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.count(F.lit(1)).alias("n"), F.max(F.datediff("o_orderdate", F.lit("1992-01-01").cast("date"))).alias("days"))


@register("q_fn_math", "SELECT l_quantity AS q, round(ln(l_quantity), 9) AS a, round(sqrt(l_quantity), 9) AS b, ceil(l_quantity / 7)::BIGINT AS c, floor(l_quantity / 7)::BIGINT AS f, round(pow(l_quantity, 1.5), 6) AS p, greatest(l_quantity, 10.0) AS g FROM (SELECT DISTINCT l_quantity FROM lineitem)")
def q_fn_math(spark, d):
    q = F.col("l_quantity")
    return read(spark, d, "lineitem", "l_quantity").distinct().select(q.alias("q"), F.round(F.log(q), 9).alias("a"), F.round(F.sqrt(q), 9).alias("b"), F.ceil(q / 7).alias("c"), F.floor(q / 7).alias("f"), F.round(F.pow(q, 1.5), 6).alias("p"), F.greatest(q, F.lit(10.0)).alias("g"))


@register("q_fn_array", "SELECT o_custkey AS v, count(*) AS n, list_sum(list_transform(list_sort(list(o_orderkey))[1:3], lambda x: x * 2))::BIGINT AS s FROM orders GROUP BY 1")
def q_fn_array(spark, d):
    # One customer's orders: no more than a customer has; not for hubs.
    o = read(spark, d, "orders", "o_custkey", "o_orderkey").groupBy(F.col("o_custkey").alias("v")).agg(F.sort_array(F.collect_list("o_orderkey")).alias("x"))
    return o.select("v", F.size("x").cast("long").alias("n"), F.aggregate(F.transform(F.slice("x", 1, 3), lambda x: x * 2), F.lit(0).cast("long"), lambda a, x: a + x).alias("s"))


@register("q_fn_map_struct", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(DISTINCT event_type) AS kinds FROM events GROUP BY 1")
def q_fn_map_struct(spark, d):
    e = read(spark, d, "events", "user_id", "event_type").groupBy("user_id", "event_type").count()
    m = e.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "count"))).alias("m"))
    return m.select("user_id", F.coalesce(F.col("m")["click"], F.lit(0)).alias("clicks"), F.size("m").cast("long").alias("kinds"))


@register("q_fn_json", "SELECT (props->>'$.k')::INT AS k, count(*) AS n FROM events GROUP BY 1")
def q_fn_json(spark, d):
    return read(spark, d, "events", "props").select(F.from_json("props", "k int")["k"].alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@register("q_subquery", "SELECT c_custkey FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer) AND c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 1)")
def q_subquery(spark, d):
    read(spark, d, "customer").createOrReplaceTempView("pw_customer")
    read(spark, d, "nation").createOrReplaceTempView("pw_nation")
    return spark.sql("SELECT c_custkey FROM pw_customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM pw_customer) AND c_nationkey IN (SELECT n_nationkey FROM pw_nation WHERE n_regionkey = 1)")


@register("q_case_null", "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 1000 THEN 'low' ELSE 'ok' END AS kind, coalesce(nullif(c_mktsegment, 'BUILDING'), 'B') AS seg FROM customer")
def q_case_null(spark, d):
    b = F.col("c_acctbal")
    return read(spark, d, "customer").select("c_custkey", F.when(b < 0, "debt").when(b < 1000, "low").otherwise("ok").alias("kind"), F.coalesce(F.nullif("c_mktsegment", F.lit("BUILDING")), F.lit("B")).alias("seg"))


@register("q_join_nested_loop", O.query("SELECT i::INT AS rung, count(*) AS n FROM push, range(8) t(i) WHERE p > pow(2.0, -i) / 10 GROUP BY 1", O.graph_cte("event_user"), O.sources_cte(2), O.push_cte(O.POINT, "0.0", 100)))
def q_join_nested_loop(spark, d):
    """How many exact scores exceed each threshold of a ladder: the ladder has a dozen rows at most."""
    g = graph(spark, d, "event_user")
    steps = spark.createDataFrame([(i, 2.0**-i / 10) for i in range(8)], "rung int, delta double")
    return truth(g).join(F.broadcast(steps), F.col("score") > F.col("delta")).groupBy("rung").agg(F.count(F.lit(1)).alias("n"))


@register("q_join_range", O.query("SELECT v, count(*) AS n FROM (SELECT ((('0x' || substr(md5(i::VARCHAR), 1, 8))::BIGINT) + 0.5) / 4294967296.0 AS u FROM range(2000) t(i)) JOIN (SELECT v, sum(mass) OVER (ORDER BY v) AS high, sum(mass) OVER (ORDER BY v) - mass AS low FROM (SELECT v, d::DOUBLE / (SELECT count(*) FROM arcs) AS mass FROM nodes)) ON u >= low AND u < high GROUP BY v", O.graph_cte("event_user")))
def q_join_range(spark, d):
    """Starts drawn from a distribution by its cumulative mass: buckets of mass make it an equi-join."""
    g = graph(spark, d, "event_user")
    n = g.n
    mass = g.nodes.select("v", (F.col("out_deg") / g.m).alias("mass"))
    w = Window.orderBy("v").rowsBetween(Window.unboundedPreceding, 0)  # small graphs only; larger ones draw by stratified counts
    cdf = mass.withColumn("high", F.sum("mass").over(w)).withColumn("low", F.col("high") - F.col("mass"))
    cells = cdf.withColumn("cell", F.explode(F.sequence(F.floor(F.col("low") * n), F.floor(F.col("high") * n))))
    draws = spark.range(2000).select("id", ((F.conv(F.substring(F.md5(F.col("id").cast("string")), 1, 8), 16, 10).cast("long") + 0.5) / 2.0**32).alias("u"))
    return draws.withColumn("cell", F.floor(F.col("u") * n)).join(cells, "cell").filter("u >= low and u < high").groupBy("v").agg(F.count(F.lit(1)).alias("n"))




_PLAN = """SELECT round(c, 6) AS walk_constant, round(CASE WHEN m <= c THEN 1 / sqrt(m * c) ELSE 1 / c END, 12) AS rho, CASE WHEN m <= c THEN 1 ELSE 2 END AS threshold_case, round(least(sqrt(m * c), c), 6) AS push_walk, round(c, 6) AS monte_carlo
FROM (SELECT m, (2 + 1.0 / 3) * ln(2.0 * n) / (0.25 / n) AS c FROM (SELECT (SELECT count(*) FROM nodes) AS n, count(*) AS m FROM arcs))"""


@register("q_udtf_plan", O.query(_PLAN, O.graph_cte("supp_next")))
def q_udtf_plan(spark, d):
    """The numbers that queries on a graph of the given tables would run with, by a lateral table function."""
    from pushwave.functions.udx import register_sql
    from pushwave.plans.durable import ship

    ship(spark)
    register_sql(spark)
    g = graph(spark, d, "supp_next")
    size = g.nodes.agg(F.count(F.lit(1)).alias("n")).crossJoin(g.arcs.agg(F.count(F.lit(1)).alias("m")))
    size.createOrReplaceTempView("pushwave_size")
    return spark.sql("SELECT round(walk_constant, 6) AS walk_constant, round(rho, 12) AS rho, threshold_case, round(push_walk, 6) AS push_walk, round(monte_carlo, 6) AS monte_carlo FROM pushwave_size, LATERAL ppr_plan(n, m, 0.5D, 1D / n, 1D / n)")


@register("q_udf_small_push", O.query("SELECT query_id, v, round(p, 9) AS score FROM push WHERE p > 0", O.graph_cte("event_user"), O.sources_cte(2), O.push_cte(O.POINT, "0.000987654", 40)))
def q_udf_small_push(spark, d):
    from pushwave.functions.udx import small_graph_push
    from pushwave.workloads import first_sources

    g = graph(spark, d, "event_user")
    return small_graph_push(g.arcs.select("src", "dst"), first_sources(g, 2), 0.000987654).select("query_id", "v", F.round("score", 9).alias("score"))
