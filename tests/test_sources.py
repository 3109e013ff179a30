"""Readers, sinks, the generator and user-defined surfaces."""

import pytest
from pyspark.sql import functions as F

from pushwave.functions.udx import ndcg_of, register_sql, small_graph_push
from pushwave.operators.graph import build_graph, power_law_fit
from pushwave.operators.push import push_only
from pushwave.sources import graphs as S


@pytest.mark.parametrize("fmt", ["csv", "json", "orc", "parquet"])
def test_edges_round_trip(spark, tmp_path, fmt):
    arcs = spark.createDataFrame([(1, 2), (2, 3), (3, 1), (1, 1), (None, 4)], "src long, dst long")
    w = arcs.write.format(fmt)
    (w.option("header", True) if fmt == "csv" else w).save(str(tmp_path / "e"))
    got = {tuple(r) for r in S.read_edges(spark, str(tmp_path / "e"), fmt).collect()}
    assert got == {(1, 2), (2, 3), (3, 1), (1, 1)}
    assert S.read_edges(spark, str(tmp_path / "e"), fmt, undirected=True, keep_loops=False).count() == 6


def test_edge_lists_and_names(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# comment\n% other\n1 2\n2\t3\n1,2\n\n")
    assert {tuple(r) for r in S.read_edges(spark, str(tmp_path / "e.txt")).collect()} == {(1, 2), (2, 3)}
    names = spark.createDataFrame([("b",), ("a",), (None,), ("b",), ("c",)], "x string")
    assert {tuple(r) for r in S.node_ids(names, "x").collect()} == {("a", 0), ("b", 1), ("c", 2)}


def test_generator_is_deterministic_and_skewed(spark):
    a, b = (S.rmat(spark.newSession(), 8, 8), S.rmat(spark, 8, 8))
    assert {tuple(r) for r in a.collect()} == {tuple(r) for r in b.collect()}
    g = build_graph(b)
    assert g.n <= 256 and g.m <= 2048
    assert power_law_fit(g).first()["slope"] < 0
    deg = g.nodes.agg(F.max("out_deg"), F.avg("out_deg")).first()
    assert deg[0] > 4 * deg[1]


def test_positions_are_gapless(spark):
    g = build_graph(spark.createDataFrame([(0, i) for i in range(1, 200)] + [(i, 0) for i in range(1, 200)], "src long, dst long"))
    pos = sorted(r["pos"] for r in g.arcs.filter("src = 0").collect())
    assert pos == list(range(199))
    assert g.arcs.filter("src_deg <> 199 and src = 0").count() == 0


def test_user_defined_surfaces(spark):
    register_sql(spark)
    r = spark.sql("SELECT * FROM ppr_plan(100, 500, 0.5D, 0.01D, 0.01D)").first()
    assert r["threshold_case"] == 1 and r["rho"] > 0
    arcs = spark.createDataFrame([(0, 1), (0, 2), (1, 2), (2, 0), (3, 2)], "src long, dst long")
    src = spark.createDataFrame([(0, 0), (1, 3)], "query_id long, src long")
    a = {(r["query_id"], r["v"]): round(r["score"], 12) for r in small_graph_push(arcs, src, 0.01).collect()}
    b = {(r["query_id"], r["v"]): round(r["score"], 12) for r in push_only(build_graph(arcs), src, 0.01).collect()}
    assert a == b
    rows = spark.createDataFrame([(0, 0.5, 1, 0.5), (0, 0.1, 2, 0.3)], "q long, t double, rk int, i double")
    assert 0.8 < rows.groupBy("q").agg(ndcg_of("t", "rk", "i").alias("n")).first()["n"] < 1
