"""The driver's contract, on the smallest tables, and DuckDB's view of a few queries."""

import glob
import os

import duckdb
import pytest

import __spark_entry__ as entry_module

SF = "/root/testdata/sf0.001"


def test_entry_runs(spark):
    got = entry_module.entry(spark).collect()
    assert 0 < len(got) <= 20


def test_names_agree():
    queries, oracles = entry_module.queries(), entry_module.oracle_sql()
    assert set(oracles) <= set(queries)
    assert len(queries) > 80


@pytest.mark.parametrize("name", ["q_graph_part_next", "q_params", "q_power_ppr_trade_nation", "q_push_event_user", "q_push_walk_pruned", "q_ndcg", "q_join_asof", "q_win_frames", "q_set_except_all"])
def test_queries_equal_their_sql(spark, name):
    con = duckdb.connect()
    for p in glob.glob(f"{SF}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
    got = entry_module.queries()[name](spark, SF).toPandas()
    want = con.sql(entry_module.oracle_sql()[name]).df()
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    key = lambda d: d[columns].astype(str).sort_values(columns).reset_index(drop=True)
    if any(t.kind == "f" for t in got.dtypes if hasattr(t, "kind")):
        got, want = got.round(8), want.round(8)
    assert key(got.astype(want.dtypes.to_dict())).equals(key(want))
