"""Some of the contract's queries against their SQL in DuckDB, and the rest for being there."""

import glob
import os

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
SOME = [
    "exact_euk", "exact_ocp_total_order", "edge_estimate", "interval_copies", "interval_estimate", "static_quad_estimate", "static_topology_multiplicity", "six_window_estimate", "six_window_time_estimate",
    "variance_interval", "graph_stats", "window_degree", "rate_curve_node_lower", "coverage", "bounds_grid", "plan_from_pilot", "join_asof", "agg_cube", "fn_array", "udaf_rank_count",
    "stream_tumbling", "stream_session", "stream_wedges", "stream_counts", "stream_late", "stream_dedup", "agg_approx_distinct", "set_except", "edges_repeated", "trailing_repeated", "rate_curve_interval", "accuracy_edge", "accuracy_six_window", "accuracy_static_quad",
    "accuracy_static_topology", "errors_interval", "errors_node_lower", "speedup_at_level", "graph_stats_ocs", "type_share_lsp",
]


CLOCKED = ("accuracy_vs_time", "errors_at_equal_budget", "time_vs_tau", "ablations", "single_type_times")


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return con


def same(v):
    return round(float(v), 5) if isinstance(v, float) or type(v).__name__ == "Decimal" else v


@pytest.mark.parametrize("name", SOME)
def test_query(spark, db, name):
    df = entry.queries()[name](spark, SF)
    got = db.execute(entry.oracle_sql()[name])
    names = [c[0] for c in got.description]
    assert sorted(df.columns) == sorted(names)
    at = [names.index(c) for c in sorted(names)]
    want = sorted(repr([same(r[i]) for i in at]) for r in got.fetchall())
    assert sorted(repr([same(r[c]) for c in sorted(names)]) for r in df.collect()) == want


def test_contract():
    queries, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(queries) and len(queries) > 120
    assert not [n for n in queries if not n.startswith(("op", "pipeline", "speedup")) and n not in sql and n not in CLOCKED]


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns == ["type", "estimate"] and df.count() == 6
