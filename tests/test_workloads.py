"""The experiments with a clock run on the whole view and the survey's grids."""

import datetime

import pytest
from pyspark.sql import functions as F

from wingcount import queries, workloads
from wingcount.functions import metrics
from wingcount.operators import counting, estimators, sampling
from wingcount.operators.estimators import grid_estimates
from wingcount.sources import edges as edges_
from wingcount.sources.edges import HOUR, view

SF = "/root/testdata/sf0.001"


def test_all_methods_have_full_grids():
    names = ("edge", "node_upper", "node_lower", "interval", "six_edge", "six_window", "static_quad", "static_topology")
    assert set(workloads.METHODS) == set(names)
    for name in names:
        assert {f"accuracy_{name}", f"errors_{name}"} <= set(queries.QUERIES) & set(queries.ORACLES)
    assert queries.RATES == pytest.approx([0.00125 * 2**k for k in range(10)]) and len(queries.SEEDS) == 10


@pytest.mark.parametrize("method", ["interval", "six_window", "static_quad", "static_topology"])
def test_grids_agree_with_single_runs(spark, method):
    """An estimate from units' parts is the method's own estimate at that rate and seed."""
    edges = view(spark, SF, "eut")
    grid = {(r["seed"], r["rate"], r["type"]): r["estimate"] for r in grid_estimates(edges, 24 * HOUR, method, [0.1, 0.5], [3, 4]).collect()}
    for rate in (0.1, 0.5):
        for r in workloads.METHODS[method](edges, 24 * HOUR, rate, 4).collect():
            assert grid[4, rate, r["type"]] == pytest.approx(r["estimate"], rel=1e-6, abs=1e-6)


def test_edge_lists_round_trip(spark, tmp_path):
    """Text, csv and written edges; repeated edges keep their number and have ids of their own."""
    (tmp_path / "a.txt").write_text("% comment\n1 2 10\n1\t2  10\n3 4 11\n")
    (tmp_path / "a.csv").write_text("1,2,10\n1,2,10\n3,4,11\n")
    for fmt in ("text", "csv"):
        got = edges_.read_edges(spark, str(tmp_path / f"a.{'txt' if fmt == 'text' else 'csv'}"), fmt).collect()
        assert sorted((r["u"], r["l"], r["t"]) for r in got) == [(1, 2, 10), (1, 2, 10), (3, 4, 11)] and len({r["eid"] for r in got}) == 3
    edges = view(spark, SF, "euk")
    edges_.write_edges(edges, str(tmp_path / "out"), 24 * HOUR)
    assert sorted(spark.read.parquet(str(tmp_path / "out")).select(*edges.columns).collect()) == sorted(edges.collect())
    assert edges_.duration(datetime.timedelta(hours=1)) == HOUR


def test_literal_and_folded_agree_on_repeated_edges(spark):
    rows = [(1, 1, 1), (1, 1, 1), (2, 1, 2), (1, 2, 3), (2, 2, 4), (2, 2, 4)]
    edges = edges_.from_df(spark.createDataFrame(rows, "u long, l long, t long"), "u", "l", "t")
    exact = {r["type"]: r["count"] for r in counting.exact_count(edges, 5).collect()}
    for mode in ("folded", "literal"):
        got = estimators.estimate(edges, 5, sampling.IntervalSampler(draws=6, c=0.4, replace=False, mode=mode)).collect()
        assert {r["type"]: round(r["estimate"], 9) for r in got} == exact and max(exact.values()) > 1


def test_time_vs_tau_takes_the_smallest_good_rate(spark):
    edges = view(spark, SF, "euk")
    got = workloads.time_vs_tau(edges, (72 * HOUR,), ("edge",), rates=(1.0, 0.02), seeds=(0, 1)).collect()
    assert [(r["tau"], r["method"], r["rate"], r["mape"]) for r in got] == [(72 * HOUR, "edge", 1.0, 0.0)]


def test_errors_at_equal_budget(spark):
    got = workloads.errors_at_equal_budget(view(spark, SF, "euk"), 72 * HOUR, ("edge",), (1.0,), seeds=(0, 1)).collect()
    assert sorted((r["type"], r["rel_error"]) for r in got) == [(k, 0.0) for k in range(1, 7)]


def test_stage_costs(spark):
    """A grouping shuffles some bytes and spills none; a plain scan does neither."""
    last = metrics.stage_costs(spark)["last"]
    spark.range(0, 200_000, 1, 4).groupBy((F.col("id") % 50_000).alias("k")).count().write.format("noop").mode("overwrite").save()
    first = metrics.stage_costs(spark, last)
    assert first["shuffle_mb"] > 0 and first["spill_mb"] == 0 and first["peak_mb"] > 0 and first["last"] > last
    spark.range(10).write.format("noop").mode("overwrite").save()
    assert metrics.stage_costs(spark, first["last"])["shuffle_mb"] == 0
