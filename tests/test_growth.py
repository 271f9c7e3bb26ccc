"""Queries whose lists, plans or results grew beyond a task, a disk or the driver: now they count without listing, and results stay in files."""

import time
from collections import Counter
from itertools import groupby

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from tests.test_queries import SF, db, same  # noqa: F401  db is a fixture
from wingcount import queries, workloads
from wingcount.operators import counting, estimators, joins, sampling, static_graph, timeline
from wingcount.shared import is_settled
from wingcount.sources.edges import edges_from_rows
from wingcount.streaming import replay


def _same_as_sql(spark, db, name):  # noqa: F811
    df = entry.queries()[name](spark, SF)
    got = db.execute(entry.oracle_sql()[name])
    names = [c[0] for c in got.description]
    at = [names.index(c) for c in sorted(names)]
    assert sorted(df.columns) == sorted(names)
    assert sorted(repr([same(r[c]) for c in sorted(names)]) for r in df.collect()) == sorted(repr([same(r[i]) for i in at]) for r in got.fetchall())
    return df


def _refuse(*_, **__):
    raise AssertionError("instances are listed")


@pytest.mark.parametrize(
    "name",
    ["edge_estimate", "errors_node_lower", "errors_node_upper", "errors_six_edge", "interval_estimate", "interval_estimate_literal", "node_estimate_lower", "node_estimate_upper", "six_edge_estimate", "stream_counts", "tau_curve_days"],
)  # F10, F12-F16, F18-F20, F22, F23
def test_counts_without_lists(spark, db, monkeypatch, name):  # noqa: F811
    for listing in ("star", "wedge_pair", "chrono"):
        monkeypatch.setattr(counting, listing, _refuse)
    monkeypatch.setattr(counting, "PLANS", {"star": _refuse, "wedge_pair": _refuse})
    _same_as_sql(spark, db, name)


@pytest.mark.parametrize("name,rows", [("errors_at_equal_budget", 18), ("ablations", 10)])  # F11, F24
def test_clocked_without_quadratic_lists(spark, monkeypatch, name, rows):
    monkeypatch.setattr(counting, "star", _refuse)
    monkeypatch.setattr(counting, "chrono", _refuse)
    assert entry.queries()[name](spark, SF).count() == rows


def test_budget_runs_leave_no_shuffles(spark, monkeypatch):  # each run once, over edges written once, and its shuffle files go with it
    def shuffled():
        files = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
        return {name for name in (files.apply(k).getName() for k in range(files.size())) if name.startswith("shuffle_")}

    read, own, before = [], workloads.METHODS["edge"], shuffled()
    monkeypatch.setitem(workloads.METHODS, "edge", lambda e, *a: (read.append(is_settled(e)), own(e, *a))[1])
    workloads.errors_at_equal_budget(replay.view(spark, SF, "euk"), 72 * replay.HOUR, ("edge",), (0.3, 1.0), seeds=(0,))
    assert read == [True, True]
    deadline = time.monotonic() + 10
    while shuffled() - before and time.monotonic() < deadline:
        time.sleep(0.2)
    assert not shuffled() - before


def test_stream_results_stay_in_files(spark):  # F6
    edges = replay.view(spark, SF, "euk")
    path = replay.slices(edges, 240 * replay.HOUR)
    for mode, stream in (("append", replay.source(spark, path).select("eid")), ("complete", replay.tumbling(replay.source(spark, path, files=1), "1 day"))):
        df = replay.drained(stream, mode)
        assert df.inputFiles()  # a memory sink has none
        assert (df.count() if mode == "append" else df.agg({"n": "sum"}).first()[0]) == edges.count()


@pytest.mark.parametrize("name", ["bounds_grid", "brute_force", "udtf_bounds"])  # F26, F27, F29
def test_reads_a_table(spark, db, name):  # noqa: F811
    df = _same_as_sql(spark, db, name)
    assert [f for f in df.inputFiles() if f.endswith("events.parquet")]


def test_speedups_plan_a_method_at_a_time(spark, monkeypatch):  # F5
    held = []
    monkeypatch.setattr(queries, "settled", lambda df, *a: (held.append(1), df)[1])
    queries.speedups(spark, SF)
    assert len(held) == 5


@pytest.mark.parametrize("crowd", [1_000_000, 10])
def test_trailing_sums_against_loops(spark, monkeypatch, crowd):  # F15
    monkeypatch.setattr(timeline, "CROWD", crowd)  # a small one takes the way by prefix counts
    monkeypatch.setattr(timeline, "WIDE", 30)
    rows = [(2**60 + k, k % 7, k % 3, (k * k) % 211 - 40) for k in range(150)]
    drawn = [r for r in rows if r[0] % 11 == 0]
    got = {tuple(r) for r in timeline.trailing_sums(edges_from_rows(spark, rows), edges_from_rows(spark, drawn).select("t"), 9).collect()}
    within = lambda x, t: sum(t - 9 <= r[3] <= t for r in x)
    assert got == {(*r, within(drawn, r[3]), within(rows, r[3])) for r in rows if within(drawn, r[3])}


def test_samples_are_dealt_once(spark):  # F10, F15, F18-F20: starts bring their weights along, so no count looks for its edge by id
    for x in (sampling.EdgeSampler(0.3, 7), sampling.NodeSampler(0.3, "lower", 7), sampling.IntervalSampler(draws=50, c=0.1, seed=7)):
        for counter in ("wedge", "chrono"):
            plan = estimators.estimate(replay.view(spark, SF, "euk"), 72 * replay.HOUR, x, counter)._jdf.queryExecution().optimizedPlan().toString()
            assert plan.count("FlatMapGroupsInArrow") == 1 + isinstance(x, sampling.IntervalSampler) and "Join" not in plan


def test_wide_stretches_copy_few_edges(spark):  # F1, F2, F7-F9, F12-F14
    df = counting.chrono_counts(edges := replay.view(spark, SF, "eut"), edges, 3600_000_000, 3)
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("LogicalRelation") + plan.count("Relation [") == 2  # edges with their starts, and those near the stretch before
    assert "Generate explode" not in plan


@pytest.mark.parametrize("block", [256, 3])  # a small one divides a crowded stretch
def test_block_join_against_loops(spark, monkeypatch, block):  # F17
    monkeypatch.setattr(joins, "BLOCK", block)
    rows = [(k, k % 3, k % 2, (k * k) % 97 - 40) for k in range(90)] + [(90 + k, 7, 1, 5) for k in range(9)]
    edges = edges_from_rows(spark, rows)
    for width in (0, 1, 5, 50, 500):
        got = sorted(map(tuple, joins.block_join(edges, edges, ["l"], "t", width).collect()))
        assert got == sorted((*a, *b) for a in rows for b in rows if a[2] == b[2] and a[3] < b[3] <= a[3] + width)


def test_interval_pairs_come_in_runs(spark, db, monkeypatch):  # a left row's partners are those of the row before, so that files of pairs stay small
    monkeypatch.setattr(queries, "euk", lambda *_: edges_from_rows(spark, [(k, 0, 0, k * queries.J // 800) for k in range(1600)]))
    pairs = [tuple(r) for r in entry.queries()["join_interval"](spark, SF).collect()]
    runs = [[b for _, b in run] for _, run in groupby(pairs, key=lambda r: r[0])]
    assert len(set(pairs)) == len(pairs) == sum(min(800, 1599 - k) for k in range(1600))
    assert sum(len(y) for x, y in zip(runs, runs[1:]) if x == y) > 0.7 * len(pairs)
    monkeypatch.undo()
    _same_as_sql(spark, db, "join_interval")


@pytest.mark.parametrize("upper,lower", [(40, 5), (5, 40)])
def test_butterflies_shuffle_the_fewer_wedges(spark, monkeypatch, upper, lower):  # F21
    rows = [(k, k % upper, k // upper % lower, k) for k in range(upper * lower) if k % 7]
    held, own = {}, static_graph.settled
    monkeypatch.setattr(static_graph, "settled", lambda df, name="settled": held.setdefault(name, own(df, name)))
    got = sorted(map(tuple, static_graph.static_butterflies(edges_from_rows(spark, rows)).collect()))
    of = {u: {r[2] for r in rows if r[1] == u} for u in range(upper)}
    want = sorted((a, b, c, d) for a in of for b in of if a < b for c in of[a] & of[b] for d in of[a] & of[b] if c < d)
    assert got == want and len(got) > 1000
    wedges = lambda k: sum(n * (n - 1) // 2 for n in Counter(x[k] for x in {r[1:3] for r in rows}).values())
    assert held["wedges"].count() == min(wedges(0), wedges(1)) < max(wedges(0), wedges(1))


@pytest.mark.parametrize("block,p", [(256, 1.0), (3, 1.0), (256, 0.4)])
def test_stream_wedges_are_kept_in_blocks(spark, monkeypatch, block, p):  # over several batches, of which a stream keeps and writes blocks and not wedges
    monkeypatch.setattr(replay, "BLOCK", block)
    hour, held, own = replay.HOUR, [], replay.drained
    rows = [(k, k % 11, k % 2, k * hour // 60 + k * k % 977) for k in range(1500)] + [(1500 + k, k % 11, 0, 5 * hour) for k in range(30)]
    monkeypatch.setattr(replay, "drained", lambda *a: (held.append(own(*a)), held[-1])[1])
    monkeypatch.setattr(replay, "view", lambda s, *_: edges_from_rows(s, rows))
    sampled = replay.stream_wedges
    monkeypatch.setattr(replay, "stream_wedges", lambda *a, **k: sampled(*a, p=p, seed=3, **k))
    monkeypatch.setattr(replay, "slices", lambda edges, _, own=replay.slices: own(edges, 2 * hour))  # 13 files, four batches
    tau, starts = 6 * hour, {r[0] for r in edges_from_rows(spark, rows).where(replay.u01(3, "eid") < p).collect()}
    df = replay.QUERIES["stream_wedges"][0](spark, SF)
    got = sorted(map(tuple, df.select("e1", "e2", "ua", "ub", "center", "t1", "t2").collect()))
    assert got == sorted((a[0], b[0], a[1], b[1], a[2], a[3], b[3]) for a in rows if a[0] in starts for b in rows if a[2] == b[2] and a[1] != b[1] and a[3] < b[3] <= a[3] + tau)
    assert len(got) > 50_000 and held[0].count() < len(got) / (5 if block == 3 else 50)


def test_stream_gives_wedges_or_their_blocks(spark):  # rows of the stream itself are those listed from its blocks
    path = replay.slices(edges_from_rows(spark, [(k, k % 5, k % 3, k * replay.HOUR // 7) for k in range(300)]), 5 * replay.HOUR)
    tau = 2 * replay.HOUR
    plain = replay.drained(replay.stream_wedges(spark, path, tau, "1 hour"))
    packed = replay.listed(replay.drained(replay.stream_wedges(spark, path, tau, "1 hour", packed=True)), tau)
    assert sorted(plain.collect()) == sorted(packed.collect()) and plain.count() > 500


@pytest.mark.parametrize("block,salts,stretches", [(256, 16, 16), (3, 4, 5), (1, 2, 2)])
def test_butterflies_in_blocks_against_loops(spark, monkeypatch, block, salts, stretches):  # F2
    for name, value in (("BLOCK", block), ("SALTS", salts), ("STRETCHES", stretches)):
        monkeypatch.setattr(static_graph, name, value)
    rows = [(k, k * k % 47 - 20, 100 + k % 6, k) for k in range(160)] + [(200 + k, 500 + k, 900, 0) for k in range(3)]
    for flip in (False, True):
        own = [(e, b, a, t) if flip else (e, a, b, t) for e, a, b, t in rows]
        got = sorted(map(tuple, static_graph.static_butterflies(edges_from_rows(spark, own)).collect()))
        of = {}
        for _, u, l, _ in own:
            of.setdefault(u, set()).add(l)
        assert got == sorted((a, b, c, d) for a in of for b in of if a < b for c in of[a] & of[b] for d in of[a] & of[b] if c < d) and len(got) > 500
    assert static_graph.static_butterflies(edges_from_rows(spark, [])).collect() == []


def test_butterflies_come_in_runs(spark):  # a centre's partners are those of the centre before, so that files of butterflies stay small
    found = static_graph.static_butterflies(edges_from_rows(spark, [(k, k // 2, k % 2, k) for k in range(2000)]))
    parts = [tuple(r) for r in found.collect()]
    runs = [[r[1] for r in run] for _, run in groupby(parts, key=lambda r: r[0])]
    assert len(set(parts)) == len(parts) == 1000 * 999 // 2 and {r[2:] for r in parts} == {(0, 1)}
    assert sum(len(y) for x, y in zip(runs, runs[1:]) if x == y) > 0.7 * len(parts) and max(map(len, runs)) <= 256


def test_block_lists_hold_one_row_of_a_block(spark):  # whole-stage code holds what it makes of one input row, so a block's rows come to it one at a time
    edges = edges_from_rows(spark, [(k, k % 3, k % 2, k) for k in range(90)])
    path = edges.select(F.col("l").alias("center"), F.expr("array(named_struct('e', eid, 'u', u, 't', t))").alias("edges1")).withColumn("edges2", F.col("edges1"))
    for df in (joins.block_join(edges, edges, ["l"], "t", 5), static_graph.static_butterflies(edges), replay.listed(path, 5)):
        spark.conf.set("spark.sql.adaptive.enabled", "false")
        try:
            plan = df.select(*df.columns)._jdf.queryExecution().executedPlan().toString().splitlines()
        finally:
            spark.conf.unset("spark.sql.adaptive.enabled")
        lists = [x.lstrip(" :+-") for x in plan if "Generate explode(" in x or "Generate inline(" in x][:2]  # the outer one first
        assert lists[0].startswith("*") and lists[1].startswith("Generate")
