"""Counts by ranks against lists and plain loops."""

import numpy as np
import pytest

from wingcount.functions.order_types import ORDERS, TYPES
from wingcount.operators import counting, ranked
from wingcount.sources.edges import edges_from_rows

TYPE_OF = {order: kind for kind, order in ORDERS.items()}


def looped(edges, starts, tau):
    out = np.zeros((len(starts), 6), int)
    for n, (ux, lx, t1) in enumerate(starts):
        near = [e for e in edges if t1 < e[2] <= t1 + tau]
        for b in (e for e in near if e[0] == ux and e[1] != lx):
            for a in (e for e in near if e[1] == lx and e[0] != ux):
                for c in (e for e in near if e[0] == a[0] and e[1] == b[1]):
                    at = {"a": a[2], "b": b[2], "c": c[2]}
                    if len(set(at.values())) == 3:
                        out[n][TYPE_OF["".join(sorted(at, key=at.get))] - 1] += 1
    return out


@pytest.mark.parametrize("part", [1_000_000, 40])
@pytest.mark.parametrize("last,tau", [(60, 12), (1000, 200)])
def test_cell_against_loops(monkeypatch, part, last, tau):
    monkeypatch.setattr(ranked, "PART", part)  # small parts divide points and starts
    rnd = np.random.default_rng(last)
    edges = np.c_[rnd.integers(0, 5, 120), rnd.integers(0, 4, 120), rnd.integers(0, last, 120)]
    starts = edges[rnd.random(120) < 0.6]
    want = looped(edges.tolist(), starts.tolist(), tau)
    got = sum(ranked.count_cell((*edges.T, edges[:, 1] % 3), (*starts.T, starts[:, 1] % 3), tau, (i, j)) for i in range(3) for j in range(i, 3))
    assert (got == want).all() and want.sum(0).all()


def _graph(spark, n=600, span=300):
    rnd = np.random.default_rng(7)
    return edges_from_rows(spark, [(k, *map(int, x)) for k, x in enumerate(zip(rnd.integers(0, 12, n), rnd.integers(0, 6, n), rnd.integers(-50, span, n)))])


@pytest.mark.parametrize("center", ["lower", "upper"])
@pytest.mark.parametrize("classes", [1, 3])
def test_ranked_against_lists(spark, monkeypatch, center, classes):
    monkeypatch.setattr(ranked, "classes_for", lambda *a: classes)
    edges = _graph(spark)
    starts = edges.where("eid % 3 <> 0")
    want = {r["eid"]: tuple(r[c] for c in counting.COUNTS) for r in counting.six(counting.list_instances(edges, 20, starts, "wedge_pair"), counting.F.col("e1").alias("eid")).collect()}
    got = {r["eid"]: tuple(r[c] for c in counting.COUNTS) for r in ranked.ranked(edges, starts, 20, center).collect()}
    assert got == want and len(got) > 100


def _holds(df, *names):
    plan = df._jdf.queryExecution().toString()
    return [n for n in names if n in plan]


def test_plans_count_without_lists(spark):  # F3, F4
    edges = _graph(spark)
    want = {r["type"]: r["count"] for r in counting.exact_count(edges, 20, "wedge_pair").collect()}
    for plan in ("star", "grouped", "auto"):
        df = counting.exact_count(edges, 20, plan)
        assert {r["type"]: r["count"] for r in df.collect()} == want
        assert _holds(df, "FlatMapGroupsInArrow") and not _holds(df, "Join", "CoGroup"), plan
    assert not any(r["count"] for r in counting.exact_count(edges.where("eid < 0"), 20, "star").collect())


@pytest.mark.parametrize("kind", TYPES)
def test_chrono_counts_without_lists(spark, kind):  # F1, F2, F7, F8, F9
    edges = _graph(spark)
    df = counting.chrono_counts(edges, edges.where("eid % 2 = 0"), 20, kind)
    want = counting.chrono(edges, edges.where("eid % 2 = 0"), 20, kind).groupBy("e1").count()
    assert sorted(map(tuple, df.select("eid", "count").collect())) == sorted(map(tuple, want.collect()))
    assert not _holds(df, "Join")
