import itertools

import pytest
from pyspark.sql import functions as F

from wingcount.functions.order_types import ORDERS, TRANSPOSED
from wingcount.operators import counting
from wingcount.sources.edges import HOUR, TOY, edges_from_rows, from_df, toy, view

SF = "/root/testdata/sf0.001"


def six(df):
    return [r["count"] for r in df.orderBy("type").collect()]


def by_hand(rows, tau, ties="strict"):
    """All sequences of four edges, in plain Python."""
    o = (lambda e: e[3]) if ties == "strict" else (lambda e: (e[3], e[0]))
    out = [0] * 6
    for one in rows:
        for a in rows:
            if a[2] != one[2] or a[1] == one[1] or not (o(a) > o(one) and a[3] <= one[3] + tau):
                continue
            for b in rows:
                if b[1] != one[1] or b[2] == one[2] or not (o(b) > o(one) and b[3] <= one[3] + tau):
                    continue
                for c in rows:
                    if c[1] != a[1] or c[2] != b[2] or not (o(c) > o(one) and c[3] <= one[3] + tau):
                        continue
                    at = {"a": o(a), "b": o(b), "c": o(c)}
                    for kind, order in ORDERS.items():
                        out[kind - 1] += at[order[0]] < at[order[1]] < at[order[2]]
    return out


@pytest.mark.parametrize("tau,want", [(5, [0, 1, 0, 0, 1, 0]), (8, [0, 1, 1, 0, 1, 0]), (9, [0, 1, 1, 0, 1, 0]), (10, [0, 2, 1, 0, 1, 0])])
def test_worked_example(spark, tau, want):
    assert six(counting.exact_count(toy(spark), tau)) == want == by_hand(TOY, tau)


def test_worked_example_one_start(spark):
    one = counting.per_edge_counts(toy(spark), toy(spark).where("eid = 0"), 10).first()
    assert tuple(one) == (0, 0, 2, 0, 0, 0, 0)


@pytest.mark.parametrize("ties", ["strict", "total_order"])
def test_all_plans_agree_with_brute_force(spark, ties):
    import random

    rnd = random.Random(5)
    rows = [(k, rnd.randrange(5), rnd.randrange(5), rnd.randrange(40)) for k in range(70)]
    edges = edges_from_rows(spark, rows)
    want = by_hand(rows, 12, ties)
    assert sum(want) > 50
    assert six(counting.long_form(counting.six(counting.brute_force(edges, 12, ties)))) == want
    for plan, center in itertools.product(("star", "wedge_pair"), ("lower", "upper")):
        assert six(counting.exact_count(edges, 12, plan, center, ties)) == want, (plan, center)
    if ties == "strict":
        for plan in ("factored", "grouped"):
            assert six(counting.exact_count(edges, 12, plan)) == want, plan
    assert six(counting.long_form(counting.six(counting.chrono_all(edges, edges, 12, ties)))) == want


@pytest.mark.parametrize("name,tau,want", [("euk", 72 * HOUR, [57, 66, 51, 61, 65, 59]), ("euk", 168 * HOUR, [714, 702, 752, 716, 754, 720]), ("nat", 7, [55, 53, 61, 56, 52, 53])])
def test_known_counts(spark, name, tau, want):
    assert six(counting.exact_count(view(spark, SF, name), tau)) == want


def test_symmetries(spark):
    edges = view(spark, SF, "euk")
    tau = 168 * HOUR
    want = six(counting.exact_count(edges, tau))
    swapped = six(counting.exact_count(counting.transposed_edges(edges), tau))
    assert [swapped[TRANSPOSED[k] - 1] for k in range(1, 7)] == want
    assert six(counting.exact_count(edges.withColumn("t", -F.col("t")), tau)) == want
    assert six(counting.exact_count(edges.withColumn("t", F.col("t") * 3 + 17), tau * 3)) == want
    assert six(counting.exact_count(edges.repartition(7), tau)) == want


@pytest.mark.parametrize(
    "rows,tau,strict,total",
    [
        ([], 5, 0, 0),
        ([(0, 1, 1, 1)], 5, 0, 0),
        ([(0, 1, 1, 1), (1, 2, 1, 1), (2, 1, 2, 2), (3, 2, 2, 3)], 5, 0, 1),
        ([(0, 1, 1, 1), (1, 2, 1, 2), (2, 1, 2, 2), (3, 2, 2, 3)], 5, 0, 1),
        ([(0, 1, 1, 1), (1, 2, 1, 2), (2, 1, 2, 3), (3, 2, 2, 6)], 5, 1, 1),
        ([(0, 1, 1, 1), (1, 2, 1, 2), (2, 1, 2, 3), (3, 2, 2, 7)], 5, 0, 0),
        ([(0, 1, 1, 1), (1, 2, 1, 2), (2, 2, 1, 3), (3, 1, 2, 4), (4, 2, 2, 5)], 9, 2, 2),
        ([(k, 1, 1, 1) for k in range(4)], 5, 0, 0),
    ],
)
def test_edge_cases(spark, rows, tau, strict, total):
    edges = edges_from_rows(spark, rows)
    for ties, want in (("strict", strict), ("total_order", total)):
        assert sum(six(counting.exact_count(edges, tau, ties=ties))) == want == sum(by_hand(rows, tau, ties))


def test_each_type_once(spark):
    rows = []
    for kind, order in ORDERS.items():
        at = {c: k + 2 for k, c in enumerate(order)}
        u, base = 10 * kind, 100 * kind
        rows += [(base, u, u, 1), (base + 1, u + 1, u, at["a"]), (base + 2, u, u + 1, at["b"]), (base + 3, u + 1, u + 1, at["c"])]
    assert six(counting.exact_count(edges_from_rows(spark, rows), 9)) == [1] * 6


def test_adapter(spark):
    df = spark.createDataFrame([("a", "x", 1), ("a", "x", 1), (None, "x", 2), ("b", "y", None)], "src string, dst string, at long")
    assert from_df(df, "src", "dst", "at").count() == 2
    assert from_df(df, "src", "dst", "at", duplicates="collapse").count() == 1
    with pytest.raises(Exception, match="null"):
        from_df(df, "src", "dst", "at", nulls="error").collect()


def test_plans_hold_no_cartesian_product(spark):
    edges = view(spark, SF, "euk")
    plan = counting.exact_count(edges, HOUR, "wedge_pair", "lower")._jdf.queryExecution().toString()
    assert "Cartesian" not in plan and "NestedLoop" not in plan
    assert "ReadSchema: struct<ts:timestamp_ntz,user_id:bigint,props:string>" in plan  # ids are not needed to count
