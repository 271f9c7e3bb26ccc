"""Sizes, degrees and predicted work of a graph."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wingcount.functions.order_types import TYPES
from wingcount.operators.counting import COUNTS, added, exact_count, list_instances, wedges
from wingcount.operators.ranked import ranked
from wingcount.operators.static_graph import static_edges, static_exact
from wingcount.operators.timeline import range_counts
from wingcount.shared import settled


def degrees(edges: DataFrame) -> DataFrame:
    """(layer, node, degree) in edges, repeats included."""
    one = lambda side, name: edges.groupBy(F.col(side).alias("node")).agg(F.count(F.lit(1)).alias("degree")).select(F.lit(name).alias("layer"), "node", "degree")
    return one("u", "upper").union(one("l", "lower"))


def summary(edges: DataFrame, tau: int, butterflies: bool = True) -> DataFrame:
    """One row: n, m, static_edges, d_max, timespan, and with `butterflies` the static and temporal ones."""
    deg = degrees(edges).agg(F.count(F.lit(1)).alias("n"), F.max("degree").alias("d_max"))
    base = edges.agg(F.count(F.lit(1)).alias("m"), (F.max("t") - F.min("t")).alias("timespan"))
    out = base.crossJoin(deg).crossJoin(static_edges(edges).agg(F.count(F.lit(1)).alias("static_edges")))  # single rows
    if butterflies:
        out = out.crossJoin(static_exact(edges)).crossJoin(exact_count(edges, tau).agg(F.sum("count").alias("temporal")))
    return out


def type_share(edges: DataFrame, tau: int) -> DataFrame:
    """(type, count, share): each type's share of all instances, in percent."""
    counts = exact_count(edges, tau)
    return counts.withColumn("share", F.round(100 * F.col("count") / F.nullif(F.sum("count").over(Window.partitionBy()), F.lit(0)), 6))


def window_degree(edges: DataFrame, tau: int, c: float = 1.0) -> DataFrame:
    """One row: d_upper and d_lower, the most edges at one node within tau of one of its edges; delta, the most edges in any stretch of c * tau."""
    def most(side: str, name: str) -> DataFrame:
        ahead = Window.partitionBy(side).orderBy("t").rangeBetween(0, tau)
        return edges.select(F.count(F.lit(1)).over(ahead).alias("n")).agg(F.max("n").alias(name))

    length = int(c * tau)
    delta = range_counts(edges, edges, F.col("t"), F.col("t") + F.lit(length), "n").agg(F.max("n").alias("delta"))
    return most("u", "d_upper").crossJoin(most("l", "d_lower")).crossJoin(delta)  # single rows


def cost_terms(edges: DataFrame, tau: int, c: float = 1.0, eps: float = 0.1, delta: float = 0.1) -> DataFrame:
    """One row with the terms of the cost model: m, d_tau, delta, and the predicted work of exact counting and of interval sampling."""
    import math

    d = F.greatest("d_upper", "d_lower")
    both = window_degree(edges, tau, c).crossJoin(edges.agg(F.count(F.lit(1)).alias("m")))  # single rows
    return both.select("m", d.alias("d_tau"), "delta", (F.col("m") * d * d).cast("double").alias("exact_work"), F.round(F.col("m") * F.col("delta") * d * d * F.log2("m") * F.lit(math.log(1 / delta) / eps**2), 0).alias("interval_work"))


def work_profile(edges: DataFrame, starts: DataFrame, tau: int) -> DataFrame:
    """One row of counts that no clock disturbs: starts, wedges on them, instances, and start edges that have any."""
    w = wedges(edges, tau).join(starts.select(F.col("eid").alias("e1")), "e1", "left_semi").agg(F.count(F.lit(1)).alias("wedges"))
    found = list_instances(edges, tau, starts).agg(F.count(F.lit(1)).alias("instances"), F.countDistinct("e1").alias("with_instances"))
    return starts.agg(F.count(F.lit(1)).alias("starts")).crossJoin(w).crossJoin(found)  # single rows


def tau_curve(edges: DataFrame, taus: list[int]) -> DataFrame:
    """(tau, type, count) for every tau, counted by ranks from one deal of the edges to cells as wide as the largest."""
    edges = settled(edges.select(F.lit(0).cast("long").alias("eid"), "u", "l", "t"), "edges")
    grid = edges.sparkSession.createDataFrame([(int(x),) for x in sorted(set(taus))], "tau long")
    counts = grid.join(added(ranked(edges, edges, sorted(set(taus)), totals=True), "tau"), "tau", "left").fillna(0, COUNTS)  # a row for each tau
    return counts.selectExpr("tau", "stack(6, " + ", ".join(f"{k}, c{k}" for k in TYPES) + ") as (type, count)")
