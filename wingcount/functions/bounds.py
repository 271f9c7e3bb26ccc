"""Variance of the estimates, and how large a sample must be for an error of at most eps with probability 1 - delta."""

from __future__ import annotations

import math
import warnings

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wingcount.functions.order_types import TYPES
from wingcount.operators.counting import COUNTS, long_form, per_edge_counts
from wingcount.operators.sampling import EdgeSampler, IntervalSampler, NodeSampler


def _unit(**values: float) -> None:
    for name, x in values.items():
        if not 0 < x < 1:
            raise ValueError(f"{name} lies in (0, 1)")


def bennett_rate(eps: float) -> float:
    return (1 + eps) * math.log1p(eps) - eps


def variance_ceiling(kind: str, count: float, p: float | None = None, m: int | None = None, s: int | None = None) -> float:
    """At most this variance: for edge and node sampling by p, for intervals by m edges and s draws."""
    return (m - 1) / s * count**2 if kind == "interval" else (1 - p) / p * count**2


def min_probability(eps: float, delta: float, method: str = "chebyshev", m: int | None = None) -> float:
    _unit(eps=eps, delta=delta)
    if method == "chebyshev":
        return 1 / (1 + delta * eps * eps)
    p = (m - 1) * math.log(2 / delta) / (m * bennett_rate(eps))
    if p >= 1:
        warnings.warn("this bound asks for the whole graph", stacklevel=2)
    return min(p, 1.0)


def min_draws(m: int, eps: float, delta: float, method: str = "bennett") -> int:
    _unit(eps=eps, delta=delta)
    return math.ceil((m - 1) / (delta * eps * eps)) if method == "chebyshev" else math.ceil((m - 1) * math.log(2 / delta) / bennett_rate(eps))


def bounds_grid(graphs: DataFrame, eps: tuple[float, ...] = (0.05, 0.1, 0.2, 0.5), delta: tuple[float, ...] = (0.01, 0.05, 0.1)) -> DataFrame:
    """(eps, delta, m, p, s_bennett, s_chebyshev) as column arithmetic for each row of `graphs`, which has m and columns that stay."""
    grid = graphs.select("*", F.explode(F.array(*(F.struct(F.lit(float(e)).alias("eps"), F.lit(float(d)).alias("delta")) for e in eps for d in delta))).alias("g")).select(*graphs.columns, "g.*")
    h = (1 + F.col("eps")) * F.ln(1 + F.col("eps")) - F.col("eps")
    return grid.select(
        *(c for c in graphs.columns if c != "m"), "eps", "delta", "m", F.round(1 / (1 + F.col("delta") * F.col("eps") * F.col("eps")), 9).alias("p"),
        F.ceil((F.col("m") - 1) * F.ln(2 / F.col("delta")) / h).cast("long").alias("s_bennett"), F.round((F.col("m") - 1) / (F.col("delta") * F.col("eps") * F.col("eps")), 3).alias("s_chebyshev"),
    )


def exact_variance(edges: DataFrame, tau: int, sampler, formula: str = "exact") -> DataFrame:
    """(type, variance) of an estimate, from exact counts per start edge. For one interval draw exactly one indicator is 1, which formula='exact'
    takes into account; 'paper' treats the draws as independent, and is never smaller."""
    per = per_edge_counts(edges, edges, tau)
    if isinstance(sampler, NodeSampler):
        side = {"upper": "u", "lower": "l"}[sampler.layer]
        per = per.join(edges.select("eid", side), "eid").groupBy(side).agg(*(F.sum(c).alias(c) for c in COUNTS))
    if isinstance(sampler, (EdgeSampler, NodeSampler)):
        squares = per.agg(*(F.coalesce(F.sum((F.col(c) * F.col(c)).cast("decimal(38,0)")), F.lit(0)).alias(c) for c in COUNTS))
        return long_form(squares.select(*((F.col(c).cast("double") * F.lit((1 - sampler.p) / sampler.p)).alias(c) for c in COUNTS)), "variance")
    from wingcount.operators.timeline import prefix_counts, trailing_count

    m, s, length = edges.count(), sampler.size(edges, tau), sampler.length(tau)
    shares = per.join(edges.select("eid", "t"), "eid").join(trailing_count(edges, length), "eid")
    out = []
    for k in TYPES:
        points = shares.where(F.col(f"c{k}") > 0).select("t", (F.col(f"c{k}") / F.col("m_prime")).alias("w"))
        ends = edges.select("eid", F.explode(F.array(F.struct((F.col("t") + F.lit(length)).alias("x"), F.lit(True).alias("inclusive"), F.lit(1).alias("sign")), F.struct(F.col("t").alias("x"), F.lit(False).alias("inclusive"), F.lit(-1).alias("sign")))).alias("q")).select("eid", "q.*")
        inside = prefix_counts(points, ends, "w").groupBy("eid").agg(F.sum(F.col("upto") * F.col("sign")).alias("c"))
        out.append(inside.agg(F.coalesce(F.sum(F.col("c") * F.col("c")), F.lit(0.0)).alias("squares"), F.coalesce(F.sum("c"), F.lit(0.0)).alias("total")).select(F.lit(k).alias("type"), "squares", "total"))
    all_types = out[0]
    for one in out[1:]:
        all_types = all_types.union(one)
    single = F.col("squares") * m - F.col("total") * F.col("total") if formula == "exact" else F.col("squares") * (m - 1)
    scale = (1.0 if sampler.replace else (m - s) / max(1, m - 1)) / s
    return all_types.select("type", F.greatest(F.lit(0.0), single * F.lit(scale)).alias("variance"))


def plan_from_pilot(edges: DataFrame, tau: int, eps: float, delta: float, p0: float, seed: int = 0) -> DataFrame:
    """(type, count, p): a probability for edge sampling from a pilot sample, by Chebyshev's bound on the estimated variance instead of its ceiling."""
    _unit(eps=eps, delta=delta)
    sample = EdgeSampler(p0, seed).draw(edges)
    per = per_edge_counts(edges, sample.select("eid", "u", "l", "t"), tau)
    wide = per.agg(*(F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in COUNTS), *(F.coalesce(F.sum(F.col(c) * F.col(c)), F.lit(0)).alias(f"s{c}") for c in COUNTS))
    rows = wide.selectExpr("stack(6, " + ", ".join(f"{k}, c{k}, sc{k}" for k in TYPES) + ") as (type, c, squares)")
    # (1 - p) / p * squares / p0 <= delta * (eps * c / p0)^2
    ratio = F.col("squares") / F.lit(p0) / (F.lit(delta * eps * eps / p0 / p0) * F.col("c") * F.col("c"))
    return rows.select("type", (F.col("c") / F.lit(p0)).alias("count"), F.when(F.col("c") > 0, ratio / (1 + ratio)).otherwise(F.lit(1.0)).alias("p"))
