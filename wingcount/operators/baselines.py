"""The estimators that the sampling framework is compared with, each unbiased by inverse-probability weights."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wingcount.functions.hashing import u01
from wingcount.functions.order_types import TYPES
from wingcount.operators.counting import COUNTS, chrono, long_form, six
from wingcount.operators.estimators import estimate
from wingcount.operators.sampling import EdgeSampler, IntervalSampler
from wingcount.operators.static_graph import static_edges
from wingcount.operators.timeline import range_counts


def _summed(rows: DataFrame, weight: Column, scale: float) -> DataFrame:
    wide = six(rows, weight=weight).select(*((F.col(c) * F.lit(scale)).cast("double").alias(c) for c in COUNTS))
    return long_form(wide, "estimate")


def quadruples(edges: DataFrame, sampled: DataFrame) -> DataFrame:
    """(u_lo, u_hi, l_lo, l_hi, weight): butterflies of the static graph through sampled static edges (u, l, weight), the weights of a butterfly's
    sampled edges added. Times play no part here."""
    pairs = static_edges(edges).select("u", "l")
    p1, p2 = pairs.select(F.col("u").alias("u2"), F.col("l").alias("k1")), pairs.select(F.col("u").alias("k2"), F.col("l").alias("l2"))
    p3 = pairs.select(F.col("u").alias("u3"), F.col("l").alias("l3"))
    x = sampled.join(p1, (sampled.l == p1.k1) & (sampled.u != p1.u2)).join(p2, (sampled.u == p2.k2) & (sampled.l != p2.l2))
    x = x.join(p3, (x.u2 == p3.u3) & (x.l2 == p3.l3))
    return x.groupBy(F.least("u", "u2").alias("u_lo"), F.greatest("u", "u2").alias("u_hi"), F.least("l", "l2").alias("l_lo"), F.greatest("l", "l2").alias("l_hi")).agg(F.sum("weight").alias("weight"))


def instances_in(edges: DataFrame, quads: DataFrame, tau: int) -> DataFrame:
    """Instances within the four nodes of each quadruple, with its weight. The cells' edges are joined first and times looked at last, as these baselines do."""
    cell = lambda k, u, l: (edges.select(F.col("eid").alias(f"e{k}"), F.col("u").alias(f"p{k}"), F.col("l").alias(f"q{k}"), F.col("t").alias(f"t{k}")), u, l)
    x = quads.withColumn("_o", F.explode(F.array(*(F.struct(F.col(a).alias("ux"), F.col(b).alias("uy"), F.col(c).alias("lx"), F.col(d).alias("ly")) for a, b in (("u_lo", "u_hi"), ("u_hi", "u_lo")) for c, d in (("l_lo", "l_hi"), ("l_hi", "l_lo")))))).select("weight", "_o.*")
    for e, u, l in (cell(1, "ux", "lx"), cell(2, "uy", "lx"), cell(3, "ux", "ly"), cell(4, "uy", "ly")):
        k = e.columns[0][1]
        x = x.join(e, (x[u] == e[f"p{k}"]) & (x[l] == e[f"q{k}"])).drop(f"p{k}", f"q{k}")
    from wingcount.functions.order_types import classify

    last = F.greatest("t2", "t3", "t4")
    inside = (F.least("t2", "t3", "t4") > F.col("t1")) & (last <= F.col("t1") + F.lit(tau))
    return x.where(inside).withColumn("type", classify(F.col("t2"), F.col("t3"), F.col("t4"))).where(F.col("type").isNotNull())


@dataclass(frozen=True)
class StaticQuadEstimator:
    """Draws static edges with replacement (draw j takes the one of rank floor(u01(j) * count) in the order of (u, l)) and counts the instances inside every butterfly
    through each. A butterfly has four edges, so the weight is count / (4 * draws)."""

    draws: int
    seed: int = 0

    def estimate(self, edges: DataFrame, tau: int) -> DataFrame:
        from wingcount.operators.timeline import ranks

        pairs = static_edges(edges).select("u", "l")
        n = pairs.count()
        picks = edges.sparkSession.range(self.draws).select(F.floor(u01(self.seed, F.col("id")) * F.lit(n)).cast("long").alias("rank")).groupBy("rank").agg(F.count(F.lit(1)).alias("weight"))
        sampled = ranks(pairs.select(F.col("l").alias("eid"), "u", "l", F.col("u").alias("t"))).join(picks, "rank").select("u", "l", "weight")
        return _summed(instances_in(edges, quadruples(edges, sampled), tau), F.col("weight"), n / (4.0 * self.draws))


@dataclass(frozen=True)
class StaticTopologyEstimator:
    """Static edges with probability q each ('uniform'), or by their multiplicity, min(1, q * multiplicity / mean); weight 1 / (4 * probability)."""

    q: float
    proposal: str = "uniform"
    seed: int = 0

    def estimate(self, edges: DataFrame, tau: int) -> DataFrame:
        pairs = static_edges(edges)
        if self.proposal == "uniform":
            p, weight, scale = F.lit(self.q), F.lit(1).cast("long"), 1 / (4 * self.q)
        else:
            mean = pairs.agg(F.avg("multiplicity")).first()[0] or 1.0
            p = F.least(F.lit(1.0), F.col("multiplicity") * F.lit(self.q / mean))
            weight, scale = 1 / p, 0.25
        sampled = pairs.where(u01(self.seed, "u", "l") < p).select("u", "l", weight.alias("weight"))
        return _summed(instances_in(edges, quadruples(edges, sampled), tau), F.col("weight"), scale)


@dataclass(frozen=True)
class SixPassEdge:
    """Edge sampling with a run for each type."""

    p: float
    seed: int = 0

    def estimate(self, edges: DataFrame, tau: int) -> DataFrame:
        return estimate(edges, tau, EdgeSampler(self.p, self.seed), counter="chrono")


@dataclass(frozen=True)
class SixPassWindow:
    """Windows of length c * tau; a run for each type counts the instances that lie in one window as a whole.

    anchor 'edge': a window begins at a drawn edge; an instance lies in the windows of the r edges from last - c * tau to first, so its weight is m / (s * r).
    anchor 'time': windows begin anywhere; the weight follows from the room that an instance leaves, R / (s * (c * tau - duration)), and c is above 1."""

    draws: int
    c: float = 1.5
    anchor: str = "edge"
    seed: int = 0

    def estimate(self, edges: DataFrame, tau: int) -> DataFrame:
        length = int(self.c * tau)
        if length < tau or (self.anchor == "time" and length <= tau):
            raise ValueError("a window is at least as long as tau, and longer for 'time'")
        if self.anchor == "edge":
            m = edges.count()
            begins = IntervalSampler(draws=self.draws, c=self.c, seed=self.seed).drawn(edges, tau).select("t")
        else:
            low, high = edges.agg(F.min("t"), F.max("t")).first()
            room = float(high - low + length)
            begins = edges.sparkSession.range(self.draws).select((F.lit(float(low - length)) + u01(self.seed, F.col("id")) * F.lit(room)).alias("t"))
        covered = range_counts(begins, edges, F.col("t") - F.lit(length), F.col("t"), "n").where("n > 0")
        starts = edges.join(covered.select("eid"), "eid", "left_semi")
        out = None
        for kind in TYPES:
            own = chrono(edges, starts, tau, kind).select("type", "t1", "duration").withColumn("id", F.struct("type", "t1", "duration"))
            out = own if out is None else out.union(own)
        kinds = out.groupBy("type", "t1", "duration").agg(F.count(F.lit(1)).alias("n")).withColumn("id", F.struct("type", "t1", "duration"))
        first, last = F.col("t1"), F.col("t1") + F.col("duration")
        hit = range_counts(begins, kinds, last - F.lit(length), first, "copies", key="id")
        weighed = kinds.join(hit.where("copies > 0"), "id")
        if self.anchor == "edge":
            weighed = weighed.join(range_counts(edges, kinds, last - F.lit(length), first, "r", key="id"), "id")
            weight = F.col("n") * F.col("copies") / F.col("r")
            return _summed(weighed, weight, m / self.draws)
        return _summed(weighed, F.col("n") * F.col("copies") / (F.lit(float(length)) - F.col("duration")), room / self.draws)
