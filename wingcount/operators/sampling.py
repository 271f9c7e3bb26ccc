"""Samples of start edges: by edge, by node of one layer, and by intervals of time. A sample is edges with copies (a long) and weight (a double)."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wingcount.functions.hashing import u01
from wingcount.operators.timeline import ranks, trailing_count, trailing_sums
from wingcount.shared import settled


def _share(p: float) -> None:
    if not 0 < p <= 1:
        raise ValueError("a sampling rate lies in (0, 1]")


@dataclass(frozen=True)
class EdgeSampler:
    """Each edge on its own with probability p. The hash predicate runs in the scan."""

    p: float
    seed: int = 0

    def draw(self, edges: DataFrame, tau: int = 0) -> DataFrame:
        _share(self.p)
        return edges.where(u01(self.seed, "eid") < self.p).select("eid", "u", "l", "t", F.lit(1).cast("long").alias("copies"), F.lit(1.0 / self.p).alias("weight"))


@dataclass(frozen=True)
class NodeSampler:
    """Each node of one layer with probability p, and all its edges. Hashing the node id stands for a table of nodes."""

    p: float
    layer: str = "upper"
    seed: int = 0
    relational: bool = False

    def draw(self, edges: DataFrame, tau: int = 0) -> DataFrame:
        _share(self.p)
        side = {"upper": "u", "lower": "l"}[self.layer]
        if self.relational:
            kept = edges.join(edges.select(side).distinct().where(u01(self.seed, side) < self.p), side, "left_semi")
        else:
            kept = edges.where(u01(self.seed, side) < self.p)
        return kept.select("eid", "u", "l", "t", F.lit(1).cast("long").alias("copies"), F.lit(1.0 / self.p).alias("weight"))


@dataclass(frozen=True)
class IntervalSampler:
    """`draws` edges, and every edge within c * tau after each. An edge found by several draws has as many copies (folded), or a row for each (literal).

    replace: draw j takes the edge of rank floor(u01(j) * m) in the order of (t, eid); without it, the edges with the smallest hashes are drawn.
    rate instead of draws: rate_unit 'draws' takes rate * m draws, 'edge_copies' as many as give rate * m copies on average."""

    draws: int | None = None
    rate: float | None = None
    c: float = 1.0
    replace: bool = True
    mode: str = "folded"
    seed: int = 0
    rate_unit: str = "draws"

    def size(self, edges: DataFrame, tau: int) -> int:
        if self.draws is not None:
            return self.draws
        m = edges.count()
        if self.rate_unit == "draws":
            return max(1, round(self.rate * m))
        mean = trailing_count(edges, self.length(tau)).agg(F.avg("m_prime")).first()[0] or 1.0
        return max(1, round(self.rate * m / mean))

    def length(self, tau: int) -> int:
        if self.c <= 0:
            raise ValueError("an interval has a length above 0")
        return int(self.c * tau)

    def drawn(self, edges: DataFrame, tau: int) -> DataFrame:
        """(draw, eid, t) of the drawn edges."""
        s = self.size(edges, tau)
        if not self.replace:
            return edges.withColumn("_h", u01(self.seed, "eid")).orderBy("_h", "eid").limit(s).select(F.col("eid").alias("draw"), "eid", "t")
        m = edges.count()
        picks = edges.sparkSession.range(s).select(F.col("id").alias("draw"), F.floor(u01(self.seed, F.col("id")) * F.lit(m)).cast("long").alias("rank"))
        return ranks(edges).join(picks, "rank").select("draw", "eid", "t")

    def draw(self, edges: DataFrame, tau: int) -> DataFrame:
        edges = settled(edges)
        s, m, length = self.size(edges, tau), edges.count(), self.length(tau)
        found = settled(replace(self, draws=s).drawn(edges, tau))
        weight = (F.lit(float(m)) / (F.lit(float(s)) * F.col("m_prime"))).alias("weight")
        if self.mode == "literal":
            from wingcount.operators.joins import interval_join

            # an edge meets its trailing count before it is repeated for each draw
            weighed = edges.join(trailing_count(edges, length), "eid")
            hits = interval_join(found.select("draw", "t"), weighed, [], "t", max(1, length), closed_low=True).where(F.col("r_t") <= F.col("t") + F.lit(length))
            return hits.select(*(F.col(f"r_{c}").alias(c) for c in ("eid", "u", "l", "t", "m_prime"))).select("eid", "u", "l", "t", F.lit(1).cast("long").alias("copies"), weight)
        return trailing_sums(edges, found.select("t"), length).select("eid", "u", "l", "t", "copies", weight)
