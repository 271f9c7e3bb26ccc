"""Sample, count per start edge, weigh, add: one plan, whatever the sampler and the counter."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wingcount.functions.order_types import TYPES
from wingcount.operators.counting import COUNTS, list_instances, long_form, per_edge_counts, six_passes
from wingcount.operators.ranked import ranked
from wingcount.operators.timeline import range_counts
from wingcount.shared import settled


def estimate(edges: DataFrame, tau: int, sampler, counter: str = "wedge", ties: str = "strict", plan: str = "star") -> DataFrame:
    """(type, estimate): sums of copies * weight * count over the sampled start edges. counter 'wedge' finds all types at once, 'chrono' each on its own."""
    by_ranks = ties == "strict" and (counter != "wedge" or plan == "star")
    edges = settled(edges, "edges") if by_ranks else edges
    sample = sampler.draw(edges, tau)
    if getattr(sampler, "mode", None) == "literal":  # rows of one edge are added before they are dealt
        sample = sample.groupBy("eid", "u", "l", "t", "weight").agg(F.sum("copies").alias("copies"))
    if by_ranks:  # each start brings its weight along, so no count has to find its edge again
        parts = ranked(edges, sample, tau, weighed=True, runs=None if counter == "wedge" else tuple((k,) for k in TYPES))
        return long_form(_weighted(parts.groupBy("weight").agg(*(F.sum(c).alias(c) for c in COUNTS))), "estimate")
    sample = settled(sample, "sample")
    starts = sample.select("eid", "u", "l", "t")
    per = per_edge_counts(edges, starts, tau, plan, ties) if counter == "wedge" else six_passes(edges, starts, tau, ties)
    joined = sample.select("eid", "copies", "weight").join(per, "eid")
    # integers of equal weight are added first, so that the sum doesn't depend on how rows are dealt
    exact = joined.groupBy("weight").agg(*(F.sum(F.col("copies") * F.col(c)).alias(c) for c in COUNTS))
    return long_form(_weighted(exact), "estimate")


def _weighted(exact: DataFrame) -> DataFrame:
    return exact.agg(*(F.coalesce(F.sum(F.col("weight") * F.col(c)), F.lit(0.0)).alias(c) for c in COUNTS))


def estimates_by_seed(edges: DataFrame, tau: int, kind: str, rates: list[float], seeds: list[int], layer: str = "upper") -> DataFrame:
    """(seed, rate, type, estimate) of edge or node sampling in one job: exact counts per start edge once, then each seed and rate takes its share of them."""
    from wingcount.functions.hashing import u01

    edges = settled(edges, "edges")
    per = ranked(edges, edges, tau, label="eid" if kind == "edge" else {"upper": "u", "lower": "l"}[layer])
    sessions = per.sparkSession
    grid = sessions.createDataFrame([(s, float(r)) for s in seeds for r in rates], "seed int, rate double")
    shares = F.array(*(F.struct(F.lit(s).alias("seed"), u01(s, "eid").alias("x")) for s in seeds))
    hashed = per.withColumn("h", F.explode(shares)).select("h.seed", "h.x", *COUNTS)
    kept = hashed.join(F.broadcast(grid), "seed").where("x < rate").groupBy("seed", "rate").agg(*(F.sum(c).alias(c) for c in COUNTS))
    full = grid.join(kept, ["seed", "rate"], "left").select("seed", "rate", *((F.coalesce(c, F.lit(0)) / F.col("rate")).alias(c) for c in COUNTS))
    pairs = ", ".join(f"{k}, c{k}" for k in TYPES)
    return full.selectExpr("seed", "rate", f"stack(6, {pairs}) as (type, estimate)")


def _per_type(df: DataFrame, key: list[str], value: str = "v") -> DataFrame:
    """One row a key with c1..c6 from rows of (key, type, value)."""
    return df.groupBy(*key).agg(*(F.coalesce(F.sum(F.when(F.col("type") == k, F.col(value))), F.lit(0)).cast("double").alias(f"c{k}") for k in TYPES))


def unit_values(edges: DataFrame, tau: int, method: str, c: float = 0.1, window: float = 1.5) -> DataFrame:
    """What one sampled unit of a method adds to the estimates, for all units that add something: (rank, c1..c6) for methods that draw units by rank, with the unit's own columns
    for those that keep each with a probability. An estimate is then a weighted sum over the units of a sample, so whole grids of rates and seeds need one count."""
    from wingcount.operators.static_graph import static_edges
    from wingcount.operators.timeline import prefix_counts, ranks, trailing_count

    edges = settled(edges)
    if method in ("edge", "six_edge"):
        return per_edge_counts(edges, edges, tau)
    if method in ("static_quad", "static_topology"):
        cells = F.explode(F.array(*(F.struct(F.col(a).alias("u"), F.col(b).alias("l")) for a in ("ux", "uy") for b in ("lx", "ly")))).alias("q")
        found = list_instances(edges, tau, edges).groupBy("ux", "uy", "lx", "ly", "type").agg(F.count(F.lit(1)).alias("v")).select("type", "v", cells)
        per = _per_type(found.select("q.u", "q.l", "type", "v"), ["u", "l"])
        pairs = ranks(static_edges(edges).select(F.col("l").alias("eid"), "u", "l", F.col("u").alias("t"))).select("u", "l", "rank")
        return per.join(pairs, ["u", "l"])
    order = ranks(edges).select("eid", "t", "rank")
    if method == "interval":  # an edge's share of its instances, added up over the interval after each drawn edge
        length = int(c * tau)
        shares = per_edge_counts(edges, edges, tau).join(edges.select("eid", "t"), "eid").join(trailing_count(edges, length), "eid")
        points, ends = shares.select("t", *((F.col(x) / F.col("m_prime")).alias(x) for x in COUNTS)), [("t", False, -1.0), (F.col("t") + F.lit(length), True, 1.0)]
    elif method == "six_window":  # 1 / r for each instance, added up over the windows that hold it as a whole
        length = int(window * tau)
        spans = list_instances(edges, tau, edges).groupBy("type", "t1", "duration").agg(F.count(F.lit(1)).alias("n"))
        spans = spans.withColumns({"id": F.struct("type", "t1", "duration"), "low": F.col("t1") + F.col("duration") - F.lit(length)})
        r = range_counts(edges, spans, F.col("low"), F.col("t1"), "r", key="id")
        own = spans.join(r, "id").withColumn("v", F.col("n") / F.col("r"))
        # a window's begin x holds the instance for low <= x <= t1: it comes in at low and goes after t1
        steps = own.select("type", F.explode(F.array(F.struct(F.col("low").alias("t"), F.col("v").alias("v")), F.struct((F.col("t1") + 1).alias("t"), (-F.col("v")).alias("v")))).alias("s")).select("type", "s.*")
        points, ends = _per_type(steps, ["t"]), [("t", True, 1.0)]
    else:
        raise ValueError(f"no units for {method!r}")
    asked = order.select("rank", F.explode(F.array(*(F.struct((F.col(x) if isinstance(x, str) else x).alias("x"), F.lit(i).alias("inclusive"), F.lit(g).alias("sign")) for x, i, g in ends))).alias("q")).select("rank", "q.*")
    out = None
    for x in COUNTS:
        one = prefix_counts(points.select("t", F.col(x).alias("w")), asked, "w").groupBy("rank").agg(F.sum(F.col("upto") * F.col("sign")).alias(x))
        out = one if out is None else out.join(one, "rank")
    return out


#: Methods that keep each unit with a probability: its columns, and by how many units an instance is found; methods that draw units: draws for a rate of 1 over all units.
KEPT = {"edge": (("eid",), 1), "six_edge": (("eid",), 1), "node_upper": (("u",), 1), "node_lower": (("l",), 1), "static_topology": (("u", "l"), 4)}
DRAWN = {"interval": (1, 1), "static_quad": (1, 4), "six_window": (10, 1)}


def grid_estimates(edges: DataFrame, tau: int, method: str, rates: list[float], seeds: list[int]) -> DataFrame:
    """(seed, rate, type, estimate) of any of the eight methods for a grid of rates and seeds; instances are counted once."""
    from wingcount.functions.hashing import u01

    spark = edges.sparkSession
    if method in ("node_upper", "node_lower"):
        return estimates_by_seed(edges, tau, "node", rates, seeds, method.removeprefix("node_"))
    units = unit_values(edges, tau, method)
    pairs = ", ".join(f"{k}, c{k}" for k in TYPES)
    if method in KEPT:
        keys, found = KEPT[method]
        grid = spark.createDataFrame([(s, float(r)) for s in seeds for r in rates], "seed int, rate double")
        hashed = units.withColumn("h", F.explode(F.array(*(F.struct(F.lit(s).alias("seed"), u01(s, *keys).alias("x")) for s in seeds)))).select("h.seed", "h.x", *COUNTS)
        sums = hashed.join(F.broadcast(grid), "seed").where("x < rate").groupBy("seed", "rate").agg(*(F.sum(c).alias(c) for c in COUNTS))
        scaled = grid.join(sums, ["seed", "rate"], "left").select("seed", "rate", *((F.coalesce(c, F.lit(0)) / (F.col("rate") * found)).alias(c) for c in COUNTS))
    else:
        share, found = DRAWN[method]
        n = edges.select("u", "l").distinct().count() if method == "static_quad" else edges.count()
        size = {r: max(1, math.floor(r * n / share + 0.5)) for r in rates}
        grid = spark.createDataFrame([(s, float(r), size[r]) for s in seeds for r in rates], "seed int, rate double, s long")
        draws = spark.range(max(size.values())).withColumn("h", F.explode(F.array(*(F.struct(F.lit(s).alias("seed"), F.floor(u01(s, "id") * F.lit(n)).cast("long").alias("rank")) for s in seeds)))).select("id", "h.*")
        hit = draws.join(units.select("rank", *COUNTS), "rank").join(F.broadcast(grid), "seed").where("id < s").groupBy("seed", "rate").agg(*(F.sum(c).alias(c) for c in COUNTS))
        scaled = grid.join(hit, ["seed", "rate"], "left").select("seed", "rate", *((F.coalesce(c, F.lit(0.0)) * F.lit(float(n)) / (F.col("s") * found)).alias(c) for c in COUNTS))
    return scaled.selectExpr("seed", "rate", f"stack(6, {pairs}) as (type, estimate)")
