"""How many edges lie in a stretch of time, for many stretches at once, by prefix counts on two levels: per bucket, and within it."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: A bucket has some ROWS edges; there are MOST_BUCKETS at most, a bound for the histogram that all tasks get (24 MB), so beyond 10^11 edges buckets grow.
ROWS, MOST_BUCKETS, LEAST_BUCKETS = 100_000, 1_000_000, 64
#: Edges of a cell whose stretches are counted in one task: as many as that on average, and the most.
WIDE, CROWD = 300_000, 1_000_000


def _width(points: DataFrame) -> tuple[int, int, int]:
    """Width of a bucket, and the first and the last time; from one aggregate."""
    low, high, n = points.agg(F.min("t"), F.max("t"), F.count(F.lit(1))).first()
    low, high = (0, 0) if low is None else (int(low), int(high))
    buckets = min(MOST_BUCKETS, max(LEAST_BUCKETS, n // ROWS))
    return max(1, -(-(high - low + 1) // buckets)), low, high


def prefix_counts(points: DataFrame, asked: DataFrame, weight: str | None = None) -> DataFrame:
    """`asked` has any columns besides x (a time) and inclusive (whether points at x count); `upto` is added, the number (or sum of `weight`) of points
    with t up to x. A time is looked up in its own bucket, so buckets may be narrower than the stretches that are asked for: their number follows from the points alone.
    The histogram has a row a bucket and is broadcast; the one window without a partition sees these rows only."""
    width, low, high = _width(points)
    one = F.lit(1).cast("long") if weight is None else F.col(weight)
    at = lambda t: F.least(F.greatest(F.floor((t - F.lit(low)) / F.lit(width)), F.lit(-1)), F.lit((high - low) // width + 1)).cast("long")
    cols = asked.columns
    histogram = points.groupBy(at(F.col("t")).alias("b")).agg(F.sum(one).alias("n"))
    all_buckets = points.sparkSession.range(-1, (high - low) // width + 2).select(F.col("id").alias("b"))
    before = Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)
    ahead = all_buckets.join(F.broadcast(histogram), "b", "left").select("b", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("ahead"))
    null_row = F.lit(None).cast(asked.select(F.struct(*cols).alias("r")).schema["r"].dataType)
    rows = points.select(null_row.alias("r"), at(F.col("t")).alias("b"), F.col("t").alias("x"), F.lit(1).alias("side"), one.alias("w"))
    zero = F.lit(0).cast(rows.schema["w"].dataType)
    wanted = asked.select(F.struct(*cols).alias("r"), at(F.col("x")).alias("b"), "x", F.when(F.col("inclusive"), 2).otherwise(0).alias("side"), zero.alias("w"))
    inner = Window.partitionBy("b").orderBy("x", "side").rowsBetween(Window.unboundedPreceding, 0)
    counted = rows.union(wanted).withColumn("within", F.sum("w").over(inner)).where(F.col("r").isNotNull())
    return counted.join(F.broadcast(ahead), "b").select("r.*", (F.col("within") + F.col("ahead")).alias("upto"))


def range_counts(points: DataFrame, asked: DataFrame, low: Column, high: Column, name: str, key: str = "eid", weight: str | None = None) -> DataFrame:
    """(key, name): points with t in the closed stretch [low, high] of each row of `asked`."""
    ends = asked.select(F.col(key), F.explode(F.array(F.struct(high.alias("x"), F.lit(True).alias("inclusive"), F.lit(1).alias("sign")), F.struct(low.alias("x"), F.lit(False).alias("inclusive"), F.lit(-1).alias("sign")))).alias("q"))
    got = prefix_counts(points, ends.select(key, "q.x", "q.inclusive", "q.sign"), weight)
    return got.groupBy(key).agg(F.sum(F.col("upto") * F.col("sign")).alias(name))


def trailing_count(edges: DataFrame, width: int) -> DataFrame:
    """(eid, m_prime): edges with a time in the closed stretch [t - width, t], the edge itself among them."""
    return range_counts(edges, edges, F.col("t") - F.lit(width), F.col("t"), "m_prime")


def trailing_sums(edges: DataFrame, found: DataFrame, width: int) -> DataFrame:
    """(eid, u, l, t, copies, m_prime) of the edges whose closed stretch [t - width, t] holds some of `found`: how many of these, and how many edges. Edges are dealt once, with times
    alone to the stretch after theirs; where a stretch is too crowded for a task, prefix counts on two levels take over."""
    low, high, m = edges.agg(F.min("t"), F.max("t"), F.count(F.lit(1))).first()
    wide = max(1, width, 0 if low is None else (high - low + 1) * WIDE // max(1, m))
    own = F.floor(F.col("t") / F.lit(wide)).cast("long")
    if (edges.groupBy(own.alias("b")).count().agg(F.max("count")).first()[0] or 0) > CROWD:
        copies = range_counts(found, edges, F.col("t") - F.lit(width), F.col("t"), "copies").where("copies > 0")
        return edges.join(copies, "eid").join(trailing_count(edges, width), "eid").select("eid", "u", "l", "t", "copies", "m_prime")
    none = [F.lit(None).cast("long").alias(c) for c in ("eid", "u", "l")]

    def times(df: DataFrame, role: int, b: Column) -> DataFrame:
        return df.select(*none, "t", F.lit(role).alias("role"), b.alias("b"))

    both = edges.select("eid", "u", "l", "t", F.lit(0).alias("role"), own.alias("b")).unionByName(times(found, 2, own))
    for df, role in ((edges, 1), (found, 2)):  # those that a stretch of the next cell reaches back to
        both = both.unionByName(times(df, role, own + 1).where(F.col("b") * F.lit(wide) - F.col("t") <= F.lit(width)))

    def count(table: pa.Table) -> pa.Table:
        role, t = table.column("role").to_numpy(), table.column("t").to_numpy()
        mine, edge, drawn = t[role == 0], np.sort(t[role < 2]), np.sort(t[role == 2])
        within = lambda x: np.searchsorted(x, mine, "right") - np.searchsorted(x, mine - width, "left")
        copies = within(drawn)
        some = pa.array(copies > 0)
        own_rows = table.select(["eid", "u", "l", "t"]).filter(pa.array(role == 0)).filter(some)
        return own_rows.append_column("copies", pa.array(copies).filter(some)).append_column("m_prime", pa.array(within(edge)).filter(some)).combine_chunks()

    return both.groupBy("b").applyInArrow(count, "eid long, u long, l long, t long, copies long, m_prime long")


def ranks(edges: DataFrame) -> DataFrame:
    """Edges with `rank`, their place from 0 on in the order of (t, eid), without one task that sees all edges."""
    width, low, _ = _width(edges)
    bucketed = edges.withColumn("_b", F.floor((F.col("t") - F.lit(low)) / F.lit(width)).cast("long"))
    histogram = bucketed.groupBy("_b").agg(F.count(F.lit(1)).alias("_n"))
    ahead = histogram.select("_b", F.coalesce(F.sum("_n").over(Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_ahead"))
    inner = F.row_number().over(Window.partitionBy("_b").orderBy("t", "eid"))
    return bucketed.withColumn("_in", inner).join(F.broadcast(ahead), "_b").withColumn("rank", F.col("_ahead") + F.col("_in") - 1).drop("_b", "_in", "_ahead")
