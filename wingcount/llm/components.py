"""Connected components of a link table, by alternating large-star and small-star steps.

Each step groups links by node and points neighbours at the smallest node seen; both keep components as they are, and
the links end as stars about each component's smallest node. Every step's links are a table in the shared folder, so a lost
executor costs no more than one step.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wingcount.shared import written


def _large_star(links: DataFrame) -> DataFrame:
    both = links.union(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("_m")).select("a", F.least("a", "_m").alias("_m"))
    return both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("_m").alias("b")).where("a <> b")


def _small_star(links: DataFrame) -> DataFrame:
    down = links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("_m"))
    joined = down.join(least, "a")
    return joined.select(F.col("b").alias("a"), F.col("_m").alias("b")).where("a <> b").union(least.select("a", F.col("_m").alias("b")))


def components(links: DataFrame) -> DataFrame:
    """(node, component) for every node in `links` (columns a, b of one type); component is the smallest node reached.
    Links from a node to itself and repeats are harmless; rows with a null are left out."""
    now = written(links.where("a is not null and b is not null and a <> b").distinct(), "links")
    seen = None
    while True:
        mark = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if mark == seen or not mark[0]:
            break
        seen = mark
        now = written(_small_star(_large_star(now).distinct()).distinct(), "links")
    pairs = now.select(F.greatest("a", "b").alias("node"), F.least("a", "b").alias("component"))
    return pairs.union(pairs.select("component", "component")).distinct()
