"""Which plan, which layer's wedges, how wide a bucket."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wingcount.operators.joins import bucket
from wingcount.shared import size_of

HASHED_BYTES = 64 << 20


@dataclass(frozen=True)
class CountPlan:
    plan: str
    center: str
    width: int
    join: str = "merge"


def window_work(edges: DataFrame, tau: int) -> tuple[float, float, float]:
    """Estimated wedges centred in the lower and the upper layer (squares of edges per node and bucket), and how many edges a node pair has in a bucket on average. One
    aggregate over the edges, three numbers back."""
    sides = F.explode(F.array(*(F.struct(F.lit(k).alias("side"), node.alias("node")) for k, node in enumerate((F.col("l"), F.col("u"), F.xxhash64("u", "l"))))))
    cells = edges.select(sides.alias("s"), bucket(F.col("t"), tau).alias("b")).groupBy("s.side", "s.node", "b").agg(F.count(F.lit(1)).cast("double").alias("n"))
    rows = {r["side"]: (r["squares"], r["mean"]) for r in cells.groupBy("side").agg(F.sum(F.col("n") * F.col("n")).alias("squares"), F.avg("n").alias("mean")).collect()}
    return (rows[0][0], rows[1][0], rows[2][1]) if rows else (0.0, 0.0, 1.0)


def choose_center(edges: DataFrame, tau: int) -> str:
    lower, upper, _ = window_work(edges, tau)
    return "lower" if lower <= upper else "upper"


def choose(edges: DataFrame, tau: int, rate: float = 1.0, ties: str = "strict") -> CountPlan:
    """`star` for samples under a fifth of the edges, `factored` where node pairs repeat a lot within a window (it knows the 'strict' rule only), else `wedge_pair`."""
    lower, upper, repeats = window_work(edges, tau)
    plan = "factored" if repeats >= 4 and ties == "strict" else "star" if rate < 0.2 else "wedge_pair"
    # hash tables of a partition's edges and wedges are quick while they are small; sorted runs may spill
    bytes_each = (size_of(edges) + 48 * min(lower, upper)) / int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return CountPlan(plan, "lower" if lower <= upper else "upper", max(1, tau), "shuffle_hash" if bytes_each <= HASHED_BYTES else "merge")
