"""Accuracy, time and speed-up of estimates."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def relative_error(estimates: DataFrame, truth: DataFrame, zero_truth: str = "null") -> DataFrame:
    """`estimates` (type, estimate, and what else) with truth and rel_error. A true count of zero gives null, is left out ('skip'), or is refused ('error')."""
    if zero_truth not in ("null", "skip", "error"):
        raise ValueError("zero_truth is 'null', 'skip' or 'error'")
    both = truth.select("type", F.col("count").alias("truth")).join(estimates, "type", "left").withColumn("estimate", F.coalesce("estimate", F.lit(0.0)))
    if zero_truth == "skip":
        both = both.where("truth <> 0")
    zero = F.raise_error(F.lit("a true count is zero")).cast("double") if zero_truth == "error" else F.lit(None).cast("double")
    return both.withColumn("rel_error", F.when(F.col("truth") == 0, zero).otherwise(F.abs(F.col("estimate") - F.col("truth")) / F.col("truth")))


def mape(estimates: DataFrame, truth: DataFrame, by: tuple[str, ...] = (), zero_truth: str = "null") -> DataFrame:
    """Mean of the relative errors of the types, for each combination of `by`, and how many types had no count to divide by."""
    return relative_error(estimates, truth, zero_truth).groupBy(*by).agg(F.avg("rel_error").alias("mape"), F.count_if(F.col("rel_error").isNull()).alias("skipped"))


def rate_curve(errors: DataFrame, by: tuple[str, ...] = ("rate",)) -> DataFrame:
    """Mean and spread of MAPE over runs."""
    return errors.groupBy(*by).agg(F.avg("mape").alias("mean_mape"), F.stddev("mape").alias("sd_mape"), F.count(F.lit(1)).alias("runs"))


def box_stats(rows: DataFrame, value: str, by: tuple[str, ...]) -> DataFrame:
    return rows.groupBy(*by).agg(F.avg(value).alias("mean"), F.expr(f"percentile({value}, 0.25)").alias("q1"), F.expr(f"percentile({value}, 0.5)").alias("median"), F.expr(f"percentile({value}, 0.75)").alias("q3"))


def coverage(errors: DataFrame, eps: float, by: tuple[str, ...] = ("rate", "type")) -> DataFrame:
    """Share of runs with an error of at most eps."""
    return errors.groupBy(*by).agg(F.avg((F.col("rel_error") <= eps).cast("double")).alias("covered"), F.count(F.lit(1)).alias("runs"))


def within_limits(runs: DataFrame, most_mape: float = 1.0, most_seconds: float = 10_000.0) -> DataFrame:
    """Runs that a comparison shows: others are left out of the figures."""
    return runs.where((F.col("mape") <= most_mape) & (F.col("seconds") <= most_seconds))


def speedup_at(runs: DataFrame, level: float, ours: str) -> DataFrame:
    """(method, seconds, speedup): the least time of each method at a MAPE of at most `level`, over that of `ours`."""
    best = runs.where(F.col("mape") <= level).groupBy("method").agg(F.min("seconds").alias("seconds"), F.min_by("rate", "seconds").alias("rate"))
    own = best.where(F.col("method") == ours).select(F.col("seconds").alias("_ours"))
    return best.crossJoin(own).select("method", "rate", "seconds", (F.col("seconds") / F.col("_ours")).alias("speedup"))  # one row on the right


def timed(build: Callable[[], DataFrame], repeat: int = 3) -> list[float]:
    """Seconds of each run. The plan is built anew each time: a frame that has run before would reuse its shuffle files."""
    out = []
    for _ in range(repeat):
        began = time.perf_counter()
        build().write.format("noop").mode("overwrite").save()
        out.append(time.perf_counter() - began)
    return out


def stage_costs(spark: SparkSession, after: int = -1) -> dict:
    """What the stages with an id above `after` shuffled and spilled, in MB, the largest execution memory of a task's operators, and the last stage's id. Reads the
    session's own status store, which keeps some 1,000 stages, so ask after each query."""
    gateway, context = spark.sparkContext._gateway, spark.sparkContext._jsc.sc()
    context.listenerBus().waitUntilEmpty()
    held = context.statusStore().stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), gateway.jvm.java.util.ArrayList())
    stages = [x for x in (held.apply(k) for k in range(held.size())) if x.stageId() > after]
    mb = lambda values: round(sum(values) / 1e6, 1)
    return {
        "shuffle_mb": mb(x.shuffleWriteBytes() for x in stages),
        "spill_mb": mb(x.diskBytesSpilled() for x in stages),
        "peak_mb": round(max((x.peakExecutionMemory() for x in stages), default=0) / 1e6, 1),
        "last": max((x.stageId() for x in stages), default=after),
    }
