"""Joins on time that Spark has no strategy for, as equi-joins on buckets of time with the range as a residual."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Blocks that a window's width is cut into, and the most rows of a block.
CUTS, BLOCK = 24, 256


def bucket(t: Column, width: int) -> Column:
    return F.floor(t / F.lit(max(1, width))).cast("long")


def reaching(df: DataFrame, t: str, width: int, name: str = "tb", side: str = "start") -> DataFrame:
    """Rows once for each bucket in which a partner may lie. side 'start': this row's window (t, t + width] touches its bucket and the next;
    side 'partner': this row may be in the window of a start in its bucket or the one before. Explode one side only."""
    own = bucket(F.col(t), width)
    return df.withColumn(name, F.explode(F.array(own, own + (1 if side == "start" else -1))))


def interval_join(left: DataFrame, right: DataFrame, keys: list[str], t: str, width: int, explode: str = "left", prefix: str = "r_", closed_low: bool = False) -> DataFrame:
    """Pairs with equal keys where right's t lies in (t, t + width] of left (with closed_low also at t itself). Columns of `right` get the prefix.
    A row of one side has one bucket, so no pair comes twice."""
    renamed = right.select(*(F.col(c).alias(prefix + c) for c in right.columns))
    if explode == "left":
        a, b = reaching(left, t, width), renamed.withColumn("_tb", bucket(F.col(prefix + t), width))
    else:
        a, b = left.withColumn("tb", bucket(F.col(t), width)), reaching(renamed, prefix + t, width, "_tb", "partner")
    on = [a["tb"] == b["_tb"], *(a[k] == b[prefix + k] for k in keys)]
    after = b[prefix + t] >= a[t] if closed_low else b[prefix + t] > a[t]
    cond = after & (b[prefix + t] <= a[t] + F.lit(width))
    for c in on:
        cond = c & cond
    return a.join(b, cond).drop("tb", "_tb")


def lazily(rows: str) -> Column:
    """An array as it is, by an expression that Spark doesn't compile. Whole-stage code would hold copies of all rows that a pair of blocks makes; with this on the first of two arrays that
    are listed, it holds those of one row of the first."""
    return F.transform(rows, lambda x: x)


def block_join(left: DataFrame, right: DataFrame, keys: list[str], t: str, width: int, prefix: str = "r_") -> DataFrame:
    """The pairs of `interval_join` for long lists of them. Rows with equal keys and near times are packed into blocks, blocks are joined, and pairs are made where they leave the plan: a left
    row with a block's rows, the next left row with the same ones. A file of such rows is as good as one of blocks, as its writer sees the same run again and again."""
    cut = max(1, -(-width // CUTS))
    others = [[c for c in df.columns if c not in keys] for df in (left, right)]

    def blocks(df: DataFrame, columns: list[str]) -> DataFrame:
        place = F.row_number().over(Window.partitionBy(*keys, "_s").orderBy(t))
        parts = df.withColumn("_s", F.expr(f"(`{t}` - pmod(`{t}`, {cut})) div {cut}")).withColumn("_p", F.floor((place - 1) / F.lit(BLOCK)))
        return parts.groupBy(*keys, "_s", "_p").agg(F.collect_list(F.struct(*columns)).alias("_rows"), F.min(t).alias("_low"), F.max(t).alias("_high"))

    own = F.floor(F.col("_s") / F.lit(CUTS))  # a width or more
    a = blocks(left, others[0]).withColumn("_b", F.explode(F.array(own, own + 1)))
    b = blocks(right, others[1]).withColumn("_b", own)
    b = b.select(*(F.col(c).alias(prefix + c) for c in b.columns))
    near = (b[f"{prefix}_high"] > a["_low"]) & (b[f"{prefix}_low"] <= a["_high"] + F.lit(width)) & (a["_b"] == b[f"{prefix}_b"])
    for k in keys:
        near = (a[k] == b[prefix + k]) & near
    both = [*keys, *(prefix + k for k in keys)]
    one = a.join(b, near).select(*both, f"{prefix}_rows", F.inline(lazily("_rows")))
    two = one.select(*both, *others[0], F.inline(f"{prefix}_rows").alias(*(prefix + c for c in others[1])))
    pairs = two.where((F.col(prefix + t) > F.col(t)) & (F.col(prefix + t) <= F.col(t) + F.lit(width)))
    return pairs.select(*left.columns, *(prefix + c for c in right.columns))


def neighbours_within(edges: DataFrame, starts: DataFrame, side: str, tau: int) -> DataFrame:
    """(eid, neighbour, t): for each start edge the nodes of the other layer that its `side` node meets within (t, t + tau]."""
    other = "l" if side == "u" else "u"
    joined = interval_join(starts.select("eid", "t", side), edges.select(side, other, "t"), [side], "t", tau)
    return joined.select("eid", F.col(f"r_{other}").alias("neighbour"), F.col("r_t").alias("t"))


def asof_join(left: DataFrame, right: DataFrame, keys: list[str], t: str, value: str, strict: bool = True) -> DataFrame:
    """Each left row with `value` of the last right row at or before its time (strict: before), by a union and one window instead of a range join."""
    row = F.struct(F.col(t), F.col(value)) if value != t else F.struct(F.col(t))
    cols = left.columns
    a = left.select(F.struct(*cols).alias("_row"), *keys, F.col(t).alias("_t"), F.lit(0 if strict else 1).alias("_side"), F.lit(None).cast(right.select(row.alias("x")).schema["x"].dataType).alias("_hit"))
    b = right.select(F.lit(None).cast(a.schema["_row"].dataType).alias("_row"), *keys, F.col(t).alias("_t"), F.lit(1 if strict else 0).alias("_side"), row.alias("_hit"))
    order = Window.partitionBy(*keys).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn("_last", F.last("_hit", ignorenulls=True).over(order))
    return both.where(F.col("_row").isNotNull()).select("_row.*", F.col(f"_last.{value}").alias(f"last_{value}"))
