"""The graph without times: distinct pairs, wedges, and exact butterfly counts."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wingcount.operators.joins import BLOCK, lazily
from wingcount.shared import settled

#: Parts of one pair of nodes in the join that lists butterflies, and stretches that its centres are cut into to be numbered.
SALTS, STRETCHES = 16, 16


def static_edges(edges: DataFrame) -> DataFrame:
    """(u, l, multiplicity)."""
    return edges.groupBy("u", "l").agg(F.count(F.lit(1)).alias("multiplicity"))


def static_wedges(edges: DataFrame) -> DataFrame:
    """(u_lo, u_hi, l): pairs of upper nodes with a common lower node."""
    pairs = static_edges(edges).select("u", "l")
    a, b = pairs.select(F.col("u").alias("u_lo"), "l"), pairs.select(F.col("u").alias("u_hi"), F.col("l").alias("l2"))
    return a.join(b, (a.l == b.l2) & (a.u_lo < b.u_hi)).select("u_lo", "u_hi", "l")


def static_butterflies(edges: DataFrame) -> DataFrame:
    """(u_lo, u_hi, l_lo, l_hi), a row for each: pairs of the wedges with the same ends. Wedges are centred in the layer with fewer of them and only these are shuffled, as blocks of the centres
    that a pair of ends has; the rows, which grow with the square of a pair's wedges, are made where they leave the join: a centre with a block's centres, the next centre with the same, so
    files hold such runs in little space. Blocks follow each other, so each two are joined once. A pair of many blocks has them dealt to SALTS parts, so it spreads over tasks."""
    pairs = settled(static_edges(edges).select("u", "l"), "pairs")
    work = _pair_work(pairs)
    own, other = ("u", "l") if work["upper"] < work["lower"] else ("l", "u")  # the centre, and the ends
    x, y = pairs.select(own, F.col(other).alias("lo")), pairs.select(F.col(own).alias("c2"), F.col(other).alias("hi"))
    w = settled(x.join(y, (x[own] == y.c2) & (x.lo < y.hi)).select("lo", "hi", F.col(own).alias("c")), "wedges")
    b = settled(_blocks(w), "blocks")
    n = int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # by bytes alone these few blocks would be one task's
    one = b.select("lo", "hi", F.col("cs").alias("one"), F.col("low").alias("from"), F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part")).repartition(n, "lo", "hi", "part")
    two = b.select(F.col("lo").alias("x"), F.col("hi").alias("y"), F.col("cs").alias("two"), "low", F.pmod("k", "parts").alias("own")).repartition(n, "x", "y", "own")
    both = one.join(two.hint("merge"), (one.lo == two.x) & (one.hi == two.y) & (one.part == two.own) & (one["from"] <= two.low))
    found = both.select("lo", "hi", "two", F.explode(lazily("one")).alias("c_lo")).select("lo", "hi", "c_lo", F.explode("two").alias("c_hi")).where(F.col("c_lo") < F.col("c_hi"))
    ends, centres = ("l", "u") if own == "u" else ("u", "l")
    named = {f"{ends}_lo": "lo", f"{ends}_hi": "hi", f"{centres}_lo": "c_lo", f"{centres}_hi": "c_hi"}
    return found.select(*(F.col(named[c]).alias(c) for c in ("u_lo", "u_hi", "l_lo", "l_hi")))


def _blocks(wedges: DataFrame) -> DataFrame:
    """(lo, hi, cs, low, k, parts): the centres of each pair of ends in ascending blocks of at most BLOCK, their number, and the parts that the pair's blocks are dealt to."""
    cuts = wedges.agg(F.percentile_approx("c", [k / STRETCHES for k in range(1, STRETCHES)])).first()[0] or []
    stretch = sum(((F.col("c") > F.lit(x)).cast("int") for x in sorted(set(cuts))), F.lit(0))
    place = F.row_number().over(Window.partitionBy("lo", "hi", "stretch").orderBy("c"))
    rows = wedges.withColumn("stretch", stretch).withColumn("p", F.floor((place - 1) / F.lit(BLOCK)))
    found = rows.groupBy("lo", "hi", "stretch", "p").agg(F.collect_list("c").alias("cs"), F.min("c").alias("low"))
    of = Window.partitionBy("lo", "hi")
    return found.select("lo", "hi", "cs", "low", F.row_number().over(of.orderBy("low")).alias("k"), F.least(F.lit(SALTS), F.count(F.lit(1)).over(of).cast("int")).alias("parts"))


def _pair_work(pairs: DataFrame) -> dict[str, float]:
    """Squares of the degrees of the lower and the upper nodes."""
    return {k: pairs.groupBy(c).agg(F.count(F.lit(1)).cast("double").alias("d")).agg(F.sum(F.col("d") * F.col("d"))).first()[0] or 0 for k, c in (("lower", "l"), ("upper", "u"))}


def static_exact(edges: DataFrame, method: str = "pair", layer: str = "auto") -> DataFrame:
    """One row, butterflies. 'pair' counts common neighbours of pairs of one layer (wedges centred in `layer`, 'auto': the one with
    fewer of them by the squares of its degrees); 'priority' charges each butterfly to its node of
    highest degree, so a hub is never the centre of its wedges."""
    edges = settled(static_edges(edges), "pairs")
    if method == "pair":
        if layer == "auto":
            work = _pair_work(edges)
            layer = min(work, key=work.get)
        own = edges if layer == "lower" else edges.select(F.col("l").alias("u"), F.col("u").alias("l"))
        common = static_wedges(own).groupBy("u_lo", "u_hi").agg(F.count(F.lit(1)).alias("n"))
        return common.agg(F.coalesce(F.sum(F.col("n") * (F.col("n") - 1) / 2).cast("long"), F.lit(0)).alias("butterflies"))
    if method != "priority":
        raise ValueError("method is 'pair' or 'priority'")
    pairs = static_edges(edges).select(F.concat(F.lit("u"), "u").alias("u"), F.concat(F.lit("l"), "l").alias("l"))
    both = pairs.select(F.col("u").alias("a"), F.col("l").alias("b")).union(pairs.select(F.col("l").alias("a"), F.col("u").alias("b")))
    rank = both.groupBy("a").agg(F.count(F.lit(1)).alias("d")).select("a", F.struct("d", "a").alias("rank"))
    ranked = both.join(rank.withColumnRenamed("rank", "ra"), "a").join(rank.select(F.col("a").alias("b"), F.col("rank").alias("rb")), "b")
    down = ranked.where(F.col("ra") > F.col("rb")).select(F.col("a").alias("top"), F.col("ra").alias("r_top"), F.col("b").alias("mid"))
    onward = ranked.select(F.col("a").alias("mid"), F.col("b").alias("end"), F.col("rb").alias("r_end"))
    w = down.join(onward, "mid").where(F.col("r_top") > F.col("r_end")).groupBy("top", "end").agg(F.count(F.lit(1)).alias("n"))
    return w.agg(F.coalesce(F.sum(F.col("n") * (F.col("n") - 1) / 2).cast("long"), F.lit(0)).alias("butterflies"))
