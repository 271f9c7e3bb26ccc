"""Instances of the six orders, counted per start edge.

An instance is four edges (ux, lx), a = (uy, lx), b = (ux, ly), c = (uy, ly) with the first edge earliest and the last at most tau after it. All plans find the same
instances:

star         start edges join a, then b, then c; for few start edges
wedge_pair   wedges by their centre, then pairs of wedges with the same ends; for all start edges
factored     repeated edges between two nodes stay sorted arrays, and orders are counted by ranks instead of listed
grouped      within a time bucket in numpy

Where only counts are asked for under 'strict', star, grouped and 'auto' don't list instances, whose number grows with the square of the edges in a window: start edges
join b, and the pairs of a and c are counted by ranks (ranked.py). chrono lists likewise one type edge by edge, and chrono_counts counts it by ranks.

ties='strict' counts no instance with equal times; 'total_order' breaks ties by edge id, and lets the others tie with the first edge.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wingcount.functions.order_types import ORDERS, TRANSPOSED, TYPES, classify
from wingcount.operators.joins import bucket
from wingcount.operators.ranked import ranked
from wingcount.shared import is_settled, settled

COUNTS = [f"c{k}" for k in TYPES]
INSTANCE = ("e1", "e2", "e3", "e4", "ux", "uy", "lx", "ly", "t1", "t2", "t3", "t4", "type", "duration")


def _order(t: str, e: str, ties: str) -> Column:
    if ties not in ("strict", "total_order"):
        raise ValueError(f"ties is 'strict' or 'total_order', not {ties!r}")
    return F.col(t) if ties == "strict" else F.struct(F.col(t), F.col(e))


def _after(t: str, e: str, tau: int, ties: str) -> Column:
    return (_order(t, e, ties) > _order("t1", "e1", ties)) & (F.col(t) <= F.col("t1") + F.lit(tau))


def _as(edges: DataFrame, k: int, reach: int | None = None) -> DataFrame:
    """Edges renamed to e<k>, p<k>, q<k>, t<k> with bucket b<k>; with `reach` once for each bucket whose starts may reach them."""
    out = edges.select(F.col("eid").alias(f"e{k}"), F.col("u").alias(f"p{k}"), F.col("l").alias(f"q{k}"), F.col("t").alias(f"t{k}"))
    own = bucket(F.col(f"t{k}"), reach) if reach else None
    return out if own is None else out.withColumn(f"b{k}", F.explode(F.array(own, own - 1)))


def _starts(starts: DataFrame, width: int) -> DataFrame:
    return starts.select(F.col("eid").alias("e1"), F.col("u").alias("ux"), F.col("l").alias("lx"), F.col("t").alias("t1"), bucket(F.col("t"), width).alias("tb"))


def _named(rows: DataFrame, ties: str) -> DataFrame:
    kind = classify(*(_order(f"t{k}", f"e{k}", ties) for k in (2, 3, 4)))
    return rows.withColumn("type", kind).where(F.col("type").isNotNull()).withColumn("duration", F.greatest("t2", "t3", "t4") - F.col("t1")).select(*INSTANCE)


def star(edges: DataFrame, starts: DataFrame, tau: int, ties: str = "strict", width: int | None = None) -> DataFrame:
    """All instances that begin with one of `starts`."""
    width = max(1, width or tau)
    if width < tau:
        raise ValueError("a bucket is at least as wide as tau")
    two, three, four = (_as(edges, k, width) for k in (2, 3, 4))
    one = _starts(starts, width)
    x = one.join(two, (one.tb == two.b2) & (one.lx == two.q2) & (one.ux != two.p2) & _after("t2", "e2", tau, ties)).withColumn("uy", F.col("p2")).drop("b2", "p2", "q2")
    x = x.join(three, (x.tb == three.b3) & (x.ux == three.p3) & (x.lx != three.q3) & _after("t3", "e3", tau, ties)).withColumn("ly", F.col("q3")).drop("b3", "p3", "q3")
    x = x.join(four, (x.tb == four.b4) & (x.uy == four.p4) & (x.ly == four.q4) & _after("t4", "e4", tau, ties))
    return _named(x, ties)


def wedges(edges: DataFrame, tau: int, ties: str = "strict", width: int | None = None, join: str | None = None) -> DataFrame:
    """Pairs of edges with one lower node and two upper ones within tau, the earlier first: e1, e2, ua, ub, center, t1, t2."""
    width = max(1, width or tau)
    one, two = _starts(edges, width), _as(edges, 2, width)
    two = two.hint(join) if join else two
    x = one.join(two, (one.tb == two.b2) & (one.lx == two.q2) & (one.ux != two.p2) & _after("t2", "e2", tau, ties))
    return x.select("e1", "e2", F.col("ux").alias("ua"), F.col("p2").alias("ub"), F.col("lx").alias("center"), "t1", "t2")


def wedge_pair(edges: DataFrame, starts: DataFrame, tau: int, ties: str = "strict", width: int | None = None, join: str | None = None) -> DataFrame:
    """All instances that begin with one of `starts`: a wedge that holds the first edge, and a later one with the same ends. `join` is a hint for its joins."""
    width = max(1, width or tau)
    hinted = lambda df: df.hint(join) if join else df
    one, two = _starts(starts, width), hinted(_as(edges, 2, width))
    x = one.join(two, (one.tb == two.b2) & (one.lx == two.q2) & (one.ux != two.p2) & _after("t2", "e2", tau, ties))
    x = x.select("e1", "e2", "ux", F.col("p2").alias("uy"), "lx", "t1", "t2", "tb", F.least("ux", "p2").alias("lo"), F.greatest("ux", "p2").alias("hi"))
    w = wedges(edges, tau, ties, width, join)
    first = bucket(F.col("t1"), width)
    y = w.select(
        F.least("ua", "ub").alias("ylo"), F.greatest("ua", "ub").alias("yhi"), F.col("center").alias("ly"), (F.col("ua") < F.col("ub")).alias("up"),
        F.col("e1").alias("ea"), F.col("e2").alias("eb"), F.col("t1").alias("ta"), F.col("t2").alias("tz"), F.explode(F.array(first, first - 1)).alias("yb"),
    )
    late = (_order("ta", "ea", ties) > _order("t1", "e1", ties)) & (F.col("tz") <= F.col("t1") + F.lit(tau))
    y = hinted(y)
    z = x.join(y, (x.lo == y.ylo) & (x.hi == y.yhi) & (x.tb == y.yb) & (x.lx != y.ly) & late)
    mine = F.col("up") == (F.col("ux") < F.col("uy"))  # the later wedge's first leg is ux's
    for k, leg, time in ((3, ("ea", "eb"), ("ta", "tz")), (4, ("eb", "ea"), ("tz", "ta"))):
        z = z.withColumns({f"e{k}": F.when(mine, F.col(leg[0])).otherwise(F.col(leg[1])), f"t{k}": F.when(mine, F.col(time[0])).otherwise(F.col(time[1]))})
    return _named(z, ties)


def six(rows: DataFrame, *by: str, weight: Column | None = None) -> DataFrame:
    """c1..c6 of instances, for each combination of `by`."""
    counts = [F.count_if(F.col("type") == k).alias(f"c{k}") for k in TYPES] if weight is None else [F.coalesce(F.sum(F.when(F.col("type") == k, weight)), F.lit(0)).alias(f"c{k}") for k in TYPES]
    return rows.groupBy(*by).agg(*counts)


def factored(edges: DataFrame, starts: DataFrame, tau: int, width: int | None = None) -> DataFrame:
    """(eid, c1..c6) under 'strict' without listing instances: the times of each pair of nodes are a sorted array, and for each start, uy and ly the orders are
    counted from how many times of one array lie before or after each time of another."""
    width = max(1, width or tau)
    own = bucket(F.col("t"), width)
    cells = edges.select("u", "l", "t", F.explode(F.array(own, own - 1)).alias("b")).groupBy("u", "l", "b").agg(F.array_sort(F.collect_list("t")).alias("ts"))
    one = _starts(starts, width)

    def window(c: str) -> Column:
        return F.filter(c, lambda t: (t > F.col("t1")) & (t <= F.col("t1") + F.lit(tau)))

    def cell(k: str) -> DataFrame:
        return cells.select(F.col("u").alias(f"u{k}"), F.col("l").alias(f"l{k}"), F.col("b").alias(f"b{k}"), F.col("ts").alias(f"ts{k}"))

    a, b, c = cell("a"), cell("b"), cell("c")
    x = one.join(a, (one.tb == a.ba) & (one.lx == a.la) & (one.ux != a.ua)).withColumn("a", window("tsa")).where(F.size("a") > 0).select("e1", "ux", "lx", "t1", "tb", F.col("ua").alias("uy"), "a")
    x = x.join(b, (x.tb == b.bb) & (x.ux == b.ub) & (x.lx != b.lb)).withColumn("b", window("tsb")).where(F.size("b") > 0).select("e1", "t1", "tb", "uy", F.col("lb").alias("ly"), "a", "b")
    x = x.join(c, (x.tb == c.bc) & (x.uy == c.uc) & (x.ly == c.lc)).withColumn("c", window("tsc")).where(F.size("c") > 0)

    def orders(order: str) -> Column:
        first, middle, last = order
        below = lambda m: F.size(F.filter(first, lambda t: t < m)).cast("long")
        above = lambda m: F.size(F.filter(last, lambda t: t > m)).cast("long")
        return F.aggregate(middle, F.lit(0).cast("long"), lambda acc, m: acc + below(m) * above(m))

    counted = x.select("e1", *(orders(o).alias(f"c{k}") for k, o in ORDERS.items()))
    return counted.groupBy(F.col("e1").alias("eid")).agg(*(F.sum(c).alias(c) for c in COUNTS))


def grouped(edges: DataFrame, starts: DataFrame, tau: int, width: int | None = None) -> DataFrame:
    """(eid, c1..c6) under 'strict', counted by ranks within a bucket and the next one in numpy."""
    return ranked(edges, starts, tau, width=width).select("eid", *COUNTS)


def brute_force(edges: DataFrame, tau: int, ties: str = "strict", most: int = 300, cell: Column | None = None) -> DataFrame:
    """All sequences of four edges, for tiny graphs; refuses more than `most` edges. With `cell`, each cell is a graph of its own."""
    cell = F.lit(0) if cell is None else cell
    if (n := edges.groupBy(cell.alias("cell")).count().agg(F.max("count")).first()[0] or 0) > most:
        raise ValueError(f"brute force over {n} edges is refused")
    parts = [_as(edges.withColumn("eid", F.struct("eid", cell.alias("cell"))), k) for k in (1, 2, 3, 4)]
    parts = [x.select(F.col(f"e{k}.eid").alias(f"e{k}"), F.col(f"e{k}.cell").alias("cell"), f"p{k}", f"q{k}", f"t{k}") for k, x in enumerate(parts, 1)]
    x = parts[0].select("e1", "cell", F.col("p1").alias("ux"), F.col("q1").alias("lx"), "t1")
    for part in parts[1:]:
        x = x.join(part, "cell")
    shape = "p2 <> ux and q2 = lx and p3 = ux and q3 <> lx and p4 = p2 and q4 = q3"
    x = x.where(shape).where(_after("t2", "e2", tau, ties) & _after("t3", "e3", tau, ties) & _after("t4", "e4", tau, ties))
    return _named(x.withColumns({"uy": F.col("p2"), "ly": F.col("q3")}), ties)


PLANS = {"star": star, "wedge_pair": wedge_pair}


def transposed_edges(edges: DataFrame) -> DataFrame:
    return edges.select("eid", F.col("l").alias("u"), F.col("u").alias("l"), "t")


def list_instances(edges: DataFrame, tau: int, starts: DataFrame | None = None, plan: str = "auto", center: str = "lower", ties: str = "strict", types: tuple[int, ...] | None = None, join: str | None = None) -> DataFrame:
    """Rows of instances: edge ids, nodes, times, type and duration. center='upper' finds them from the other layer's wedges."""
    if center == "auto":
        from wingcount.plans.planner import choose_center

        center = choose_center(edges, tau)
    plan = ("wedge_pair" if starts is None else "star") if plan == "auto" else plan
    own = edges if center == "lower" else transposed_edges(edges)
    first = own if starts is None else (starts.select("eid", "u", "l", "t") if center == "lower" else transposed_edges(starts))
    out = wedge_pair(own, first, tau, ties, join=join) if plan == "wedge_pair" else PLANS[plan](own, first, tau, ties)
    if center == "upper":
        swap = F.create_map(*(F.lit(x) for pair in TRANSPOSED.items() for x in pair))
        names = {"ux": "lx", "lx": "ux", "uy": "ly", "ly": "uy", "e2": "e3", "e3": "e2", "t2": "t3", "t3": "t2"}
        out = out.select(*(F.col(names.get(c, c)).alias(c) if c != "type" else F.element_at(swap, F.col("type")).alias("type") for c in INSTANCE))
    return out if types is None else out.where(F.col("type").isin(*types))


def per_edge_counts(edges: DataFrame, starts: DataFrame, tau: int, plan: str = "star", ties: str = "strict") -> DataFrame:
    """(eid, c1..c6) of the start edges that begin an instance."""
    if plan == "star" and ties == "strict":
        whole, edges = starts is edges, settled(edges, "edges")
        return ranked(edges, edges if whole else starts, tau).select("eid", *COUNTS)
    if plan in ("factored", "grouped"):
        if ties != "strict":
            raise ValueError(f"{plan} counts under 'strict' alone")
        return (factored if plan == "factored" else grouped)(edges, starts, tau)
    return six(list_instances(edges, tau, starts, plan, ties=ties), F.col("e1").alias("eid"))


def long_form(wide: DataFrame, value: str = "count") -> DataFrame:
    """(type, value) from one row of c1..c6."""
    pairs = ", ".join(f"{k}, c{k}" for k in TYPES)
    return wide.selectExpr(f"stack(6, {pairs}) as (type, {value})")


def added(parts: DataFrame, *by: str) -> DataFrame:
    """c1..c6 from parts of them."""
    return parts.groupBy(*by).agg(*(F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in COUNTS))


def exact_count(edges: DataFrame, tau: int, plan: str = "auto", center: str = "auto", ties: str = "strict") -> DataFrame:
    """(type, count), six rows also where nothing is found. What is left open is chosen by the work that a first look at the edges foretells; edges that are more than a
    plain scan are written once, as the plans read them several times ('strict' needs no ids). 'auto' counts by ranks under 'strict'."""
    join = None
    if ties == "strict" and plan in ("auto", "star", "grouped"):
        edges = edges if is_settled(edges) else settled(edges.select("u", "l", "t"), "edges")
        return long_form(added(ranked(edges, edges, tau, center, totals=True)))
    if "auto" in (plan, center):
        from wingcount.plans.planner import choose

        edges = settled(edges.select(F.lit(0).cast("long").alias("eid"), "u", "l", "t") if ties == "strict" else edges, "edges")
        chosen = choose(edges, tau, ties=ties)
        plan, center, join = chosen.plan if plan == "auto" else plan, chosen.center if center == "auto" else center, chosen.join
    if plan in ("factored", "grouped"):
        own = edges if center == "lower" else transposed_edges(edges)
        per = per_edge_counts(own, own, tau, plan, ties)
        name = {k: f"c{k if center == 'lower' else TRANSPOSED[k]}" for k in TYPES}
        return long_form(per.agg(*(F.coalesce(F.sum(name[k]), F.lit(0)).alias(f"c{k}") for k in TYPES)))
    return long_form(six(list_instances(edges, tau, None, plan, center, ties, join=join)))


def chrono(edges: DataFrame, starts: DataFrame, tau: int, kind: int, ties: str = "strict", width: int | None = None) -> DataFrame:
    """Instances of one type, matched edge by edge in the order of time. For the types whose second edge touches neither node of the first, that step joins on
    time alone, which is what makes them slow."""
    width = max(1, width or tau)
    x, last = _starts(starts, width), ("t1", "e1")
    known_uy = known_ly = False
    place = {"a": 2, "b": 3, "c": 4}
    for step in ORDERS[kind]:
        k = place[step]
        e = _as(edges, k, width)
        cond = (x.tb == e[f"b{k}"]) & (_order(f"t{k}", f"e{k}", ties) > _order(*last, ties)) & (F.col(f"t{k}") <= F.col("t1") + F.lit(tau))
        p, q = F.col(f"p{k}"), F.col(f"q{k}")
        upper = p == F.col("ux") if step == "b" else p == F.col("uy") if known_uy else p != F.col("ux")
        lower = q == F.col("lx") if step == "a" else q == F.col("ly") if known_ly else q != F.col("lx")
        x = x.join(e, cond & upper & lower)
        if step in "ac" and not known_uy:
            x, known_uy = x.withColumn("uy", F.col(f"p{k}")), True
        if step in "bc" and not known_ly:
            x, known_ly = x.withColumn("ly", F.col(f"q{k}")), True
        x, last = x.drop(f"b{k}", f"p{k}", f"q{k}"), (f"t{k}", f"e{k}")
    return x.select(*(F.lit(kind).alias("type") if c == "type" else (F.col(last[0]) - F.col("t1")).alias("duration") if c == "duration" else F.col(c) for c in INSTANCE))


def chrono_counts(edges: DataFrame, starts: DataFrame, tau: int, kind: int, ties: str = "strict") -> DataFrame:
    """(eid, count) for one type."""
    if ties == "strict":
        whole, edges = starts is edges, settled(edges, "edges")
        return ranked(edges, edges if whole else starts, tau, kinds=(kind,)).select("eid", F.col(f"c{kind}").alias("count")).where("count > 0")
    return chrono(edges, starts, tau, kind, ties).groupBy(F.col("e1").alias("eid")).agg(F.count(F.lit(1)).alias("count"))


def six_passes(edges: DataFrame, starts: DataFrame, tau: int, ties: str = "strict") -> DataFrame:
    """(eid, c1..c6) of the start edges that begin an instance, by a run for each type."""
    edges, out = settled(edges, "edges"), None
    for kind in TYPES:
        one = chrono_counts(edges, starts, tau, kind, ties).select("eid", *((F.col("count") if k == kind else F.lit(0).cast("long")).alias(f"c{k}") for k in TYPES))
        out = one if out is None else out.union(one)
    return added(out, "eid")


def chrono_all(edges: DataFrame, starts: DataFrame, tau: int, ties: str = "strict") -> DataFrame:
    """Instances of all types by six separate runs."""
    out = None
    for kind in TYPES:
        one = chrono(edges, starts, tau, kind, ties)
        out = one if out is None else out.union(one)
    return out
