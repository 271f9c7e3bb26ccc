"""Queries of the butterfly engine by name, each with the SQL that must give the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from wingcount import workloads
from wingcount.functions import bounds, metrics
from wingcount.functions.hashing import u01, u01_sql
from wingcount.functions.order_types import ORDERS, TYPES, classify_sql
from wingcount.operators import baselines, counting, estimators, sampling, static_graph, stats, timeline
from wingcount.operators.joins import asof_join, block_join, bucket, interval_join
from wingcount.shared import settled
from wingcount.sources.edges import DAY, HOUR, from_df, load, toy, view, view_sql
from wingcount.sqlapi import instances_sql, register, six_sql

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

#: Durations by graph, in the unit of its time: microseconds for events, days for the others.
TAU = {"euk": 72 * HOUR, "eut": 6 * HOUR, "lsp": 90, "ocp": 365, "ocs": 90}
RATES = [0.00125 * 2**k for k in range(10)]
SEEDS = list(range(10))
E, S, J = view_sql("euk"), instances_sql(view_sql("euk"), TAU["euk"]), TAU["euk"]


def add(name: str, run: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        ORACLES[name] = sql


def euk(spark: SparkSession, d: str) -> DataFrame:
    return view(spark, d, "euk")


def flagship(spark: SparkSession, d: str) -> DataFrame:
    return estimators.estimate(euk(spark, d), J, sampling.EdgeSampler(0.3, seed=1))


def rounded(df: DataFrame, *columns: str, digits: int = 6) -> DataFrame:
    return df.withColumns({c: F.round(c, digits) for c in columns})


# Exact counts, plans, tie rules, layers

for _name, _tau in TAU.items():
    add(f"edges_{_name}", lambda s, d, n=_name: view(s, d, n), view_sql(_name))
    add(f"exact_{_name}", lambda s, d, n=_name, t=_tau: counting.exact_count(view(s, d, n), t), f"{instances_sql(view_sql(_name), _tau)} {six_sql()}")
add("exact_toy", lambda s, d: counting.exact_count(toy(s), 10), "select * from (values (1, 0::bigint), (2, 2), (3, 1), (4, 0), (5, 1), (6, 0)) x(type, count)")
add("exact_ocp_total_order", lambda s, d: counting.exact_count(view(s, d, "ocp"), 365, ties="total_order"), f"{instances_sql(view_sql('ocp'), 365, 'total_order')} {six_sql()}")
add("exact_transposed", lambda s, d: counting.exact_count(euk(s, d), J, center="upper"), f"{S} {six_sql()}")
for _plan in ("star", "wedge_pair", "factored", "grouped"):
    add(f"exact_plan_{_plan}", lambda s, d, p=_plan: counting.exact_count(view(s, d, "eut"), TAU["eut"], plan=p), f"{instances_sql(view_sql('eut'), TAU['eut'])} {six_sql()}")
# four-fold products are for tiny graphs: the event graph of each ten users and two days is one
_TINY = 2 * DAY
add(
    "brute_force", lambda s, d: counting.long_form(counting.six(counting.brute_force(view(s, d, "eut"), TAU["eut"], cell=F.struct(bucket(F.col("u"), 10), bucket(F.col("t"), _TINY))))),
    f"{instances_sql(view_sql('eut'), TAU['eut'], starts=f'e1.u // 10 = e2.u // 10 and e1.t // {_TINY} = greatest(e2.t, e3.t, e4.t) // {_TINY}')} {six_sql()}",
)
_COLS = ", ".join(f"count(*) filter (type = {k}) as c{k}" for k in TYPES)
add("per_edge_counts", lambda s, d: counting.per_edge_counts(euk(s, d), euk(s, d), J), f"{S} select e1 as eid, {_COLS} from inst group by e1")
add("per_node_counts", lambda s, d: counting.six(counting.list_instances(euk(s, d), J), F.col("ux").alias("u")), f"{S} select ux as u, {_COLS} from inst group by ux")
_INST = "e1, e2, e3, e4, ux, uy, lx, ly, t1, t2, t3, t4, type::int as type, duration"
add("list_instances", lambda s, d: counting.list_instances(euk(s, d), J), f"{S} select {_INST} from inst")
add("wedges", lambda s, d: counting.wedges(euk(s, d), J), f"with e as ({E}) select a.eid as e1, b.eid as e2, a.u as ua, b.u as ub, a.l as center, a.t as t1, b.t as t2 from e a join e b on a.l = b.l and a.u <> b.u and b.t > a.t and b.t <= a.t + {J}")
for _k in TYPES:
    add(f"chrono_type_{_k}", lambda s, d, k=_k: counting.chrono_counts(edges := view(s, d, "eut"), edges, TAU["eut"], k), f"{instances_sql(view_sql('eut'), TAU['eut'])} select e1 as eid, count(*) as count from inst where type = {_k} group by e1")

# Samples and estimates

_edge = u01_sql(7, "eid")
add("edge_sample", lambda s, d: sampling.EdgeSampler(0.3, 7).draw(euk(s, d)), f"select eid, u, l, t, 1::bigint as copies, 1 / 0.3::double as weight from ({E}) where {_edge} < 0.3")
add("node_sample_upper", lambda s, d: sampling.NodeSampler(0.3, "upper", 7).draw(euk(s, d)), f"select eid, u, l, t, 1::bigint as copies, 1 / 0.3::double as weight from ({E}) where {u01_sql(7, 'u')} < 0.3")
add("node_sample_relational", lambda s, d: sampling.NodeSampler(0.3, "lower", 7, relational=True).draw(euk(s, d)), f"select eid, u, l, t, 1::bigint as copies, 1 / 0.3::double as weight from ({E}) where {u01_sql(7, 'l')} < 0.3")


def _estimated(name: str, sampler, condition: str, p: float) -> None:
    add(name, lambda s, d: rounded(estimators.estimate(euk(s, d), J, sampler), "estimate"), f"{instances_sql(E, J, starts=condition)} select type, round(count / {p}::double, 6) as estimate from ({six_sql()})")


_estimated("edge_estimate", sampling.EdgeSampler(0.3, 7), u01_sql(7, "e1.eid") + " < 0.3", 0.3)
_estimated("node_estimate_upper", sampling.NodeSampler(0.3, "upper", 7), u01_sql(7, "e1.u") + " < 0.3", 0.3)
_estimated("node_estimate_lower", sampling.NodeSampler(0.3, "lower", 7), u01_sql(7, "e1.l") + " < 0.3", 0.3)

_LEN = J // 10
_DRAWS = f"""m as (select count(*) as m from e), ranked as (select *, row_number() over (order by t, eid) - 1 as rank from e),
  draws as (select j, r.eid, r.t from (select j, floor({u01_sql(7, "j")} * m)::bigint as rank from range(0, 500) x(j), m) p join ranked r using (rank)),
  prime as (select a.eid, count(*) as m_prime from e a join e b on b.t between a.t - {_LEN} and a.t group by a.eid),
  hits as (select e.eid, count(*) as copies from e join draws d on e.t between d.t and d.t + {_LEN} group by e.eid)"""
_folded, _literal = (sampling.IntervalSampler(draws=500, c=0.1, seed=7, mode=x) for x in ("folded", "literal"))
add("trailing_count", lambda s, d: timeline.trailing_count(euk(s, d), _LEN), f"with e as ({E}) select a.eid, count(*) as m_prime from e a join e b on b.t between a.t - {_LEN} and a.t group by a.eid")
add("interval_draws", lambda s, d: _folded.drawn(euk(s, d), J), f"with e as ({E}), {_DRAWS} select j as draw, eid, t from draws")
add("interval_draws_once", lambda s, d: sampling.IntervalSampler(draws=500, c=0.1, seed=7, replace=False).drawn(euk(s, d), J), f"select eid as draw, eid, t from ({E}) order by {u01_sql(7, 'eid')}, eid limit 500")
add("interval_copies", lambda s, d: rounded(_folded.draw(euk(s, d), J), "weight"), f"with e as ({E}), {_DRAWS} select e.*, copies, round(m / (500.0::double * m_prime), 6) as weight from e join hits using (eid) join prime using (eid), m")
add("interval_sample_literal", lambda s, d: rounded(_literal.draw(euk(s, d), J), "weight"), f"with e as ({E}), {_DRAWS} select e.eid, e.u, e.l, e.t, 1::bigint as copies, round(m / (500.0::double * m_prime), 6) as weight from e join draws d on e.t between d.t and d.t + {_LEN} join prime on prime.eid = e.eid, m")
_ISQL = f"{S}, {_DRAWS} select type, round(estimate, 4) as estimate from ({six_sql('(select type, copies, m_prime, m from inst join hits on hits.eid = e1 join prime on prime.eid = e1, m)', 'sum(copies * m / (500.0::double * m_prime))', 'estimate', 'double')})"
for _name, _sampler in (("interval_estimate", _folded), ("interval_estimate_literal", _literal)):
    add(_name, lambda s, d, x=_sampler: rounded(estimators.estimate(euk(s, d), J, x), "estimate", digits=4), _ISQL)



def repeated(s: SparkSession, d: str) -> DataFrame:
    """The event graph by days and without ids: edges repeat, and each repetition has an id of its own."""
    return from_df(view(s, d, "eut").select("u", "l", F.floor(F.col("t") / DAY).alias("t")), "u", "l", "t")


_REPEATED = f"select u, l, t, count(*) as n from (select u, l, t // {DAY} as t from ({view_sql('eut')})) group by all"
add("edges_repeated", lambda s, d: repeated(s, d).groupBy("u", "l", "t").agg(F.countDistinct("eid").alias("n")), _REPEATED)
add("trailing_repeated", lambda s, d: timeline.trailing_count(repeated(s, d), 2).groupBy("m_prime").agg(F.count(F.lit(1)).alias("edges")), f"with g as ({_REPEATED}), t as (select t, sum(n) as n from g group by t) select m_prime, sum(n)::bigint as edges from (select a.n, (select sum(b.n) from t b where b.t between a.t - 2 and a.t)::bigint as m_prime from t a) group by m_prime")

# Baselines

_STATIC = "p as (select distinct u, l from e)"
_FOUR = "(select type, unnest([{ux: ux, ly: lx}, {ux: uy, ly: lx}, {ux: ux, ly: ly}, {ux: uy, ly: ly}]) as q from inst)"
add("static_edges", lambda s, d: static_graph.static_edges(euk(s, d)), f"select u, l, count(*) as multiplicity from ({E}) group by u, l")
add("static_wedges", lambda s, d: static_graph.static_wedges(view(s, d, "eut")), f"with e as ({view_sql('eut')}), {_STATIC} select a.u as u_lo, b.u as u_hi, a.l from p a join p b on a.l = b.l and a.u < b.u")
_BUTTERFLIES = f"with e as ({E}), {_STATIC}, w as (select a.u as x, b.u as y, count(*) as n from p a join p b on a.l = b.l and a.u < b.u group by all) select coalesce(sum(n * (n - 1) // 2), 0)::bigint as butterflies from w"
for _method in ("pair", "priority"):
    add(f"static_exact_{_method}", lambda s, d, m=_method: static_graph.static_exact(euk(s, d), m), _BUTTERFLIES)
add("static_butterflies", lambda s, d: static_graph.static_butterflies(view(s, d, "eut")), f"with e as ({view_sql('eut')}), {_STATIC}, w as (select a.u as x, b.u as y, a.l from p a join p b on a.l = b.l and a.u < b.u) select a.x as u_lo, a.y as u_hi, a.l as l_lo, b.l as l_hi from w a join w b on a.x = b.x and a.y = b.y and a.l < b.l")
_EUT, _ETAU = view_sql("eut"), TAU["eut"]
_TOP = f"{instances_sql(_EUT, _ETAU)}, {_STATIC}, four as {_FOUR}"
add(
    "static_quad_estimate", lambda s, d: rounded(baselines.StaticQuadEstimator(20, 7).estimate(view(s, d, "eut"), _ETAU), "estimate"),
    f"{_TOP}, n as (select count(*) as n from p), pr as (select *, row_number() over (order by u, l) - 1 as rank from p), dr as (select u, l, count(*) as w from (select floor({u01_sql(7, 'j')} * n)::bigint as rank from range(0, 20) x(j), n) join pr using (rank) group by u, l) "
    f"select type, round(estimate, 6) as estimate from ({six_sql('(select type, w, n from four join dr on q.ux = dr.u and q.ly = dr.l, n)', 'sum(w) * max(n) / 80.0::double', 'estimate', 'double')})",
)
add(
    "static_topology_estimate", lambda s, d: rounded(baselines.StaticTopologyEstimator(0.05, seed=7).estimate(view(s, d, "eut"), _ETAU), "estimate"),
    f"{_TOP}, dr as (select u, l from p where {u01_sql(7, 'u', 'l')} < 0.05) select type, round(estimate, 6) as estimate from ({six_sql('(select type from four join dr on q.ux = dr.u and q.ly = dr.l)', 'count(*) / (4 * 0.05::double)', 'estimate', 'double')})",
)
add(
    "static_topology_multiplicity", lambda s, d: rounded(baselines.StaticTopologyEstimator(0.05, "multiplicity", 7).estimate(view(s, d, "eut"), _ETAU), "estimate", digits=4),
    f"{_TOP}, pm as (select u, l, count(*) as k from e group by u, l), pp as (select u, l, least(1.0::double, k * (0.05::double / (select avg(k) from pm))) as pr from pm), dr as (select * from pp where {u01_sql(7, 'u', 'l')} < pr) select type, round(estimate, 4) as estimate from ({six_sql('(select type, pr from four join dr on q.ux = dr.u and q.ly = dr.l)', 'sum(1 / pr) / 4', 'estimate', 'double')})",
)
add("six_edge_estimate", lambda s, d: rounded(baselines.SixPassEdge(0.3, 7).estimate(view(s, d, "eut"), _ETAU), "estimate"), f"{instances_sql(_EUT, _ETAU, starts=u01_sql(7, 'e1.eid') + ' < 0.3')} select type, round(count / 0.3::double, 6) as estimate from ({six_sql()})")
_W = int(1.5 * _ETAU)
_WIN = f"""{instances_sql(_EUT, _ETAU)}, m as (select count(*) as m from e), ranked as (select *, row_number() over (order by t, eid) - 1 as rank from e),
  draws as (select r.t from (select floor({u01_sql(7, "j")} * m)::bigint as rank from range(0, 300) x(j), m) p join ranked r using (rank)),
  spans as (select type, t1, duration, count(*) as n from inst group by all),
  hit as (select type, t1, duration, n, count(*) as copies from spans join draws on draws.t between t1 + duration - {_W} and t1 group by all),
  r as (select type, t1, duration, n, copies, count(*) as r from hit join e on e.t between t1 + duration - {_W} and t1 group by all)"""
add("six_window_estimate", lambda s, d: rounded(baselines.SixPassWindow(300, 1.5, "edge", 7).estimate(view(s, d, "eut"), _ETAU), "estimate", digits=4), f"{_WIN} select type, round(estimate, 4) as estimate from ({six_sql('(select * from r, m)', 'sum(n * copies / r::double) * max(m) / 300', 'estimate', 'double')})")
_TIME = f"""{instances_sql(_EUT, _ETAU)}, b as (select min(t) as low, max(t) as high, max(t) - min(t) + {_W} as room from e),
  draws as (select (low - {_W})::double + {u01_sql(7, "j")} * room::double as t from range(0, 300) x(j), b), spans as (select type, t1, duration, count(*) as n from inst group by all),
  hit as (select type, t1, duration, n, count(*) as copies from spans join draws on draws.t between t1 + duration - {_W} and t1 group by all)"""
add("six_window_time_estimate", lambda s, d: rounded(baselines.SixPassWindow(300, 1.5, "time", 7).estimate(view(s, d, "eut"), _ETAU), "estimate", digits=4), f"{_TIME} select type, round(estimate, 4) as estimate from ({six_sql('(select * from hit, b)', f'sum(n * copies / ({_W}::double - duration)) * max(room) / 300', 'estimate', 'double')})")

# Statistics and measures

_DEGREES = "deg as (select u as x, 0 as s, count(*) as d from e group by u union all select l, 1, count(*) from e group by l), w as (select a.u as x, b.u as y, count(*) as n from p a join p b on a.l = b.l and a.u < b.u group by all)"
_FACTS = "(select count(*) from deg) as n, (select max(d) from deg) as d_max, (select count(*) from p) as static_edges, (select coalesce(sum(n * (n - 1) // 2), 0)::bigint from w) as butterflies, (select count(*) from inst) as temporal"
for _name, _tau in TAU.items():
    _inst, _end = instances_sql(view_sql(_name), _tau), "" if _name == "euk" else f"_{_name}"
    add(f"type_share{_end}", lambda s, d, n=_name, t=_tau: stats.type_share(view(s, d, n), t), f"{_inst} select type, count, round(100.0::double * count / nullif(sum(count) over (), 0), 6) as share from ({six_sql()})")
    add(f"graph_stats{_end}", lambda s, d, n=_name, t=_tau: stats.summary(view(s, d, n), t), f"{_inst}, {_STATIC}, {_DEGREES} select count(*) as m, max(t) - min(t) as timespan, {_FACTS} from e")
_AHEAD = "(select max(n) from (select count(*) over (partition by {side} order by t range between current row and {tau} following) as n from e))"
_WD = f"select {_AHEAD.format(side='u', tau=J)} as d_upper, {_AHEAD.format(side='l', tau=J)} as d_lower, {_AHEAD.format(side='1', tau=J)} as delta"
add("window_degree", lambda s, d: stats.window_degree(euk(s, d), J), f"with e as ({E}) {_WD}")
add("cost_terms", lambda s, d: stats.cost_terms(euk(s, d), J).select("m", "d_tau", "delta", "exact_work"), f"with e as ({E}), w as ({_WD}), x as (select greatest(d_upper, d_lower) as d_tau, delta, (select count(*) from e) as m from w) select m, d_tau, delta, (m * d_tau * d_tau)::double as exact_work from x")
add("work_profile", lambda s, d: stats.work_profile(euk(s, d), euk(s, d), J), f"{S} select (select count(*) from e) as starts, (select count(*) from e a join e b on a.l = b.l and a.u <> b.u and b.t > a.t and b.t <= a.t + {J}) as wedges, count(*) as instances, count(distinct e1) as with_instances from inst")
_TAUS = [h * HOUR for h in (*range(1, 9), 24, 48, 72, 96, 120, 144, 168)]
add("tau_curve", lambda s, d: stats.tau_curve(euk(s, d), _TAUS), f"{instances_sql(E, max(_TAUS))} select x.tau, k.type::int as type, count(inst.type) as count from (select unnest({_TAUS})::bigint as tau) x cross join (values {', '.join(f'({k})' for k in TYPES)}) k(type) left join inst on inst.type = k.type and inst.duration <= x.tau group by x.tau, k.type")
add("tau_curve_days", lambda s, d: stats.tau_curve(view(s, d, "ocs"), [7, 14, 30, 60, 90]), f"{instances_sql(view_sql('ocs'), 90)} select x.tau, k.type::int as type, count(inst.type) as count from (select unnest([7, 14, 30, 60, 90])::bigint as tau) x cross join (values {', '.join(f'({k})' for k in TYPES)}) k(type) left join inst on inst.type = k.type and inst.duration <= x.tau group by x.tau, k.type")


def _by_rate(s: SparkSession, d: str, kind: str = "edge", name: str = "euk", rates: list[float] = RATES, layer: str = "upper") -> tuple[DataFrame, DataFrame]:
    edges = view(s, d, name)
    return estimators.estimates_by_seed(edges, TAU[name], kind, rates, SEEDS, layer), counting.exact_count(edges, TAU[name])


def _rates_sql(rates: list[float], node: str = "e1") -> str:
    return (
        f"{S}, per as (select {node} as k, type, count(*) as n from inst group by all), truth as ({six_sql()}), grid as (select s.seed::int as seed, r.rate from (select unnest({SEEDS}) as seed) s, (select unnest({rates})::double as rate) r), "
        f"est as (select g.seed, g.rate, t.type, t.count as truth, coalesce(sum(per.n) filter ({u01_sql('', 'k').replace(chr(39) * 2, 'g.seed::varchar')} < g.rate), 0) / g.rate as estimate from grid g cross join truth t left join per on per.type = t.type group by g.seed, g.rate, t.type, t.count), "
        "err as (select *, abs(estimate - truth) / nullif(truth, 0)::double as rel_error from est), mp as (select seed, rate, avg(rel_error) as mape from err group by seed, rate)"
    )


add("mape_by_rate", lambda s, d: rounded(metrics.mape(*_by_rate(s, d), by=("seed", "rate")), "mape").select("seed", "rate", "mape"), f"{_rates_sql(RATES)} select seed, rate, round(mape, 6) as mape from mp")
_SEVEN = [0.001, 0.01, 0.1, 0.3, 0.5, 0.9, 0.999]
_NODE = {"edge": "e1", "node_upper": "ux", "node_lower": "lx"}
for _name, _node in _NODE.items():
    add(f"rate_curve_{_name}", lambda s, d, n=_name: rounded(metrics.rate_curve(metrics.mape(*_by_rate(s, d, "edge" if n == "edge" else "node", rates=_SEVEN, layer=n.rpartition("_")[2] if n != "edge" else "upper"), by=("seed", "rate"))), "mean_mape", "sd_mape"), f"{_rates_sql(_SEVEN, _node)} select rate, round(avg(mape), 6) as mean_mape, round(stddev(mape), 6) as sd_mape, count(*) as runs from mp group by rate")
add("relative_error", lambda s, d: rounded(metrics.relative_error(*_by_rate(s, d, rates=_SEVEN)).groupBy("rate", "type").agg(F.avg("rel_error").alias("rel_error")), "rel_error"), f"{_rates_sql(_SEVEN)} select rate, type, round(avg(rel_error), 6) as rel_error from err group by rate, type")
add("box_stats", lambda s, d: rounded(metrics.box_stats(metrics.relative_error(*_by_rate(s, d, rates=_SEVEN)), "rel_error", ("rate",)), "mean", "q1", "median", "q3"), f"{_rates_sql(_SEVEN)} select rate, round(avg(rel_error), 6) as mean, round(quantile_cont(rel_error, 0.25), 6) as q1, round(quantile_cont(rel_error, 0.5), 6) as median, round(quantile_cont(rel_error, 0.75), 6) as q3 from err group by rate")
add("coverage", lambda s, d: rounded(metrics.coverage(metrics.relative_error(*_by_rate(s, d, rates=_SEVEN)), 0.1), "covered"), f"{_rates_sql(_SEVEN)} select rate, type, round(avg((rel_error <= 0.1)::int), 6) as covered, count(*) as runs from err group by rate, type")
_SQ = "select type::int as type, sum(n::double * n) as s from (select {k}, type, count(*) as n from inst group by all) group by type"
for _name, _sampler, _node in (("edge", sampling.EdgeSampler(0.1), "e1"), ("node_upper", sampling.NodeSampler(0.1), "ux"), ("node_lower", sampling.NodeSampler(0.1, "lower"), "lx")):
    add(f"variance_{_name}", lambda s, d, x=_sampler: rounded(bounds.exact_variance(euk(s, d), J, x), "variance", digits=2), f"{S}, q as ({_SQ.format(k=_node)}), t as ({six_sql()}) select t.type, round(coalesce(s, 0) * ((1 - 0.1::double) / 0.1::double), 2) as variance from t left join q using (type)")
_VAR = f"""{S}, {_DRAWS}, w as (select e.t, type, count(*) / max(m_prime)::double as w from inst join e on e.eid = e1 join prime on prime.eid = e1 group by e.t, e.eid, type),
  c as (select e.eid, w.type, sum(w.w) as c from e join w on w.t between e.t and e.t + {_LEN} group by e.eid, w.type), q as (select type, sum(c * c) as squares, sum(c) as total from c group by type)"""
add("variance_interval", lambda s, d: bounds.exact_variance(euk(s, d), J, _folded).select("type", F.round(F.sqrt("variance"), 4).alias("sd")), f"{_VAR} select q.type::int as type, round(sqrt(greatest(0, (squares * m - total * total) * (1.0::double / 500))), 4) as sd from q, m")
add("variance_interval_paper", lambda s, d: bounds.exact_variance(euk(s, d), J, _folded, "paper").select("type", F.round(F.sqrt("variance"), 4).alias("sd")), f"{_VAR} select q.type::int as type, round(sqrt(squares * (m - 1) * (1.0::double / 500)), 4) as sd from q, m")
add(
    "variance_ceiling", lambda s, d: counting.exact_count(euk(s, d), J).crossJoin(euk(s, d).agg(F.count(F.lit(1)).alias("m"))).select("type", F.round((1 - 0.1) / 0.1 * F.col("count") * F.col("count"), 2).alias("edge"), F.round((F.col("m") - 1) / 500 * F.col("count") * F.col("count"), 2).alias("interval")),
    f"{S} select type, round((1 - 0.1::double) / 0.1::double * count * count, 2) as edge, round((m - 1) / 500.0::double * count * count, 2) as interval from ({six_sql()}), (select count(*) as m from e)",
)
_GRID = "(select unnest([0.05, 0.1, 0.2, 0.5])::double as eps) a, (select unnest([0.01, 0.05, 0.1])::double as delta) b"
_SIZES = f"(select u, count(l) as m from ({E}) group by u) g"


def user_sizes(s: SparkSession, d: str) -> DataFrame:
    """Each user's graph: its number of edges."""
    return euk(s, d).groupBy("u").agg(F.count("l").alias("m"))


add("bounds_grid", lambda s, d: bounds.bounds_grid(user_sizes(s, d)), f"select u, eps, delta, m, round(1 / (1 + delta * eps * eps), 9) as p, ceil((m - 1) * ln(2 / delta) / ((1 + eps) * ln(1 + eps) - eps))::bigint as s_bennett, round((m - 1) / (delta * eps * eps), 3) as s_chebyshev from {_SIZES}, {_GRID}")
_PILOT = f"{instances_sql(E, J, starts=u01_sql(3, 'e1.eid') + ' < 0.3')}, q as ({_SQ.format(k='e1')}), t as ({six_sql()}), r as (select t.type, t.count, coalesce(s, 0) / 0.3::double / ((0.1 * 0.1 * 0.1)::double / 0.3::double / 0.3::double * t.count * t.count) as ratio from t left join q using (type))"
add("plan_from_pilot", lambda s, d: rounded(bounds.plan_from_pilot(euk(s, d), J, 0.1, 0.1, 0.3, seed=3), "count", "p"), f"{_PILOT} select type, round(count / 0.3::double, 6) as count, round(case when count > 0 then ratio / (1 + ratio) else 1 end, 6) as p from r")


def _fixed(s: SparkSession, d: str, name: str = "eut", most: int = 10_000) -> DataFrame:
    """The start edges with the lowest hashes."""
    return view(s, d, name).orderBy(u01(11, "eid"), "eid").limit(most)


_STARTS = f"e1.eid in (select eid from ({_EUT}) order by {u01_sql(11, 'eid')}, eid limit 10000)"
for _name in ("wedge", "chrono"):
    add(f"fixed_starts_{_name}", lambda s, d, n=_name: counting.long_form(counting.six(counting.list_instances(view(s, d, "eut"), _ETAU, _fixed(s, d)) if n == "wedge" else counting.chrono_all(view(s, d, "eut"), _fixed(s, d), _ETAU))), f"{instances_sql(_EUT, _ETAU, starts=_STARTS)} {six_sql()}")


# Accuracy of all eight methods over ten rates and ten seeds, on the whole graph. An estimate is a weighted sum over sampled units, so each unit's part is counted once.

_UNITS = {
    "edge": ("select e1 as k, type, count(*) as v from inst group by all", "k"),
    "node_upper": ("select ux as k, type, count(*) as v from inst group by all", "k"),
    "node_lower": ("select lx as k, type, count(*) as v from inst group by all", "k"),
    "six_edge": ("select e1 as k, type, count(*) as v from inst group by all", "k"),
    "static_topology": (f"select q.ux as k, q.ly as k2, type, count(*) as v from {_FOUR} group by all", "k::varchar || ':' || k2::varchar"),
    "interval": (
        f"select x.rank, w.type, sum(w.v) as v from ranked x join (select e.t, inst.type, count(*) / max(m_prime)::double as v from inst join e on e.eid = e1 join prime on prime.eid = e1 group by e.t, e.eid, inst.type) w on w.t between x.t and x.t + {_ETAU // 10} group by all",
        "m",
    ),
    "static_quad": (f"select pr.rank, type, count(*) as v from {_FOUR} join pr on q.ux = pr.u and q.ly = pr.l group by all", "(select count(*) from p)"),
    "six_window": (
        f"select x.rank, g.type, sum(g.n / g.r::double) as v from ranked x join (select type, t1, duration, n, count(*) as r from (select type, t1, duration, count(*) as n from inst group by all) i join e on e.t between t1 + duration - {_W} and t1 group by all) g on x.t between g.t1 + g.duration - {_W} and g.t1 group by all",
        "m",
    ),
}


def _grid_sql(method: str, rates: list[float]) -> str:
    """CTEs up to err (seed, rate, type, rel_error) and mp (seed, rate, mape)."""
    units, key = _UNITS[method]
    out = (
        f"{instances_sql(_EUT, _ETAU)}, {_STATIC}, m as (select count(*) as m from e), ranked as (select *, row_number() over (order by t, eid) - 1 as rank from e), pr as (select *, row_number() over (order by u, l) - 1 as rank from p), "
        f"prime as (select a.eid, count(*) as m_prime from e a join e b on b.t between a.t - {_ETAU // 10} and a.t group by a.eid), truth as ({six_sql()}), "
        f"grid as (select s.seed::int as seed, r.rate from (select unnest({SEEDS}) as seed) s, (select unnest({rates})::double as rate) r), unit as materialized ({units}), "
    )
    if method in estimators.KEPT:
        found = estimators.KEPT[method][1]
        hashed = f"select s.seed, unit.type, unit.v, {u01_sql('', 'unit.k').replace(chr(39) * 2, 's.seed::varchar').replace('(unit.k)::varchar', key.replace('k::', 'unit.k::') if key != 'k' else '(unit.k)::varchar')} as x from unit, (select unnest({SEEDS}) as seed) s"
        out += f"hashed as materialized ({hashed}), est as (select g.seed, g.rate, t.type, t.count as truth, coalesce(sum(h.v), 0) / (g.rate * {found}) as estimate from grid g cross join truth t left join hashed h on h.seed = g.seed and h.type = t.type and h.x < g.rate group by g.seed, g.rate, t.type, t.count), "
    else:
        share, found = estimators.DRAWN[method]
        out += (
            f"sized as (select g.*, n, greatest(1, floor(rate * n / {share} + 0.5))::bigint as s from grid g, (select {key} as n from m) x), "
            f"draws as (select seed, j, floor({u01_sql('', 'j').replace(chr(39) * 2, 'seed::varchar')} * n)::bigint as rank from (select distinct seed, n from sized) q, range(0, (select max(s) from sized)) r(j)), "
            f"hit as materialized (select draws.seed, j, type, v from draws join unit using (rank)), "
            f"est as (select g.seed, g.rate, t.type, t.count as truth, coalesce(sum(h.v), 0) * max(g.n) / (max(g.s) * {found}::double) as estimate from sized g cross join truth t left join hit h on h.seed = g.seed and h.type = t.type and h.j < g.s group by g.seed, g.rate, t.type, t.count), "
        )
    return out + "err as (select *, abs(estimate - truth) / nullif(truth, 0)::double as rel_error from est), mp as (select seed, rate, avg(rel_error) as mape from err group by seed, rate)"


def _errors(s: SparkSession, d: str, method: str, rates: list[float]) -> DataFrame:
    edges = settled(view(s, d, "eut"), "edges")
    return metrics.relative_error(estimators.grid_estimates(edges, _ETAU, method, rates, SEEDS), counting.exact_count(edges, _ETAU))


_SPAN = [0.001, 0.003, 0.01, 0.03, 0.1, 0.3, 0.5, 0.7, 0.9, 0.999]
for _method in _UNITS:
    add(
        f"accuracy_{_method}",
        lambda s, d, m=_method: rounded(metrics.rate_curve(_errors(s, d, m, RATES).groupBy("seed", "rate").agg(F.avg("rel_error").alias("mape"))), "mean_mape", "sd_mape"),
        f"{_grid_sql(_method, RATES)} select rate, round(avg(mape), 6) as mean_mape, round(stddev(mape), 6) as sd_mape, count(*) as runs from mp group by rate",
    )
    add(
        f"errors_{_method}",
        lambda s, d, m=_method: rounded(metrics.box_stats(_errors(s, d, m, [0.32]), "rel_error", ("type",)), "mean", "q1", "median", "q3"),
        f"{_grid_sql(_method, [0.32])} select type, round(avg(rel_error), 6) as mean, round(quantile_cont(rel_error, 0.25), 6) as q1, round(quantile_cont(rel_error, 0.5), 6) as median, round(quantile_cont(rel_error, 0.75), 6) as q3 from err group by type",
    )
add(
    "rate_curve_interval",
    lambda s, d: rounded(metrics.rate_curve(_errors(s, d, "interval", _SPAN).groupBy("seed", "rate").agg(F.avg("rel_error").alias("mape"))), "mean_mape", "sd_mape"),
    f"{_grid_sql('interval', _SPAN)} select rate, round(avg(mape), 6) as mean_mape, round(stddev(mape), 6) as sd_mape, count(*) as runs from mp group by rate",
)


def speedups(s: SparkSession, d: str) -> DataFrame:
    """(level, method, rate, work, speedup): the least work with a mean MAPE within the level, over that of edge sampling. Work is matchings of start edges: the rate's share of the
    edges, once for the methods that count all types at once, six times for those with a run for each type."""
    m = view(s, d, "eut").count()
    out = None
    for method, passes in (("edge", 1), ("node_upper", 1), ("node_lower", 1), ("six_edge", 6)):
        one = _errors(s, d, method, RATES).groupBy("seed", "rate").agg(F.avg("rel_error").alias("mape")).groupBy("rate").agg(F.avg("mape").alias("mape"))
        one = settled(one.select(F.lit(method).alias("method"), "rate", "mape", (F.col("rate") * m * passes).alias("seconds")))  # ten rows; one method's plan at a time
        out = one if out is None else out.union(one)
    runs = settled(out)  # forty rows
    both = None
    for level in (0.1, 0.05):
        one = metrics.speedup_at(runs, level, "edge").select(F.lit(level).alias("level"), "method", "rate", F.round("seconds", 3).alias("work"), F.round("speedup", 6).alias("speedup"))
        both = one if both is None else both.union(one)
    return both


_RUNS = " union all ".join(f"select '{m}' as method, rate, avg(mape) as mape, rate * (select count(*) from ({_EUT})) * {p} as work from ({_grid_sql(m, RATES)} select * from mp) group by rate" for m, p in (("edge", 1), ("node_upper", 1), ("node_lower", 1), ("six_edge", 6)))
add("speedup_at_level", speedups, f"with runs as materialized ({_RUNS}), best as (select level::double as level, method, min(work) as work, arg_min(rate, work) as rate from runs, (select unnest([0.1, 0.05]) as level) l where mape <= level group by all) select b.level, b.method, b.rate, round(b.work, 3) as work, round(b.work / o.work, 6) as speedup from best b join best o on o.level = b.level and o.method = 'edge'")

# Experiments with a clock: rows only. All methods on the whole graph; two rates and one seed here, any grid as parameters (the accuracy_* queries have the full grids).
_CLOCK = {"methods": tuple(workloads.METHODS), "rates": (0.04, 0.32), "seeds": (0,)}
add("accuracy_vs_time", lambda s, d: workloads.accuracy_vs_time(view(s, d, "eut"), HOUR, **_CLOCK))
add("errors_at_equal_budget", lambda s, d: workloads.errors_at_equal_budget(view(s, d, "eut"), HOUR, ("edge", "interval", "six_edge"), (0.04, 0.32), seeds=(0,)))
add("time_vs_tau", lambda s, d: workloads.time_vs_tau(view(s, d, "eut"), (HOUR, 4 * HOUR), ("edge", "interval", "six_edge"), (0.32,), seeds=(0,)))
add("ablations", lambda s, d: workloads.ablations(view(s, d, "eut"), HOUR))
add("single_type_times", lambda s, d: workloads.single_type_times(view(s, d, "eut"), _fixed(s, d), HOUR))

# The relational, window, set and function operators around the methods

E_ = f"with e as ({E})"
add("scan_prune", lambda s, d: load(s, d, "lineitem", "l_partkey", "l_suppkey", "l_shipdate").where("l_shipdate >= timestamp_ntz'1995-01-01' and l_shipdate < timestamp_ntz'1996-01-01'").select("l_partkey", "l_suppkey", F.datediff(F.col("l_shipdate").cast("date"), F.lit("1970-01-01").cast("date")).alias("day")), "select l_partkey, l_suppkey, date_diff('day', date '1970-01-01', l_shipdate::date)::int as day from lineitem where l_shipdate >= '1995-01-01' and l_shipdate < '1996-01-01'")
add("project_bucket", lambda s, d: euk(s, d).select("eid", bucket(F.col("t"), J).alias("b"), (bucket(F.col("t"), J) * J).alias("begin")), f"{E_} select eid, t // {J} as b, t // {J} * {J} as begin from e")
add("filter_window", lambda s, d: euk(s, d).where(F.col("l").isin(1, 2, 3) & F.col("eid").between(100, 5000)), f"{E_} select * from e where l in (1, 2, 3) and eid between 100 and 5000")
for _hint in ("merge", "shuffle_hash"):
    add(f"join_inner_{_hint}", lambda s, d, h=_hint: load(s, d, "lineitem", "l_orderkey", "l_partkey").join(load(s, d, "orders", "o_orderkey", "o_custkey").hint(h), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey").agg(F.count(F.lit(1)).alias("lines"), F.countDistinct("l_partkey").alias("parts")), "select o_custkey, count(*) as lines, count(distinct l_partkey) as parts from lineitem join orders on l_orderkey = o_orderkey group by o_custkey")
add("join_broadcast", lambda s, d: interval_join(F.broadcast(euk(s, d).where(u01(7, "eid") < 0.01)), euk(s, d), ["l"], "t", J).select("eid", "r_eid"), f"{E_} select a.eid, b.eid as r_eid from e a join e b on a.l = b.l and b.t > a.t and b.t <= a.t + {J} where {u01_sql(7, 'a.eid')} < 0.01")
_PER = f"{S}, per as (select e1 as eid, count(*) as n from inst group by e1)"


def per_edge_total(s: SparkSession, d: str) -> DataFrame:
    return counting.list_instances(euk(s, d), J).groupBy(F.col("e1").alias("eid")).agg(F.count(F.lit(1)).alias("n"))


add("join_left", lambda s, d: euk(s, d).select("eid").join(per_edge_total(s, d), "eid", "left").fillna(0, ["n"]), f"{_PER} select eid, coalesce(n, 0) as n from e left join per using (eid)")
add("join_full", lambda s, d: euk(s, d).where("eid % 2 = 0").select("eid", F.col("u")).join(per_edge_total(s, d), "eid", "full"), f"{_PER} select eid, u, n from (select eid, u from e where eid % 2 = 0) full join per using (eid)")
for _kind in ("semi", "anti"):
    add(f"join_{_kind}", lambda s, d, k=_kind: euk(s, d).join(per_edge_total(s, d), "eid", f"left_{k}"), f"{_PER} select e.* from e where eid {'not ' if _kind == 'anti' else ''}in (select eid from per)")
add("join_interval", lambda s, d: block_join(*2 * [euk(s, d).select("eid", "l", "t")], ["l"], "t", J).select("eid", "r_eid"), f"{E_} select a.eid, b.eid as r_eid from e a join e b on a.l = b.l and b.t > a.t and b.t <= a.t + {J}")
add("join_theta", lambda s, d: load(s, d, "nation", "n_nationkey", "n_regionkey").join(load(s, d, "region", "r_regionkey"), F.col("n_regionkey") > F.col("r_regionkey")), "select n_nationkey, n_regionkey, r_regionkey from nation join region on n_regionkey > r_regionkey")
add("join_asof", lambda s, d: asof_join(euk(s, d), euk(s, d), ["u"], "t", "eid"), f"{E_} select eid, u, l, t, lag(eid) over (partition by u order by t) as last_eid from e")
add("join_lateral", lambda s, d: (register(s, d, ("euk",)), s.sql("select e.eid, x.kind from edges_euk e, lateral (select explode(sequence(1, cast(e.eid % 3 as int) + 1)) as kind) x"))[1], f"{E_} select eid, unnest(range(1, (eid % 3)::int + 2))::int as kind from e")
add("neighbours_within", lambda s, d: counting_neighbours(s, d), f"{E_} select a.eid, b.l as neighbour, b.t from e a join e b on a.u = b.u and b.t > a.t and b.t <= a.t + {J}")


def counting_neighbours(s: SparkSession, d: str) -> DataFrame:
    from wingcount.operators.joins import neighbours_within

    return neighbours_within(euk(s, d), euk(s, d), "u", J)


add("agg_degree", lambda s, d: stats.degrees(view(s, d, "lsp")), f"with e as ({view_sql('lsp')}) select 'upper' as layer, u as node, count(*) as degree from e group by u union all select 'lower', l, count(*) from e group by l")
add("agg_distinct", lambda s, d: euk(s, d).agg(F.countDistinct("u").alias("users"), F.countDistinct("u", "l").alias("pairs")), f"{E_} select count(distinct u) as users, count(distinct (u, l)) as pairs from e")
add("agg_approx_distinct", lambda s, d: euk(s, d).agg((F.abs(F.approx_count_distinct("u", 0.01) - F.countDistinct("u")) <= 0.05 * F.countDistinct("u")).alias("close"), F.countDistinct("u").alias("users")), f"{E_} select true as close, count(distinct u) as users from e")


def daily(s: SparkSession, d: str) -> DataFrame:
    return counting.list_instances(euk(s, d), J).select("type", F.floor(F.col("t1") / DAY).alias("day"))


_DAILY = f"{S}, x as (select type::int as type, t1 // {DAY} as day from inst)"
add("agg_rollup", lambda s, d: daily(s, d).rollup("type", "day").agg(F.count(F.lit(1)).alias("n")), f"{_DAILY} select type, day, count(*) as n from x group by rollup (type, day)")
add("agg_cube", lambda s, d: daily(s, d).cube("type", "day").agg(F.count(F.lit(1)).alias("n")), f"{_DAILY} select type, day, count(*) as n from x group by cube (type, day)")
add("agg_grouping_sets", lambda s, d: daily(s, d).groupingSets([[F.col("type")], [F.col("day")]], "type", "day").agg(F.count(F.lit(1)).alias("n")), f"{_DAILY} select type, day, count(*) as n from x group by grouping sets ((type), (day))")
add("agg_pivot", lambda s, d: daily(s, d).groupBy("day").pivot("type", list(TYPES)).count().fillna(0).select("day", *(F.col(str(k)).alias(f"c{k}") for k in TYPES)), f"{_DAILY} select day, {_COLS} from x group by day")
add("agg_unpivot", lambda s, d: counting.six(counting.list_instances(euk(s, d), J)).unpivot([], counting.COUNTS, "name", "count"), f"{S} select 'c' || type as name, count from ({six_sql()})")
add("agg_percentiles", lambda s, d: counting.list_instances(euk(s, d), J).groupBy("type").agg(*(F.round(F.expr(f"percentile(duration, {q})"), 3).alias(f"q{int(100 * q)}") for q in (0.25, 0.5, 0.75))), f"{S} select type::int as type, " + ", ".join(f"round(quantile_cont(duration::double, {q}), 3) as q{int(100 * q)}" for q in (0.25, 0.5, 0.75)) + " from inst group by type")
add("agg_argmax", lambda s, d: euk(s, d).join(per_edge_total(s, d), "eid").groupBy("u").agg(F.max_by("eid", F.struct("n", "eid")).alias("busiest"), F.max("n").alias("n")), f"{_PER}, j as (select u, eid, n from e join per using (eid)) select u, arg_max(eid, n * 10000000000 + eid) as busiest, max(n) as n from j group by u")
def _by():
    return Window.partitionBy("u").orderBy("t", "eid")


for _f in ("rank", "dense_rank", "row_number"):
    add(f"win_{_f}", lambda s, d, f=_f: view(s, d, "lsp").select("eid", "u", getattr(F, f)().over(Window.partitionBy("u").orderBy("t")).cast("long").alias("r") if f != "row_number" else F.row_number().over(_by()).cast("long").alias("r")), f"with e as ({view_sql('lsp')}) select eid, u, {_f}() over (partition by u order by t{', eid' if _f == 'row_number' else ''}) as r from e")
add("win_ntile", lambda s, d: euk(s, d).select("eid", F.ntile(4).over(_by()).cast("long").alias("r")), f"{E_} select eid, ntile(4) over (partition by u order by t, eid) as r from e")
add("win_lag_lead", lambda s, d: euk(s, d).select("eid", (F.col("t") - F.lag("t").over(_by())).alias("gap"), (F.lead("t").over(_by()) - F.col("t")).alias("wait")), f"{E_} select eid, t - lag(t) over w as gap, lead(t) over w - t as wait from e window w as (partition by u order by t, eid)")
add("win_running", lambda s, d: euk(s, d).select("eid", F.count(F.lit(1)).over(_by().rowsBetween(Window.unboundedPreceding, 0)).alias("n")), f"{E_} select eid, count(*) over (partition by u order by t, eid rows between unbounded preceding and current row) as n from e")
add("win_range_frame", lambda s, d: euk(s, d).select("eid", F.count(F.lit(1)).over(Window.partitionBy("u").orderBy("t").rangeBetween(0, J)).alias("n")), f"{E_} select eid, count(*) over (partition by u order by t range between current row and {J} following) as n from e")
add("sort_topk", lambda s, d: per_edge_total(s, d).orderBy(F.desc("n"), "eid").limit(20), f"{_PER} select * from per order by n desc, eid limit 20")
add("topk_per_group", lambda s, d: euk(s, d).join(per_edge_total(s, d), "eid").withColumn("r", F.row_number().over(Window.partitionBy("u").orderBy(F.desc("n"), "eid"))).where("r <= 2").select("u", "eid", "n"), f"{_PER}, j as (select u, eid, n, row_number() over (partition by u order by n desc, eid) as r from e join per using (eid)) select u, eid, n from j where r <= 2")


def two_users(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    return euk(s, d).where("u = 1").select("l"), euk(s, d).where("u = 2").select("l")


for _f, _sql in {"union": "union", "union_all": "union all", "intersect": "intersect", "intersect_all": "intersect all", "except": "except", "except_all": "except all"}.items():
    _m = {"union": lambda a, b: a.union(b).distinct(), "union_all": lambda a, b: a.unionByName(b), "intersect": lambda a, b: a.intersect(b), "intersect_all": lambda a, b: a.intersectAll(b), "except": lambda a, b: a.subtract(b), "except_all": lambda a, b: a.exceptAll(b)}[_f]
    add(f"set_{_f}", lambda s, d, m=_m: m(*two_users(s, d)), f"{E_} select l from e where u = 1 {_sql} select l from e where u = 2")
add("fn_string", lambda s, d: load(s, d, "events", "event_id", "event_type").select("event_id", F.md5(F.concat_ws("-", "event_id", F.lower("event_type"))).alias("h"), F.regexp_extract("event_type", "^([a-z])", 1).alias("first"), F.size(F.split("event_type", "i")).alias("parts")), "select event_id, md5(event_id::varchar || '-' || lower(event_type)) as h, regexp_extract(event_type, '^([a-z])', 1) as first, len(string_split(event_type, 'i'))::int as parts from events")
add("fn_date", lambda s, d: load(s, d, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", F.date_format(F.date_trunc("month", F.col("o_orderdate").cast("timestamp")), "yyyy-MM-dd").alias("month"), F.datediff(F.date_add(F.col("o_orderdate").cast("date"), 30), F.lit("1992-01-01").cast("date")).cast("long").alias("days")), "select o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as month, date_diff('day', date '1992-01-01', o_orderdate::date + 30) as days from orders")
add("fn_math", lambda s, d: euk(s, d).select("eid", F.round(F.sqrt("eid"), 6).alias("root"), F.round(F.ln(F.col("eid") + 1), 6).alias("log"), F.greatest("u", "l").alias("most"), F.expr("eid div 7").alias("seventh"), F.pmod("eid", F.lit(7)).alias("rest")), f"{E_} select eid, round(sqrt(eid), 6) as root, round(ln(eid + 1), 6) as log, greatest(u, l) as most, eid // 7 as seventh, eid % 7 as rest from e")
add("fn_array", lambda s, d: euk(s, d).groupBy("u").agg(F.array_sort(F.collect_list("l")).alias("a")).select("u", F.size(F.filter("a", lambda x: x > 50)).cast("long").alias("above"), F.aggregate("a", F.lit(0).cast("long"), lambda acc, x: acc + x).alias("total"), F.size(F.array_intersect("a", F.array(*(F.lit(k).cast("long") for k in range(10))))).cast("long").alias("low")), f"{E_} select u, count(*) filter (l > 50) as above, sum(l)::bigint as total, count(distinct l) filter (l < 10) as low from e group by u")
add("fn_map", lambda s, d: load(s, d, "events", "user_id", "event_type").groupBy("user_id").agg(F.map_from_entries(F.collect_set(F.struct("event_type", F.length("event_type")))).alias("m")).select("user_id", F.size(F.map_filter("m", lambda k, v: v > 4)).cast("long").alias("long_kinds")), "select user_id, count(distinct event_type) filter (length(event_type) > 4) as long_kinds from events group by user_id")
add("fn_json", lambda s, d: load(s, d, "events", "event_id", "props").select("event_id", F.from_json("props", "k long")["k"].alias("k"), F.get_json_object("props", "$.k").alias("text")), "select event_id, json_extract_string(props, '$.k')::bigint as k, json_extract_string(props, '$.k') as text from events")
add("udf_type", lambda s, d: (register(s, d, ("euk",)), counting.list_instances(euk(s, d), J).select("t2", "t3", "t4").selectExpr("butterfly_type(t2, t3, t4) as type").groupBy("type").agg(F.count(F.lit(1)).alias("count")))[1], f"{S} select type::int as type, count(*) as count from inst group by type")


def udtf_bounds(s: SparkSession, d: str) -> DataFrame:
    from pyspark.sql.functions import lit, udtf

    @udtf(returnType="eps double, delta double, p double, draws double")
    class SamplingBounds:
        def eval(self, m: int, delta: float):
            for eps in (0.05, 0.1, 0.2, 0.5):
                yield eps, delta, round(1 / (1 + delta * eps * eps), 9), round((m - 1) / (delta * eps * eps), 3)

    return user_sizes(s, d).lateralJoin(SamplingBounds(F.col("m").outer(), lit(0.1))).select("u", "m", "eps", "delta", "p", "draws")


add("udtf_bounds", udtf_bounds, f"select u, m, eps, 0.1::double as delta, round(1 / (1 + 0.1::double * eps * eps), 9) as p, round((m - 1) / (0.1::double * eps * eps), 3) as draws from {_SIZES}, (select unnest([0.05, 0.1, 0.2, 0.5])::double as eps) a")


def rank_count(s: SparkSession, d: str) -> DataFrame:
    """Orders of repeated edges counted by ranks in a pandas aggregate; the same number as listing them."""
    import numpy as np
    import pandas as pd

    def rising(t: pd.Series) -> int:
        a = np.sort(t.to_numpy())
        below = np.searchsorted(a, a, "left")
        above = len(a) - np.searchsorted(a, a, "right")
        return int((below * above).sum())

    count = F.pandas_udf(rising, "long", F.PandasUDFType.GROUPED_AGG)
    return view(s, d, "eut").groupBy("u", "l").agg(count("t").alias("triples"))


add("udaf_rank_count", rank_count, f"with e as ({_EUT}), r as (select u, l, (rank() over (partition by u, l order by t) - 1) * (rank() over (partition by u, l order by t desc) - 1) as n from e) select u, l, sum(n)::bigint as triples from r group by u, l")

from wingcount.streaming import replay  # noqa: E402  needs the names above for nothing, but reads best here

for _name, (_run, _sql) in replay.QUERIES.items():
    add(_name, _run, _sql)
