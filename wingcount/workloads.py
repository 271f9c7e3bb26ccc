"""The experiments that need a clock: accuracy against time, errors at an equal budget, time against tau, and plans against each other.

Each returns rows of runs. Grids are parameters; the defaults are small enough for a test table.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wingcount.functions import metrics
from wingcount.operators import baselines, counting, estimators, sampling
from wingcount.operators.ranked import ranked
from wingcount.shared import settled, shuffles_dropped

#: Estimates by method: (edges, tau, rate, seed) to (type, estimate). A rate is a share of edges, draws or static edges.
METHODS: dict[str, Callable[[DataFrame, int, float, int], DataFrame]] = {
    "edge": lambda e, t, r, k: estimators.estimate(e, t, sampling.EdgeSampler(r, k)),
    "node_upper": lambda e, t, r, k: estimators.estimate(e, t, sampling.NodeSampler(r, "upper", k)),
    "node_lower": lambda e, t, r, k: estimators.estimate(e, t, sampling.NodeSampler(r, "lower", k)),
    "interval": lambda e, t, r, k: estimators.estimate(e, t, sampling.IntervalSampler(rate=r, c=0.1, seed=k)),
    "six_edge": lambda e, t, r, k: baselines.SixPassEdge(r, k).estimate(e, t),
    "six_window": lambda e, t, r, k: baselines.SixPassWindow(max(1, round(r * e.count() / 10)), 1.5, "edge", k).estimate(e, t),
    "static_quad": lambda e, t, r, k: baselines.StaticQuadEstimator(max(1, round(r * e.select("u", "l").distinct().count())), k).estimate(e, t),
    "static_topology": lambda e, t, r, k: baselines.StaticTopologyEstimator(r, seed=k).estimate(e, t),
}


def accuracy_vs_time(edges: DataFrame, tau: int, methods: tuple[str, ...] = tuple(METHODS), rates: tuple[float, ...] = (0.05, 0.4), seeds: tuple[int, ...] = (0,)) -> DataFrame:
    """(method, rate, seed, seconds, mape). Runs over the limits of `metrics.within_limits` are what a figure leaves out."""
    edges = settled(edges, "edges")
    truth = _truth(edges, tau)
    rows = [(name, rate, seed, *_run(edges, tau, truth, name, rate, seed)[:2]) for name in methods for rate in rates for seed in seeds]
    return edges.sparkSession.createDataFrame(rows, "method string, rate double, seed int, seconds double, mape double")


def _truth(edges: DataFrame, tau: int) -> dict[int, int]:
    with shuffles_dropped(edges.sparkSession):
        return {r["type"]: r["count"] for r in counting.exact_count(edges, tau).collect()}


def _run(edges: DataFrame, tau: int, truth: dict[int, int], name: str, rate: float, seed: int) -> tuple[float, float | None, dict[int, float]]:
    """Seconds, MAPE and estimates of one run. What it shuffled is gone once it is over, so runs need no more disk than the largest of them."""
    held: list = []
    with shuffles_dropped(edges.sparkSession):
        seconds = _clocked(lambda: held.extend(METHODS[name](edges, tau, rate, seed).select("type", "estimate").collect()))
    estimates = {r["type"]: float(r["estimate"]) for r in held}
    errors = [abs(x - truth[k]) / truth[k] for k, x in estimates.items() if truth[k]]
    return seconds, sum(errors) / len(errors) if errors else None, estimates


def _clocked(run: Callable[[], None]) -> float:
    import time

    began = time.perf_counter()
    run()
    return time.perf_counter() - began


def errors_at_equal_budget(edges: DataFrame, tau: int, methods: tuple[str, ...] = ("edge", "interval", "static_topology"), rates: tuple[float, ...] = (0.05, 0.2, 0.5), level: float = 0.05, seeds: tuple[int, ...] = (0, 1)) -> DataFrame:
    """(method, rate, type, rel_error): each method at its largest rate that stays within the time that edge sampling needs for a MAPE of at most `level`
    (its last rate, if none gets there)."""
    spark, edges = edges.sparkSession, settled(edges, "edges")
    truth = _truth(edges, tau)
    curve = {(name, rate): _run(edges, tau, truth, name, rate, 0) for name in methods for rate in rates}
    ours = [(seconds, mape) for (name, _), (seconds, mape, _) in curve.items() if name == "edge"]
    budget = min((seconds for seconds, mape in ours if mape is not None and mape <= level), default=max(seconds for seconds, _ in ours))
    rows = []
    for name in methods:
        rate = max((r for r in rates if curve[name, r][0] <= budget), default=min(rates))
        for seed in seeds:  # the curve has the runs of seed 0
            found = curve[name, rate][2] if seed == 0 else _run(edges, tau, truth, name, rate, seed)[2]
            rows += [(name, rate, k, x) for k, x in found.items()]
    table = spark.createDataFrame(rows, "method string, rate double, type int, estimate double")  # six rows a run
    exact = spark.createDataFrame(list(truth.items()), "type int, count long")
    return metrics.relative_error(table, exact).groupBy("method", "rate", "type").agg(F.avg("rel_error").alias("rel_error"))


def time_vs_tau(
    edges: DataFrame, taus: tuple[int, ...], methods: tuple[str, ...] = ("edge", "static_topology"), rates: tuple[float, ...] = (0.05, 0.4), level: float = 0.05, seeds: tuple[int, ...] = (0,)
) -> DataFrame:
    """(tau, method, rate, seconds, mape): how time grows with the duration, each method at its smallest rate with a MAPE below `level` (its largest rate, if
    none gets there); averages over the seeds."""
    edges, rows = settled(edges, "edges"), []
    for tau in taus:
        truth = _truth(edges, tau)
        for name in methods:
            for rate in sorted(rates):
                runs = [_run(edges, tau, truth, name, rate, seed) for seed in seeds]
                errors = [m for _, m, _ in runs if m is not None]
                mape = sum(errors) / len(errors) if errors else None
                if mape is not None and mape < level:
                    break
            rows.append((int(tau), name, rate, sum(s for s, *_ in runs) / len(runs), mape))
    return edges.sparkSession.createDataFrame(rows, "tau long, method string, rate double, seconds double, mape double")


def ablations(edges: DataFrame, tau: int, rate: float = 0.2) -> DataFrame:
    """(what, variant, seconds): plans, layers, bucket widths, and the two ways to take intervals."""
    edges = settled(edges, "edges")
    folded, literal = (sampling.IntervalSampler(rate=rate, c=0.1, mode=m) for m in ("folded", "literal"))
    span = edges.agg((F.max("t") - F.min("t")).alias("span")).first()["span"] + 1
    runs = {
        ("plan", "star"): lambda: counting.exact_count(edges, tau, "star"), ("plan", "wedge_pair"): lambda: counting.exact_count(edges, tau, "wedge_pair"),
        ("plan", "factored"): lambda: counting.exact_count(edges, tau, "factored"), ("center", "upper"): lambda: counting.exact_count(edges, tau, center="upper"),
        ("bucket", "tau"): lambda: counting.added(ranked(edges, edges, tau, totals=True)), ("bucket", "none"): lambda: counting.added(ranked(edges, edges, tau, width=max(tau, span), totals=True)),
        ("interval", "folded"): lambda: estimators.estimate(edges, tau, folded), ("interval", "literal"): lambda: estimators.estimate(edges, tau, literal),
        ("passes", "one"): lambda: counting.per_edge_counts(edges, edges, tau), ("passes", "six"): lambda: counting.six_passes(edges, edges, tau),
    }
    rows = [(what, variant, metrics.timed(build, 1)[0]) for (what, variant), build in runs.items()]
    return edges.sparkSession.createDataFrame(rows, "what string, variant string, seconds double")


def single_type_times(edges: DataFrame, starts: DataFrame, tau: int) -> DataFrame:
    """(what, seconds): all types at once from given start edges, against each type matched on its own."""
    rows = [("all types at once", metrics.timed(lambda: counting.six(counting.list_instances(edges, tau, starts)), 1)[0])]
    rows += [(f"type {k}", metrics.timed(lambda k=k: counting.chrono_counts(edges, starts, tau, k), 1)[0]) for k in range(1, 7)]
    return edges.sparkSession.createDataFrame(rows, "what string, seconds double")
