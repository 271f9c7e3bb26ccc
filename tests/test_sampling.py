import math

import pytest
from pyspark.sql import functions as F

from wingcount.functions import bounds, metrics
from wingcount.operators import baselines, counting, estimators, sampling, static_graph, stats, timeline
from wingcount.sources.edges import HOUR, TOY, toy, view

SF = "/root/testdata/sf0.001"
TAU = 168 * HOUR


def values(df, column="estimate"):
    return [r[column] for r in df.orderBy("type").collect()]


def test_full_samples_are_exact(spark):
    edges = view(spark, SF, "euk")
    want = [float(x) for x in values(counting.exact_count(edges, TAU), "count")]
    assert values(estimators.estimate(edges, TAU, sampling.EdgeSampler(1.0))) == want
    assert values(estimators.estimate(edges, TAU, sampling.NodeSampler(1.0, "lower"))) == want
    every = sampling.IntervalSampler(draws=1000, c=0.1, replace=False)
    assert values(estimators.estimate(edges, TAU, every)) == pytest.approx(want)
    assert values(baselines.StaticTopologyEstimator(1.0).estimate(view(spark, SF, "eut").where("eid < 150"), 24 * HOUR)) == pytest.approx(
        [float(x) for x in values(counting.exact_count(view(spark, SF, "eut").where("eid < 150"), 24 * HOUR), "count")]
    )


def test_literal_and_folded_intervals_agree(spark):
    edges = view(spark, SF, "euk")
    folded, literal = (sampling.IntervalSampler(draws=80, c=0.2, seed=3, mode=m) for m in ("folded", "literal"))
    a = folded.draw(edges, TAU).select("eid", "copies")
    b = literal.draw(edges, TAU).groupBy("eid").agg(F.sum("copies").alias("copies"))
    assert sorted(a.collect()) == sorted(b.collect())
    assert values(estimators.estimate(edges, TAU, folded)) == pytest.approx(values(estimators.estimate(edges, TAU, literal)))


def test_worked_interval(spark):
    drawn = sampling.IntervalSampler(draws=1, c=0.6)
    near = toy(spark).where("t between 17 and 20").orderBy("eid").select("eid").collect()
    assert drawn.length(5) == 3 and [r[0] for r in near] == [5, 8, 9]


def test_trailing_count(spark):
    got = {r["eid"]: r["m_prime"] for r in timeline.trailing_count(toy(spark), 3).collect()}
    assert got == {e: sum(t - 3 <= x[3] <= t for x in TOY) for e, _, _, t in TOY}


def test_every_single_draw_gives_mean_and_variance(spark):
    """All single interval draws on the worked example: expectation and variance, exactly."""
    counts = {r["eid"]: r["c2"] for r in counting.per_edge_counts(toy(spark), toy(spark), 10).collect()}
    m, length = len(TOY), 3
    prime = {e: sum(t - length <= x[3] <= t for x in TOY) for e, _, _, t in TOY}
    outcomes = [sum(m / prime[x[0]] * counts.get(x[0], 0) for x in TOY if e[3] <= x[3] <= e[3] + length) for e in TOY]
    mean = sum(outcomes) / m
    assert mean == pytest.approx(2)
    want = sum((x - mean) ** 2 for x in outcomes) / m
    got = {r["type"]: r["variance"] for r in bounds.exact_variance(toy(spark), 10, sampling.IntervalSampler(draws=1, c=0.3)).collect()}
    assert got[2] == pytest.approx(want)
    assert got[2] <= bounds.variance_ceiling("interval", 2, m=m, s=1)


def test_ranking_of_strategies(spark):
    """At one rate, sampling nodes strays further than sampling edges."""
    edges = view(spark, "/root/testdata/sf0.01", "eut")
    truth = counting.exact_count(edges, 6 * HOUR).first()["count"]
    sd = {k: math.sqrt(bounds.exact_variance(edges, 6 * HOUR, s).orderBy("type").first()["variance"]) / truth for k, s in (("edge", sampling.EdgeSampler(0.1)), ("node", sampling.NodeSampler(0.1)))}
    assert sd["edge"] == pytest.approx(0.105, abs=0.002) and sd["node"] == pytest.approx(0.275, abs=0.005)


def test_unbiased_over_seeds(spark):
    edges = view(spark, SF, "euk")
    truth = values(counting.exact_count(edges, TAU), "count")
    runs = estimators.estimates_by_seed(edges, TAU, "edge", [0.3], list(range(60)))
    mean = [r["m"] for r in runs.groupBy("type").agg(F.avg("estimate").alias("m")).orderBy("type").collect()]
    sd = [math.sqrt(v) for v in values(bounds.exact_variance(edges, TAU, sampling.EdgeSampler(0.3)), "variance")]
    assert all(abs(a - b) < 4 * s / math.sqrt(60) for a, b, s in zip(mean, truth, sd, strict=True))
    one = runs.where("seed = 7 and rate = 0.3")
    assert values(one) == pytest.approx(values(estimators.estimate(edges, TAU, sampling.EdgeSampler(0.3, 7))))


def test_static_counts(spark):
    edges = view(spark, SF, "euk")
    n = {static_graph.static_exact(edges, m, layer).first()[0] for m, layer in (("pair", "lower"), ("pair", "upper"), ("priority", "lower"))}
    assert n == {static_graph.static_butterflies(edges).count()} == {29_477}


def test_bounds():
    assert bounds.min_probability(0.1, 0.1) == pytest.approx(1 / 1.001)
    assert bounds.min_draws(1000, 0.5, 0.001) < bounds.min_draws(1000, 0.5, 0.001, "chebyshev")
    assert all(bounds.bennett_rate(k / 20) >= (k / 20) ** 2 / 3 for k in range(1, 20))
    with pytest.warns(UserWarning):
        assert bounds.min_probability(0.5, 0.1, "bennett", m=100) == 1.0
    with pytest.raises(ValueError):
        bounds.min_draws(10, 1.5, 0.1)


def test_measures(spark):
    truth = spark.createDataFrame([(1, 10), (2, 0)], "type int, count long")
    est = spark.createDataFrame([(1, 12.0), (2, 3.0)], "type int, estimate double")
    one = metrics.mape(est, truth).first()
    assert one["mape"] == pytest.approx(0.2) and one["skipped"] == 1
    assert metrics.mape(est, truth, zero_truth="skip").first()["skipped"] == 0
    with pytest.raises(Exception, match="zero"):
        metrics.mape(est, truth, zero_truth="error").collect()
    runs = spark.createDataFrame([("edge", 0.1, 1.0, 0.05), ("other", 0.1, 5.0, 0.05), ("other", 0.5, 9.0, 0.01)], "method string, rate double, seconds double, mape double")
    assert {r["method"]: r["speedup"] for r in metrics.speedup_at(runs, 0.1, "edge").collect()} == {"edge": 1.0, "other": 5.0}


def test_tau_curve(spark):
    edges = view(spark, SF, "euk")
    curve = stats.tau_curve(edges, [72 * HOUR, 168 * HOUR])
    for tau in (72 * HOUR, 168 * HOUR):
        assert values(curve.where(F.col("tau") == tau), "count") == values(counting.exact_count(edges, tau), "count")
