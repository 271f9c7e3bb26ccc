"""Times the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS] and prints one JSON line. Each plan is built anew and written to the noop sink."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def headline() -> dict:
    """Exact counts, samples with their errors' order of rate, baselines, and single-pass against six-pass counting per start edge."""
    from wingcount.operators import baselines, counting, estimators, sampling, static_graph
    from wingcount.sources.edges import HOUR, view

    def euk(s, d):
        return view(s, d, "euk")

    return {
        "exact_euk_24h_star": lambda s, d: counting.exact_count(euk(s, d), 24 * HOUR, plan="star"),
        "exact_euk_24h_wedge_pair": lambda s, d: counting.exact_count(euk(s, d), 24 * HOUR, plan="wedge_pair"),
        "exact_eut_1h": lambda s, d: counting.exact_count(view(s, d, "eut"), HOUR),
        "exact_ocs_30d": lambda s, d: counting.exact_count(view(s, d, "ocs"), 30),
        "exact_lsp_30d": lambda s, d: counting.exact_count(view(s, d, "lsp"), 30),
        "exact_ocp_365d": lambda s, d: counting.exact_count(view(s, d, "ocp"), 365),
        "edge_estimate_euk_24h": lambda s, d: estimators.estimate(euk(s, d), 24 * HOUR, sampling.EdgeSampler(0.1, 1)),
        "node_estimate_euk_24h": lambda s, d: estimators.estimate(euk(s, d), 24 * HOUR, sampling.NodeSampler(0.1, seed=1)),
        "interval_estimate_euk_24h": lambda s, d: estimators.estimate(euk(s, d), 24 * HOUR, sampling.IntervalSampler(rate=0.01, c=0.1, seed=1)),
        "six_edge_estimate_eut_1h": lambda s, d: baselines.SixPassEdge(0.05, 1).estimate(view(s, d, "eut"), HOUR),
        "six_window_estimate_eut_1h": lambda s, d: baselines.SixPassWindow(200, 1.5, "edge", 1).estimate(view(s, d, "eut"), HOUR),
        "wedge_10k_starts_eut_1h": lambda s, d: counting.long_form(counting.six(counting.list_instances(view(s, d, "eut"), HOUR, view(s, d, "eut").where("eid < 10000")))),
        "chrono_10k_starts_eut_1h": lambda s, d: counting.long_form(counting.six(counting.chrono_all(view(s, d, "eut"), view(s, d, "eut").where("eid < 10000"), HOUR))),
        "static_exact_euk": lambda s, d: static_graph.static_exact(euk(s, d)),
    }


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    spark.range(1000).selectExpr("sum(id)").collect()
    from wingcount.functions.metrics import stage_costs

    seconds, costs, last = {}, {}, -1
    for name, build in headline().items():
        began = time.perf_counter()
        build(spark, SF_DIR).write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - began, 3)
        costs[name] = stage_costs(spark, last)
        last = costs[name].pop("last")
    print(json.dumps({"metric": "headline_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "costs": costs, "sf": SF_DIR.rpartition("sf")[2]}))


if __name__ == "__main__":
    main()
