"""Headline workloads at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = os.pathsep.join([ROOT, *filter(None, [os.environ.get("PYTHONPATH")])])

from pyspark.sql import SparkSession  # noqa: E402

from duelspark.functions import metrics  # noqa: E402
from duelspark.operators import baselines, extremum, kcenter, linkage, proximity  # noqa: E402
from duelspark.operators.judges import Judge  # noqa: E402
from duelspark.sources import tables  # noqa: E402


LONGEST = 900  # seconds after which no further run begins


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    judge = Judge.band(1.0, seed=7)
    large, events, planted = (f(spark, sf_dir) for f in (tables.values_large, tables.values_skewed, tables.planted))
    metric = metrics.planted(4.0)
    runs = {
        "farthest_robust_lineitem": lambda: extremum.robust_band(large, judge, t=1).collect(),
        "nearest_robust_lineitem": lambda: extremum.robust_band(large, judge, t=1, want="min").collect(),
        "farthest_knockout_lineitem": lambda: baselines.knockout(large, judge).collect(),
        "farthest_sampler_lineitem": lambda: baselines.sampled_round_robin(large, judge).collect(),
        "maximum_coin_events": lambda: extremum.robust_coin(events, Judge.coin(0.2)).collect(),
        "farthest_embeddings": lambda: proximity.farthest_band(planted, 0, metric, judge, t=1).collect(),
        "kcenter_band_k10_embeddings": lambda: kcenter.band(planted.select("id", "payload"), 10, metric, judge)[0].collect(),
        "kcenter_exact_k10_embeddings": lambda: kcenter.exact_greedy(planted.select("id", "payload"), 10, metric)[0].collect(),
        "linkage_complete_by_label": lambda: linkage.hierarchy(planted, linkage.planted(4.0), judge, "complete", "truth").collect(),
        "linkage_sampler_by_label": lambda: baselines.linkage_sampled(planted, linkage.planted(4.0), judge, "single", block="truth").collect(),
        "linkage_single_by_label": lambda: linkage.hierarchy(planted, linkage.planted(4.0), judge, "single", "truth").collect(),
        "kcenter_band_k50_embeddings": lambda: kcenter.band(planted.select("id", "payload"), 50, metric, judge)[0].collect(),
        "kcenter_knockout_k50_embeddings": lambda: baselines.kcenter_knockout(planted.select("id", "payload"), 50, metric, judge)[0].collect(),
    }
    spark.range(10).count()
    took, found = {}, {}
    started = time.monotonic()
    for name, run in runs.items():
        began = time.monotonic()
        if began - started > LONGEST:  # what is left is not measured, and not reported
            break
        rows = run()
        took[name] = round(time.monotonic() - began, 3)
        if rows and "questions" in rows[0].__fields__:
            found[name] = max(r["questions"] for r in rows)
    print(json.dumps({"metric": "headline seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "questions": found, "sf": sf_dir.rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()
