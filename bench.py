"""Headline timings: one JSON line.  BENCH_SF_DIR and BENCH_CPUS choose the tables and the cores."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")

HEADLINE = ("line_fit_supplier", "best_single_cut_user", "sliding_contrast_curve", "covering_scores", "optimal_partition_k3_user", "refine_fixpoint", "bottom_up_hourly", "natural_saw_tooth", "stream_half_window")


def published(spark: SparkSession, sf: str) -> dict[str, list[dict]]:
    """The published comparisons re-run: relative time and cost, accuracy, seconds and counters of each method."""
    from linseg import experiments as X

    tables = {
        "one_cut": X.published_single_cut(spark),
        "many_cuts_small": X.published_many_small(spark),
        "many_cuts_large": X.published_many_large(spark),
        "frames": X.frames(spark, sf),
        "million_points": X.million_points(spark, sf),
    }
    return {k: [{c: (round(v, 5) if isinstance(v, float) else v) for c, v in r.asDict().items()} for r in t.orderBy("method").collect()] for k, t in tables.items()}


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "16g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from linseg.queries import QUERIES

    seconds, shapes = {}, {}
    for name in HEADLINE:
        t0 = time.perf_counter()
        QUERIES[name](spark, SF_DIR).write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - t0, 3)
    t0 = time.perf_counter()
    shapes = published(spark, SF_DIR)
    seconds["published_comparisons"] = round(time.perf_counter() - t0, 3)
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": SF_DIR, "cpus": CPUS, "published": shapes}))


if __name__ == "__main__":
    main()
