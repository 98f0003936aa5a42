"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time


def main() -> None:
    from pyspark.sql import SparkSession

    from corrsentry.catalog import queries
    from corrsentry.operators.detect import DetectConfig, best_scores, detect
    from corrsentry.plans.evaluate import log_cells

    sf, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    took: dict[str, float] = {}

    def timed(name: str, df) -> None:  # noqa: ANN001
        began = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        took[name] = round(time.perf_counter() - began, 3)

    q = queries()
    timed("warm_up", q["cells_tumbling"](spark, sf))
    for name in ("cells_tumbling", "cells_from_panes", "row_windows_30_3", "workload_access_log", "workload_prices", "cascade_alerts", "block_scores", "peel_score", "draws_systematic"):
        timed(name, q[name](spark, sf))
    for d in ("direct", "sampled", "block", "peel"):
        timed(f"detect_{d}", best_scores(detect(log_cells(spark, sf, slide="6 hours"), DetectConfig(detectors=(d,)))))
    per = {r["detector"]: r for r in q["speed_ratio"](spark, sf).collect()}
    took.pop("warm_up")
    out = {"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": sf, "seconds_per_window": {d: round(r["seconds_avg"], 5) for d, r in per.items()}, "ratio_to_direct": {d: round(r["ratio"], 2) for d, r in per.items()}}
    try:
        from corrsentry.llm import queries as llm
    except ImportError:
        llm = None
    if llm:
        began = time.perf_counter()
        for name in ("op9_url_reputation", "op6_media_columns", "op5_simhash_decontamination"):
            timed(name, llm.queries()[name](spark, sf))
        out["value"] = round(out["value"] + time.perf_counter() - began, 3)
    print(json.dumps(out))
    sys.stdout.flush()
    spark.stop()


if __name__ == "__main__":
    main()
