"""Headline timings: one JSON line. BENCH_SF_DIR and BENCH_CPUS choose the input and the cores."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

HEADLINE = [
    "sample_draws_orders",
    "sample_lineitem_ranked",
    "sample_by_file_row",
    "est_select_orders_u_m2_b5",
    "est_select_orders_c_m2_b8",
    "est_select_lineitem",
    "est_join_uniform_m1_b1",
    "est_join_le_customer_supplier",
    "est_cross_le",
    "est_multijoin_u5",
    "exact_select_batch",
    "exact_join_le",
    "exact_join_keys",
    "equidepth_orders",
    "plan_choice_star",
    "violations_select_uniform",
    "op_join_auto",
    "op_agg_basic",
]


def main() -> None:
    from pyspark.sql import SparkSession

    from cardest import catalog

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", str(min(8, os.cpu_count() or 1)))
    builder = SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
    spark = builder.config("spark.sql.shuffle.partitions", cpus).config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "6g").getOrCreate()
    spark.sparkContext.setLogLevel("OFF")
    spark.range(1000).selectExpr("sum(id)").collect()
    times = {}
    for name in HEADLINE:
        began = time.perf_counter()
        catalog.QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        times[name] = round(time.perf_counter() - began, 3)
    print(json.dumps({"metric": "headline queries, total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": Path(sf_dir).name.removeprefix("sf"), "estimate_ms_per_query": round(10 * times["est_select_orders_u_m2_b5"], 2)}))
    spark.stop()


if __name__ == "__main__":
    main()
