"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; one JSON line."""

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import SparkSession  # noqa: E402

from virtcol import queries as methods  # noqa: E402
from virtcol import workloads  # noqa: E402

HEADLINE = (
    "count_full_scan_fr", "uniform_count_est", "stratified_count_est_source", "stratified_group_est", "active_search_trace", "mips_topk", "mips_then_judge", "dnf_mixed", "packed_count_est",
    "sampler_study", "vsql_w29_sampled", "vsql_w30_dialogs", "vsql_w33_sampled", "vsql_w35_structured", "rel_pricing", "rel_merge_join",
)


def main() -> None:
    sf, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", cpus).config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    methods.QUERIES["positive_share"](spark, sf).collect()
    took, quality = {}, {}
    for name in HEADLINE:
        start = time.time()
        methods.QUERIES[name](spark, sf).write.format("noop").mode("overwrite").save()
        took[name] = round(time.time() - start, 3)
    for name, method, budget in (("w5", "stratified", 128), ("w5", "uniform", 128), ("w5", "packed", 128), ("w5", "active", 256), ("w5", "mips", 256), ("w5", "udf", 256)):
        r = workloads.run(name, spark, sf, method, budget, 0, pool=1024)  # the pool is for active search alone
        took[f"{name}_{method}_{budget}"] = round(r["seconds"], 3)
        quality[f"{name}_{method}_{budget}"] = round(r.get("relative_error", r.get("f1", 0.0)), 4)
    print(json.dumps({"metric": "seconds over the headline queries", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "quality": quality, "sf": sf}))


if __name__ == "__main__":
    main()
