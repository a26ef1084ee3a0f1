"""Times the headline queries. BENCH_SF_DIR and BENCH_CPUS choose data and threads; prints one JSON line.

Each query runs once untimed, which also builds the stored maps and indexes that it reads, and then up to
three times until BENCH_EACH seconds (8) are spent; its median counts. A builder's own time is in wl_build
and wl_index_build. Baselines stand beside what they are compared with in `beside`, in rows or queries a second.
Times appear on stderr as they come."""

import json
import os
import statistics
import sys
import time

from pyspark.sql import SparkSession

D, CPUS, EACH = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "4"), float(os.environ.get("BENCH_EACH", "8"))
NAMES = """wl_union_equal wl_union_small wl_find_many wl_build wl_filter_even wl_multi_insert wl_range_many wl_left_many wl_range_sum_day
wl_range_sum_90d wl_range_max_day sum_range wl_filter_max_p999 wl_stab_orders wl_rect_sum wl_rect_list wl_index_build wl_and_top10
base_union_merge base_bulk_insert base_hash_build base_plain_filter base_scan_range base_rect_scan base_idx_fullsort""".split()
#: method, its baseline, table whose rows are the method's queries (or entries), share of them that the baseline asks
BESIDE = [
    ("wl_union_equal", "base_union_merge", "orders", 1), ("wl_multi_insert", "base_bulk_insert", "events", 1), ("wl_range_sum_day", "base_scan_range", "events", 1),
    ("wl_filter_max_p999", "base_plain_filter", "events", 1), ("wl_rect_sum", "base_rect_scan", "orders", 1), ("wl_and_top10", "base_idx_fullsort", "documents", 1),
]


def main() -> None:
    from ordsum.workloads import ALL

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "8g").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    took = {}
    for name in NAMES:
        times: list[float] = []
        while len(times) < 4 and (len(times) < 2 or sum(times) < EACH):
            at = time.perf_counter()
            ALL[name][0](spark, D).write.format("noop").mode("overwrite").save()
            times.append(time.perf_counter() - at)
        took[name] = round(statistics.median(times[1:]), 3)
        print(name, took[name], "first", round(times[0], 3), "runs", len(times) - 1, file=sys.stderr, flush=True)
    rows = {t: spark.read.parquet(f"{D}/{t}.parquet").count() for t in {x[2] for x in BESIDE}}
    beside = {a: {"per_s": round(rows[t] / took[a]), "baseline": b, "baseline_per_s": round(rows[t] / part / took[b])} for a, b, t, part in BESIDE}
    print(json.dumps({"metric": "headline_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "beside": beside, "sf": D.rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()
