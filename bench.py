"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]: prints one JSON line.

Each query runs once to warm up and then $BENCH_RUNS times (default 3; the mean counts) into a sink that stores nothing;
it is not repeated once $BENCH_ENOUGH seconds (default 8) have been measured. A run is charged $BENCH_LIMIT seconds
(default 40) if it takes longer, and listed under timed_out; the warm-up counts where it takes longer than the half.
Ratios compare methods.
"""

from __future__ import annotations

import json
import os
import sys
import threading
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

HEADLINE = [
    "path4_count_memo", "path4_count_plain", "path4_count_bagtree", "path4_count_pairwise", "path5_count_memo", "path7_count_memo", "path7_count_bagtree",
    "cycle4_count_memo", "cycle4_count_plain", "cycle4_count_bagtree", "cycle4_count_pairwise", "cycle5_count_memo", "cycle5_count_bagtree", "cycle5_count_kernel_memo", "cycle6_count_memo", "cycle6_count_bagtree",
    "lollipop_count_plain", "lollipop_cs1_count", "lollipop_cs2_count", "lollipop_cs3_count", "bip4_td_person_count", "bip4_td_movie_count", "path5_g_parts_count_memo", "path5_g_words_count_memo", "path5_g_words_count_bagtree", "path4_eval_memo", "path4_eval_bagtree", "cycle5_eval_memo", "cycle5_eval_plain", "cycle5_eval_bagtree", "rand5_4_1_count", "rand5_6_2_count",
]
RATIOS = {
    "path4_plain_over_memo": ("path4_count_plain", "path4_count_memo"), "path7_bagtree_over_memo": ("path7_count_bagtree", "path7_count_memo"),
    "cycle4_plain_over_memo": ("cycle4_count_plain", "cycle4_count_memo"), "cycle5_bagtree_over_memo": ("cycle5_count_bagtree", "cycle5_count_memo"), "cycle6_bagtree_over_memo": ("cycle6_count_bagtree", "cycle6_count_memo"),
    "path5_words_bagtree_over_memo": ("path5_g_words_count_bagtree", "path5_g_words_count_memo"), "path4_eval_bagtree_over_memo": ("path4_eval_bagtree", "path4_eval_memo"),
    "cycle5_eval_plain_over_memo": ("cycle5_eval_plain", "cycle5_eval_memo"), "cycle5_eval_bagtree_over_memo": ("cycle5_eval_bagtree", "cycle5_eval_memo"),
    "lollipop_plain_over_cs1": ("lollipop_count_plain", "lollipop_cs1_count"), "lollipop_plain_over_cs2": ("lollipop_count_plain", "lollipop_cs2_count"), "lollipop_plain_over_cs3": ("lollipop_count_plain", "lollipop_cs3_count"),
    "bip4_movie_over_person": ("bip4_td_movie_count", "bip4_td_person_count"),
}


def main() -> None:
    from memojoin import workloads
    from memojoin.sources.files import drain
    from pyspark.sql import SparkSession

    cpus, sf = os.environ.get("BENCH_CPUS", "8"), os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    runs, limit = int(os.environ.get("BENCH_RUNS", "3")), float(os.environ.get("BENCH_LIMIT", "40"))
    enough = float(os.environ.get("BENCH_ENOUGH", "8"))
    only = sys.argv[1:] or HEADLINE
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "12g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    spark.range(1000).groupBy("id").count().count()  # the session's own start is not a query's time
    seconds, late, failed = {}, [], {}
    for name in only:
        took = []
        for k in range(runs + 1):
            if sum(took) >= enough:
                break
            spark.sparkContext.setJobGroup(name, name, interruptOnCancel=True)
            timer = threading.Timer(limit, lambda name=name: spark.sparkContext.cancelJobGroup(name))
            timer.start()
            began = time.perf_counter()
            try:
                drain(workloads.QUERIES[name](spark, sf))
                if k or time.perf_counter() - began > limit / 2:
                    took.append(time.perf_counter() - began)
            except Exception as e:
                if time.perf_counter() - began < limit:
                    failed[name] = str(e)[:200]
                    break
                late.append(name)
                took.append(limit)
            finally:
                timer.cancel()
        if took:
            seconds[name] = round(sum(took) / len(took), 3)
    spark.stop()
    ratios = {k: round(seconds[a] / seconds[b], 2) for k, (a, b) in RATIOS.items() if a in seconds and b in seconds}
    print(json.dumps({"metric": "headline_queries_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(sf.rstrip("/")), "ratios": ratios, "timed_out": sorted(set(late)), "failed": failed}))


if __name__ == "__main__":
    main()
