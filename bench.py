"""Headline queries at ``BENCH_SF_DIR`` on ``local[BENCH_CPUS]``; prints one JSON line.

The tasks run on stored regions under each access path (indices are built before and reported apart),
so that the speed-up over no index can be read off.
"""

from __future__ import annotations

import json
import os
import sys
import tempfile
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
REPEATS = int(os.environ.get("BENCH_REPEATS", "3"))


def main() -> None:
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "16g"))
        .config("spark.sql.shuffle.partitions", CPUS).config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.warehouse.dir", tempfile.mkdtemp()).getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from layout_ie.measures.accuracy import work_of
    from layout_ie.workloads import catalogue, modes

    def run(df) -> None:  # noqa: ANN001
        df.write.format("noop").mode("overwrite").save()

    def best(make) -> float:  # noqa: ANN001
        took = []
        for _ in range(REPEATS):
            t = time.perf_counter()
            run(make())
            took.append(time.perf_counter() - t)
        return round(sorted(took)[len(took) // 2], 3)

    build = {}
    for name, make in (("regions", modes.stored_regions), ("postings", modes.stored_postings), ("clustered", modes.stored_clustered), ("summary", modes.stored_summary)):
        t = time.perf_counter()
        make(spark, SF_DIR)
        build[name] = round(time.perf_counter() - t, 3)
    queries, work = {}, {}
    for task, (fn, paths) in modes.TASKS.items():
        for mode in paths:
            if mode == "per_page" and task != "q4":
                continue
            queries[f"{task}_{mode}"] = best(lambda f=fn, m=mode: f(spark, SF_DIR, m))
            if mode in ("none", "text", "region", "text+region"):
                work[f"{task}_{mode}"] = work_of(lambda f=fn, m=mode: f(spark, SF_DIR, m))
    for name in () if os.environ.get("BENCH_SHORT") else ("sheet_boxes", "page_regions", "grid_regions", "dict_word_spans", "text_block", "strict_south_of", "aligned_consecutive", "polygon_q4", "source_identical_q3", "q1_dense", "q4_dense"):
        queries[name] = best(lambda n=name: catalogue.QUERIES[n](spark, SF_DIR))
    indexed = lambda t: [v for k, v in queries.items() if k.split("_", 1) in ([t, "text"], [t, "region"], [t, "text+region"])]
    speed = {t: round(queries[f"{t}_none"] / min(indexed(t)), 2) for t in modes.TASKS}
    chosen = {t: modes.choose(spark, SF_DIR, t) for t in modes.TASKS}
    print(json.dumps({"metric": "headline_total", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "build": build, "index_speedup": speed, "chosen": chosen, "work": work, "sf": os.path.basename(SF_DIR.rstrip("/"))}))
    spark.stop()


if __name__ == "__main__":
    main()
