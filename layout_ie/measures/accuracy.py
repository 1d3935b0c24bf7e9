"""Accuracy, robustness, corpus and cost measures."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def accuracy(found: DataFrame, gold: DataFrame, keys: list[str], by: list[str] | None = None) -> DataFrame:
    """Returned, right, gold, recall %, precision % and F1 % (4 places), over distinct keys, one row (a group).

    One full outer join on the keys; empty denominators give null.
    """
    by = by or []
    f = found.select(*by, *keys).distinct().withColumn("_f", F.lit(1))
    g = gold.select(*by, *keys).distinct().withColumn("_g", F.lit(1))
    both = f.join(g, [*by, *keys], "full")
    total = both.groupBy(*by).agg(
        F.coalesce(F.sum("_f"), F.lit(0)).cast("long").alias("returned"), F.coalesce(F.sum(F.col("_f") * F.col("_g")), F.lit(0)).cast("long").alias("right"), F.coalesce(F.sum("_g"), F.lit(0)).cast("long").alias("gold")
    )
    part = lambda a, b: F.when(F.col(b) > 0, F.round(100.0 * F.col(a) / F.col(b), 4))
    f1 = F.when(F.col("returned") + F.col("gold") > 0, F.round(200.0 * F.col("right") / (F.col("returned") + F.col("gold")), 4))
    return total.withColumns({"recall": part("right", "gold"), "precision": part("right", "returned"), "f1": f1})


def robustness(by_variant: DataFrame) -> DataFrame:
    """Largest and least recall over markup variants, and the drop between them."""
    return by_variant.agg(F.max("recall").alias("best"), F.min("recall").alias("worst"), F.round(F.max("recall") - F.min("recall"), 4).alias("drop"))


def corpus_stats(regions: DataFrame) -> DataFrame:
    pages = regions.groupBy("page_id").agg(F.count("*").alias("n"))
    return pages.agg(F.count("*").alias("n_pages"), F.sum("n").cast("long").alias("n_regions"), F.min("n").alias("least"), F.max("n").alias("most"), F.round(F.avg("n"), 4).alias("mean"))


def time_query(make: Callable[[], DataFrame], repeats: int = 3) -> dict[str, float]:
    """Wall seconds of writing the result nowhere: the first run and the median of the others."""
    took = []
    for _ in range(repeats + 1):
        t = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        took.append(time.perf_counter() - t)
    return {"cold": took[0], "warm": statistics.median(took[1:])}


def speedup(times: dict[str, float], base: str = "none") -> dict[str, float]:
    """Times of the access modes as multiples of no index."""
    return {k: times[base] / v for k, v in times.items()}


def work_of(make: Callable[[], DataFrame]) -> dict[str, int]:
    """What one run reads and moves, as the executors counted it: rows and bytes read, bytes shuffled, tasks."""
    import uuid

    df = make()
    context = df.sparkSession.sparkContext
    group = uuid.uuid4().hex
    context.setJobGroup(group, "measured run")
    try:
        df.write.format("noop").mode("overwrite").save()
    finally:
        context.setLocalProperty("spark.jobGroup.id", None)
    tracker, store = context.statusTracker(), context._jsc.sc().statusStore()
    stages = {s for j in tracker.getJobIdsForGroup(group) for s in tracker.getJobInfo(j).stageIds}
    out = {"rows_read": 0, "bytes_read": 0, "bytes_shuffled": 0, "tasks": 0}
    for s in sorted(stages):
        try:
            stage = store.lastStageAttempt(s)
        except Exception:  # noqa: BLE001  a stage that was skipped has no attempt
            continue
        for key, value in zip(out, (stage.inputRecords(), stage.inputBytes(), stage.shuffleWriteBytes(), stage.numCompleteTasks()), strict=True):
            out[key] += value
    return out


def plan_counts(df: DataFrame) -> dict[str, int]:
    """Operators in the executed plan that cost most: scans, exchanges, sorts, joins, Python."""
    import re

    text = df._jdf.queryExecution().executedPlan().toString()
    return {k: len(re.findall(p, text)) for k, p in {"scans": r"Scan parquet|FileScan", "exchanges": r"\bExchange\b", "broadcasts": r"BroadcastExchange", "sorts": r"\bSort\b", "joins": r"Join\b", "python": r"Python|Arrow|Pandas"}.items()}
