"""Operators on the node hierarchy, by the dotted paths of region ids.

Ancestors are found by generated prefixes (an equi-join bounded by the depth), not by a
prefix theta-join.  ``1.2`` is no ancestor of ``1.20``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

KEY = ["page_id", "region_id"]


def prefixes(region_id: Column, or_self: bool = False) -> Column:
    """Paths of the proper ancestors, the root first."""
    path = F.split(region_id, r"\.")
    last = F.size(path) - (0 if or_self else 1)
    found = F.transform(F.sequence(F.lit(1), last), lambda i: F.array_join(F.slice(path, F.lit(1), i), "."))
    return F.when(last >= 1, found).otherwise(F.array().cast("array<string>"))


def is_ancestor(up: Column, down: Column) -> Column:
    return F.startswith(down, F.concat(up, F.lit(".")))


def all_regions(regions: DataFrame, page_id: int | None = None) -> DataFrame:
    """Every visual span of the collection or of one page."""
    return regions if page_id is None else regions.where(F.col("page_id") == page_id)


def ancestors(vs: DataFrame, regions: DataFrame, or_self: bool = False) -> DataFrame:
    """Rows of ``regions`` above each row of ``vs``, with the lower id as ``of_region``."""
    low = vs.select("page_id", F.col("region_id").alias("of_region"), F.explode(prefixes(F.col("region_id"), or_self)).alias("region_id"))
    return regions.join(low, KEY)


def descendants(vs: DataFrame, regions: DataFrame, or_self: bool = False) -> DataFrame:
    """Rows of ``regions`` below each row of ``vs``, with the upper id as ``of_region``."""
    low = regions.withColumn("of_region", F.explode(prefixes(F.col("region_id"), or_self)))
    return low.join(vs.select("page_id", F.col("region_id").alias("of_region")), ["page_id", "of_region"])


def parent_path(region_id: Column) -> Column:
    path = F.split(region_id, r"\.")
    return F.when(F.size(path) > 1, F.array_join(F.slice(path, F.lit(1), F.size(path) - 1), "."))


def parent(vs: DataFrame, regions: DataFrame) -> DataFrame:
    return regions.join(vs.select("page_id", F.col("region_id").alias("of_region"), parent_path(F.col("region_id")).alias("region_id")), KEY)


def children(vs: DataFrame, regions: DataFrame) -> DataFrame:
    low = regions.withColumn("of_region", parent_path(F.col("region_id")))
    return low.join(vs.select("page_id", F.col("region_id").alias("of_region")), ["page_id", "of_region"])


def siblings(vs: DataFrame, regions: DataFrame) -> DataFrame:
    up = F.coalesce(parent_path(F.col("region_id")), F.lit(""))
    low = regions.withColumn("_up", up)
    own = vs.select("page_id", F.col("region_id").alias("of_region"), up.alias("_up"))
    return low.join(own, ["page_id", "_up"]).where("region_id <> of_region").drop("_up")


def annotate_extremes(regions: DataFrame) -> DataFrame:
    """Fill ``minimal_region`` and ``maximal_region``: the deepest and highest node of the chain with the same text.

    Nodes of a page with the same non-empty text interval lie on one path, so
    one window per interval suffices; nodes without text stand for themselves.
    """
    w = Window.partitionBy("page_id", "text_start", "text_end")
    some = F.col("text_end") > F.col("text_start")
    return regions.withColumns(
        {
            "minimal_region": F.when(some, F.max_by("region_id", "depth").over(w)).otherwise(F.col("region_id")),
            "maximal_region": F.when(some, F.min_by("region_id", "depth").over(w)).otherwise(F.col("region_id")),
        }
    )


def _follow(vs: DataFrame, regions: DataFrame, column: str) -> DataFrame:
    """The rows that the ids in ``column`` name; ids of ``vs`` go along as ``of_region``."""
    named = regions.select(*KEY, F.col(column).alias("_to")).join(vs.select("page_id", "region_id"), KEY)
    return regions.join(named.select("page_id", F.col("region_id").alias("of_region"), F.col("_to").alias("region_id")), KEY)


def maximal_region(vs: DataFrame, regions: DataFrame) -> DataFrame:
    return _follow(vs, regions, "maximal_region")


def minimal_region(vs: DataFrame, regions: DataFrame) -> DataFrame:
    return _follow(vs, regions, "minimal_region")


def enclosing_node(spans: DataFrame, regions: DataFrame, begin: str = "begin", end: str = "end", key: list[str] | None = None) -> DataFrame:
    """Adds id and box of the deepest node of the page whose text covers the span (null if none)."""
    key = key or ["page_id", begin, end]
    r = regions.select("page_id", *(F.col(c).alias(f"_{c}") for c in ("region_id", "x_l", "y_l", "x_h", "y_h", "text_start", "text_end", "depth")))
    hit = spans.select(*key).distinct().join(r, "page_id").where((F.col("_text_start") <= F.col(begin)) & (F.col("_text_end") >= F.col(end)))
    best = hit.groupBy(*key).agg(F.max_by(F.struct(*(F.col(f"_{c}").alias(c) for c in ("region_id", "x_l", "y_l", "x_h", "y_h"))), F.struct("_depth", "_region_id")).alias("node"))
    return spans.join(best, key, "left").select(*spans.columns, "node.*")


def region_text(vs: DataFrame, page_text: DataFrame) -> DataFrame:
    """Adds the text of each node, its descendants' included."""
    return vs.join(page_text, "page_id").withColumn("full_text", F.expr("substring(page_text, int(text_start + 1), int(text_end - text_start))")).drop("page_text")


def page_texts(regions: DataFrame) -> DataFrame:
    """Text of each page from its innermost nodes."""
    runs = regions.where("text is not null and text <> ''")
    parts = F.array_sort(F.collect_list(F.struct("text_start", "text")))
    return runs.groupBy("page_id").agg(F.array_join(F.transform(parts, lambda p: p["text"]), "\n").alias("page_text"))
