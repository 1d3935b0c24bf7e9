"""Alignment groups: spans that share an edge, split where they are not consecutive or too far apart.

A column shares ``x_l`` (a vertical stack), a row shares ``y_l``.  The groups keep
their members as rows with a ``group_id``; bounds and counts come from partial aggregates.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: axis -> (shared edge, along low, along high, across low, across high)
AXES = {"column": ("x_l", "y_l", "y_h", "x_l", "x_h"), "row": ("y_l", "x_l", "x_h", "y_l", "y_h")}


def _tolerant_key(vs: DataFrame, edge: str, tol: int) -> DataFrame:
    """Adds ``_key``: the smallest edge of a chain whose neighbours differ by ``tol`` at most."""
    w = Window.partitionBy("page_id").orderBy(edge)
    cut = vs.withColumn("_new", F.when(F.col(edge) - F.lag(edge).over(w) > tol, 1).otherwise(0))
    chain = cut.withColumn("_chain", F.sum("_new").over(w.rangeBetween(Window.unboundedPreceding, 0)))
    return chain.withColumn("_key", F.min(edge).over(Window.partitionBy("page_id", "_chain"))).drop("_new", "_chain")


def aligned(vs: DataFrame, axis: str = "column", consecutive: bool = False, max_dist: int | None = None, tol: int = 0, between: str = "geometric", edge: str | None = None) -> DataFrame:
    """``vs`` with ``group_key`` (the shared edge) and ``island`` (number of the run in the group).

    ``consecutive`` splits a group where another span of ``vs`` stands between neighbours:
    one whose extent across overlaps theirs and which meets the open gap between
    them (``geometric``), or any span between them in document order (``order``).
    ``max_dist`` splits it where the gap is longer.  ``edge`` is another shared edge, or ``centre``: then the key
    is twice the centre across the axis, a whole number.
    """
    default, lo, hi, a_lo, a_hi = AXES[axis]
    edge = edge or default
    if edge == "centre":
        keyed = vs.withColumn("_centre", F.col(a_lo) + F.col(a_hi))
        keyed = _tolerant_key(keyed, "_centre", tol) if tol else keyed.withColumn("_key", F.col("_centre"))
    else:
        keyed = _tolerant_key(vs, edge, tol) if tol else vs.withColumn("_key", F.col(edge))
    w = Window.partitionBy("page_id", "_key").orderBy(lo, hi, "region_id")
    out = keyed.withColumns({"_prev_hi": F.lag(hi).over(w), "_prev_a": F.lag(a_lo).over(w), "_prev_b": F.lag(a_hi).over(w), "_first": F.row_number().over(w) == 1})
    cut: Column = F.lit(False)
    if max_dist is not None:
        cut = cut | F.coalesce(F.col(lo) - F.col("_prev_hi") > max_dist, F.lit(False))
    if consecutive and between == "order":
        order = Window.partitionBy("page_id").orderBy("ord")
        out = keyed.withColumn("_place", F.row_number().over(order))
        w2 = Window.partitionBy("page_id", "_key").orderBy("_place")
        out = out.withColumns({"_prev_hi": F.lag(hi).over(w2), "_first": F.row_number().over(w2) == 1, "_skip": F.col("_place") - F.lag("_place").over(w2) > 1})
        cut = cut | F.coalesce(F.col("_skip"), F.lit(False))
        w = w2
    elif consecutive:
        gaps = out.where(~F.col("_first") & (F.col(lo) > F.col("_prev_hi"))).select(
            "page_id", "region_id", "_key", F.col("_prev_hi").alias("g_lo"), F.col(lo).alias("g_hi"), F.least(a_lo, "_prev_a").alias("g_a"), F.greatest(a_hi, "_prev_b").alias("g_b")
        )
        other = keyed.select("page_id", F.col("_key").alias("_other"), F.col(lo).alias("o_lo"), F.col(hi).alias("o_hi"), F.col(a_lo).alias("o_a"), F.col(a_hi).alias("o_b"))
        on = (gaps["page_id"] == other["page_id"]) & (other["_other"] != gaps["_key"]) & (other["o_a"] < gaps["g_b"]) & (other["o_b"] > gaps["g_a"]) & (other["o_lo"] < gaps["g_hi"]) & (other["o_hi"] > gaps["g_lo"])
        split = gaps.join(other, on, "left_semi").select("page_id", "region_id", F.lit(True).alias("_split"))
        out = out.join(split, ["page_id", "region_id"], "left")
        cut = cut | F.coalesce("_split", F.lit(False))
    out = out.withColumn("_cut", F.when(cut & ~F.col("_first"), 1).otherwise(0))
    out = out.withColumn("island", F.sum("_cut").over(w.rowsBetween(Window.unboundedPreceding, 0)).cast("long"))
    return out.withColumn("group_key", F.col("_key")).select(*vs.columns, "group_key", "island")


def vertically_aligned(vs: DataFrame, **flags) -> DataFrame:  # noqa: ANN003
    return aligned(vs, "column", **flags)


def horizontally_aligned(vs: DataFrame, literal_mapping: bool = False, **flags) -> DataFrame:  # noqa: ANN003
    """Rows of equal ``y_l``; with ``literal_mapping`` the groups of equal ``x_l`` of the printed mapping."""
    return aligned(vs, "column" if literal_mapping else "row", **flags)


GROUP = ["page_id", "group_key", "island"]


def group_regions(vs: DataFrame, by: list[str] = GROUP, **aggregates: Column) -> DataFrame:
    return vs.groupBy(*by).agg(*(v.alias(k) for k, v in aggregates.items()))


def minimal_bounding_region(vs: DataFrame, by: list[str] = GROUP) -> DataFrame:
    """Bounding box, text interval and size of each group."""
    return vs.groupBy(*by).agg(
        F.min("x_l").alias("x_l"), F.min("y_l").alias("y_l"), F.max("x_h").alias("x_h"), F.max("y_h").alias("y_h"),
        F.min("text_start").alias("text_start"), F.max("text_end").alias("text_end"), F.count("*").alias("n_members"),
    )


def minimal_super_region(groups: DataFrame, regions: DataFrame, by: list[str] = GROUP) -> DataFrame:
    """The existing node of least area (then deepest) that holds each group's bounding box."""
    r = regions.select("page_id", *(F.col(c).alias(f"s_{c}") for c in ("region_id", "x_l", "y_l", "x_h", "y_h", "depth")))
    hit = groups.join(r, "page_id").where((F.col("s_x_l") <= F.col("x_l")) & (F.col("s_y_l") <= F.col("y_l")) & (F.col("s_x_h") >= F.col("x_h")) & (F.col("s_y_h") >= F.col("y_h")))
    size = (F.col("s_x_h") - F.col("s_x_l")) * (F.col("s_y_h") - F.col("s_y_l"))
    best = F.min_by(F.struct(*(F.col(f"s_{c}").alias(c) for c in ("region_id", "x_l", "y_l", "x_h", "y_h"))), F.struct(size, -F.col("s_depth"), F.col("s_region_id")))
    return hit.groupBy(*by).agg(best.alias("n")).select(*by, "n.*")


def nearest(a: DataFrame, b: DataFrame, direction: str, k: int = 1) -> DataFrame:
    """For each row of ``a`` the ``k`` nearest rows of ``b`` in that direction, projections overlapping."""
    left = a.select("page_id", F.col("region_id").alias("a_id"), *(F.col(c).alias(f"a_{c}") for c in ("x_l", "y_l", "x_h", "y_h")))
    right = b.select("page_id", F.col("region_id").alias("b_id"), *(F.col(c).alias(f"b_{c}") for c in ("x_l", "y_l", "x_h", "y_h")))
    gap = {"south": F.col("b_y_l") - F.col("a_y_h"), "north": F.col("a_y_l") - F.col("b_y_h"), "east": F.col("b_x_l") - F.col("a_x_h"), "west": F.col("a_x_l") - F.col("b_x_h")}[direction]
    side = ("x_l", "x_h") if direction in ("north", "south") else ("y_l", "y_h")
    faced = (F.col(f"a_{side[0]}") < F.col(f"b_{side[1]}")) & (F.col(f"b_{side[0]}") < F.col(f"a_{side[1]}"))
    pairs = left.join(right, "page_id").where((gap >= 0) & faced & (F.col("a_id") != F.col("b_id"))).withColumn("gap", gap)
    w = Window.partitionBy("page_id", "a_id").orderBy("gap", "b_id")
    return pairs.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k).select("page_id", "a_id", "b_id", "gap", "place")
