"""Extraction and aggregation on visual spans (text interval and box)."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.predicates import ascii_word
from ..session import shipped
from .hierarchy import enclosing_node, page_texts
from .spans import dict_spans, islands, regex_spans, text_block

BOX = ("x_l", "y_l", "x_h", "y_h")


def regex_regions(regions: DataFrame, pattern: str, scope: str = "node") -> DataFrame:
    """Visual spans of a pattern: nodes whose own text matches, or matches in the page text with their deepest node."""
    if scope == "node":
        return regions.where(F.col("text").isNotNull() & F.col("text").rlike(pattern))
    found = regex_spans(page_texts(regions), pattern, "page_text", ("page_id",))
    return enclosing_node(found, regions)


def phrase_regions(regions: DataFrame, phrase: str) -> DataFrame:
    """Nodes whose own text holds the phrase as whole words, in any case."""
    return regions.where(F.col("text").isNotNull() & F.col("text").rlike(ascii_word(phrase)))


def dict_regions(regions: DataFrame, terms: DataFrame, scope: str = "node") -> DataFrame:
    """Node and term for every occurrence of a dictionary entry."""
    if scope == "node":
        keep = ("page_id", "region_id", *BOX)
        return dict_spans(regions.where("text is not null").select(*keep, "text"), terms, "text", keep)
    return enclosing_node(dict_spans(page_texts(regions), terms, "page_text", ("page_id",)), regions)


def consolidate_contained_visual(vs: DataFrame) -> DataFrame:
    """Drop visual spans that lie in another one by text and by box; equal ones count once."""
    cols = ["page_id", "text_start", "text_end", *BOX]
    one = vs.select(*cols).distinct()
    a, b = one.alias("a"), one.alias("b")
    inside = (
        (F.col("a.page_id") == F.col("b.page_id")) & (F.col("b.text_start") <= F.col("a.text_start")) & (F.col("a.text_end") <= F.col("b.text_end"))
        & (F.col("b.x_l") <= F.col("a.x_l")) & (F.col("b.y_l") <= F.col("a.y_l")) & (F.col("a.x_h") <= F.col("b.x_h")) & (F.col("a.y_h") <= F.col("b.y_h"))
    )
    other = F.lit(False)
    for c in cols[1:]:
        other = other | (F.col(f"a.{c}") != F.col(f"b.{c}"))
    return a.join(b, inside & other, "left_anti")


def consolidate_overlapping_visual(vs: DataFrame, regions: DataFrame) -> DataFrame:
    """Merge visual spans whose texts overlap; the box is that of the closest node around the merged text."""
    rel = vs.select("page_id", F.col("text_start").alias("begin"), F.col("text_end").alias("end"))
    runs = islands(rel, "page_id", F.col("begin") >= F.col("_far"))
    merged = runs.groupBy("page_id", "island").agg(F.min("begin").alias("begin"), F.max("end").alias("end")).drop("island")
    return enclosing_node(merged, regions)


def text_block_visual(vs: DataFrame, regions: DataFrame, min_count: int, max_gap: int) -> DataFrame:
    rel = vs.select("page_id", F.col("text_start").alias("begin"), F.col("text_end").alias("end"))
    return enclosing_node(text_block(rel, min_count, max_gap, "page_id"), regions)


def region_block(vs: DataFrame, min_count: int, max_dx: int, max_dy: int, mode: str = "reading") -> DataFrame:
    """Blocks of spans that follow each other within ``max_dx`` and ``max_dy`` (both strict).

    ``reading`` orders the spans of a page by line, column and text and breaks where a
    step is too far; ``component`` takes the connected components of the nearness graph.
    """
    cols = ["page_id", *BOX, "text_start", "text_end"]
    if mode == "reading":
        w = Window.partitionBy("page_id").orderBy("y_l", "x_l", "text_start")
        prev = {c: F.lag(c).over(w) for c in BOX}
        gx = F.greatest(F.lit(0), F.col("x_l") - F.col("p_x_h"), F.col("p_x_l") - F.col("x_h"))
        gy = F.greatest(F.lit(0), F.col("y_l") - F.col("p_y_h"), F.col("p_y_l") - F.col("y_h"))
        step = vs.select(*cols, *(v.alias(f"p_{k}") for k, v in prev.items()))
        new = F.when(F.col("p_x_l").isNull() | (gx >= max_dx) | (gy >= max_dy), 1).otherwise(0)
        label = step.withColumn("block", F.sum(new).over(w.rowsBetween(Window.unboundedPreceding, 0))).select(*cols, "block")
    elif mode == "component":
        label = shipped(vs).select(*cols).groupBy("page_id").applyInPandas(_components(max_dx, max_dy), ", ".join(f"{c} long" for c in (*cols, "block")))
    else:
        raise ValueError(f"unknown mode {mode}")
    blocks = label.groupBy("page_id", "block").agg(
        F.min("x_l").alias("x_l"), F.min("y_l").alias("y_l"), F.max("x_h").alias("x_h"), F.max("y_h").alias("y_h"), F.min("text_start").alias("text_start"), F.max("text_end").alias("text_end"), F.count("*").alias("n_spans")
    )
    return blocks.where(F.col("n_spans") >= min_count).drop("block")


def _components(max_dx: int, max_dy: int):  # noqa: ANN202
    """Union-find over the near pairs of one page, swept by y so that only close lines are compared."""

    def run(page: pd.DataFrame) -> pd.DataFrame:
        page = page.sort_values(["y_l", "x_l", "text_start"], kind="stable").reset_index(drop=True)
        n = len(page)
        up = list(range(n))

        def find(i: int) -> int:
            while up[i] != i:
                up[i] = up[up[i]]
                i = up[i]
            return i

        x_l, y_l, x_h, y_h = (page[c].tolist() for c in BOX)
        active: list[int] = []
        for i in range(n):
            active = [j for j in active if y_l[i] - y_h[j] < max_dy]
            for j in active:
                if max(0, x_l[i] - x_h[j], x_l[j] - x_h[i]) < max_dx:
                    a, b = find(i), find(j)
                    if a != b:
                        up[max(a, b)] = min(a, b)
            active.append(i)
        page["block"] = [find(i) for i in range(n)]
        return page

    return run


def covering_regions(blocks: DataFrame, regions: DataFrame) -> DataFrame:
    """Adds the deepest node around each block's box, and that node's text interval."""
    r = regions.select("page_id", *(F.col(c).alias(f"n_{c}") for c in ("region_id", "text_start", "text_end", "depth", *BOX)))
    hit = blocks.join(r, "page_id").where((F.col("n_x_l") <= F.col("x_l")) & (F.col("n_y_l") <= F.col("y_l")) & (F.col("n_x_h") >= F.col("x_h")) & (F.col("n_y_h") >= F.col("y_h")))
    best = F.max_by(F.struct(F.col("n_region_id").alias("region_id"), F.col("n_text_start").alias("node_start"), F.col("n_text_end").alias("node_end")), F.struct("n_depth", "n_region_id"))
    keys = ["page_id", *BOX, "text_start", "text_end", "n_spans"]
    return hit.groupBy(*keys).agg(best.alias("n")).select(*keys, "n.*")

