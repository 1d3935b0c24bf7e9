"""Aggregate and table functions that Spark lacks."""

from __future__ import annotations

from collections.abc import Iterator
from typing import Any

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from ..model import REGION
from ..sources.pages import draw


def mbr_agg(x_l: str, y_l: str, x_h: str, y_h: str) -> Column:
    """Bounding box of a group as one struct: four partial minima and maxima."""
    return F.struct(F.min(x_l).alias("x_l"), F.min(y_l).alias("y_l"), F.max(x_h).alias("x_h"), F.max(y_h).alias("y_h")).cast(REGION)


class HtmlNodes:
    """Table function: the nodes of one page."""

    def eval(self, page_id: Any, html: Any) -> Iterator[tuple]:
        for r in draw(page_id, html):
            yield r[1], r[9], r[2], r[3], r[4], r[5], r[8]


def register_table_functions(spark: SparkSession) -> None:
    """``html_nodes(page_id, html)`` for SQL."""
    spark.udtf.register("html_nodes", F.udtf(HtmlNodes, returnType="region_id string, tag string, x_l long, y_l long, x_h long, y_h long, text string"))
