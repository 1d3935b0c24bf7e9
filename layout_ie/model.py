"""Types of the visual algebra: span, region, visual span, and the relation of regions.

Offsets are code points, 0-based and half-open.  y grows downward.  A virtual
region may lack bounds: a missing bound puts no condition.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

EDGES = ("x_l", "y_l", "x_h", "y_h")

SPAN = T.StructType([T.StructField(c, T.LongType()) for c in ("begin", "end")])
REGION = T.StructType([T.StructField(c, T.LongType()) for c in EDGES])
VISUAL_SPAN = T.StructType([T.StructField("s", SPAN), T.StructField("r", REGION)])

#: One row per node of a drawn page.  Text stands on innermost nodes only.
REGIONS = T.StructType(
    [
        T.StructField("page_id", T.LongType()),
        T.StructField("region_id", T.StringType()),
        *(T.StructField(c, T.LongType()) for c in EDGES),
        T.StructField("text_start", T.LongType()),
        T.StructField("text_end", T.LongType()),
        T.StructField("text", T.StringType()),
        T.StructField("html_tag", T.StringType()),
        T.StructField("minimal_region", T.StringType()),
        T.StructField("maximal_region", T.StringType()),
        T.StructField("depth", T.LongType()),
        T.StructField("ord", T.LongType()),
        T.StructField("template", T.LongType()),
    ]
)


@dataclass(frozen=True)
class Box:
    """The four edges of a rectangle as columns or numbers; None is an open bound."""

    x_l: Column | int | None
    y_l: Column | int | None
    x_h: Column | int | None
    y_h: Column | int | None

    @staticmethod
    def of(alias: str | None = None) -> Box:
        """Edges of the rows of ``alias`` (of the frame itself if None)."""
        return Box(*(F.col(f"{alias}.{c}" if alias else c) for c in EDGES))

    @staticmethod
    def suffixed(suffix: str) -> Box:
        return Box(*(F.col(f"{c}{suffix}") for c in EDGES))

    def struct(self) -> Column:
        edge = lambda v: v if isinstance(v, Column) else F.lit(v).cast("long")
        return F.struct(*(edge(v).alias(c) for c, v in zip(EDGES, (self.x_l, self.y_l, self.x_h, self.y_h), strict=True)))


def virtual_region(x_l: int | None = None, y_l: int | None = None, x_h: int | None = None, y_h: int | None = None) -> Box:
    """A constant rectangle; a bound that is None is infinite and yields no predicate."""
    return Box(x_l, y_l, x_h, y_h)


def span(begin: Column, end: Column) -> Column:
    return F.struct(begin.cast("long").alias("begin"), end.cast("long").alias("end"))


def visual_span(s: Column, r: Column) -> Column:
    return F.struct(s.alias("s"), r.alias("r"))
