"""Predicates and scalar operators on boxes and spans, as columns and as SQL functions.

All of them are plain comparisons, so Spark generates code for them, inlines the
SQL functions, and pushes those on constants down to the scan.  Pairs must be of one
page; joins add that equality (see ``operators.relational``).
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from ..model import Box


def _all(*terms: Column | None) -> Column:
    given = [t for t in terms if t is not None]
    return reduce(lambda a, b: a & b, given) if given else F.lit(True)


def _le(a: Column | None, b: Column | None) -> Column | None:
    return None if a is None or b is None else a <= b


# ---------------------------------------------------------------- directions
def north_of(a: Box, b: Box) -> Column:
    return _all(_le(a.y_h, b.y_l))


def south_of(a: Box, b: Box) -> Column:
    return _all(_le(b.y_h, a.y_l))


def west_of(a: Box, b: Box) -> Column:
    return _all(_le(a.x_h, b.x_l))


def east_of(a: Box, b: Box) -> Column:
    return _all(_le(b.x_h, a.x_l))


def _x_inside(a: Box, b: Box) -> Column:
    return _all(_le(b.x_l, a.x_l), _le(a.x_h, b.x_h))


def _y_inside(a: Box, b: Box) -> Column:
    return _all(_le(b.y_l, a.y_l), _le(a.y_h, b.y_h))


def strict_north_of(a: Box, b: Box) -> Column:
    return north_of(a, b) & _x_inside(a, b)


def strict_south_of(a: Box, b: Box) -> Column:
    return south_of(a, b) & _x_inside(a, b)


def strict_west_of(a: Box, b: Box) -> Column:
    return west_of(a, b) & _y_inside(a, b)


def strict_east_of(a: Box, b: Box) -> Column:
    return east_of(a, b) & _y_inside(a, b)


def north_west_of(a: Box, b: Box) -> Column:
    return north_of(a, b) & west_of(a, b)


def north_east_of(a: Box, b: Box) -> Column:
    return north_of(a, b) & east_of(a, b)


def south_west_of(a: Box, b: Box) -> Column:
    return south_of(a, b) & west_of(a, b)


def south_east_of(a: Box, b: Box) -> Column:
    return south_of(a, b) & east_of(a, b)


# ---------------------------------------------------------------- containment
def within(inner: Box, outer: Box) -> Column:
    """``inner`` lies inside ``outer``, borders included."""
    return _all(_x_inside(inner, outer), _y_inside(inner, outer))


def contains(a: Box, b: Box) -> Column:
    """Rule-language order: the first lies inside the second."""
    return within(a, b)


def intersects(a: Box, b: Box, interior: bool = False) -> Column:
    """The rectangles share a point, or an area if ``interior``."""
    if interior:
        return (a.x_l < b.x_h) & (b.x_l < a.x_h) & (a.y_l < b.y_h) & (b.y_l < a.y_h)
    return _all(_le(a.x_l, b.x_h), _le(b.x_l, a.x_h), _le(a.y_l, b.y_h), _le(b.y_l, a.y_h))


def touches(a: Box, b: Box, corners: bool = False) -> Column:
    """Edges lie on each other and the interiors are apart; contact in a corner alone only if asked for."""
    x_edge = (a.x_h == b.x_l) | (b.x_h == a.x_l)
    y_edge = (a.y_h == b.y_l) | (b.y_h == a.y_l)
    x_shared = (a.x_l < b.x_h) & (b.x_l < a.x_h)
    y_shared = (a.y_l < b.y_h) & (b.y_l < a.y_h)
    sides = (x_edge & y_shared) | (y_edge & x_shared)
    return sides | (x_edge & y_edge) if corners else sides


# ---------------------------------------------------------------- measures
def area(r: Box) -> Column:
    return (r.x_h - r.x_l) * (r.y_h - r.y_l)


def centroid_x(r: Box) -> Column:
    return (r.x_l + r.x_h) / F.lit(2.0)


def centroid_y(r: Box) -> Column:
    return (r.y_l + r.y_h) / F.lit(2.0)


def gap_x(a: Box, b: Box) -> Column:
    return F.greatest(F.lit(0).cast("long"), a.x_l - b.x_h, b.x_l - a.x_h)


def gap_y(a: Box, b: Box) -> Column:
    return F.greatest(F.lit(0).cast("long"), a.y_l - b.y_h, b.y_l - a.y_h)


# ---------------------------------------------------------------- spans
def follows(a_end: Column, b_begin: Column, d: int) -> Column:
    """The first ends before the second begins, with at most ``d`` characters between."""
    return (a_end <= b_begin) & (b_begin - a_end <= d)


def overlaps(a_begin: Column, a_end: Column, b_begin: Column, b_end: Column) -> Column:
    return (a_begin < b_end) & (b_begin < a_end)


def strictly_in(a_begin: Column, a_end: Column, b_begin: Column, b_end: Column) -> Column:
    return (b_begin <= a_begin) & (a_end <= b_end) & ((a_begin != b_begin) | (a_end != b_end))


def same_span(a_begin: Column, a_end: Column, b_begin: Column, b_end: Column) -> Column:
    return (a_begin == b_begin) & (a_end == b_end)


# ---------------------------------------------------------------- text
def ascii_word(term: str) -> str:
    """Java pattern of a whole word, where only ASCII letters, digits and _ are word characters."""
    import re

    return r"(?i)(?<![A-Za-z0-9_])" + re.escape(term).replace(r"\ ", " ") + r"(?![A-Za-z0-9_])"


def matches_phrase(text: Column, phrase: str) -> Column:
    """The text holds the words of the phrase one after the other, in any case, white space being alike."""
    return text.rlike(ascii_word(phrase).replace(" ", r"\s+"))


# ---------------------------------------------------------------- SQL
_BOX = "STRUCT<x_l: BIGINT, y_l: BIGINT, x_h: BIGINT, y_h: BIGINT>"
_SPAN = "STRUCT<begin: BIGINT, end: BIGINT>"




def sql_definitions() -> dict[str, tuple[str, str, str]]:
    """Name to (parameters, result type, body)."""
    two = f"a {_BOX}, b {_BOX}"
    x_in, y_in = "a.x_l >= b.x_l AND a.x_h <= b.x_h", "a.y_l >= b.y_l AND a.y_h <= b.y_h"
    plain = {"north": "a.y_h <= b.y_l", "south": "a.y_l >= b.y_h", "east": "a.x_l >= b.x_h", "west": "a.x_h <= b.x_l"}
    found = {f"{k}_of": (two, "BOOLEAN", v) for k, v in plain.items()}
    found |= {f"strict_{k}_of": (two, "BOOLEAN", f"{v} AND {x_in if k in ('north', 'south') else y_in}") for k, v in plain.items()}
    found |= {f"{v}_{h}_of": (two, "BOOLEAN", f"{plain[v]} AND {plain[h]}") for v in ("north", "south") for h in ("east", "west")}
    x_on, y_on = "(a.x_h = b.x_l OR b.x_h = a.x_l)", "(a.y_h = b.y_l OR b.y_h = a.y_l)"
    x_sh, y_sh = "(a.x_l < b.x_h AND b.x_l < a.x_h)", "(a.y_l < b.y_h AND b.y_l < a.y_h)"
    found |= {
        "box_within": (two, "BOOLEAN", f"{x_in} AND {y_in}"),
        "box_intersects": (two, "BOOLEAN", "a.x_l <= b.x_h AND b.x_l <= a.x_h AND a.y_l <= b.y_h AND b.y_l <= a.y_h"),
        "box_touches": (two, "BOOLEAN", f"({x_on} AND {y_sh}) OR ({y_on} AND {x_sh})"),
        "box_area": (f"a {_BOX}", "BIGINT", "(a.x_h - a.x_l) * (a.y_h - a.y_l)"),
        "box_gap_x": (two, "BIGINT", "greatest(0L, a.x_l - b.x_h, b.x_l - a.x_h)"),
        "box_gap_y": (two, "BIGINT", "greatest(0L, a.y_l - b.y_h, b.y_l - a.y_h)"),
        "span_follows": (f"a {_SPAN}, b {_SPAN}, d BIGINT", "BOOLEAN", "a.end <= b.begin AND b.begin - a.end <= d"),
        "span_overlaps": (f"a {_SPAN}, b {_SPAN}", "BOOLEAN", "a.begin < b.end AND b.begin < a.end"),
        "span_strictly_in": (f"a {_SPAN}, b {_SPAN}", "BOOLEAN", "b.begin <= a.begin AND a.end <= b.end AND NOT (a.begin = b.begin AND a.end = b.end)"),
        "is_path_prefix": ("up STRING, down STRING", "BOOLEAN", "startswith(down, concat(up, '.'))"),
    }
    return found


def register_all(spark: SparkSession) -> list[str]:
    """Create a temporary SQL function for each predicate; returns their names."""
    for name, (params, result, body) in sql_definitions().items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({params}) RETURNS {result} RETURN {body}")
    return list(sql_definitions())
