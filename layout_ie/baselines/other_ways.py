"""Other ways to evaluate the same rule: UDF matching, general geometry, aggregation outside SQL, one page at a time."""

from __future__ import annotations

import re
from collections.abc import Iterable

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.predicates import within
from ..model import Box

_TOKEN = re.compile(r"[A-Za-z0-9_]+")


def udf_match(pattern: str):  # noqa: ANN201
    """Text matching in Python, Arrow batches at a time: what an index or a built-in match is measured against."""

    @F.pandas_udf(T.BooleanType())
    def matches(text: pd.Series) -> pd.Series:
        rx = re.compile(pattern, re.ASCII)
        return text.map(lambda t: t is not None and rx.search(t) is not None)

    return matches


def udf_phrase(phrase: str):  # noqa: ANN201
    return udf_match(r"(?i)(?<![A-Za-z0-9_])" + re.escape(phrase) + r"(?![A-Za-z0-9_])")


def udf_dictionary(terms: Iterable[str]):  # noqa: ANN201
    """Dictionary matching in Python: whether a text holds one of the entries as whole words."""
    keys = sorted({k for t in terms if (k := " ".join(_TOKEN.findall(t.lower())))})

    @F.pandas_udf(T.BooleanType())
    def matches(text: pd.Series) -> pd.Series:
        found = text.map(lambda t: f" {' '.join(_TOKEN.findall(t.lower()))} " if t is not None else "")
        return found.map(lambda t: any(f" {k} " in t for k in keys))

    return matches


# ---------------------------------------------------------------- general geometry
def ring(x_l: Column, y_l: Column, x_h: Column, y_h: Column) -> Column:
    """Corners of a rectangle as a closed polygon (x, y, x, y, ...)."""
    return F.array(x_l, y_l, x_h, y_l, x_h, y_h, x_l, y_h, x_l, y_l).cast("array<double>")


def _half_plane(poly: list[float], axis: int, low: bool) -> float:
    values = poly[axis::2]
    return min(values) if low else max(values)


def polygon_strict(direction: str):  # noqa: ANN201
    """Strict direction of two polygons by their extents, computed vertex by vertex."""

    @F.pandas_udf(T.BooleanType())
    def test(a: pd.Series, b: pd.Series) -> pd.Series:
        out = []
        for p, o in zip(a, b, strict=True):
            p, o = list(p), list(o)
            if direction in ("south", "north"):
                inside = all(min(o[0::2]) <= x <= max(o[0::2]) for x in p[0::2])
                place = _half_plane(p, 1, True) >= _half_plane(o, 1, False) if direction == "south" else _half_plane(p, 1, False) <= _half_plane(o, 1, True)
            else:
                inside = all(min(o[1::2]) <= y <= max(o[1::2]) for y in p[1::2])
                place = _half_plane(p, 0, True) >= _half_plane(o, 0, False) if direction == "east" else _half_plane(p, 0, False) <= _half_plane(o, 0, True)
            out.append(inside and place)
        return pd.Series(out)

    return test


def right_of_match_polygons(vis: DataFrame, heading: DataFrame, matches: DataFrame) -> DataFrame:
    """Set result of the fourth task with polygons in place of edge comparisons."""
    box = lambda df, a: df.select("page_id", F.col("region_id").alias(f"{a}_id"), ring(*(F.col(c) for c in ("x_l", "y_l", "x_h", "y_h"))).alias(f"{a}_p"))
    south, east = polygon_strict("south"), polygon_strict("east")
    pairs = box(matches, "m").join(box(heading, "h"), "page_id").where(south("m_p", "h_p")).select("page_id", "m_id", "m_p").distinct()
    return box(vis, "s").join(pairs, "page_id").where(east("s_p", "m_p")).select("page_id", F.col("s_id").alias("region_id")).distinct()


# ---------------------------------------------------------------- outside the engine
def consolidate_outside(rel: DataFrame, page: str = "doc_id") -> DataFrame:
    """Overlapping spans merged in Python, a document at a time."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        out: list[list[int]] = []
        for a, b in sorted(zip(pdf["begin"], pdf["end"], strict=True)):
            if out and a < out[-1][1]:
                out[-1][1] = max(out[-1][1], b)
            else:
                out.append([a, b])
        return pd.DataFrame({page: pdf[page].iloc[0], "begin": [x[0] for x in out], "end": [x[1] for x in out]})

    return rel.select(page, "begin", "end").groupBy(page).applyInPandas(run, f"{page} long, begin long, end long")


def blocks_outside(rel: DataFrame, min_count: int, max_gap: int, page: str = "doc_id") -> DataFrame:
    """Text blocks in Python, a document at a time."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        out: list[list[int]] = []
        for a, b in sorted(zip(pdf["begin"], pdf["end"], strict=True)):
            if out and a - out[-1][1] <= max_gap:
                out[-1][1] = max(out[-1][1], b)
                out[-1][2] += 1
            else:
                out.append([a, b, 1])
        kept = [x for x in out if x[2] >= min_count]
        return pd.DataFrame({page: [pdf[page].iloc[0]] * len(kept), "begin": [x[0] for x in kept], "end": [x[1] for x in kept], "n_spans": [x[2] for x in kept]})

    return rel.select(page, "begin", "end").groupBy(page).applyInPandas(run, f"{page} long, begin long, end long, n_spans long")


# ---------------------------------------------------------------- one page at a time
def nest(vis: DataFrame, columns: tuple[str, ...] = ("region_id", "x_l", "y_l", "x_h", "y_h", "text")) -> DataFrame:
    """One row per page with its regions as an array."""
    return vis.groupBy("page_id").agg(F.collect_list(F.struct(*columns)).alias("regions"))


def right_of_match_per_page(nested: DataFrame, heading_pattern: str, match_pattern: str) -> DataFrame:
    """The fourth task by higher-order functions inside one row: no shuffle once pages are nested; a set."""
    text = lambda p: lambda r: F.coalesce(r["text"].rlike(p), F.lit(False))
    heads, found = F.filter("regions", text(heading_pattern)), F.filter("regions", text(match_pattern))
    below = lambda m: F.exists("_heads", lambda h: (m["y_l"] >= h["y_h"]) & (m["x_l"] >= h["x_l"]) & (m["x_h"] <= h["x_h"]))
    right = lambda s: F.exists("_pairs", lambda m: (s["x_l"] >= m["x_h"]) & (s["y_l"] >= m["y_l"]) & (s["y_h"] <= m["y_h"]))
    one = nested.select("page_id", "regions", heads.alias("_heads"), found.alias("_found"))
    two = one.select("page_id", "regions", F.filter("_found", below).alias("_pairs"))
    return two.select("page_id", F.explode(F.transform(F.filter("regions", right), lambda s: s["region_id"])).alias("region_id"))


def _holds(pattern: str):  # noqa: ANN202
    return lambda r: F.coalesce(r["text"].rlike(pattern), F.lit(False))


def _ids(page: Column) -> Column:
    return F.explode(F.transform(page, lambda r: r["region_id"])).alias("region_id")


def _edges_of(r: Column) -> Box:
    return Box(r["x_l"], r["y_l"], r["x_h"], r["y_h"])


def left_bar_per_page(nested: DataFrame, n: int, box: Box) -> DataFrame:
    """The first task inside one row: each region's column is gathered and its bounds are tested."""
    bar = F.filter("regions", lambda r: r["x_l"] >= box.x_l) if box.x_l is not None else F.col("regions")
    edge = lambda xs, name, best: best(F.transform(xs, lambda x: x[name]))

    def column(key: Column) -> Column:
        own = F.filter("_bar", lambda r: r["x_l"] == key)
        bound = Box(key, edge(own, "y_l", F.array_min), edge(own, "x_h", F.array_max), edge(own, "y_h", F.array_max))
        return F.when((F.size(own) > n) & within(bound, box), own)

    keys = F.array_distinct(F.transform("_bar", lambda r: r["x_l"]))
    groups = F.filter(F.transform(keys, column), lambda g: g.isNotNull())
    return nested.select("page_id", bar.alias("_bar")).select("page_id", _ids(F.flatten(groups)))


def top_term_per_page(nested: DataFrame, pattern: str, box: Box) -> DataFrame:
    """The second task inside one row."""
    return nested.select("page_id", _ids(F.filter("regions", lambda r: within(_edges_of(r), box) & _holds(pattern)(r))))


def names_per_page(nested: DataFrame, heading_pattern: str, patterns: list[str]) -> DataFrame:
    """The third task inside one row; a set."""
    heads, found = F.filter("regions", _holds(heading_pattern)), F.filter("regions", _holds("|".join(f"(?:{p})" for p in patterns)))
    south = lambda v, h: (v["y_l"] >= h["y_h"]) & (v["x_l"] >= h["x_l"]) & (v["x_h"] <= h["x_h"])
    east = lambda v, h: (v["x_l"] >= h["x_h"]) & (v["y_l"] >= h["y_l"]) & (v["y_h"] <= h["y_h"])
    one = nested.select("page_id", heads.alias("_heads"), found.alias("_found"))
    return one.select("page_id", _ids(F.filter("_found", lambda v: F.exists("_heads", lambda h: south(v, h) | east(v, h)))))
