"""All queries of the engine, each with SQL that computes the same rows from the raw tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..baselines import other_ways, source_rules
from ..functions import predicates as P
from ..functions import tables_functions
from ..index import text as text_index
from ..measures.accuracy import accuracy, corpus_stats, robustness
from ..model import Box, span, virtual_region, visual_span
from ..operators import align, hierarchy, spans, visual
from ..oracles import drawings as D
from ..oracles.drawings import q
from ..plans import evaluate, rules
from ..sources import pages, sheets, textgrid
from ..sources.tables import load, read_pages, write_matches
from ..streaming import stream
from . import modes, tasks

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
L = "BIGINT"


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLES[name] = sql


def docs(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "documents").select("doc_id", "text")


# ---------------------------------------------------------------- regex and dictionary spans
PATTERNS = {
    "regex_email_spans": r"[A-Za-z0-9._]+@[A-Za-z0-9.]+",
    "regex_ip_spans": r"[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}",
    "regex_token_spans": r'token = "[0-9a-f]+"',
    "regex_digits16_spans": r"[0-9]{16}",
    "regex_license_spans": r"[Ll]icen[sc]e[^\n]*",
}
for _name, _pattern in PATTERNS.items():
    add(_name, lambda s, d, p=_pattern: spans.regex_spans(docs(s, d), p), q('SELECT doc_id, "begin", "end", matched FROM sp', D.spans(_pattern)))
add(
    "regex_flags_spans",
    lambda s, d: spans.regex_spans(docs(s, d), "[a-z]+ing", flags="i"),
    q('SELECT doc_id, "begin", "end", matched FROM sp', D.spans("(?i)[a-z]+ing")),
)
add(
    "regex_group_spans",
    lambda s, d: spans.regex_spans(docs(s, d), "[A-Za-z0-9._]+@([A-Za-z0-9.]+)", group=1),
    q("""SELECT doc_id, "begin" + length(split_part(matched, '@', 1)) + 1 AS "begin", "end", split_part(matched, '@', 2) AS matched FROM sp""", D.spans(PATTERNS["regex_email_spans"])),
)
add(
    "regex_empty_spans",
    lambda s, d: spans.regex_spans(docs(s, d), r"(?=\n)"),
    q("SELECT doc_id, CAST(i - 1 AS BIGINT) AS \"begin\", CAST(i - 1 AS BIGINT) AS \"end\", '' AS matched FROM (SELECT doc_id, text, unnest(range(1, length(text) + 1)) AS i FROM documents) WHERE substr(text, i, 1) = chr(10)"),
)
add(
    "regex_turn_spans",
    lambda s, d: spans.regex_spans(load(s, d, "conversations"), r"[^.!?\n]+[.!?]", keep=("conv_id", "turn")),
    q('SELECT conv_id, turn, "begin", "end", matched FROM sp', D.spans(r"[^.!?\n]+[.!?]", "conversations", "conv_id, turn")),
)

WORDS = ("the", "and", "of")
TOKENS = D.spans(spans.TOKEN, name="tk")


def words_df(s: SparkSession, *terms: str) -> DataFrame:
    return s.range(1).select(F.explode(F.array(*map(F.lit, terms))).alias("term"))


def word_spans(s: SparkSession, d: str, *terms: str) -> DataFrame:
    return spans.dict_spans(docs(s, d), words_df(s, *terms), max_words=max(len(t.split()) for t in terms))


_IN = ", ".join(f"'{w}'" for w in WORDS)
add("dict_word_spans", lambda s, d: word_spans(s, d, *WORDS), q(f'SELECT doc_id, "begin", "end", lower(matched) AS term FROM tk WHERE lower(matched) IN ({_IN})', TOKENS))
_PAIR = 'tw AS (SELECT doc_id, "begin", lower(matched) AS w, lead("end") OVER x AS e2, lower(lead(matched) OVER x) AS w2 FROM tk_n WINDOW x AS (PARTITION BY rid ORDER BY "begin"))'
_TK_N = TOKENS + ', tk_n AS (SELECT doc_id, rid, CAST(sum(length(gap) + length(w)) OVER (PARTITION BY rid ORDER BY i) AS BIGINT) - length(w) AS "begin", CAST(sum(length(gap) + length(w)) OVER (PARTITION BY rid ORDER BY i) AS BIGINT) AS "end", w AS matched FROM tk_u)'
add(
    "dict_phrase_spans",
    lambda s, d: word_spans(s, d, "of the", "and the"),
    q("""SELECT doc_id, "begin", e2 AS "end", w || ' ' || w2 AS term FROM tw WHERE w || ' ' || w2 IN ('of the', 'and the')""", _TK_N, _PAIR),
)
add(
    "dict_from_table_spans",
    lambda s, d: spans.dict_spans(docs(s, d), load(s, d, "benchmark").select(F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("term")).where("length(term) >= 12").distinct(), max_words=1),
    q(
        'SELECT doc_id, "begin", "end", lower(matched) AS term FROM tk WHERE lower(matched) IN (SELECT t FROM bt)',
        TOKENS,
        "bt AS (SELECT DISTINCT t FROM (SELECT unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS t FROM benchmark) WHERE length(t) >= 12)",
    ),
)

# ---------------------------------------------------------------- span predicates and aggregation
_S = 'w AS (SELECT doc_id, "begin" AS b, "end" AS e, lower(matched) AS term FROM tk)'


def spans_of(s: SparkSession, d: str, *terms: str) -> DataFrame:
    return word_spans(s, d, *terms).select("doc_id", "begin", "end")


add(
    "span_follows_d",
    lambda s, d: spans.follows_join(spans_of(s, d, "of"), spans_of(s, d, "the"), 30).groupBy("doc_id").agg(F.count("*").alias("n_pairs"), F.sum("b_begin").alias("sum_begin")),
    q("SELECT a.doc_id, count(*) AS n_pairs, CAST(sum(b.b) AS BIGINT) AS sum_begin FROM w a JOIN w b ON a.doc_id = b.doc_id AND a.e <= b.b AND b.b - a.e <= 30 WHERE a.term = 'of' AND b.term = 'the' GROUP BY 1", TOKENS, _S),
)
WIDE, NARROW = r"[a-z]+ [a-z]+ [a-z]+", r"[a-z]+, [a-z]+"
_WN = (D.spans(WIDE, name="wi"), D.spans(NARROW, name="na"))


def _span_pairs(s: SparkSession, d: str, test: Callable) -> DataFrame:
    a = spans.regex_spans(docs(s, d), NARROW).select(F.col("doc_id"), F.col("begin").alias("ab"), F.col("end").alias("ae"))
    b = spans.regex_spans(docs(s, d), WIDE).select(F.col("doc_id"), F.col("begin").alias("bb"), F.col("end").alias("be"))
    # Overlapping spans start within one bucket's width of each other.
    width = 64
    bucket = lambda x, y: F.explode(F.sequence(F.floor(F.col(x) / width), F.floor((F.col(y) - 1) / width)))
    a, b = a.withColumn("_k", bucket("ab", "ae")), b.withColumn("_k", bucket("bb", "be"))
    lowest = F.col("_k") == F.floor(F.greatest("ab", "bb") / width)
    pairs = a.join(b, ["doc_id", "_k"]).where(lowest & test(F.col("ab"), F.col("ae"), F.col("bb"), F.col("be")))
    return pairs.groupBy("doc_id").agg(F.count("*").alias("n_pairs"), F.sum(F.col("ab") + F.col("be")).alias("checksum"))


for _name, _test, _cond in (
    ("span_overlap", P.overlaps, 'a."begin" < b."end" AND b."begin" < a."end"'),
    ("span_strict_in", P.strictly_in, 'b."begin" <= a."begin" AND a."end" <= b."end" AND (a."begin" <> b."begin" OR a."end" <> b."end")'),
):
    add(
        _name,
        lambda s, d, t=_test: _span_pairs(s, d, t),
        q(f'SELECT a.doc_id, count(*) AS n_pairs, CAST(sum(a."begin" + b."end") AS BIGINT) AS checksum FROM na a JOIN wi b ON a.doc_id = b.doc_id AND {_cond} GROUP BY 1', *_WN),
    )
add(
    "span_equal",
    lambda s, d: spans_of(s, d, "the").join(spans.regex_spans(docs(s, d), "[a-z]+").select("doc_id", "begin", "end"), ["doc_id", "begin", "end"]).groupBy("doc_id").agg(F.count("*").alias("n_pairs")),
    q("""SELECT w.doc_id, count(*) AS n_pairs FROM w JOIN lo ON w.doc_id = lo.doc_id AND w.b = lo."begin" AND w.e = lo."end" WHERE w.term = 'the' GROUP BY 1""", TOKENS, _S, D.spans("[a-z]+", name="lo")),
)


def mixed_spans(s: SparkSession, d: str) -> DataFrame:
    return spans.union(spans.regex_spans(docs(s, d), WIDE).select("doc_id", "begin", "end"), spans.regex_spans(docs(s, d), NARROW).select("doc_id", "begin", "end"))


_MIX = 'mx AS (SELECT doc_id, "begin" AS b, "end" AS e FROM wi UNION ALL SELECT doc_id, "begin", "end" FROM na)'
add(
    "consolidate_contained",
    lambda s, d: spans.consolidate_contained(mixed_spans(s, d)),
    q(
        'SELECT DISTINCT a.doc_id, a.b AS "begin", a.e AS "end" FROM (SELECT DISTINCT * FROM mx) a LEFT JOIN (SELECT DISTINCT * FROM mx) c ON a.doc_id = c.doc_id AND c.b <= a.b AND a.e <= c.e AND (a.b <> c.b OR a.e <> c.e) WHERE c.b IS NULL',
        *_WN,
        _MIX,
    ),
)
_ISL = """far AS (SELECT *, max(e) OVER (PARTITION BY doc_id ORDER BY b, e ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS f FROM {src}),
isl AS (SELECT *, sum(CASE WHEN f IS NULL OR {cut} THEN 1 ELSE 0 END) OVER (PARTITION BY doc_id ORDER BY b, e ROWS UNBOUNDED PRECEDING) AS i FROM far)"""
add("consolidate_overlapping", lambda s, d: spans.consolidate_overlapping(mixed_spans(s, d)), q('SELECT doc_id, min(b) AS "begin", max(e) AS "end" FROM isl GROUP BY doc_id, i', *_WN, _MIX, _ISL.format(src="mx", cut="b >= f")))
add("consolidate_outside_engine", lambda s, d: other_ways.consolidate_outside(mixed_spans(s, d)), ORACLES["consolidate_overlapping"])
_D3 = f"dw AS (SELECT doc_id, b, e FROM w WHERE term IN ({_IN}))"
_BLK = q('SELECT doc_id, min(b) AS "begin", max(e) AS "end", count(*) AS n_spans FROM isl GROUP BY doc_id, i HAVING count(*) >= 4', TOKENS, _S, _D3, _ISL.format(src="dw", cut="b - f > 25"))
add("text_block", lambda s, d: spans.text_block(spans_of(s, d, *WORDS), 4, 25), _BLK)
add("text_block_outside_engine", lambda s, d: other_ways.blocks_outside(spans_of(s, d, *WORDS), 4, 25), _BLK)

# ---------------------------------------------------------------- drawings
add("sheet_boxes", sheets.boxes, q("SELECT * FROM vis", D.SHEETS))
add("page_regions", pages.regions, q("SELECT * FROM reg", D.PAGES))
add("grid_regions", textgrid.regions, q("SELECT * FROM grid_words", D.GRID))
add(
    "page_region_text",
    lambda s, d: hierarchy.region_text(pages.regions(s, d), hierarchy.page_texts(pages.regions(s, d))).select("page_id", "region_id", F.length("full_text").cast("long").alias("n_chars"), F.md5("full_text").alias("digest")),
    q(
        "SELECT page_id, region_id, CAST(length(t) AS BIGINT) AS n_chars, md5(t) AS digest FROM (SELECT r.page_id, r.region_id, substr(w.t, r.text_start + 1, r.text_end - r.text_start) AS t FROM reg r JOIN pt2 w ON w.page_id = r.page_id)",
        D.PAGES,
        "pt2 AS (SELECT page_id, string_agg(said, chr(10) ORDER BY a) AS t FROM rn GROUP BY 1)",
    ),
)
add(
    "page_extremes",
    lambda s, d: hierarchy.annotate_extremes(pages.regions(s, d).drop("minimal_region", "maximal_region")).select("page_id", "region_id", "minimal_region", "maximal_region"),
    q("SELECT page_id, region_id, minimal_region, maximal_region FROM reg", D.PAGES),
)
_VREGS = (
    D.SHEETS,
    """cont AS (SELECT page_id, region_id, unnest(range(1, len(string_split(region_id, '.')))) AS k, text_start, text_end FROM vis),
nodes AS (SELECT page_id, array_to_string(string_split(region_id, '.')[1:k], '.') AS region_id, min(text_start) AS a, max(text_end) AS b FROM cont GROUP BY ALL
  UNION ALL SELECT page_id, region_id, text_start, text_end FROM vis),
ext AS (SELECT page_id, region_id, arg_max(region_id, len(string_split(region_id, '.'))) OVER x AS minimal_region, arg_min(region_id, len(string_split(region_id, '.'))) OVER x AS maximal_region, b > a AS said FROM nodes WINDOW x AS (PARTITION BY page_id, a, b))""",
)
add("sheet_extremes", lambda s, d: sheets.regions(s, d).select("page_id", "region_id", "minimal_region", "maximal_region"), q("SELECT page_id, region_id, minimal_region, maximal_region FROM ext", *_VREGS))
add("regions_of_page", lambda s, d: hierarchy.all_regions(pages.regions(s, d)).select("page_id", "region_id", "html_tag", "x_l", "y_l", "x_h", "y_h"), q("SELECT page_id, region_id, html_tag, x_l, y_l, x_h, y_h FROM reg", D.PAGES))
_STATS = "SELECT count(*) AS n_pages, CAST(sum(n) AS BIGINT) AS n_regions, min(n) AS least, max(n) AS most, round(avg(n), 4) AS mean FROM (SELECT page_id, count(*) AS n FROM {t} GROUP BY 1)"
add("corpus_stats", lambda s, d: corpus_stats(sheets.boxes(s, d)), q(_STATS.format(t="vis"), D.SHEETS))
add("corpus_stats_pages", lambda s, d: corpus_stats(pages.regions(s, d)), q(_STATS.format(t="reg"), D.PAGES))

# ---------------------------------------------------------------- hierarchy
_R = ("page_id", "of_region", "region_id")


def _tag(s: SparkSession, d: str, tag: str) -> tuple[DataFrame, DataFrame]:
    regions = pages.regions(s, d)
    return regions.where(F.col("html_tag") == tag), regions


for _name, _fn, _t, _on in (
    ("ancestors", hierarchy.ancestors, "b", "starts_with(v.region_id, r.region_id || '.')"),
    ("descendants", hierarchy.descendants, "nav", "starts_with(r.region_id, v.region_id || '.')"),
    ("children", hierarchy.children, "article", "starts_with(r.region_id, v.region_id || '.') AND r.depth = v.depth + 1"),
    ("parent", hierarchy.parent, "a", "starts_with(v.region_id, r.region_id || '.') AND r.depth = v.depth - 1"),
    ("siblings", hierarchy.siblings, "h1", "r.region_id <> v.region_id AND r.depth = v.depth AND starts_with(r.region_id, regexp_replace(v.region_id, '[0-9]+$', ''))"),
    ("maximal_region", hierarchy.maximal_region, "a", "r.region_id = v.maximal_region"),
    ("minimal_region", hierarchy.minimal_region, "nav", "r.region_id = v.minimal_region"),
):
    add(_name, lambda s, d, f=_fn, t=_t: f(*_tag(s, d, t)).select(*_R), q(f"SELECT v.page_id, v.region_id AS of_region, r.region_id FROM reg v JOIN reg r ON r.page_id = v.page_id AND {_on} WHERE v.html_tag = '{_t}'", D.PAGES))

# ---------------------------------------------------------------- directions, topology, geometry


def _pairs(boxes: DataFrame, test: Callable) -> DataFrame:
    """Pairs per page for which the predicate holds, with a checksum of their places in the document."""
    cols = ("page_id", "ord", "x_l", "y_l", "x_h", "y_h")
    a, b = boxes.select(*cols).alias("a"), boxes.select(*cols).alias("b")
    on = (F.col("a.page_id") == F.col("b.page_id")) & (F.col("a.ord") != F.col("b.ord")) & test(Box.of("a"), Box.of("b"))
    return a.join(b, on).groupBy(F.col("a.page_id").alias("page_id")).agg(F.count("*").alias("n_pairs"), F.sum(F.col("a.ord") * 1000 + F.col("b.ord")).alias("checksum"))


def _pairs_sql(cond: str, table: str, part: str) -> str:
    return q(f"SELECT a.page_id, count(*) AS n_pairs, CAST(sum(a.ord * 1000 + b.ord) AS BIGINT) AS checksum FROM {table} a JOIN {table} b ON a.page_id = b.page_id AND a.ord <> b.ord AND {cond} GROUP BY 1", part)


_N, _SO, _E, _W = "a.y_h <= b.y_l", "a.y_l >= b.y_h", "a.x_l >= b.x_h", "a.x_h <= b.x_l"
_XI, _YI = "a.x_l >= b.x_l AND a.x_h <= b.x_h", "a.y_l >= b.y_l AND a.y_h <= b.y_h"
_XO, _YO = "(a.x_h = b.x_l OR a.x_l = b.x_h)", "(a.y_h = b.y_l OR a.y_l = b.y_h)"
_XS, _YS = "(a.x_l < b.x_h AND b.x_l < a.x_h)", "(a.y_l < b.y_h AND b.y_l < a.y_h)"
PREDICATES = {
    "north_of": (P.north_of, _N), "south_of": (P.south_of, _SO), "east_of": (P.east_of, _E), "west_of": (P.west_of, _W),
    "strict_north_of": (P.strict_north_of, f"{_N} AND {_XI}"), "strict_south_of": (P.strict_south_of, f"{_SO} AND {_XI}"),
    "strict_east_of": (P.strict_east_of, f"{_E} AND {_YI}"), "strict_west_of": (P.strict_west_of, f"{_W} AND {_YI}"),
    "north_west_of": (P.north_west_of, f"{_N} AND {_W}"), "south_east_of": (P.south_east_of, f"{_SO} AND {_E}"),
    "north_east_of": (P.north_east_of, f"{_N} AND {_E}"), "south_west_of": (P.south_west_of, f"{_SO} AND {_W}"),
    "within_pairs": (P.within, f"{_XI} AND {_YI}"), "touches": (P.touches, f"(({_XO} AND {_YS}) OR ({_YO} AND {_XS}))"),
    "touches_corners": (lambda a, b: P.touches(a, b, corners=True), f"(({_XO} AND {_YS}) OR ({_YO} AND {_XS}) OR ({_XO} AND {_YO}))"),
    "intersects": (P.intersects, "a.x_l <= b.x_h AND b.x_l <= a.x_h AND a.y_l <= b.y_h AND b.y_l <= a.y_h"),
    "intersects_interior": (lambda a, b: P.intersects(a, b, interior=True), f"{_XS} AND {_YS}"),
}
for _name, (_fn, _cond) in PREDICATES.items():
    add(_name, lambda s, d, f=_fn: _pairs(sheets.boxes(s, d), f), _pairs_sql(_cond, "vis", D.SHEETS))
for _name in ("north_of", "strict_south_of", "east_of", "within_pairs", "touches", "intersects"):
    add(f"{_name}_pages", lambda s, d, f=PREDICATES[_name][0]: _pairs(pages.regions(s, d), f), _pairs_sql(PREDICATES[_name][1], "reg", D.PAGES))
add("within_virtual", lambda s, d: sheets.boxes(s, d).where(P.within(Box.of(), virtual_region(0, 90, 500, None))).select("page_id", "region_id"), q("SELECT page_id, region_id FROM vis WHERE x_l >= 0 AND y_l >= 90 AND x_h <= 500", D.SHEETS))
add("area", lambda s, d: pages.regions(s, d).select("page_id", "region_id", P.area(Box.of()).alias("area")), q("SELECT page_id, region_id, (x_h - x_l) * (y_h - y_l) AS area FROM reg", D.PAGES))
add("centroid", lambda s, d: pages.regions(s, d).select("page_id", "region_id", P.centroid_x(Box.of()).alias("cx"), P.centroid_y(Box.of()).alias("cy")), q("SELECT page_id, region_id, (x_l + x_h) / 2.0 AS cx, (y_l + y_h) / 2.0 AS cy FROM reg", D.PAGES))
add(
    "nearest_south",
    lambda s, d: align.nearest(sheets.boxes(s, d).where("kind = 'head'"), sheets.boxes(s, d), "south").select("page_id", "a_id", "b_id", "gap"),
    q(
        "SELECT page_id, a_id, b_id, gap FROM (SELECT a.page_id, a.region_id AS a_id, b.region_id AS b_id, b.y_l - a.y_h AS gap, row_number() OVER (PARTITION BY a.page_id, a.region_id ORDER BY b.y_l - a.y_h, b.region_id) AS k FROM vis a JOIN vis b ON a.page_id = b.page_id AND b.y_l >= a.y_h AND a.x_l < b.x_h AND b.x_l < a.x_h AND a.region_id <> b.region_id WHERE a.kind = 'head') WHERE k = 1",
        D.SHEETS,
    ),
)
for _name, _gap, _face in (
    ("north", "a.y_l - b.y_h", "a.x_l < b.x_h AND b.x_l < a.x_h"), ("east", "b.x_l - a.x_h", "a.y_l < b.y_h AND b.y_l < a.y_h"), ("west", "a.x_l - b.x_h", "a.y_l < b.y_h AND b.y_l < a.y_h"),
):
    add(
        f"nearest_{_name}_2",
        lambda s, d, w=_name: align.nearest(sheets.boxes(s, d).where("kind = 'head'"), sheets.boxes(s, d), w, 2).select("page_id", "a_id", "b_id", "gap", F.col("place").cast("long").alias("place")),
        q(f"SELECT * FROM (SELECT a.page_id, a.region_id AS a_id, b.region_id AS b_id, {_gap} AS gap, row_number() OVER (PARTITION BY a.page_id, a.region_id ORDER BY {_gap}, b.region_id) AS place FROM vis a JOIN vis b ON a.page_id = b.page_id AND {_gap} >= 0 AND {_face} AND a.region_id <> b.region_id WHERE a.kind = 'head') WHERE place <= 2", D.SHEETS),
    )
_GAPX, _GAPY = (f"greatest(0, a.{e}_l - b.{e}_h, b.{e}_l - a.{e}_h)" for e in "xy")
add(
    "gaps",
    lambda s, d: _gaps(pages.regions(s, d)),
    q(f"SELECT a.page_id, CAST(sum({_GAPX}) AS BIGINT) AS dx, CAST(sum({_GAPY}) AS BIGINT) AS dy FROM reg a JOIN reg b ON a.page_id = b.page_id WHERE a.html_tag = 'h1' GROUP BY 1", D.PAGES),
)


def _gaps(r: DataFrame) -> DataFrame:
    a, b = r.where("html_tag = 'h1'").alias("a"), r.alias("b")
    pairs = a.join(b, F.col("a.page_id") == F.col("b.page_id"))
    return pairs.groupBy(F.col("a.page_id").alias("page_id")).agg(F.sum(P.gap_x(Box.of("a"), Box.of("b"))).alias("dx"), F.sum(P.gap_y(Box.of("a"), Box.of("b"))).alias("dy"))


from ..index.region import grid_pairs, page_grid  # noqa: E402

add(
    "intersects_by_grid",
    lambda s, d: grid_pairs(pages.regions(s, d), pages.regions(s, d), P.intersects).where("a_id <> b_id").groupBy("page_id").agg(F.count("*").alias("n_pairs")),
    q("SELECT a.page_id, count(*) AS n_pairs FROM reg a JOIN reg b ON a.page_id = b.page_id AND a.ord <> b.ord AND a.x_l <= b.x_h AND b.x_l <= a.x_h AND a.y_l <= b.y_h AND b.y_l <= a.y_h GROUP BY 1", D.PAGES),
)
add(
    "page_grid_cells",
    lambda s, d: page_grid(pages.regions(s, d)).groupBy("page_id").agg(F.count("*").alias("n_cells")),
    q("SELECT page_id, CAST(sum((x_h // 200 - x_l // 200 + 1) * (y_h // 200 - y_l // 200 + 1)) AS BIGINT) AS n_cells FROM reg GROUP BY 1", D.PAGES),
)

# ---------------------------------------------------------------- grouping
_GB = ["page_id", "group_key", "island"]
_MBR = "min(x_l) AS x_l, min(y_l) AS y_l, max(x_h) AS x_h, max(y_h) AS y_h, count(*) AS n_members"


def _groups(df: DataFrame) -> DataFrame:
    return align.minimal_bounding_region(df).drop("text_start", "text_end", "island")


add("vertically_aligned", lambda s, d: _groups(align.vertically_aligned(sheets.boxes(s, d))), q(f"SELECT page_id, x_l AS group_key, {_MBR} FROM vis GROUP BY page_id, vis.x_l", D.SHEETS))
add("horizontally_aligned", lambda s, d: _groups(align.horizontally_aligned(sheets.boxes(s, d))), q(f"SELECT page_id, y_l AS group_key, {_MBR} FROM vis GROUP BY page_id, vis.y_l", D.SHEETS))
add("aligned_literal", lambda s, d: _groups(align.horizontally_aligned(sheets.boxes(s, d), literal_mapping=True)), ORACLES["vertically_aligned"])
_MAXD = """g AS (SELECT *, CASE WHEN y_l - lag(y_h) OVER w > 10 THEN 1 ELSE 0 END AS c FROM vis WINDOW w AS (PARTITION BY page_id, x_l ORDER BY y_l, y_h, region_id)),
gi AS (SELECT *, sum(c) OVER (PARTITION BY page_id, x_l ORDER BY y_l, y_h, region_id ROWS UNBOUNDED PRECEDING) AS i FROM g)"""
add("aligned_maxdist", lambda s, d: _groups(align.vertically_aligned(sheets.boxes(s, d), max_dist=10)), q(f"SELECT page_id, x_l AS group_key, {_MBR} FROM gi GROUP BY page_id, gi.x_l, i", D.SHEETS, _MAXD))
_CONS = """p AS (SELECT *, lag(y_h) OVER w AS py, lag(x_h) OVER w AS px FROM vis WINDOW w AS (PARTITION BY page_id, x_l ORDER BY y_l, y_h, region_id)),
cut AS (SELECT DISTINCT p.page_id, p.region_id FROM p JOIN vis o ON o.page_id = p.page_id AND o.x_l <> p.x_l AND o.x_l < greatest(p.x_h, p.px) AND o.x_h > p.x_l AND o.y_l < p.y_l AND o.y_h > p.py WHERE p.y_l > p.py),
gi AS (SELECT p.*, sum(CASE WHEN cut.page_id IS NOT NULL THEN 1 ELSE 0 END) OVER (PARTITION BY p.page_id, x_l ORDER BY y_l, y_h, p.region_id ROWS UNBOUNDED PRECEDING) AS i FROM p LEFT JOIN cut ON cut.page_id = p.page_id AND cut.region_id = p.region_id)"""
add("aligned_consecutive", lambda s, d: _groups(align.vertically_aligned(sheets.boxes(s, d), consecutive=True)), q(f"SELECT page_id, x_l AS group_key, {_MBR} FROM gi GROUP BY page_id, gi.x_l, i", D.SHEETS, _CONS))
_TOL = """ch AS (SELECT *, CASE WHEN x_l - lag(x_l) OVER (PARTITION BY page_id ORDER BY x_l) > 25 THEN 1 ELSE 0 END AS c FROM vis),
cg AS (SELECT *, sum(c) OVER (PARTITION BY page_id ORDER BY x_l RANGE UNBOUNDED PRECEDING) AS i FROM ch)"""
add("aligned_tolerance", lambda s, d: _groups(align.aligned(sheets.boxes(s, d), tol=25)), q(f"SELECT page_id, min(x_l) AS group_key, {_MBR} FROM cg GROUP BY page_id, i", D.SHEETS, _TOL))
for _name, _axis, _edge, _key in (("right", "column", "x_h", "x_h"), ("bottom", "row", "y_h", "y_h"), ("centre", "column", "centre", "(x_l + x_h)"), ("middle", "row", "centre", "(y_l + y_h)")):
    add(
        f"aligned_{_name}",
        lambda s, d, a=_axis, e=_edge: _groups(align.aligned(sheets.boxes(s, d), a, edge=e)),
        q(f"SELECT page_id, k AS group_key, {_MBR} FROM (SELECT *, {_key} AS k FROM vis) GROUP BY page_id, k", D.SHEETS),
    )
add("minimal_bounding_region", lambda s, d: align.minimal_bounding_region(pages.regions(s, d), ["page_id", "html_tag"]).drop("text_start", "text_end"), q(f"SELECT page_id, html_tag, {_MBR} FROM reg GROUP BY ALL", D.PAGES))
add(
    "minimal_super_region",
    lambda s, d: align.minimal_super_region(align.minimal_bounding_region(pages.regions(s, d).where("html_tag in ('li', 'p')"), ["page_id", "html_tag"]), pages.regions(s, d), ["page_id", "html_tag"]).select("page_id", "html_tag", "region_id"),
    q(
        "SELECT g.page_id, g.html_tag, arg_min(r.region_id, ((r.x_h - r.x_l) * (r.y_h - r.y_l)) * 100 - r.depth) AS region_id FROM (SELECT page_id, html_tag, min(x_l) AS a, min(y_l) AS b, max(x_h) AS c, max(y_h) AS d FROM reg WHERE html_tag IN ('li', 'p') GROUP BY ALL) g JOIN reg r ON r.page_id = g.page_id AND r.x_l <= a AND r.y_l <= b AND r.x_h >= c AND r.y_h >= d GROUP BY 1, 2",
        D.PAGES,
    ),
)
add(
    "group_regions",
    lambda s, d: align.group_regions(pages.regions(s, d), ["page_id", "x_l"], n=F.count("*"), total=F.sum(P.area(Box.of())), tags=F.count_distinct("html_tag")),
    q("SELECT page_id, x_l, count(*) AS n, CAST(sum((x_h - x_l) * (y_h - y_l)) AS BIGINT) AS total, count(DISTINCT html_tag) AS tags FROM reg GROUP BY 1, 2", D.PAGES),
)
add(
    "bounding_boxes_agg",
    lambda s, d: pages.regions(s, d).groupBy("page_id").agg(tables_functions.mbr_agg("x_l", "y_l", "x_h", "y_h").alias("b")).select("page_id", "b.*"),
    q("SELECT page_id, min(x_l) AS x_l, min(y_l) AS y_l, max(x_h) AS x_h, max(y_h) AS y_h FROM reg GROUP BY 1", D.PAGES),
)


def _html_tags(s: SparkSession, d: str) -> DataFrame:
    tables_functions.register_table_functions(s)
    load(s, d, "pages").select("page_id", "html").createOrReplaceTempView("raw_pages")
    return s.sql("SELECT p.page_id, t.tag, count(*) AS n FROM raw_pages p, LATERAL html_nodes(p.page_id, p.html) t GROUP BY 1, 2")


add("html_nodes_udtf", _html_tags, q("SELECT page_id, html_tag AS tag, count(*) AS n FROM reg GROUP BY 1, 2", D.PAGES))

# ---------------------------------------------------------------- visual extraction and aggregation
_VIS_COLS = ("page_id", "text_start", "text_end", "x_l", "y_l", "x_h", "y_h")


def grid_hits(s: SparkSession, d: str) -> DataFrame:
    return textgrid.regions(s, d).where(F.lower("text").isin(*WORDS))


def grid_lines(s: SparkSession, d: str) -> DataFrame:
    return textgrid.line_regions(docs(s, d))


_GH = f"gh AS (SELECT * FROM grid_words WHERE lower(text) IN ({_IN}))"
_GT = "gtree AS (SELECT * FROM grid_lines UNION ALL SELECT page_id, '1', min(x_l), min(y_l), max(x_h), max(y_h), min(text_start), max(text_end), 1 FROM grid_lines GROUP BY page_id)"
add("regex_regions_node", lambda s, d: visual.regex_regions(pages.regions(s, d), "the[a-z]+ and").select("page_id", "region_id"), q("SELECT page_id, region_id FROM reg WHERE regexp_matches(text, 'the[a-z]+ and')", D.PAGES))
_PT2 = "pt2 AS (SELECT page_id, string_agg(said, chr(10) ORDER BY a) AS text FROM rn GROUP BY 1)"
_COVER = "(SELECT arg_max(r.region_id, r.depth) FROM reg r WHERE r.page_id = s.page_id AND r.text_start <= s.\"begin\" AND r.text_end >= s.\"end\")"
add(
    "regex_regions_page",
    lambda s, d: visual.regex_regions(pages.regions(s, d), r"[a-z]+\.\n[A-Z][a-z]+", "page").select("page_id", "begin", "end", "matched", "region_id"),
    q(f'SELECT page_id, "begin", "end", matched, {_COVER} AS region_id FROM sp s', D.PAGES, _PT2, D.spans(r"[a-z]+\.\n[A-Z][a-z]+", "pt2", "page_id")),
)
add(
    "dict_regions_node",
    lambda s, d: visual.dict_regions(pages.regions(s, d), words_df(s, *WORDS)).groupBy("page_id", "region_id", "term").agg(F.count("*").alias("n")),
    q(f"SELECT page_id, region_id, term, count(*) AS n FROM (SELECT page_id, region_id, lower(unnest(regexp_extract_all(text, '[A-Za-z0-9_]+'))) AS term FROM reg WHERE text IS NOT NULL) WHERE term IN ({_IN}) GROUP BY ALL", D.PAGES),
)
add(
    "dict_regions_page",
    lambda s, d: visual.dict_regions(pages.regions(s, d), words_df(s, "of"), "page").select("page_id", "begin", "end", "term", "region_id"),
    q(f"SELECT page_id, \"begin\", \"end\", 'of' AS term, {_COVER} AS region_id FROM sp s WHERE lower(matched) = 'of'", D.PAGES, _PT2, D.spans(spans.TOKEN, "pt2", "page_id")),
)
_SEL = ", ".join(f"a.{c}" for c in _VIS_COLS)
add(
    "visual_consolidate_contained",
    lambda s, d: visual.consolidate_contained_visual(pages.regions(s, d)),
    q(
        f"SELECT {_SEL} FROM (SELECT DISTINCT {', '.join(_VIS_COLS)} FROM reg) a WHERE NOT EXISTS (SELECT 1 FROM reg b WHERE b.page_id = a.page_id AND b.text_start <= a.text_start AND a.text_end <= b.text_end AND b.x_l <= a.x_l AND b.y_l <= a.y_l AND a.x_h <= b.x_h AND a.y_h <= b.y_h AND (b.text_start, b.text_end, b.x_l, b.y_l, b.x_h, b.y_h) <> (a.text_start, a.text_end, a.x_l, a.y_l, a.x_h, a.y_h))",
        D.PAGES,
    ),
)


def _span_rows(s: SparkSession, d: str) -> DataFrame:
    m = mixed_spans(s, d)
    return m.select(F.col("doc_id").alias("page_id"), F.col("begin").alias("text_start"), F.col("end").alias("text_end"))


_NODE = "(SELECT arg_max(r.region_id, r.depth) FROM gtree r WHERE r.page_id = s.doc_id AND r.text_start <= s.\"begin\" AND r.text_end >= s.\"end\")"
add(
    "visual_consolidate_overlapping",
    lambda s, d: visual.consolidate_overlapping_visual(_span_rows(s, d), grid_lines(s, d)).select("page_id", "begin", "end", "region_id"),
    q(f'SELECT doc_id AS page_id, "begin", "end", {_NODE} AS region_id FROM (SELECT doc_id, min(b) AS "begin", max(e) AS "end" FROM isl GROUP BY doc_id, i) s', *_WN, _MIX, _ISL.format(src="mx", cut="b >= f"), D.GRID, _GT),
)
_GW = "gw AS (SELECT page_id AS doc_id, text_start AS b, text_end AS e FROM gh)"
add(
    "visual_text_block",
    lambda s, d: visual.text_block_visual(grid_hits(s, d), grid_lines(s, d), 4, 25).select("page_id", "begin", "end", "n_spans", "region_id"),
    q(f'SELECT doc_id AS page_id, "begin", "end", n_spans, {_NODE} AS region_id FROM (SELECT doc_id, min(b) AS "begin", max(e) AS "end", count(*) AS n_spans FROM isl GROUP BY doc_id, i HAVING count(*) >= 4) s', D.GRID, _GH, _GT, _GW, _ISL.format(src="gw", cut="b - f > 25")),
)
_STEP = """st AS (SELECT *, lag(x_l) OVER w AS a, lag(y_l) OVER w AS b, lag(x_h) OVER w AS c, lag(y_h) OVER w AS d FROM gh WINDOW w AS (PARTITION BY page_id ORDER BY y_l, x_l, text_start)),
bk AS (SELECT *, sum(CASE WHEN a IS NULL OR greatest(0, x_l - c, a - x_h) >= 200 OR greatest(0, y_l - d, b - y_h) >= 30 THEN 1 ELSE 0 END) OVER (PARTITION BY page_id ORDER BY y_l, x_l, text_start ROWS UNBOUNDED PRECEDING) AS k FROM st)"""
_BLOCK = "SELECT page_id, min(x_l) AS x_l, min(y_l) AS y_l, max(x_h) AS x_h, max(y_h) AS y_h, min(text_start) AS text_start, max(text_end) AS text_end, count(*) AS n_spans FROM {t} GROUP BY page_id, k HAVING count(*) >= {n}"
add("region_block_reading", lambda s, d: visual.region_block(grid_hits(s, d), 4, 200, 30), q(_BLOCK.format(t="bk", n=4), D.GRID, _GH, _STEP))
_COMP = """sel AS (SELECT *, row_number() OVER (PARTITION BY page_id ORDER BY ord) AS i FROM reg WHERE html_tag IN ('li', 'h1', 'div')),
ed AS (SELECT a.page_id, a.i AS u, b.i AS v FROM sel a JOIN sel b ON a.page_id = b.page_id AND greatest(0, a.x_l - b.x_h, b.x_l - a.x_h) < 30 AND greatest(0, a.y_l - b.y_h, b.y_l - a.y_h) < 30),
rc AS (SELECT page_id, i AS u, i AS k FROM sel UNION SELECT rc.page_id, ed.v, rc.k FROM rc JOIN ed ON ed.page_id = rc.page_id AND ed.u = rc.u WHERE rc.k < ed.v),
lb AS (SELECT s.*, m.k FROM sel s JOIN (SELECT page_id, u, min(k) AS k FROM rc GROUP BY 1, 2) m ON m.page_id = s.page_id AND m.u = s.i)"""
add("region_block_component", lambda s, d: visual.region_block(pages.regions(s, d).where("html_tag in ('li', 'h1', 'div')"), 2, 30, 30, "component"), q(_BLOCK.format(t="lb", n=2), D.PAGES, _COMP))
add(
    "region_block_covering_node",
    lambda s, d: visual.covering_regions(visual.region_block(pages.regions(s, d).where("html_tag = 'li'"), 3, 300, 30), pages.regions(s, d)).select("page_id", "n_spans", "region_id"),
    q(
        "SELECT page_id, n_spans, (SELECT arg_max(r.region_id, r.depth) FROM reg r WHERE r.page_id = s.page_id AND r.x_l <= s.x_l AND r.y_l <= s.y_l AND r.x_h >= s.x_h AND r.y_h >= s.y_h) AS region_id FROM (" + _BLOCK.format(t="bk", n=3) + ") s",
        D.PAGES,
        "gh AS (SELECT * FROM reg WHERE html_tag = 'li')",
        _STEP.replace("200", "300"),
    ),
)

# ---------------------------------------------------------------- workloads
_A = "min(x_l) OVER g AS mx, min(y_l) OVER g AS my, max(x_h) OVER g AS mh, count(*) OVER g AS n"
_IN_A = "n > 3 AND mx >= 0 AND my >= 90 AND mh <= {w}"


def _bar_sql(src: str, group: str, wide: int, *parts: str) -> str:
    return q(f"SELECT page_id, region_id FROM (SELECT *, {_A} FROM {src} WINDOW g AS (PARTITION BY {group})) WHERE {_IN_A.format(w=wide)}", *parts)


_Q1 = {
    "q1_sheets": ({}, _bar_sql("(SELECT * FROM vis WHERE x_l >= 0)", "page_id, x_l", 500, D.SHEETS)),
    "q1_sheets_restrict": ({"restrict_first": True}, _bar_sql("(SELECT * FROM vis WHERE x_l >= 0 AND y_l >= 90 AND x_h <= 500)", "page_id, x_l", 500, D.SHEETS)),
    "q1_sheets_maxdist": ({"max_dist": 10}, _bar_sql("gi", "page_id, x_l, i", 500, D.SHEETS, _MAXD)),
    "q1_sheets_consecutive": ({"consecutive": True}, _bar_sql("gi", "page_id, x_l, i", 500, D.SHEETS, _CONS)),
    "q1_sheets_tuned": ({"box": tasks.LEFT_BAR_TUNED}, _bar_sql("vis", "page_id, x_l", 190, D.SHEETS)),
}
for _name, (_options, _sql) in _Q1.items():
    add(_name, lambda s, d, o=_options: tasks.q1_sheets(s, d, **o), _sql)

_BLOCKS = "blk AS (SELECT r.*, substr(w.text, r.text_start + 1, r.text_end - r.text_start) AS said FROM (SELECT * EXCLUDE (text) FROM reg) r JOIN pt2 w ON w.page_id = r.page_id WHERE r.html_tag IN ('li', 'h1', 'p', 'div', 'footer') AND r.text_end > r.text_start)"
_PG = (D.PAGES, _PT2, _BLOCKS)


def page_blocks(s: SparkSession, d: str) -> DataFrame:
    return tasks.block_nodes(pages.regions(s, d))


def _wd(col: str, *terms: str) -> str:
    return "(" + " OR ".join(f"regexp_matches({col}, '(?i)\\b{t}\\b')" for t in terms) + ")"


_V = "SELECT v.page_id, v.region_id FROM {v} v WHERE {words} AND EXISTS (SELECT 1 FROM {h} h WHERE h.page_id = v.page_id AND ({cond}))"
_SOUTH = "v.y_l >= h.y_h AND v.x_l >= h.x_l AND v.x_h <= h.x_h"
_EAST = "v.x_l >= h.x_h AND v.y_l >= h.y_l AND v.y_h <= h.y_h"
_HEAD = "hd AS (SELECT * FROM vis WHERE text = 'Return Flag')"
_CELL = "hd AS (SELECT * FROM headcell WHERE text = 'Return Flag')"
_NAMES = _wd("v.text", "Returned", "Accepted")
_RIGHT = """SELECT s.page_id, s.region_id FROM {t} s JOIN (WITH mh AS MATERIALIZED (SELECT m.page_id, m.x_h, m.y_l, m.y_h FROM (SELECT * FROM {t} m WHERE {words}) m
JOIN {h} h ON h.page_id = m.page_id AND m.y_l >= h.y_h AND m.x_l >= h.x_l AND m.x_h <= h.x_h) SELECT * FROM mh) m ON m.page_id = s.page_id AND s.x_l >= m.x_h AND s.y_l >= m.y_l AND s.y_h <= m.y_h"""

add("q1_pages", lambda s, d: tasks.q1_pages(page_blocks(s, d)), _bar_sql("blk", "page_id, x_l", 500, *_PG))
add("q2_sheets", tasks.q2_sheets, q(f"SELECT page_id, region_id FROM vis WHERE {_wd('text', 'Order Summary')} AND x_l >= 190 AND y_l >= 0 AND y_h <= 60", D.SHEETS))
add("q2_pages", lambda s, d: tasks.q2_pages(page_blocks(s, d)), q(f"SELECT page_id, region_id FROM blk WHERE {_wd('said', 'eriner')} AND x_l >= 210 AND y_l >= 0 AND y_h <= 500", *_PG))
add("q3_sheets", tasks.q3_sheets, q(_V.format(v="vis", h="hd", words=_NAMES, cond=f"({_SOUTH}) OR ({_EAST})"), D.SHEETS, _HEAD))
add("q3_sheets_maximal", lambda s, d: tasks.q3_sheets(s, d, True), q(_V.format(v="vis", h="hd", words=_NAMES, cond=f"({_SOUTH}) OR ({_EAST})"), D.SHEETS, D.HEAD_CELLS, _CELL))
add("q3_pages", lambda s, d: tasks.q3_pages(page_blocks(s, d)), q(_V.format(v="blk", h=f"(SELECT * FROM blk WHERE html_tag = 'h1' AND {_wd('said', 'eriner')})", words=_wd("v.said", *WORDS), cond=_SOUTH), *_PG))
add("q4_sheets", tasks.q4_sheets, q(_RIGHT.format(t="vis", h="hd", words=_wd("m.text", "Returned")), D.SHEETS, _HEAD))
add("q4_sheets_maximal", lambda s, d: tasks.q4_sheets(s, d, True), q(_RIGHT.format(t="vis", h="hd", words=_wd("m.text", "Returned")), D.SHEETS, D.HEAD_CELLS, _CELL))
_Q4D = q(_RIGHT.format(t="vis", h="hd", words=_wd("m.text", "Returned")).replace("SELECT s.", "SELECT DISTINCT s.", 1), D.SHEETS, _HEAD)
add("q4_sheets_distinct", lambda s, d: tasks.q4_sheets(s, d, distinct=True), _Q4D)
add("q4_pages", lambda s, d: tasks.q4_pages(page_blocks(s, d)), q(_RIGHT.format(t="blk", h=f"(SELECT * FROM blk WHERE {_wd('said', 'the')})", words=_wd("m.said", "of")).replace("SELECT s.", "SELECT DISTINCT s.", 1), *_PG))
add("example_column_names", tasks.column_names, q(_V.format(v="vis", h="hd", words=_NAMES, cond=f"{_SOUTH} AND v.x_l = h.x_l"), D.SHEETS, _HEAD))

# ---------------------------------------------------------------- a dense corpus
_DENSE = f"""dv AS (SELECT page_id // {sheets.DENSE} AS page_id, '1.' || (page_id % {sheets.DENSE} + 1) || substr(region_id, 2) AS region_id, x_l, y_l + page_id % {sheets.DENSE} * {sheets.STRIP} AS y_l,
x_h, y_h + page_id % {sheets.DENSE} * {sheets.STRIP} AS y_h, text, html_tag, kind, page_id % {sheets.DENSE} * 1000 + ord AS ord FROM vis)"""
_DHEAD = "hd AS (SELECT * FROM dv WHERE text = 'Return Flag')"


def dense(s: SparkSession, d: str) -> DataFrame:
    return sheets.dense_boxes(sheets.boxes(s, d))


add("corpus_stats_dense", lambda s, d: corpus_stats(dense(s, d)), q(_STATS.format(t="dv"), D.SHEETS, _DENSE))
add("q1_dense", lambda s, d: tasks.left_bar(dense(s, d), max_dist=10), _bar_sql("gi", "page_id, x_l, i", 500, D.SHEETS, _DENSE, _MAXD.replace("FROM vis", "FROM dv")))
add("q2_dense", lambda s, d: tasks.top_term(dense(s, d), "Order Summary", tasks.TOP_SHEETS), q(f"SELECT page_id, region_id FROM dv WHERE {_wd('text', 'Order Summary')} AND x_l >= 190 AND y_l >= 0 AND y_h <= 60", D.SHEETS, _DENSE))
add("q3_dense", lambda s, d: tasks.names_by_heading(dense(s, d), visual.phrase_regions(dense(s, d), "Return Flag"), ["Returned", "Accepted"]), q(_V.format(v="dv", h="hd", words=_NAMES, cond=f"({_SOUTH}) OR ({_EAST})"), D.SHEETS, _DENSE, _DHEAD))
add("q4_dense", lambda s, d: tasks.right_of_match(dense(s, d), visual.phrase_regions(dense(s, d), "Return Flag"), "Returned", True), q(_RIGHT.format(t="dv", h="hd", words=_wd("m.text", "Returned")).replace("SELECT s.", "SELECT DISTINCT s.", 1), D.SHEETS, _DENSE, _DHEAD))
add(
    "touches_dense_by_grid",
    lambda s, d: grid_pairs(dense(s, d), dense(s, d), P.touches).where("a_id <> b_id").groupBy("page_id").agg(F.count("*").alias("n_pairs")),
    q(f"SELECT a.page_id, count(*) AS n_pairs FROM dv a JOIN dv b ON a.page_id = b.page_id AND a.x_l // 200 BETWEEN b.x_l // 200 - 6 AND b.x_h // 200 + 1 AND a.y_l <= b.y_h AND b.y_l <= a.y_h AND a.region_id <> b.region_id AND {PREDICATES['touches'][1]} GROUP BY 1", D.SHEETS, _DENSE),
)

# ---------------------------------------------------------------- access modes
_MODE_NAMES = {"none": "no_index", "udf": "udf", "per_page": "per_page", "auto": "auto"}


def _mode_name(task: str, mode: str) -> str:
    return f"{task}_{_MODE_NAMES.get(mode) or mode.replace('+', '_') + '_index'}"


for _t, _sql in (("q1", ORACLES["q1_sheets"]), ("q2", ORACLES["q2_sheets"]), ("q3", ORACLES["q3_sheets"]), ("q4", _Q4D)):
    for _mode in modes.TASKS[_t][1]:
        add(_mode_name(_t, _mode), lambda s, d, f=modes.TASKS[_t][0], m=_mode: f(s, d, m), _sql)
add(
    "text_index_postings",
    lambda s, d: text_index.build_text_index(pages.regions(s, d)),
    q("SELECT term, page_id, region_id, CAST(pos AS BIGINT) AS pos FROM (SELECT page_id, region_id, unnest(t) AS term, unnest(range(0, len(t))) AS pos FROM (SELECT page_id, region_id, regexp_extract_all(lower(text), '[A-Za-z0-9_]+') AS t FROM reg WHERE text IS NOT NULL))", D.PAGES),
)
add("text_index_lookup", lambda s, d: text_index.lookup_phrase(modes.stored_postings(s, d), "Order Summary").select("page_id", "region_id"), q("SELECT page_id, region_id FROM vis WHERE text ILIKE '%Order Summary%'", D.SHEETS))

# ---------------------------------------------------------------- rule language
RULE_Q4 = """SELECT DISTINCT s.page_id, s.region_id FROM PHRASE('Return Flag', D) AS h, PHRASE('Returned', D) AS m, REGIONS(D) AS s
WHERE StrictSouthOf(m, h) AND StrictEastOf(s, m)"""
RULE_Q3 = """SELECT DISTINCT v.page_id, v.region_id FROM PHRASE('Return Flag', D) AS h, DICT('names', D) AS v
WHERE StrictSouthOf(v, h) OR StrictEastOf(v, h)"""
RULE_Q3_REGEX = RULE_Q3.replace("DICT('names', D)", "REGEX('^(Returned|Accepted)\\b|\\bReturned\\b', D)")
RULE_Q2 = "SELECT t.page_id, t.region_id FROM PHRASE('Order Summary', D) AS t WHERE Contains(t, BOX(190, 0, INF, 60))"
RULE_Q1 = "SELECT v.page_id, v.region_id FROM REGIONS(D) AS v GROUP BY ALIGNED(COLUMN) HAVING COUNT > 3 AND Contains(MBR, BOX(0, 90, 500, INF))"
RULE_Q1_NEAR = RULE_Q1.replace("COLUMN", "COLUMN, MAXDIST 10")
RULE_Q1_NEXT = RULE_Q1.replace("COLUMN", "COLUMN, CONSECUTIVE")
RULE_UP = "SELECT DISTINCT c.page_id, c.region_id FROM PHRASE('Return Flag', D) AS h, MAXIMAL(h) AS c, PHRASE('Returned', D) AS m WHERE StrictSouthOf(m, c)"
RULE_DICT = "SELECT v.page_id, v.region_id FROM DICT('phrases', D) AS v"


def by_rule(text: str, access: str = "none") -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        vis = modes.stored_regions(s, d)
        rule = rules.rewrite(rules.parse(text), access)
        views = {"postings": modes.stored_postings(s, d)} if "text" in access else {}
        views |= {"names": words_df(s, *modes.NAMES)} if "'names'" in text else {}
        return rules.to_df(rule, vis, views)

    return run


add("rule_q1", by_rule(RULE_Q1), ORACLES["q1_sheets"])
add("rule_q1_maxdist", by_rule(RULE_Q1_NEAR), ORACLES["q1_sheets_maxdist"])
add("rule_q1_consecutive", by_rule(RULE_Q1_NEXT), ORACLES["q1_sheets_consecutive"])
add("rule_q2", by_rule(RULE_Q2), ORACLES["q2_sheets"])
add("rule_q2_text_index", by_rule(RULE_Q2, "text"), ORACLES["q2_sheets"])
add("rule_q3", by_rule(RULE_Q3), ORACLES["q3_sheets"])
add("rule_q3_regex", by_rule(RULE_Q3_REGEX), ORACLES["q3_sheets"])
add("rule_q3_text_index", by_rule(RULE_Q3, "text"), ORACLES["q3_sheets"])
add("rule_q4", by_rule(RULE_Q4), _Q4D)
add("rule_q4_per_page", lambda s, d: evaluate.run_per_page(rules.parse(RULE_Q4), other_ways.nest(modes.stored_regions(s, d), evaluate.NESTED)), _Q4D)
add("rule_q3_per_page", lambda s, d: evaluate.run_per_page(rules.parse(RULE_Q3_REGEX), other_ways.nest(modes.stored_regions(s, d), evaluate.NESTED)), ORACLES["q3_sheets"])
add("rule_q4_text_index", by_rule(RULE_Q4, "text"), _Q4D)
add(
    "rule_dict_phrases",
    lambda s, d: rules.to_df(rules.parse(RULE_DICT), pages.regions(s, d), {"phrases": words_df(s, "of the", "and the", "This is not in any of them")}),
    q("SELECT page_id, region_id FROM reg WHERE text IS NOT NULL AND regexp_matches(' ' || array_to_string(regexp_extract_all(lower(text), '[A-Za-z0-9_]+'), ' ') || ' ', ' (of the|and the|this is not in any of them) ')", D.PAGES),
)
add(
    "rule_maximal_heading",
    lambda s, d: rules.to_df(rules.parse(RULE_UP), sheets.regions(s, d)),
    q("SELECT DISTINCT h.page_id, h.region_id FROM headcell h JOIN vis m ON m.page_id = h.page_id AND m.y_l >= h.y_h AND m.x_l >= h.x_l AND m.x_h <= h.x_h WHERE h.text = 'Return Flag' AND regexp_matches(m.text, '\\bReturned\\b')", D.SHEETS, D.HEAD_CELLS),
)


_PAGE_RULES = {
    "rule_ancestors": (
        "SELECT DISTINCT u.page_id, u.region_id FROM PHRASE('the', D) AS b, ANCESTORS(b) AS u WHERE u.html_tag <> 'body'",
        "SELECT DISTINCT r.page_id, r.region_id FROM reg v JOIN reg r ON r.page_id = v.page_id AND starts_with(v.region_id, r.region_id || '.') WHERE regexp_matches(v.text, '(?i)\\bthe\\b') AND r.html_tag <> 'body'",
    ),
    "rule_descendants": (
        "SELECT x.page_id, x.region_id FROM REGIONS(D) AS a, DESCENDANTS(a) AS x WHERE a.html_tag = 'nav' AND x.html_tag = 'a'",
        "SELECT r.page_id, r.region_id FROM reg v JOIN reg r ON r.page_id = v.page_id AND starts_with(r.region_id, v.region_id || '.') WHERE v.html_tag = 'nav' AND r.html_tag = 'a'",
    ),
    "rule_minimal": (
        "SELECT DISTINCT m.page_id, m.region_id FROM REGIONS(D) AS n, MINIMAL(n) AS m WHERE n.html_tag = 'li' AND StrictSouthOf(m, BOX(0, 0, 400, 100))",
        "SELECT DISTINCT r.page_id, r.region_id FROM reg v JOIN reg r ON r.page_id = v.page_id AND r.region_id = v.minimal_region WHERE v.html_tag = 'li' AND r.y_l >= 100 AND r.x_l >= 0 AND r.x_h <= 400",
    ),
    "rule_super": (
        "SELECT DISTINCT SUPER.page_id, SUPER.region_id FROM REGIONS(D) AS v WHERE v.html_tag = 'p' GROUP BY ALIGNED(COLUMN) HAVING COUNT > 2",
        "SELECT DISTINCT page_id, region_id FROM (SELECT g.page_id, r.region_id, row_number() OVER (PARTITION BY g.page_id, g.k ORDER BY (r.x_h - r.x_l) * (r.y_h - r.y_l), r.depth DESC, r.region_id) AS i FROM (SELECT page_id, x_l AS k, min(y_l) AS b, max(x_h) AS c, max(y_h) AS d FROM reg WHERE html_tag = 'p' GROUP BY 1, 2 HAVING count(*) > 2) g JOIN reg r ON r.page_id = g.page_id AND r.x_l <= g.k AND r.y_l <= g.b AND r.x_h >= g.c AND r.y_h >= g.d) WHERE i = 1",
    ),
    "rule_values": (
        "SELECT a.page_id, a.region_id FROM REGIONS(D) AS h, REGIONS(D) AS a WHERE h.html_tag = 'h1' AND a.html_tag = 'p' AND GapY(a, h) <= 40 AND CentroidX(a) >= 400 AND Area(a) > 16000",
        "SELECT a.page_id, a.region_id FROM reg h JOIN reg a ON a.page_id = h.page_id WHERE h.html_tag = 'h1' AND a.html_tag = 'p' AND greatest(0, a.y_l - h.y_h, h.y_l - a.y_h) <= 40 AND (a.x_l + a.x_h) / 2.0 >= 400 AND (a.x_h - a.x_l) * (a.y_h - a.y_l) > 16000",
    ),
}
for _name, (_text, _sql) in _PAGE_RULES.items():
    add(_name, lambda s, d, t=_text: rules.to_df(rules.parse(t), pages.regions(s, d)), q(_sql, D.PAGES))
_SPAN_RULES = {
    "rule_follows": ("Follows(a, b, 40)", "a.text_end <= b.text_start AND b.text_start - a.text_end <= 40"),
    "rule_overlap": ("Overlap(a, b)", "a.text_start < b.text_end AND b.text_start < a.text_end"),
    "rule_span_in": ("SpanIn(a, b)", "b.text_start <= a.text_start AND a.text_end <= b.text_end AND (a.text_start <> b.text_start OR a.text_end <> b.text_end)"),
    "rule_same_span": ("SameSpan(a, b)", "a.text_start = b.text_start AND a.text_end = b.text_end"),
}
for _name, (_text, _sql) in _SPAN_RULES.items():
    add(
        _name,
        lambda s, d, t=_text: rules.to_df(rules.parse(f"SELECT a.page_id, a.region_id, b.ord FROM PHRASE('the', D) AS a, REGIONS(D) AS b WHERE b.html_tag <> 'body' AND {t}"), pages.regions(s, d)),
        q(f"SELECT a.page_id, a.region_id, b.ord FROM reg a JOIN reg b ON b.page_id = a.page_id AND {_sql} WHERE regexp_matches(a.text, '(?i)\\bthe\\b') AND b.html_tag <> 'body'", D.PAGES),
    )
RULE_DIAGONAL = "SELECT DISTINCT v.page_id, v.region_id FROM PHRASE('Order Summary', D) AS t, REGIONS(D) AS v WHERE SouthWestOf(v, t)"
add("rule_diagonal", by_rule(RULE_DIAGONAL), q(f"SELECT DISTINCT v.page_id, v.region_id FROM vis t JOIN vis v ON v.page_id = t.page_id AND v.y_l >= t.y_h AND v.x_h <= t.x_l WHERE {_wd('t.text', 'Order Summary')}", D.SHEETS))
RULE_TOUCH = "SELECT v.page_id, v.region_id FROM REGIONS(D) AS v WHERE Touches(v, BOX(200, 120, INF, 160))"
add("rule_touches_open_box", by_rule(RULE_TOUCH), q("SELECT page_id, region_id FROM vis WHERE (x_h = 200 AND y_l < 160 AND 120 < y_h) OR ((y_h = 120 OR y_l = 160) AND 200 < x_h)", D.SHEETS))

RULES = {"q1": RULE_Q1, "q2": RULE_Q2, "q3": RULE_Q3, "q4": RULE_Q4}


def rule_sizes(s: SparkSession, d: str) -> DataFrame:
    """Parts of the visual rules, as their trees have them, and of the source rules for the same tasks, with the sheets they are for and the predicates to be met on them."""
    rows = [(task, "visual", *rules.rule_size(rules.parse(text)).values()) for task, text in RULES.items()]
    rows += [(*name.split("_"), *map(len, parts)) for name, parts in source_rules.PARTS.items()]
    sizes = s.createDataFrame(rows, "task string, kind string, sources long, predicates long, constants long, groupings long")
    pages = sheets.boxes(s, d).where("kind = 'title'").agg(F.count("*").alias("n_pages"))
    return sizes.crossJoin(pages).withColumn("n_tests", F.col("predicates") * F.col("n_pages"))


#: Counted by hand.
_SIZES = {
    "q1 visual": (1, 2, 4, 1), "q2 visual": (1, 1, 4, 0), "q3 visual": (2, 2, 2, 0), "q4 visual": (3, 2, 2, 0),
    "q1 identical": (3, 4, 4, 1), "q1 approximate": (1, 2, 2, 1), "q1 alternate": (1, 3, 2, 1),
    "q2 identical": (3, 1, 4, 0), "q2 approximate": (1, 1, 2, 0), "q2 alternate": (1, 2, 2, 0),
    "q3 identical": (4, 6, 5, 0), "q3 approximate": (2, 6, 3, 0),
    "q4 identical": (5, 7, 5, 0), "q4 approximate": (3, 6, 3, 0), "q4 alternate": (3, 3, 5, 0),
}
_SIZE_ROWS = ", ".join("('{}', '{}', {})".format(*k.split(), ", ".join(map(str, v))) for k, v in _SIZES.items())
add(
    "rule_size",
    rule_sizes,
    q(
        f"SELECT task, kind, {', '.join(f'CAST({c} AS BIGINT) AS {c}' for c in ('sources', 'predicates', 'constants', 'groupings'))}, n_pages, CAST(predicates * n_pages AS BIGINT) AS n_tests FROM (VALUES {_SIZE_ROWS}) v(task, kind, sources, predicates, constants, groupings), (SELECT count(DISTINCT p) AS n_pages FROM ln)",
        D.SHEETS,
    ),
)


def by_sql_functions(s: SparkSession, d: str) -> DataFrame:
    """The fourth task in SQL with the registered functions, which Spark inlines into the join."""
    P.register_all(s)
    box = lambda a: f"struct({a}.x_l, {a}.y_l, {a}.x_h, {a}.y_h)"
    sheets.boxes(s, d).createOrReplaceTempView("drawn_boxes")
    return s.sql(
        f"""SELECT DISTINCT s.page_id, s.region_id FROM drawn_boxes h JOIN drawn_boxes m ON h.page_id = m.page_id AND strict_south_of({box("m")}, {box("h")})
        JOIN drawn_boxes s ON s.page_id = m.page_id AND strict_east_of({box("s")}, {box("m")}) WHERE h.text = 'Return Flag' AND m.text rlike '(?<![A-Za-z0-9_])Returned(?![A-Za-z0-9_])'"""
    )


add("q4_sql_functions", by_sql_functions, _Q4D)

# ---------------------------------------------------------------- baselines
_ORD = "od AS (SELECT *, CAST(split_part(region_id, '.', 3) AS BIGINT) AS i, CAST(split_part(region_id, '.', 4) AS BIGINT) AS j FROM vis WHERE starts_with(region_id, '1.3.'))"
_SRC = "SELECT DISTINCT v.page_id, v.region_id FROM od v JOIN od h ON h.page_id = v.page_id AND h.text = 'Return Flag' AND ((v.j = h.j AND v.i > h.i) OR (v.i = h.i AND v.j > h.j)) WHERE {n} AND v.html_tag IN ({t})"
_SRC_ALL, _SRC_TD = (q(_SRC.format(n=_NAMES, t=t), D.SHEETS, _ORD) for t in ("'td', 'div', 'li'", "'td'"))
add("source_identical_q3", lambda s, d: source_rules.identical(sheets.boxes(s, d)), _SRC_ALL)
add("source_approximate_q3", lambda s, d: source_rules.approximate(sheets.boxes(s, d)), _SRC_TD)
_ALT = q(
    "SELECT page_id, region_id FROM (SELECT *, max(CASE WHEN starts_with(region_id, '1.3.') AND html_tag IN ('td', 'div', 'li') AND regexp_matches(text, '(?i)\\bReturned\\b') THEN ord END) OVER (PARTITION BY page_id ORDER BY ord ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS l FROM vis) WHERE ord - l <= 3",
    D.SHEETS,
)
add("source_alternate_q4", lambda s, d: source_rules.alternate(sheets.boxes(s, d)), _ALT)
add(
    "source_proximity",
    lambda s, d: source_rules.proximity(sheets.boxes(s, d)),
    q(
        "SELECT template, count(*) AS n_headings, count(*) FILTER (nx = sr) AS n_agree FROM (SELECT h.template, h.page_id, h.region_id, h.nx, arg_min(b.region_id, lpad(CAST(b.y_l - h.y_h AS VARCHAR), 9, '0') || b.region_id) AS sr FROM (SELECT *, lead(region_id) OVER w AS nx, lead(text_start) OVER w - text_end AS gap FROM vis WINDOW w AS (PARTITION BY page_id ORDER BY ord)) h JOIN vis b ON b.page_id = h.page_id AND b.y_l >= h.y_h AND b.x_l < h.x_h AND h.x_l < b.x_h WHERE h.text = 'Return Flag' AND h.gap <= 20 GROUP BY ALL) GROUP BY 1",
        D.SHEETS,
    ),
)


_STACK = "sk AS (SELECT *, CASE WHEN html_tag = 'li' THEN regexp_replace(region_id, '[.][0-9]+$', '') WHEN html_tag IN ('td', 'div') AND starts_with(region_id, '1.3.') THEN 'column ' || split_part(region_id, '.', 4) END AS st FROM vis)"
_STACKS = "SELECT page_id, region_id FROM (SELECT *, count(*) OVER (PARTITION BY page_id, st) AS n FROM sk WHERE st IS NOT NULL AND html_tag IN ({t})) WHERE n > 3"
_PLACED = "pl AS (SELECT *, CASE WHEN template = 2 THEN j ELSE i END AS rw, CASE WHEN template = 2 THEN i ELSE j END AS cl FROM od)"
_RIGHT_SRC = "SELECT DISTINCT s.page_id, s.region_id FROM pl s JOIN pl m ON m.page_id = s.page_id AND s.rw = m.rw AND s.cl > m.cl JOIN pl h ON h.page_id = m.page_id AND h.text = 'Return Flag' AND m.cl = h.cl AND m.rw > h.rw WHERE regexp_matches(m.text, '(?i)\\bReturned\\b') AND m.html_tag IN ({t}) AND s.html_tag IN ({t})"
_ALL_TAGS = "'td', 'div', 'li'"
_SOURCE_RULES = {
    "q1": {
        "identical": (source_rules.bar_identical, _STACKS.format(t=_ALL_TAGS), (_STACK,)),
        "approximate": (source_rules.bar_approximate, _STACKS.format(t="'li'"), (_STACK,)),
        "alternate": (source_rules.bar_alternate, "SELECT page_id, region_id FROM (SELECT *, count(*) OVER (PARTITION BY page_id) AS n FROM (SELECT *, arg_min(st, ord) OVER (PARTITION BY page_id) AS f FROM sk WHERE html_tag = 'li') WHERE st = f) WHERE n > 3", (_STACK,)),
    },
    "q2": {
        "identical": (source_rules.class_identical, f"SELECT page_id, region_id FROM vis WHERE html_tag IN ('h1', 'h2', 'h3') AND {_wd('text', 'Order Summary')}", ()),
        "approximate": (source_rules.class_approximate, "SELECT page_id, region_id FROM vis WHERE html_tag = 'h1' AND text = 'Order Summary'", ()),
        "alternate": (source_rules.class_alternate, f"SELECT page_id, region_id FROM vis WHERE ord <= 6 AND {_wd('text', 'Order Summary')}", ()),
    },
    "q4": {
        "identical": (source_rules.right_identical, _RIGHT_SRC.format(t=_ALL_TAGS), (_ORD, _PLACED)),
        "approximate": (source_rules.right_approximate, _RIGHT_SRC.format(t="'td'"), (_ORD, _PLACED)),
    },
}
for _t, _kinds in _SOURCE_RULES.items():
    for _k, (_fn, _body, _extra) in _kinds.items():
        add(f"source_{_k}_{_t}", lambda s, d, f=_fn: f(sheets.boxes(s, d)), q(_body, D.SHEETS, *_extra))


def polygons(s: SparkSession, d: str) -> DataFrame:
    vis = sheets.boxes(s, d)
    return other_ways.right_of_match_polygons(vis, visual.phrase_regions(vis, "Return Flag"), visual.phrase_regions(vis, "Returned"))


add("polygon_q4", polygons, _Q4D)

# ---------------------------------------------------------------- measures
_ACC = """SELECT {by}CAST(count(f) AS BIGINT) AS returned, CAST(count(CASE WHEN f = 1 AND g = 1 THEN 1 END) AS BIGINT) AS "right", CAST(count(g) AS BIGINT) AS gold,
CASE WHEN count(g) > 0 THEN round(100.0 * count(CASE WHEN f = 1 AND g = 1 THEN 1 END) / count(g), 4) END AS recall,
CASE WHEN count(f) > 0 THEN round(100.0 * count(CASE WHEN f = 1 AND g = 1 THEN 1 END) / count(f), 4) END AS "precision",
CASE WHEN count(f) + count(g) > 0 THEN round(200.0 * count(CASE WHEN f = 1 AND g = 1 THEN 1 END) / (count(f) + count(g)), 4) END AS f1
FROM (SELECT *, 1 AS f FROM ({found})) a FULL JOIN (SELECT *, 1 AS g FROM ({gold})) b USING ({keys}){group}"""
_GOLD = {
    "q1": "SELECT page_id, region_id FROM vis WHERE kind = 'bar'",
    "q2": "SELECT DISTINCT page_id FROM vis WHERE kind = 'title' AND text = 'Order Summary'",
    "q3": "SELECT page_id, region_id FROM vis WHERE kind = 'value' AND text IN ('Returned', 'Accepted')",
    "q4": "SELECT page_id, region_id FROM vis v WHERE kind = 'value' AND x_l > 200 AND page_id % 2 = 0 AND EXISTS (SELECT 1 FROM vis r WHERE r.page_id = v.page_id AND r.y_l = v.y_l AND r.kind = 'value' AND r.text = 'Returned')",
}


def _found(sql: str) -> str:
    """The body of an oracle over the sheets, without its table expressions."""
    return sql.split(D.SHEETS.strip(), 1)[1]


def _acc_sql(task: str, found: str, extra: tuple[str, ...] = (), keys: str = "page_id, region_id", by: str = "") -> str:
    return q(_ACC.format(by=f"{by}, " if by else "", found=found, gold=_GOLD[task] if not by else f"SELECT page_id % 3 AS template, * FROM ({_GOLD[task]})", keys=f"{by}, {keys}" if by else keys, group=f" GROUP BY {by}" if by else ""), D.SHEETS, *extra)


def _score(task: str, find: Query, keys: list[str]) -> Query:
    return lambda s, d: accuracy(find(s, d), tasks.gold(sheets.boxes(s, d), task), keys)


def _score_values(task: str, find: Query, keys: list[str]) -> Query:
    """As ``_score`` where the right answers are values: only values are drawn for them, once all and once those with a name."""
    named = lambda s, d: sheets.marked(s, d, ("Returned", "Accepted"), ("value",))
    return lambda s, d: accuracy(find(s, d), tasks.gold(named(s, d) if task == "q3" else sheets.marked(s, d, kinds=("value",)), task, named(s, d)), keys)


_REG = ["page_id", "region_id"]
_Q1_BODY = f"SELECT page_id, region_id FROM (SELECT *, {_A} FROM vis WINDOW g AS (PARTITION BY page_id, x_l)) WHERE {_IN_A.format(w=500)}"
add("accuracy_q1", _score("q1", QUERIES["q1_sheets"], _REG), _acc_sql("q1", _Q1_BODY))
add("accuracy_q2", _score("q2", QUERIES["q2_sheets"], ["page_id"]), _acc_sql("q2", f"SELECT DISTINCT page_id FROM vis WHERE {_wd('text', 'Order Summary')} AND x_l >= 190 AND y_l >= 0 AND y_h <= 60", keys="page_id"))
_Q3_BODY = "SELECT DISTINCT * FROM (" + _V.format(v="vis", h="hd", words=_NAMES, cond=f"({_SOUTH}) OR ({_EAST})") + ")"
_Q4_BODY = _RIGHT.format(t="vis", h="hd", words=_wd("m.text", "Returned")).replace("SELECT s.", "SELECT DISTINCT s.", 1)
for _t, _b in (("q3", _Q3_BODY), ("q4", _Q4_BODY)):
    add(f"accuracy_{_t}", _score(_t, QUERIES[f"{_t}_sheets"], _REG), _acc_sql(_t, _b, (_HEAD,)))
    add(f"accuracy_{_t}_maximal", _score_values(_t, QUERIES[f"{_t}_sheets_maximal"], _REG), _acc_sql(_t, _b, (D.HEAD_CELLS, _CELL)))
for _name, _body in (("restrict", "(SELECT * FROM vis WHERE x_l >= 0 AND y_l >= 90 AND x_h <= 500)"),):
    add(f"accuracy_q1_{_name}", _score("q1", QUERIES[f"q1_sheets_{_name}"], _REG), _acc_sql("q1", f"SELECT page_id, region_id FROM (SELECT *, {_A} FROM {_body} WINDOW g AS (PARTITION BY page_id, x_l)) WHERE {_IN_A.format(w=500)}"))


def _by_variant(find: Callable[[DataFrame], DataFrame], task: str = "q3") -> Query:
    """Accuracy per markup variant: the same drawing in three kinds of source."""

    def run(s: SparkSession, d: str) -> DataFrame:
        vis = sheets.boxes(s, d)
        tag = lambda df: df.withColumn("template", F.pmod("page_id", F.lit(3)).cast("long"))
        return accuracy(tag(find(vis)), tag(tasks.gold(vis, task)), _REG, ["template"])

    return run


_VIA = {
    "visual": (lambda vis: tasks.names_by_heading(vis, tasks.heading_sheets(vis), ["Returned", "Accepted"]), _Q3_BODY, (_HEAD,)),
    "identical": (source_rules.identical, _SRC.format(n=_NAMES, t="'td', 'div', 'li'"), (_ORD,)),
    "approximate": (source_rules.approximate, _SRC.format(n=_NAMES, t="'td'"), (_ORD,)),
}
for _name, (_fn, _body, _extra) in _VIA.items():
    _sql = _acc_sql("q3", f"SELECT page_id % 3 AS template, * FROM ({_body})", _extra, by="template")
    add(f"accuracy_by_variant_{_name}", _by_variant(_fn), _sql)
    add(f"robustness_{_name}", lambda s, d, f=_fn: robustness(_by_variant(f)(s, d)), f"SELECT max(recall) AS best, min(recall) AS worst, round(max(recall) - min(recall), 4) AS \"drop\" FROM ({_sql})")
add("accuracy_source_alternate_q4", _score("q4", lambda s, d: source_rules.alternate(sheets.boxes(s, d)), _REG), _acc_sql("q4", _ALT.split(D.SHEETS.strip(), 1)[1].strip()))

for _t, _kinds in _SOURCE_RULES.items():
    for _k, (_fn, _body, _extra) in _kinds.items():
        _keys, _sql = (["page_id"], f"SELECT DISTINCT page_id FROM ({_body})") if _t == "q2" else (_REG, _body)
        add(f"accuracy_source_{_k}_{_t}", _score(_t, lambda s, d, f=_fn: f(sheets.boxes(s, d)), _keys), _acc_sql(_t, _sql, _extra, keys=", ".join(_keys)))
        if _t != "q2":
            _sql = _acc_sql(_t, f"SELECT page_id % 3 AS template, * FROM ({_body})", _extra, by="template")
            add(f"robustness_{_k}_{_t}", lambda s, d, f=_fn, t=_t: robustness(_by_variant(f, t)(s, d)), f"SELECT max(recall) AS best, min(recall) AS worst, round(max(recall) - min(recall), 4) AS \"drop\" FROM ({_sql})")
for _name, (_options, _) in {k: v for k, v in _Q1.items() if k.endswith(("maxdist", "consecutive", "tuned"))}.items():
    _kind = _name.rsplit("_", 1)[1]
    _src, _group, _wide = ("vis", "page_id, x_l", 190) if _kind == "tuned" else ("gi", "page_id, x_l, i", 500)
    _part = {"maxdist": (_MAXD,), "consecutive": (_CONS,), "tuned": ()}[_kind]
    _body = f"SELECT page_id, region_id FROM (SELECT *, {_A} FROM {_src} WINDOW g AS (PARTITION BY {_group})) WHERE {_IN_A.format(w=_wide)}"
    add(f"accuracy_q1_{_kind}", _score("q1", QUERIES[_name], _REG), _acc_sql("q1", _body, _part))
_TAG_GOLD = {"q1": "html_tag = 'li' AND template = 0", "q2": "html_tag = 'h1'", "q3": "html_tag IN ('p', 'footer')"}
for _t, _find, _gold in (("q1", tasks.q1_pages, _TAG_GOLD["q1"]), ("q2", tasks.q2_pages, _TAG_GOLD["q2"]), ("q3", tasks.q3_pages, _TAG_GOLD["q3"])):
    add(
        f"accuracy_{_t}_pages",
        lambda s, d, f=_find, g=_gold: accuracy(f(page_blocks(s, d)), page_blocks(s, d).where(g), _REG),
        q(_ACC.format(by="", found="SELECT DISTINCT * FROM fp", gold=f"SELECT DISTINCT page_id, region_id FROM blk WHERE {_gold}", keys="page_id, region_id", group=""), *_PG, f"fp AS ({ORACLES[f'{_t}_pages'].split(_BLOCKS, 1)[1].strip()})"),
    )

# ---------------------------------------------------------------- relational surface


def _tagged(s: SparkSession, d: str) -> DataFrame:
    return pages.regions(s, d).select("page_id", F.col("template").cast("string").alias("template"), "html_tag", P.area(Box.of()).alias("area"))


def _ends(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    r = pages.regions(s, d)
    return r.where("html_tag in ('p', 'li')").select("page_id", "x_l"), r.where("html_tag in ('p', 'div')").select("page_id", "x_l")


_AB = "a AS (SELECT page_id, x_l FROM reg WHERE html_tag IN ('p', 'li')), b AS (SELECT page_id, x_l FROM reg WHERE html_tag IN ('p', 'div'))"
add("union_bag", lambda s, d: spans.union(*_ends(s, d)), q("SELECT * FROM a UNION ALL SELECT * FROM b", D.PAGES, _AB))
add("intersect_bag", lambda s, d: spans.intersect(*_ends(s, d)), q("SELECT * FROM a INTERSECT ALL SELECT * FROM b", D.PAGES, _AB))
add("intersect_set", lambda s, d: spans.intersect(*_ends(s, d), all=False), q("SELECT * FROM a INTERSECT SELECT * FROM b", D.PAGES, _AB))
add("except_bag", lambda s, d: spans.difference(*_ends(s, d)), q("SELECT * FROM a EXCEPT ALL SELECT * FROM b", D.PAGES, _AB))
add("except_set", lambda s, d: spans.difference(*_ends(s, d), all=False), q("SELECT * FROM a EXCEPT SELECT * FROM b", D.PAGES, _AB))
add(
    "product_within_page",
    lambda s, d: spans.product(pages.regions(s, d).where("html_tag = 'h1'"), pages.regions(s, d).where("html_tag = 'li'")).select(F.col("a.page_id").alias("page_id"), F.col("a.region_id").alias("a_id"), F.col("b.region_id").alias("b_id")),
    q("SELECT a.page_id, a.region_id AS a_id, b.region_id AS b_id FROM reg a JOIN reg b USING (page_id) WHERE a.html_tag = 'h1' AND b.html_tag = 'li'", D.PAGES),
)
add("select_project", lambda s, d: spans.project(spans.select(pages.regions(s, d), F.col("y_l") > 300), "page_id", "html_tag"), q("SELECT page_id, html_tag FROM reg WHERE y_l > 300", D.PAGES))
_TERM = "EXISTS (SELECT 1 FROM reg r WHERE r.page_id = p.page_id AND regexp_matches(r.text, '(?i)\\beriner\\b'))"
for _name, _how, _not in (("semi_pages_with_term", "left_semi", ""), ("anti_pages_without_term", "left_anti", "NOT ")):
    add(_name, lambda s, d, h=_how: load(s, d, "pages").select("page_id", "url").join(visual.phrase_regions(pages.regions(s, d), "eriner"), "page_id", h), q(f"SELECT page_id, url FROM pages p WHERE {_not}{_TERM}", D.PAGES))
add(
    "asof_heading",
    lambda s, d: pages.regions(s, d)
    .withColumn("heading", F.last(F.when(F.col("html_tag") == "h1", F.col("region_id")), True).over(Window.partitionBy("page_id").orderBy("ord").rowsBetween(Window.unboundedPreceding, 0)))
    .where("html_tag = 'p'")
    .select("page_id", "region_id", "heading"),
    q("SELECT p.page_id, p.region_id, (SELECT arg_max(h.region_id, h.ord) FROM reg h WHERE h.page_id = p.page_id AND h.html_tag = 'h1' AND h.ord <= p.ord) AS heading FROM reg p WHERE p.html_tag = 'p'", D.PAGES),
)
add(
    "interval_join_spans",
    lambda s, d: spans.regex_spans(hierarchy.page_texts(pages.regions(s, d)), "[A-Z][a-z]+ing", "page_text", ("page_id",))
    .join(pages.regions(s, d).where("html_tag = 'p'").select("page_id", "region_id", "text_start", "text_end"), "page_id")
    .where("begin >= text_start and end <= text_end")
    .select("page_id", "region_id", "begin", "end"),
    q('SELECT s.page_id, r.region_id, s."begin", s."end" FROM sp s JOIN reg r ON r.page_id = s.page_id AND s."begin" >= r.text_start AND s."end" <= r.text_end WHERE r.html_tag = \'p\'', D.PAGES, _PT2, D.spans("[A-Z][a-z]+ing", "pt2", "page_id")),
)


def _agg(df) -> DataFrame:  # noqa: ANN001
    return df.agg(F.count("*").alias("n"), F.sum("area").cast("long").alias("total"))


_AGG_SQL = "count(*) AS n, CAST(sum((x_h - x_l) * (y_h - y_l)) AS BIGINT) AS total FROM (SELECT * REPLACE (CAST(template AS VARCHAR) AS template) FROM reg) GROUP BY"
add("rollup_tag_counts", lambda s, d: _agg(_tagged(s, d).rollup("template", "html_tag")), q(f"SELECT template, html_tag, {_AGG_SQL} ROLLUP (template, html_tag)", D.PAGES))
add("cube_template_tag", lambda s, d: _agg(_tagged(s, d).cube("template", "html_tag")), q(f"SELECT template, html_tag, {_AGG_SQL} CUBE (template, html_tag)", D.PAGES))


def _grouping_sets(s: SparkSession, d: str) -> DataFrame:
    _tagged(s, d).createOrReplaceTempView("tagged_regions")
    return s.sql("SELECT template, html_tag, count(*) AS n, CAST(sum(area) AS BIGINT) AS total FROM tagged_regions GROUP BY GROUPING SETS ((template), (html_tag))")


add("grouping_sets_tag", _grouping_sets, q(f"SELECT template, html_tag, {_AGG_SQL} GROUPING SETS ((template), (html_tag))", D.PAGES))
add(
    "topk_area_per_page",
    lambda s, d: pages.regions(s, d).withColumn("area", P.area(Box.of())).withColumn("place", F.row_number().over(Window.partitionBy("page_id").orderBy(F.desc("area"), "region_id")).cast("long")).where("place <= 3").select("page_id", "region_id", "area", "place"),
    q("SELECT * FROM (SELECT page_id, region_id, (x_h - x_l) * (y_h - y_l) AS area, row_number() OVER (PARTITION BY page_id ORDER BY (x_h - x_l) * (y_h - y_l) DESC, region_id) AS place FROM reg) WHERE place <= 3", D.PAGES),
)
add("topk_area", lambda s, d: pages.regions(s, d).select("page_id", "region_id", P.area(Box.of()).alias("area")).orderBy(F.desc("area"), "page_id", "region_id").limit(20), q("SELECT page_id, region_id, (x_h - x_l) * (y_h - y_l) AS area FROM reg ORDER BY area DESC, page_id, region_id LIMIT 20", D.PAGES))
_TAGS = ["li", "p", "h1", "div"]
add(
    "pivot_tag",
    lambda s, d: pages.regions(s, d).groupBy("page_id").pivot("html_tag", _TAGS).agg(F.count("region_id")).na.fill(0),
    q("SELECT page_id, " + ", ".join(f"count(*) FILTER (html_tag = '{t}') AS {t}" for t in _TAGS) + " FROM reg GROUP BY 1", D.PAGES),
)
add(
    "window_rank_regions",
    lambda s, d: pages.regions(s, d).select("page_id", "region_id", F.dense_rank().over(Window.partitionBy("page_id").orderBy("y_l")).cast("long").alias("line"), F.ntile(4).over(Window.partitionBy("page_id").orderBy("ord")).cast("long").alias("quarter")),
    q("SELECT page_id, region_id, dense_rank() OVER (PARTITION BY page_id ORDER BY y_l) AS line, ntile(4) OVER (PARTITION BY page_id ORDER BY ord) AS quarter FROM reg", D.PAGES),
)
add(
    "json_props",
    lambda s, d: load(s, d, "events").groupBy("event_type").agg(F.count(F.get_json_object("props", "$.k")).alias("n"), F.sum(F.get_json_object("props", "$.k").cast("long")).alias("total")),
    "SELECT event_type, count(json_extract_string(props, '$.k')) AS n, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS total FROM events GROUP BY 1",
)



def _visual_values(s: SparkSession, d: str) -> DataFrame:
    """Visual spans as one typed value each: a text interval and a rectangle."""
    held = pages.regions(s, d).select("page_id", "region_id", visual_span(span(F.col("text_start"), F.col("text_end")), Box.of().struct()).alias("v"))
    return held.select("page_id", "region_id", "v.s.begin", "v.s.end", *(F.col(f"v.r.{e}") for e in tasks.EDGES))


add("visual_span_values", _visual_values, q('SELECT page_id, region_id, text_start AS "begin", text_end AS "end", x_l, y_l, x_h, y_h FROM reg', D.PAGES))


def _by_file(fmt: str) -> Query:
    """Pages written as files of a format and read as a collection again."""

    def run(s: SparkSession, d: str) -> DataFrame:
        import uuid

        path = f"{modes.index_folder(s, d)}/pages-{uuid.uuid4().hex}"
        writer = load(s, d, "pages").select("page_id", "url", "html").write
        if fmt == "csv":
            writer = writer.option("header", "true").option("escape", '"')
        writer.format(fmt).save(path)
        return read_pages(s, path, fmt).select("page_id", "url", F.length("html").cast("long").alias("n_chars"), F.md5("html").alias("digest"))

    return run


for _fmt in ("json", "parquet", "orc"):
    add(f"pages_from_{_fmt}", _by_file(_fmt), "SELECT page_id, url, CAST(length(html) AS BIGINT) AS n_chars, md5(html) AS digest FROM pages")


def _sink(s: SparkSession, d: str) -> DataFrame:
    import uuid

    path = f"{modes.index_folder(s, d)}/matches-{uuid.uuid4().hex}"
    write_matches(modes.top_term(s, d, "auto"), path)
    return s.read.parquet(path)


add("matches_sink", _sink, ORACLES["q2_sheets"])

# ---------------------------------------------------------------- streams
add(
    "events_tumbling",
    lambda s, d: stream.tumbling(load(s, d, "events")).select(F.unix_seconds(F.col("w.start").cast("timestamp")).alias("start"), "event_type", "n", F.round("total", 2).alias("total")),
    "SELECT CAST(epoch_us(ts) // 3600000000 * 3600 AS BIGINT) AS start, event_type, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY 1, 2",
)
add(
    "events_sliding",
    lambda s, d: stream.sliding(load(s, d, "events")).select(F.unix_seconds(F.col("w.start").cast("timestamp")).alias("start"), "event_type", "n"),
    "SELECT CAST(epoch_us(ts) // 3600000000 * 3600 - 3600 * o AS BIGINT) AS start, event_type, count(*) AS n FROM events, (VALUES (0), (1)) v(o) GROUP BY 1, 2",
)
add(
    "events_session",
    lambda s, d: stream.sessions(load(s, d, "events")).select("user_id", F.unix_seconds(F.col("w.start").cast("timestamp")).alias("start"), "n"),
    "WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS c FROM events), g AS (SELECT *, sum(c) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT user_id, CAST(epoch_us(min(ts)) // 1000000 AS BIGINT) AS start, count(*) AS n FROM g GROUP BY user_id, k",
)


def stream_q4(s: SparkSession, d: str) -> DataFrame:
    """The fourth task over a stream of nested pages, run over what is there: as the batch answers."""
    base = modes.index_folder(s, d)
    nested = other_ways.nest(modes.stored_regions(s, d))
    import uuid

    run = uuid.uuid4().hex
    nested.repartition(4).write.parquet(f"{base}/nested-{run}")
    arriving = stream.page_stream(s, f"{base}/nested-{run}", nested.schema, files_per_batch=2)
    found = stream.stream_rules(arriving, P.ascii_word("Return Flag"), P.ascii_word("Returned"))
    out = f"{base}/stream-{run}"
    stream.run_available(found, stream.upsert_sink(out, ["page_id", "region_id"]), f"{base}/state-{run}")
    return s.read.schema("page_id long, region_id string").parquet(f"{out}/batch=*")


add("stream_q4_equals_batch", stream_q4, _Q4D)
