"""Worked examples and invariants of the text and visual algebra on hand-made pages."""

import random
import re

import pytest
from pyspark.sql import functions as F

from layout_ie.functions import predicates as P
from layout_ie.model import Box, virtual_region
from layout_ie.operators import align, hierarchy, spans, visual

EDGES = ("x_l", "y_l", "x_h", "y_h")
CENTRE = (100, 100, 200, 200)
#: Boxes around the centre, by name.
AROUND = {
    "n": (120, 0, 180, 50), "s": (120, 250, 180, 300), "e": (250, 120, 300, 180), "w": (0, 120, 50, 180), "nw": (0, 0, 50, 50), "wide_n": (0, 0, 300, 100), "edge_e": (200, 150, 260, 250),
    "corner": (200, 200, 250, 250), "over": (150, 150, 250, 250), "in": (110, 110, 190, 190), "same": CENTRE, "flat": (120, 100, 180, 100),
}


def pairs(spark, boxes=AROUND):
    rows = [(k, *v, *CENTRE) for k, v in boxes.items()]
    return spark.createDataFrame(rows, "name string, " + ", ".join(f"{e}{s} long" for s in ("_a", "_b") for e in EDGES))


@pytest.mark.parametrize(
    "name,want",
    [
        ("north_of", {"n", "nw", "wide_n", "flat"}), ("south_of", {"s", "corner"}), ("east_of", {"e", "edge_e", "corner"}), ("west_of", {"w", "nw"}),
        ("strict_north_of", {"n", "flat"}), ("strict_south_of", {"s"}), ("strict_east_of", {"e"}), ("strict_west_of", {"w"}), ("north_west_of", {"nw"}), ("south_east_of", {"corner"}),
        ("within", {"in", "same", "flat"}), ("touches", {"edge_e", "wide_n", "flat"}), ("intersects", {"wide_n", "edge_e", "corner", "over", "in", "same", "flat"}),
    ],
)
def test_predicates(spark, name, want):
    got = pairs(spark).where(getattr(P, name)(Box.suffixed("_a"), Box.suffixed("_b"))).select("name").collect()
    assert {r[0] for r in got} == want


def test_sql_functions_say_the_same(spark):
    P.register_all(spark)
    df = pairs(spark)
    both = {f"{a}_of": f"{a}_of" for a in ("north", "south", "east", "west", "strict_north", "strict_south", "strict_east", "strict_west", "north_west", "south_east")}
    both |= {"box_within": "within", "box_touches": "touches", "box_intersects": "intersects"}
    a, b = ("struct(" + ", ".join(f"{e}{s} AS {e}" for e in EDGES) + ")" for s in ("_a", "_b"))
    for sql, name in both.items():
        one = df.select("name", F.expr(f"{sql}({a}, {b})").alias("x"), getattr(P, name)(Box.suffixed("_a"), Box.suffixed("_b")).alias("y")).where("x <> y")
        assert one.count() == 0, sql


def test_corner_and_interior(spark):
    a, b = Box.suffixed("_a"), Box.suffixed("_b")
    corner = pairs(spark).where(P.touches(a, b, corners=True)).select("name").collect()
    assert {r[0] for r in corner} == {"edge_e", "wide_n", "flat", "corner"}
    assert {r[0] for r in pairs(spark).where(P.intersects(a, b, interior=True)).select("name").collect()} == {"over", "in", "same"}


def test_open_bounds_put_no_condition(spark):
    df = pairs(spark).select("name", *(F.col(f"{e}_a").alias(e) for e in EDGES))
    got = df.where(P.within(Box.of(), virtual_region(100, None, None, 200))).select("name").collect()
    assert {r[0] for r in got} == {k for k, v in AROUND.items() if v[0] >= 100 and v[3] <= 200}
    assert "isnull" not in str(P.within(Box.of(), virtual_region(1)))


def test_random_box_invariants(spark):
    r = random.Random(5)
    box = lambda: (x := r.randrange(20), y := r.randrange(20), x + r.randrange(1, 8), y + r.randrange(1, 8))
    df = spark.createDataFrame([(*box(), *box()) for _ in range(3000)], ", ".join(f"{e}{s} long" for s in ("_a", "_b") for e in EDGES))
    a, b = Box.suffixed("_a"), Box.suffixed("_b")
    implied = [
        (P.strict_north_of(a, b), P.north_of(a, b)), (P.strict_east_of(a, b), P.east_of(a, b)), (P.touches(a, b), P.intersects(a, b)), (P.within(a, b), P.intersects(a, b)),
        (P.touches(a, b), ~P.intersects(a, b, interior=True)), (P.north_of(a, b), P.south_of(b, a)), (P.south_of(b, a), P.north_of(a, b)), (P.east_of(a, b), P.west_of(b, a)),
        (P.intersects(a, b) & ~P.touches(a, b, corners=True), P.intersects(a, b, interior=True)),
    ]
    for i, (p, q) in enumerate(implied):
        assert df.where(p & ~q).count() == 0, i


# ---------------------------------------------------------------- spans
def rel(spark, *xs, key="doc_id"):
    return spark.createDataFrame([(1, *x) for x in xs], f"{key} long, begin long, end long")


def got(df):
    return sorted((r["begin"], r["end"]) for r in df.collect())


def test_regex_offsets_equal_python(spark):
    texts = ["", None, "a1b22c", "éé 12 — 7", "333", "x" * 50 + "9", "1\n2\r\n3"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for pattern in (r"[0-9]+", r"[a-z]+[0-9]", r"\s", r"[0-9](?=b)"):
        want = sorted((i, m.start(), m.end(), m.group()) for i, t in enumerate(texts) for m in re.finditer(pattern, t or "", re.ASCII))
        for found in (spans.regex_spans(df, pattern), spans.regex_spans_arrow(df, pattern)):
            assert sorted(tuple(r) for r in found.collect()) == want
    empty = spans.regex_spans(df, "[0-9]*").count()
    assert empty == sum(len(list(re.finditer("[0-9]*", t or ""))) for t in texts)


@pytest.mark.parametrize(("pattern", "text", "want"), [("(?=a)", "ab cab a", [(0, 0), (4, 4), (7, 7)]), (r"\b", "a b", [(0, 0), (1, 1), (2, 2), (3, 3)]), (r"\p{L}+", "été 12 né", [(0, 3), (7, 9)]), (r"x*", "axx", [(0, 0), (1, 3), (3, 3)]), (r"(?<=a)b", "ab cb", [(1, 2)]), ("", "ab", [(0, 0), (1, 1), (2, 2)])])
def test_patterns_with_empty_matches_and_classes(spark, pattern, text, want):
    df = spark.createDataFrame([(1, text)], "doc_id long, text string")
    assert sorted((r["begin"], r["end"]) for r in spans.regex_spans(df, pattern).collect()) == want


def test_flags_and_groups(spark):
    df = spark.createDataFrame([(1, "Key=Value; key=other; lone=")], "doc_id long, text string")
    assert [r["matched"] for r in spans.regex_spans(df, r"key=\w+", flags="i").orderBy("begin").collect()] == ["Key=Value", "key=other"]
    got = spans.regex_spans(df, r"(\w+)=(\w+)?", group=2).orderBy("begin").collect()
    assert [(r["begin"], r["end"], r["matched"]) for r in got] == [(4, 9, "Value"), (15, 20, "other")]


def test_dictionary_finds_every_occurrence(spark):
    df = spark.createDataFrame([(1, "New York, new  york city; York"), (2, None), (3, "")], "doc_id long, text string")
    terms = spark.createDataFrame([("new york",), ("york city",), ("York",), ("",)], "term string")
    found = sorted((r["begin"], r["end"], r["term"]) for r in spans.dict_spans(df, terms).collect())
    assert found == [(0, 8, "new york"), (4, 8, "York"), (10, 19, "new york"), (15, 19, "York"), (15, 24, "york city"), (26, 30, "York")]


def test_dictionary_entries_of_many_words(spark):
    from layout_ie.plans import rules

    texts = ["We say: one two, three four FIVE six.", "one two three four", "word of-the day", None, ""]
    df = spark.createDataFrame([(i, str(i), t) for i, t in enumerate(texts)], "page_id int, region_id string, text string")
    terms = spark.createDataFrame([("one two three four five",), ("Two Three Four Five Six seven",), ("of the",), ("say",), (" - ",)], "term string")
    found = sorted(tuple(r) for r in spans.dict_spans(df, terms, keep=("page_id",)).select("page_id", "begin", "term").collect())
    assert found == [(0, 3, "say"), (0, 8, "one two three four five"), (2, 5, "of the")]
    rule = rules.parse("SELECT v.page_id, v.region_id FROM DICT('many_words', D) AS v")
    assert sorted(r["page_id"] for r in rules.to_df(rule, df, {"many_words": terms}).collect()) == [0, 2]
    no_say = terms.where("term <> 'say'")
    assert sorted(r["page_id"] for r in rules.to_df(rule, df, {"many_words": no_say}).collect()) == [0, 2]


def test_consolidation_and_blocks(spark):
    r = rel(spark, (0, 5), (1, 3), (0, 5), (5, 8), (7, 9), (20, 21), (20, 22))
    assert got(spans.consolidate_contained(r)) == [(0, 5), (5, 8), (7, 9), (20, 22)]
    assert got(spans.consolidate_overlapping(r)) == [(0, 5), (5, 9), (20, 22)]
    once = spans.consolidate_overlapping(r)
    assert got(spans.consolidate_overlapping(once)) == got(once)
    chain = rel(spark, (0, 1), (4, 5), (9, 10), (30, 31))
    assert got(spans.text_block(chain, 3, 4)) == [(0, 10)]
    assert got(spans.text_block(chain, 2, 3)) == [(0, 5)]


def test_predicates_on_spans(spark):
    df = spark.createDataFrame([(0, 3, 3, 5), (0, 3, 4, 6), (0, 3, 2, 4), (0, 3, 0, 3), (1, 2, 0, 3), (0, 3, 8, 9)], "ab long, ae long, bb long, be long")
    ab, ae, bb, be = (F.col(c) for c in ("ab", "ae", "bb", "be"))
    test = lambda c: [r[0] for r in df.select(c).collect()]
    assert test(P.follows(ae, bb, 1)) == [True, True, False, False, False, False]
    assert test(P.overlaps(ab, ae, bb, be)) == [False, False, True, True, True, False]
    assert test(P.strictly_in(ab, ae, bb, be)) == [False, False, False, False, True, False]
    assert test(P.same_span(ab, ae, bb, be)) == [False, False, False, True, False, False]
    pairs_ = spans.follows_join(rel(spark, (0, 3), (10, 12)), rel(spark, (3, 4), (8, 9), (13, 14), (40, 41)), 5)
    assert sorted((r["a_end"], r["b_begin"]) for r in pairs_.collect()) == [(3, 3), (3, 8), (12, 13)]


def test_bags_and_widths(spark):
    a, b = rel(spark, (0, 1), (0, 1), (2, 3)), rel(spark, (0, 1), (4, 5))
    assert spans.union(a, b).count() == 5 and spans.intersect(a, b).count() == 1 and spans.difference(a, b).count() == 2 and spans.difference(a, b, all=False).count() == 1
    with pytest.raises(ValueError):
        spans.union(a, b.select("begin"))
    assert spans.product(a, b, page="doc_id").count() == 6


# ---------------------------------------------------------------- hierarchy
PATHS = {"1": (0, 9), "1.2": (0, 5), "1.2.1": (0, 5), "1.20": (6, 9), "1.20.3": (6, 9), "1.3": (5, 5)}


def tree(spark):
    rows = [(1, k, 0, 0, 100 - 10 * k.count("."), 100, a, b, None if k in ("1", "1.2", "1.20") else "t", "div", k.count(".") + 1, i) for i, (k, (a, b)) in enumerate(PATHS.items())]
    df = spark.createDataFrame(rows, "page_id long, region_id string, x_l long, y_l long, x_h long, y_h long, text_start long, text_end long, text string, html_tag string, depth long, ord long")
    return hierarchy.annotate_extremes(df)


def test_paths(spark):
    t = tree(spark)
    pick = lambda p: t.where(F.col("region_id") == p)
    ids = lambda df: {r["region_id"] for r in df.collect()}
    assert ids(hierarchy.ancestors(pick("1.20.3"), t)) == {"1", "1.20"} and ids(hierarchy.ancestors(pick("1.20.3"), t, or_self=True)) == {"1", "1.20", "1.20.3"}
    assert ids(hierarchy.ancestors(pick("1"), t)) == set()
    assert ids(hierarchy.descendants(pick("1.2"), t)) == {"1.2.1"}
    assert ids(hierarchy.children(pick("1"), t)) == {"1.2", "1.20", "1.3"} and ids(hierarchy.parent(pick("1.2.1"), t)) == {"1.2"}
    assert ids(hierarchy.siblings(pick("1.2"), t)) == {"1.20", "1.3"}
    assert ids(hierarchy.maximal_region(pick("1.2.1"), t)) == {"1.2"} and ids(hierarchy.minimal_region(pick("1.20"), t)) == {"1.20.3"}
    assert ids(hierarchy.maximal_region(pick("1.3"), t)) == {"1.3"}


def test_enclosing_node_is_the_deepest(spark):
    s = spark.createDataFrame([(1, 0, 4), (1, 4, 7), (1, 6, 8), (2, 0, 1)], "page_id long, begin long, end long")
    assert {(r["page_id"], r["begin"], r["region_id"]) for r in hierarchy.enclosing_node(s, tree(spark)).collect()} == {(1, 0, "1.2.1"), (1, 4, "1"), (1, 6, "1.20.3"), (2, 0, None)}


# ---------------------------------------------------------------- alignment and blocks
def column(spark, rows):
    full = [(1, f"1.{i}", *r, 10 * i, 10 * i + 5, i) for i, r in enumerate(rows, 1)]
    return spark.createDataFrame(full, "page_id long, region_id string, x_l long, y_l long, x_h long, y_h long, text_start long, text_end long, ord long")


def groups(df):
    return sorted((r["group_key"], r["n_members"]) for r in align.minimal_bounding_region(df).collect())


def test_alignment_flags(spark):
    stack = [(0, 0, 50, 20), (0, 20, 50, 40), (0, 100, 50, 120)]
    assert groups(align.vertically_aligned(column(spark, stack))) == [(0, 3)]
    assert groups(align.vertically_aligned(column(spark, stack), max_dist=60)) == [(0, 3)]
    assert groups(align.vertically_aligned(column(spark, stack), max_dist=59)) == [(0, 1), (0, 2)]
    intruder, beside = (10, 60, 40, 80), (60, 60, 90, 80)
    assert groups(align.vertically_aligned(column(spark, [*stack, intruder]), consecutive=True)) == [(0, 1), (0, 2), (10, 1)]
    assert groups(align.vertically_aligned(column(spark, [*stack, beside]), consecutive=True)) == [(0, 3), (60, 1)]
    assert groups(align.vertically_aligned(column(spark, [stack[0], beside, *stack[1:]]), consecutive=True, between="order")) == [(0, 1), (0, 2), (60, 1)]
    assert groups(align.aligned(column(spark, [(0, 0, 9, 9), (3, 20, 9, 29), (6, 40, 9, 49), (30, 0, 39, 9)]), tol=3)) == [(0, 3), (30, 1)]
    assert groups(align.horizontally_aligned(column(spark, stack))) == [(0, 1), (20, 1), (100, 1)]
    assert groups(align.horizontally_aligned(column(spark, stack), literal_mapping=True)) == [(0, 3)]


def test_bounds_and_super_regions(spark):
    t = tree(spark)
    g = align.minimal_bounding_region(t.where("region_id in ('1.2.1', '1.20.3')"), ["page_id"])
    assert tuple(g.select(*EDGES, "n_members").first()) == (0, 0, 80, 100, 2)
    assert align.minimal_super_region(g, t, ["page_id"]).first()["region_id"] == "1.2.1"


def test_region_blocks(spark):
    vs = column(spark, [(0, 0, 10, 10), (14, 0, 24, 10), (0, 14, 10, 24), (100, 100, 110, 110), (115, 100, 125, 110)])
    reading = lambda dx, dy, n=2, mode="reading": sorted(r["n_spans"] for r in visual.region_block(vs, n, dx, dy, mode).collect())
    assert reading(5, 5) == [3] and reading(4, 5) == [] and reading(6, 5) == [2, 3]
    assert reading(5, 5, mode="component") == [3] and reading(6, 5, mode="component") == [2, 3] and reading(5, 4, mode="component") == [2]
    with pytest.raises(ValueError):
        visual.region_block(vs, 2, 1, 1, "other")


def test_nearest(spark):
    vs = column(spark, [(0, 0, 10, 10), (0, 30, 10, 40), (0, 20, 10, 25), (50, 12, 60, 14)])
    near = align.nearest(vs.where("region_id = '1.1'"), vs, "south", 2).collect()
    assert [(r["b_id"], r["gap"]) for r in sorted(near, key=lambda r: r["place"])] == [("1.3", 10), ("1.2", 20)]


def test_visual_consolidation_ties(spark):
    vs = column(spark, [(0, 0, 10, 10), (0, 0, 10, 10), (2, 2, 5, 5)]).withColumns({"text_start": F.lit(0).cast("long"), "text_end": F.when(F.col("ord") == 3, 2).otherwise(5).cast("long")})
    assert [tuple(r[e] for e in EDGES) for r in visual.consolidate_contained_visual(vs).collect()] == [(0, 0, 10, 10)]
