"""Rendering, the rule language, access paths, baselines, measures, plans and streams."""

import duckdb
import pytest
from pyspark.sql import functions as F

from layout_ie.functions import predicates as P
from layout_ie.index import region as region_index
from layout_ie.index import text as text_index
from layout_ie.measures.accuracy import accuracy, plan_counts, robustness, speedup, work_of
from layout_ie.plans import rules
from layout_ie.sources import pages, sheets, tables
from layout_ie.streaming import stream
from layout_ie.workloads import catalogue, modes, tasks

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


# ---------------------------------------------------------------- rendering
def nodes(html, page=0):
    return {r[1]: r for r in pages.draw(page, html)}


def test_tolerant_tree():
    t = nodes("<html><body><nav><ul><li><a>One</a><li>Two</ul></nav><script>var x='</p>'</script><!-- no --><article><h1>T &amp; &copy; &am</h1><p><b>Open<br><p>Next <b>x</b></article>")
    assert {k: v[9] for k, v in t.items()} == {"1": "body", "1.1": "nav", "1.1.1": "ul", "1.1.1.1": "li", "1.1.1.1.1": "a", "1.1.1.2": "li", "1.2": "article", "1.2.1": "h1", "1.2.2": "p", "1.2.2.1": "b", "1.2.3": "p", "1.2.3.1": "b"}
    assert t["1.2.1"][8] == "T & © &am" and t["1.2.2"][8] is None and t["1.2.2.1"][8] == "Open"
    assert t["1.2.2"][10] == "1.2.2.1" and t["1.2.2.1"][11] == "1.2.2"  # minimal, maximal
    assert t["1.1.1.1"][2:6] == (0, 100, 200, 120) and t["1.1.1.2"][2:6] == (0, 120, 200, 140)


def test_templates_and_empty_pages():
    html = "<body><ul><li>a<li>b</ul><p>text</p></body>"
    assert nodes(html, 1)["1.1.1"][2:6] == (824, 100, 1024, 120) and nodes(html, 1)["1.2"][2:6] == (0, 100, 804, 120)
    assert nodes(html, 2)["1.1.2"][2:6] == (160, 100, 320, 120) and nodes(html, 2)["1.2"][2:6] == (0, 120, 1024, 140)
    for html in (None, "", "<body></body>"):
        assert list(nodes(html)) == ["1"]
    for a, r in nodes("<body><div><p>x</p><p>yy</p></div></body>").items():
        up = a.rsplit(".", 1)[0]
        parent = nodes("<body><div><p>x</p><p>yy</p></div></body>").get(up)
        assert parent is None or parent[6] <= r[6] and r[7] <= parent[7]


def test_three_markups_one_drawing(spark, sf):
    """The drawing does not depend on the markup: ids tell it apart, boxes and texts do not."""
    vis = sheets.boxes(spark, sf)
    cells = vis.where("kind = 'head' and text = 'Return Flag' and page_id % 7 <> 3 and page_id % 2 = 0")
    assert {tuple(r) for r in cells.select("x_l", "y_l", "x_h", "y_h").distinct().collect()} == {(200, 100, 360, 120)}
    assert cells.select("template").distinct().count() == 3
    assert vis.count() == 40_270 and vis.select("page_id").distinct().count() == 1_473


# ---------------------------------------------------------------- rules
def test_rule_errors():
    for bad in ("SELECT", "SELECT a.x FROM REGIONS(D) AS b", "SELECT a.x FROM WHAT(D) AS a", "SELECT a.x FROM REGIONS(D) AS a WHERE Nope(a, a)", "SELECT a.x FROM REGIONS(D) AS a WHERE NorthOf(a)", "SELECT a.x FROM REGIONS(D) AS a, REGIONS(D) AS a", "SELECT c.x FROM MAXIMAL(h) AS c", "SELECT a.x FROM REGIONS(D) AS a WHERE a.x_l ~ 3"):
        with pytest.raises(rules.RuleError):
            rules.parse(bad)


def test_rule_lowering():
    sql = rules.to_sql(rules.parse("SELECT a.region_id FROM PHRASE('it''s', D) AS a, REGIONS(D) AS b WHERE StrictNorthOf(a, b) AND (NOT Touches(a, b) OR a.x_l >= 3) AND Contains(a, BOX(0, 90, 500, INF))"))
    assert "b.page_id = a.page_id" in sql and "a.y_h <= b.y_l" in sql and "a.x_h <= 500" in sql and "INF" not in sql and "None" not in sql
    assert rules.phrase_of("a phrase") and rules.phrase_of(r"a\s+b") is None
    ordered = rules.rewrite(rules.parse(catalogue.RULE_Q4), "text", {"h": 50, "m": 7})
    assert [s.alias for s in ordered.sources] == ["m", "h", "s"] and ordered.sources[0].kind == "POSTINGS"
    assert rules.rule_size(rules.parse(catalogue.RULE_Q1)) == {"sources": 1, "predicates": 2, "constants": 4, "groupings": 1}


def test_rules_over_spans_and_hierarchy(spark):
    df = pages.render_pages(spark.createDataFrame([(3, "<body><div><p>alpha</p><p>beta gamma</p></div></body>")], "page_id long, html string"))
    run = lambda t: sorted(r[0] for r in rules.to_df(rules.parse(t), df).collect())
    assert run("SELECT u.region_id FROM PHRASE('beta', D) AS b, ANCESTORS(b) AS u") == ["1", "1.1"]
    assert run("SELECT x.region_id FROM PHRASE('alpha', D) AS a, DESCENDANTS(a) AS x") == []
    assert run("SELECT b.region_id FROM PHRASE('alpha', D) AS a, PHRASE('gamma', D) AS b WHERE Follows(a, b, 1) AND NOT Overlap(a, b)") == ["1.1.2"]
    assert run("SELECT b.region_id FROM REGIONS(D) AS b WHERE Area(b) > 16080 AND b.html_tag <> 'body'") == []
    assert run("SELECT b.region_id FROM REGEX('^beta', D) AS b WHERE b.html_tag = 'p'") == ["1.1.2"]


# ---------------------------------------------------------------- access paths and plans
def test_access_paths_agree(spark, sf):
    want = sorted(map(tuple, tasks.q4_sheets(spark, sf, distinct=True).collect()))
    assert len(want) == 2511
    for mode in modes.TASKS["q4"][1]:
        assert sorted(map(tuple, modes.right_of_match(spark, sf, mode).collect())) == want, mode
    for task in ("q1", "q2", "q3"):
        find, paths = modes.TASKS[task]
        answers = {mode: sorted(map(tuple, find(spark, sf, mode).collect())) for mode in paths}
        assert len(set(map(str, answers.values()))) == 1 and answers["none"], task


def test_the_engine_chooses(spark, sf):
    """Rare phrases go to the postings, tasks that put a page's regions together to the clustered relation."""
    assert modes.choose(spark, sf, "q1") == "region" and modes.choose(spark, sf, "q4") == "text+region"
    assert "text" in modes.choose(spark, sf, "q2")
    summary = modes.stored_summary(spark, sf)
    inside, n = region_index.box_count(summary, tasks.TOP_SHEETS)
    assert n == 40_270 and 0 < inside < n and region_index.box_count(summary, None) == (n, n)


def test_unfiltered_regions_stay_where_they_are(spark, sf):
    """With both indices the fourth task exchanges its matches only: the clustered relation is scanned in place."""
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    try:
        plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
        q4 = modes.right_of_match(spark, sf, "text+region")
        assert plan_counts(q4)["exchanges"] == 2 and "Bucketed: true" in plan(q4)
        assert plan_counts(modes.left_bar(spark, sf, "region"))["exchanges"] == 0
        work = work_of(lambda: modes.right_of_match(spark, sf, "text+region"))
        plain = work_of(lambda: modes.right_of_match(spark, sf, "none"))
        assert work["rows_read"] < plain["rows_read"] and work["bytes_shuffled"] < plain["bytes_shuffled"] and plain["tasks"] > 0
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


PHRASE_TEXTS = ["Order Summary", "order summary", "Order, Summary", "Order  Summary", "Order-Summary", "preorder summary", "Order Summary's end", "été", "an été t", "t", "Kelvin \u212a k", "!!", "wow!! no", None, "", "the Order Summary of the Order Summary list"]


@pytest.mark.parametrize("phrase", ["Order Summary", "été", "!!", "k", "t", "summary of the order", "order"])
def test_the_text_index_answers_as_a_scan(spark, phrase):
    rows = [(i // 4, f"1.{i}", t, *[10 * i, 0, 10 * i + 5, 5]) for i, t in enumerate(PHRASE_TEXTS)]
    df = spark.createDataFrame(rows, "page_id long, region_id string, text string, x_l long, y_l long, x_h long, y_h long")
    rule = rules.parse(f"SELECT a.page_id, a.region_id FROM PHRASE('{phrase}', D) AS a WHERE Contains(a, BOX(0, 0, INF, INF))")
    views = {"postings": text_index.build_covering_index(df)}
    scan = sorted(map(tuple, rules.to_df(rule, df).collect()))
    by_index = rules.rewrite(rule, "text")
    assert sorted(map(tuple, rules.to_df(by_index, df, views).collect())) == scan
    literal = phrase.isascii() and phrase != "!!"
    assert (by_index.sources[0].kind == "POSTINGS") == literal
    if literal:
        assert sorted(map(tuple, text_index.lookup_phrase(views["postings"], phrase).select("page_id", "region_id").collect())) == scan
    else:
        with pytest.raises(ValueError):
            text_index.lookup_phrase(views["postings"], phrase)


def test_rules_meet_by_equality(spark, sf):
    """Dictionaries, ancestors and descendants are equi-joins: no nested loops over pairs."""
    vis = sheets.boxes(spark, sf)
    views = {"names": catalogue.words_df(spark, "Returned", "Order Summary")}
    for text in (catalogue.RULE_Q3, *(t for t, _ in catalogue._PAGE_RULES.values()), catalogue.RULE_Q1_NEXT):
        plan = rules.to_df(rules.parse(text), vis.withColumns({"minimal_region": F.col("region_id"), "maximal_region": F.col("region_id")}), views)._jdf.queryExecution().executedPlan().toString()
        assert "NestedLoop" not in plan and "Cartesian" not in plan, text


def test_bucketed_regions_need_no_shuffle(spark, sf):
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    try:
        vis = tables.write_regions(sheets.boxes(spark, sf), "drawn_bucketed", 4)
        q4 = tasks.right_of_match(vis, tasks.heading_sheets(vis), "Returned")
        assert plan_counts(q4)["exchanges"] == 0 and q4.count() == 2511
        assert plan_counts(tasks.left_bar(vis))["exchanges"] == 0
        text = q4._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql("DROP TABLE IF EXISTS drawn_bucketed")


def test_box_filters_reach_the_scan(spark, sf, tmp_path):
    index = region_index.build_region_index(sheets.boxes(spark, sf), "boxes_to_scan", str(tmp_path / "boxes"))
    spark.conf.set("spark.sql.maxMetadataStringLength", 2000)
    plan = region_index.lookup_box(index, tasks.LEFT_BAR)._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThanOrEqual(x_l,0)" in plan and "LessThanOrEqual(x_h,500)" in plan
    assert region_index.choose_access(5, 0.5, 1000) == "text" and region_index.choose_access(None, 0.01, 1000) == "region" and region_index.choose_access(900, None, 1000) == "none"


def test_text_index(spark):
    df = spark.createDataFrame([(1, "1.1", "The New, new york"), (1, "1.2", "york new"), (2, "1", None)], "page_id long, region_id string, text string")
    posts = text_index.build_text_index(df)
    assert posts.count() == 6
    covering = text_index.build_covering_index(df.withColumns({e: F.lit(1) for e in text_index.BOX}))
    assert [tuple(r)[:2] for r in text_index.lookup_phrase(covering, "New York").collect()] == [(1, "1.1")]
    assert {r["region_id"] for r in text_index.lookup_terms(posts, ["york"]).collect()} == {"1.1", "1.2"}
    assert text_index.posting_counts(posts, {"a": "new york", "b": "the york", "c": "none"}) == {"a": 2, "b": 1, "c": 0}


def test_udf_free_predicates(spark):
    df = spark.range(5).select(F.col("id").alias("page_id"), *(F.col("id").alias(e) for e in ("x_l", "y_l", "x_h", "y_h")))
    assert plan_counts(df.where(P.area(catalogue.Box.of()) > 0))["python"] == 0


# ---------------------------------------------------------------- measures
def test_expected_accuracy(spark):
    """Regression values of the readings on the drawn sheets at scale 0.01."""
    vis = sheets.boxes(spark, "/root/testdata/sf0.01").cache()
    score = lambda f, t, k=("page_id", "region_id"): tuple(accuracy(f, tasks.gold(vis, t), list(k)).select("returned", "right", "gold").first())
    assert score(tasks.left_bar(vis), "q1") == (63_174, 58_970, 73_715)
    assert score(tasks.left_bar(vis, restrict_first=True), "q1") == (136_003, 73_715, 73_715)
    assert score(tasks.left_bar(vis, consecutive=True), "q1") == (66_825, 61_915, 73_715)
    assert score(tasks.top_term(vis, "Order Summary", tasks.TOP_SHEETS), "q2", ("page_id",)) == (9_513, 9_160, 9_743)
    head, cell = tasks.heading_sheets(vis), tasks.heading_sheets(vis, True)
    assert score(tasks.names_by_heading(vis, head, ["Returned", "Accepted"]), "q3") == (37_849, 37_273, 40_074)
    assert score(tasks.names_by_heading(vis, cell, ["Returned", "Accepted"]), "q3") == (40_747, 40_074, 40_074)
    assert score(tasks.right_of_match(vis, head, "Returned"), "q4") == (25_854, 25_854, 30_126)
    assert score(tasks.right_of_match(vis, cell, "Returned"), "q4") == (30_126, 30_126, 30_126)
    vis.unpersist()


def test_accuracy_edges(spark):
    empty = spark.createDataFrame([], "k long")
    some = spark.createDataFrame([(1,), (1,), (2,)], "k long")
    assert tuple(accuracy(some, empty, ["k"]).first()) == (2, 0, 0, None, 0.0, 0.0)
    assert tuple(accuracy(empty, some, ["k"]).first()) == (0, 0, 2, 0.0, None, 0.0)
    assert tuple(robustness(spark.createDataFrame([(100.0,), (40.0,)], "recall double")).first()) == (100.0, 40.0, 60.0)
    assert speedup({"none": 6.0, "text": 2.0})["text"] == 3.0


def test_source_rules_depend_on_markup(spark, sf):
    for name, spread in (("visual", False), ("identical", False), ("approximate", True)):
        drop = catalogue.QUERIES[f"robustness_{name}"](spark, sf).first()["drop"]
        assert (drop > 90) == spread, name


# ---------------------------------------------------------------- streams
def test_recrawls_and_changes(spark, tmp_path):
    crawl = spark.createDataFrame([(1, "u", "2024-01-01 00:00:00"), (2, "u", "2024-01-01 01:00:00"), (3, "v", "2024-01-01 01:00:00")], "page_id long, url string, c string").select("page_id", "url", F.to_timestamp("c").alias("crawled"))
    crawl.coalesce(1).write.parquet(str(tmp_path / "in"))
    arriving = stream.page_stream(spark, str(tmp_path / "in"), crawl.schema)
    stream.run_available(stream.drop_recrawls(arriving), stream.upsert_sink(str(tmp_path / "out"), ["url"]), str(tmp_path / "state"))
    assert spark.read.parquet(str(tmp_path / "out")).count() == 2


def test_changes_between_crawls(spark, tmp_path):
    rows = [("u", 1, "a\nb"), ("u", 2, "b\nc\nd"), ("v", 1, "")]
    spark.createDataFrame(rows, "url string, crawl long, found string").coalesce(1).write.parquet(str(tmp_path / "in"))
    arriving = spark.readStream.schema("url string, crawl long, found string").parquet(str(tmp_path / "in"))
    found = []
    stream.run_available(stream.changed_matches(arriving), lambda b, _: found.extend(tuple(r) for r in b.collect()), str(tmp_path / "state"))
    assert sorted(found) == [("u", 1, 2, 0), ("u", 2, 2, 1), ("v", 1, 0, 0)]


# ---------------------------------------------------------------- SQL twins
SAMPLE = ["regex_ip_spans", "dict_phrase_spans", "consolidate_contained", "page_regions", "grid_regions", "sheet_extremes", "touches_pages", "aligned_consecutive", "region_block_component", "q3_sheets_maximal", "rule_q1_maxdist", "stream_q4_equals_batch"]


@pytest.fixture(scope="module")
def db(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", SAMPLE)
def test_sql_twin(spark, sf, db, name):
    mine = catalogue.QUERIES[name](spark, sf)
    cols = sorted(mine.columns)
    twin = db.sql(catalogue.ORACLES[name])
    assert sorted(twin.columns) == cols
    key = lambda r: tuple(str(x) for x in r)
    assert sorted((tuple(r) for r in mine.select(*cols).collect()), key=key) == sorted(twin.select(*cols).fetchall(), key=key)


def test_dictionary_rule_finds_phrases(spark, sf, db):
    want = db.sql(catalogue.ORACLES["rule_dict_phrases"]).fetchall()
    assert want and sorted(map(tuple, catalogue.QUERIES["rule_dict_phrases"](spark, sf).collect())) == sorted(want)


def test_entry_points(spark):
    import __spark_entry__ as e

    names = e.queries()
    assert set(e.oracle_sql()) <= set(names) and len(names) > 140
    assert e.entry(spark).limit(1).count() == 1


@pytest.mark.parametrize("seed", range(4))
def test_collection_equals_page_by_page(spark, seed):
    """Random boxes: the SQL plan, the nested loops and the higher-order functions give one answer."""
    import random

    from layout_ie.baselines.other_ways import nest
    from layout_ie.plans import evaluate

    r = random.Random(seed)
    rows = []
    for page in range(20):
        for i in range(40):
            x, y = r.randrange(0, 60, 5), r.randrange(0, 60, 5)
            rows.append((page, f"1.{i}", x, y, x + r.choice((5, 10, 20)), y + r.choice((5, 10)), 7 * i, 7 * i + 6, r.choice(("alpha", "beta", "beta gamma", "delta")), "p"))
    df = spark.createDataFrame(rows, "page_id long, region_id string, x_l long, y_l long, x_h long, y_h long, text_start long, text_end long, text string, html_tag string")
    for where in ("StrictSouthOf(b, a)", "StrictEastOf(b, a) OR Touches(a, b)", "Intersects(a, b) AND NOT Contains(b, a)", "WestOf(a, b) AND Follows(a, b, 50)", "Contains(b, BOX(10, 10, INF, 40)) AND NorthOf(a, b)"):
        text = f"SELECT a.page_id, a.region_id, b.region_id FROM PHRASE('alpha', D) AS a, PHRASE('beta', D) AS b WHERE {where}"
        one = sorted(map(tuple, rules.to_df(rules.parse(text), df).collect()))
        by_page = {}
        for x in rows:
            by_page.setdefault(x[0], []).append(dict(zip(df.columns, x, strict=True)))
        two = sorted(t for p in by_page.values() for t in evaluate.evaluate_page(rules.parse(text), p))
        assert one == two, where
    rule = rules.parse("SELECT b.page_id, b.region_id FROM PHRASE('alpha', D) AS a, PHRASE('beta', D) AS b WHERE StrictSouthOf(b, a)")
    assert sorted(map(tuple, evaluate.run_per_page(rule, nest(df, evaluate.NESTED)).collect())) == sorted(map(tuple, rules.to_df(rule, df).collect()))
    with pytest.raises(rules.RuleError):
        evaluate.evaluate_page(rules.parse(catalogue.RULE_Q1), [])
