"""The closed-form drawing of sheets against containers gathered from the visible boxes, and its plans."""

import duckdb
import pytest

from layout_ie.operators.visual import phrase_regions
from layout_ie.oracles.drawings import SHEETS, q
from layout_ie.sources import sheets
from layout_ie.workloads import catalogue, tasks


@pytest.fixture(scope="module")
def odd(tmp_path_factory):
    """Every kind of page (ids by 2, 3, 5, 7, 11, 13, 17; negative ones), long orders, and missing texts."""
    d = str(tmp_path_factory.mktemp("odd"))
    con = duckdb.connect()
    con.sql(f"COPY (SELECT k AS o_orderkey, ['O', 'P', 'F'][1 + abs(k) % 3] AS o_orderstatus FROM range(-40, 500) t(k)) TO '{d}/orders.parquet'")
    con.sql(f"COPY (SELECT k AS p_partkey, CASE WHEN k <> 3 THEN repeat('ab', CAST(k % 5 AS INT)) || ' part' END AS p_name FROM range(0, 10) t(k)) TO '{d}/part.parquet'")
    con.sql(
        f"""COPY (SELECT k AS l_orderkey, CAST(j AS INT) AS l_linenumber, CASE WHEN k % 19 = 0 THEN 3 ELSE abs(k + j) % 10 END AS l_partkey, j AS l_suppkey, ['R', 'A', 'N'][1 + (abs(k) + j) % 3] AS l_returnflag,
        CASE WHEN k % 19 <> 0 THEN TIMESTAMP '1995-01-01' + INTERVAL (j) DAY END AS l_shipdate, CASE WHEN k % 19 <> 0 THEN CAST(j * abs(k) AS DOUBLE) END AS l_quantity
        FROM range(-40, 500) t(k), range(1, 12) u(j) WHERE j <= 1 + abs(k) % 11) TO '{d}/lineitem.parquet'"""
    )
    return d


def test_boxes_of_odd_orders(spark, odd):
    con = duckdb.connect()
    for t in ("orders", "part", "lineitem"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{odd}/{t}.parquet'")
    cols = [c for c in sheets.boxes(spark, odd).columns if c != "template"]
    key = lambda r: tuple(map(str, r))
    want = con.sql(q(f"SELECT {', '.join(cols)} FROM vis", SHEETS)).fetchall()
    assert sorted(map(tuple, sheets.boxes(spark, odd).select(*cols).collect()), key=key) == sorted(want, key=key)


def test_closed_form_equals_gathered_containers(spark, odd, sf):
    for d, some in ((odd, "page_id % 19 <> 0"), (sf, "true")):  # missing texts have no interval of their own
        mine = sheets.regions(spark, d).where(some)
        other = sheets.close_over_containers(sheets.boxes(spark, d)).where(some).select(*mine.columns)
        assert mine.exceptAll(other).count() == 0 == other.exceptAll(mine).count() and mine.count() > 0


def test_lifted_headings_equal_gathered_ones(spark, odd, sf):
    cols = ["page_id", "region_id", "x_l", "y_l", "x_h", "y_h"]
    for d in (odd, sf):
        mine = phrase_regions(sheets.lifted(spark, d), "Return Flag").select(cols)
        other = tasks.heading_sheets(sheets.boxes(spark, d), True).select(cols)
        assert mine.exceptAll(other).count() == 0 == other.exceptAll(mine).count() and mine.count() > 0


def plan(df):
    return df._jdf.queryExecution().sparkPlan().toString()


def test_only_lines_are_sorted(spark, sf):
    """No window and no grouping of nodes: the lines' window is the only one."""
    for name in ("sheet_extremes", "sheet_boxes"):
        text = plan(catalogue.QUERIES[name](spark, sf))
        assert text.count("Window [") == 1 and "Aggregate" not in text and "Union" not in text, name
        assert text.index("Generate ") < text.index("Window ["), name


@pytest.mark.parametrize(("name", "draws"), [("q3_sheets_maximal", 2), ("q4_sheets_maximal", 3), ("accuracy_q3_maximal", 3), ("accuracy_q4_maximal", 5)])
def test_maximal_headings_draw_once(spark, sf, name, draws):
    """A heading's cell comes with the drawing of the heading; containers are not gathered from several drawings."""
    assert plan(catalogue.QUERIES[name](spark, sf)).count("Generate ") == draws


def test_maximal_tasks_on_odd_orders(spark, odd):
    con = duckdb.connect()
    for t in ("orders", "part", "lineitem"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{odd}/{t}.parquet'")
    for name in ("q3_sheets_maximal", "q4_sheets_maximal", "accuracy_q3_maximal", "accuracy_q4_maximal"):
        mine = catalogue.QUERIES[name](spark, odd)
        want = con.sql(catalogue.ORACLES[name]).select(*mine.columns).fetchall()
        assert sorted(map(tuple, mine.collect())) == sorted(want) and want, name


def test_rule_sizes_are_of_the_sheets(spark, sf):
    """The sizes come with the sheets that the tables have."""
    mine = catalogue.QUERIES["rule_size"](spark, sf)
    con = duckdb.connect()
    for t in ("orders", "part", "lineitem"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    want = con.sql(catalogue.ORACLES["rule_size"]).select(*mine.columns).fetchall()
    assert sorted(map(tuple, mine.collect())) == sorted(want)
    assert {r["n_pages"] for r in mine.collect()} == {spark.read.parquet(f"{sf}/lineitem.parquet").select("l_orderkey").distinct().count()}


def test_marked_boxes_are_those_with_the_terms(spark, odd, sf):
    """Texts searched before drawing give the same boxes as after it; no length of a text is summed for them."""
    cols = ["page_id", "region_id", "x_l", "y_l", "x_h", "y_h", "text", "html_tag", "kind"]
    for d in (odd, sf):
        for terms, kinds in ((("Returned", "Accepted"), None), (("Returned", "Accepted"), ("value",)), (("Order Summary", "part"), None), (None, ("value",)), (None, None)):
            vis = sheets.boxes(spark, d).select(cols)
            want = vis if kinds is None else vis.where(vis["kind"].isin(*kinds))
            if terms:
                want = phrase_regions(want, terms[0]).unionByName(phrase_regions(want, terms[1])).distinct()
            mine = sheets.marked(spark, d, terms, kinds).select(cols)
            assert mine.exceptAll(want).isEmpty() and want.exceptAll(mine).isEmpty() and not want.isEmpty()
    assert "sum(" not in plan(sheets.marked(spark, sf, ("Returned",)).select(cols))
